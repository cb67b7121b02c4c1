"""Phase 1: difference masks of the row pairs worth comparing."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyscout.functions.masks import WORD, difference_words, join_words, minimal_delta, minimal_masks, minimize_partitions, words_of
from keyscout.operators.prepare import Relation
from keyscout.operators.profile import ColumnStats
from keyscout.plans.lineage import release, snapshot, tidy

#: rows on one side of a tile, tasks that share a run before it is cut in tiles, distinct masks from which partitions
#: minimise first, most covered columns of one job, rows that its exchanges carry together (one column at least), rows
#: from which shuffle files are cleared after a job
TILE, SALTS, MANY_MASKS, COLUMNS_PER_JOB, JOB_ROWS, TIDY_ROWS = 2048, 8, 200_000, 8, 40_000_000, 2_000_000


def _masks_of_pairs(a: DataFrame, b: DataFrame, on: Column, columns: list[str], keep: Column | None) -> DataFrame:
    pairs = a.join(b, on)
    if keep is not None:
        pairs = pairs.where(keep)
    return pairs.select(*difference_words("a", "b", columns)).groupBy(*words_of(len(columns))).agg(F.count("*").alias("pairs"))


def tiled_pairs(rows: DataFrame, keys: list[str], columns: list[str], keep: Column | None = None, tile: int = TILE) -> DataFrame:
    """Mask words and pair counts of all unordered pairs that agree on ``keys``.

    A group of r rows is cut into ceil(r / tile) parts by row hash, and every pair of
    parts is a join key of its own, so one long run spreads over many tasks; before it is
    cut, SALTS tasks share it.  Groups of one row are left out.  Null keys agree.
    """
    salts = F.explode(F.array(*[F.lit(s) for s in range(SALTS)])).alias("_salt")
    sizes = rows.groupBy(*keys).agg(F.count("*").alias("_n")).where("_n > 1").select(*[F.col(k).alias(f"_k{i}") for i, k in enumerate(keys)], F.ceil(F.col("_n") / tile).cast("int").alias("_parts"), salts)
    match = F.col("_own_salt") == F.col("_salt")
    for i, k in enumerate(keys):
        match = match & F.col(k).eqNullSafe(F.col(f"_k{i}"))
    wanted = rows.select("rid", *dict.fromkeys([*keys, *columns, *(c for c in rows.columns if c.startswith("_"))])).withColumn("_own_salt", F.pmod(F.xxhash64(F.lit(1), "rid"), F.lit(SALTS)).cast("int"))
    live = wanted.join(sizes, match).drop("_salt", "_own_salt", *[f"_k{i}" for i in range(len(keys))])
    part = F.pmod(F.xxhash64("rid"), F.col("_parts")).cast("int")
    spread = live.withColumn("_side", part).withColumn("_other", F.explode(F.sequence(F.lit(0), F.col("_parts") - 1)))
    spread = spread.withColumn("_i", F.least("_side", "_other")).withColumn("_j", F.greatest("_side", "_other")).drop("_parts", "_other")
    a, b = spread.where("_side = _i").alias("a"), spread.where("_side = _j").alias("b")
    on = (F.col("a._i") == F.col("b._i")) & (F.col("a._j") == F.col("b._j"))
    for k in keys:
        on = on & F.col(f"a.{k}").eqNullSafe(F.col(f"b.{k}"))
    # inside one part each pair once; between two parts the sides already tell the rows apart
    on = on & ((F.col("a._i") != F.col("a._j")) | (F.col("a.rid") < F.col("b.rid")))
    return _masks_of_pairs(a, b, on, columns, keep)


def pair_masks_for_column(relation: Relation, i: int, owners: list[int] | None = None, tile: int = TILE, strategy: str = "tiled", longest_run: int | None = None) -> DataFrame:
    """Masks of all pairs that agree on column i.

    ``owners``: covered columns before i; a pair that agrees on one of them was counted
    there already.  A column whose ``longest_run`` is known to fit one tile is joined with
    itself over one exchange, which both sides share; others go in tiles.  ``strategy`` "join"
    asks for the plain self-join whatever the runs, "grouped_arrays" compares 64-bit value
    hashes inside Python, one run to a call (both for comparison on data without long runs).
    """
    keep = None
    for j in owners or []:
        differs = ~F.col(f"a.c{j}").eqNullSafe(F.col(f"b.c{j}"))
        keep = differs if keep is None else keep & differs
    key = f"c{i}"
    if strategy == "join" or strategy == "tiled" and longest_run is not None and longest_run <= tile:
        a, b = relation.rows.alias("a"), relation.rows.alias("b")
        return _masks_of_pairs(a, b, F.col(f"a.{key}").eqNullSafe(F.col(f"b.{key}")) & (F.col("a.rid") < F.col("b.rid")), relation.columns, keep)
    if strategy == "tiled":
        return tiled_pairs(relation.rows, [key], relation.columns, keep, tile)
    if strategy == "grouped_arrays":
        return _grouped_masks(relation, key, owners or [])
    raise ValueError(f"unknown strategy {strategy}")


def _grouped_masks(relation: Relation, key: str, owners: list[int]) -> DataFrame:
    """Masks by numpy inside each group, by value hashes; only for columns whose longest run is short."""
    import numpy as np
    import pandas as pd

    if relation.m > WORD:
        raise ValueError("grouped_arrays takes 63 columns at most")
    columns = relation.columns
    codes = relation.rows.select(F.col(key).alias("_key"), *[F.xxhash64(F.lit(i), F.col(c)).alias(f"h{i}") for i, c in enumerate(columns)])

    def compare(frame):
        x = frame[[f"h{i}" for i in range(len(columns))]].to_numpy()
        a, b = np.triu_indices(len(x), 1)
        differs = x[a] != x[b]
        if owners:
            differs = differs[differs[:, owners].all(1)]
        masks, n = np.unique((differs.astype(np.int64) << np.arange(len(columns))).sum(1), return_counts=True)
        return pd.DataFrame({"mask": masks.astype("int64"), "pairs": n.astype("int64")})

    return codes.groupBy("_key").applyInPandas(compare, "mask long, pairs long").groupBy("mask").agg(F.sum("pairs").alias("pairs"))


def covered_pair_masks(relation: Relation, covered: list[int], ownership: bool = True, before: list[int] | None = None, stats: list[ColumnStats] | None = None, **how) -> DataFrame | None:
    """(col_ix, mask words, pairs) over the covered columns, in the given order.

    ``before``: columns of earlier calls, whose pairs are owned there.
    """
    out, before = None, before or []
    for place, i in enumerate(covered):
        longest = stats[i].longest_run if stats else None
        part = pair_masks_for_column(relation, i, [*before, *covered[:place]] if ownership else None, longest_run=longest, **how).withColumn("col_ix", F.lit(i))
        out = part if out is None else out.unionByName(part)
    return out


def mask_count_per_column(masks: DataFrame) -> DataFrame:
    """(col_ix, masks, pairs): distinct masks and pairs per covered column."""
    return masks.groupBy("col_ix").agg(F.count("*").alias("masks"), F.sum("pairs").alias("pairs"))


def distinct_masks(masks: DataFrame, m: int) -> DataFrame:
    return masks.select(*words_of(m)).distinct()


def useful_masks(masks: DataFrame, m: int) -> DataFrame:
    """Masks with at least one agreeing column."""
    differs = F.lit(False)
    for w, name in enumerate(words_of(m)):
        differs = differs | (F.col(name) != F.lit((1 << min(WORD, m - WORD * w)) - 1))
    return masks.where(differs)


def sample_size(n: int, n_uncovered: int) -> int:
    return math.isqrt(n * n_uncovered)


def supplement_sample(relation: Relation, size: int, seed: int = 0) -> DataFrame:
    """``size`` rows by least seeded row hash: uniform and repeatable.

    Only rows whose hash lies below a bound take part in the sort: about ``size`` of them, and
    six standard deviations more, however large the relation is.
    """
    share = min(1.0, (size + 6 * math.sqrt(size) + 40) / max(1, relation.n))
    order = F.xxhash64(F.lit(seed), "rid")
    rows = relation.rows if share == 1 else relation.rows.where(F.pmod(order, F.lit(1 << 30)) < F.lit(math.ceil(share * (1 << 30))))
    return rows.orderBy(F.pmod(order, F.lit(1 << 30)), order, "rid").limit(size)


def sample_pair_masks(relation: Relation, sample: DataFrame, tile: int = 512) -> DataFrame:
    """Masks of all pairs of a sample, in blocks."""
    rows = snapshot(sample.withColumn("_all", F.lit(0)))
    return tiled_pairs(rows, ["_all"], relation.columns, tile=tile)


@dataclass
class Hypergraph:
    """Minimal difference masks seen so far, with what it took to see them.

    ``full``: the columns that are not constant, which no mask exceeds.
    """

    m: int
    edges: list[int]
    full: int
    pairs: int = 0
    distinct: int = 0
    per_column: dict[int, tuple[int, int]] = field(default_factory=dict)
    sampled_rows: int = 0
    sample_pairs: int = 0

    def absorb(self, masks: list[int]) -> None:
        self.edges = minimal_delta([e for e in self.edges if e != self.full], [v for v in masks if v != self.full]) or [self.full]


def gather(masks: DataFrame, m: int) -> tuple[list[int], dict[int, tuple[int, int]]]:
    """(masks, {column or -1: (masks, pairs)}) on the driver: masks are few, never proportional to rows.

    Beyond MANY_MASKS rows the masks are minimised inside their partitions first; the pairs are
    computed once either way.
    """
    words = words_of(m)
    column = F.col("col_ix") if "col_ix" in masks.columns else F.lit(-1)
    held = masks.select(column.alias("col_ix"), *words, "pairs").persist(StorageLevel.DISK_ONLY)
    try:
        totals = {r.col_ix: (r.masks, r.pairs) for r in mask_count_per_column(held).collect()}
        small = sum(n for n, _ in totals.values()) <= MANY_MASKS
        rows = held if small else minimize_partitions(distinct_masks(held, m), m)
        return [join_words(r) for r in rows.select(*words).collect()], totals
    finally:
        held.unpersist()


def build_initial_hypergraph(relation: Relation, stats: list[ColumnStats], covered: list[int], sampling: str | int = "sqrt", seed: int = 0, max_sample_rows: int | None = None, ownership: bool = True, compare: bool = True, timer=None, **how) -> Hypergraph:
    """Masks of covered columns and of the sample, minimised.

    Two distinct rows that agree nowhere give only the full mask, which every column
    set meets; it stands in when nothing else was seen, so that each single column is a
    candidate.  Constant columns are in no mask and need no comparing: if any other column
    is covered its pairs tell as much, and the sample does otherwise.
    """
    from contextlib import nullcontext

    part = timer or (lambda _: nullcontext())
    constant = [s.index for s in stats if s.cardinality == 1]
    graph = Hypergraph(relation.m, [], sum(1 << s.index for s in stats if s.cardinality != 1))
    seen: set[int] = set()
    order = sorted(covered, key=lambda i: (stats[i].agree_pairs, i))
    order = [i for i in order if stats[i].agree_pairs and i not in constant]
    with part("generate"):
        if compare and order:
            # wide relations: plans of bounded size; long ones: few exchanges of the whole relation at a time
            size = max(1, min(COLUMNS_PER_JOB, JOB_ROWS // max(1, relation.n)))
            for at in range(0, len(order), size):
                found, totals = gather(covered_pair_masks(relation, order[at : at + size], ownership, order[:at], stats, **how), relation.m)
                if relation.n >= TIDY_ROWS:
                    tidy(relation.rows.sparkSession)
                seen.update(found)
                graph.pairs += sum(pairs for _, pairs in totals.values())
                graph.per_column |= totals
    with part("supplement"):
        uncovered = relation.m - len(covered)
        size = {"sqrt": min(sample_size(relation.n, uncovered), max_sample_rows or relation.n), "off": 0}.get(sampling, sampling)
        if size > 1:
            sample = snapshot(supplement_sample(relation, size, seed).withColumn("_all", F.lit(0)))
            found, totals = gather(tiled_pairs(sample, ["_all"], relation.columns, tile=512), relation.m)
            release(sample)
            graph.sampled_rows, graph.sample_pairs = min(size, relation.n), sum(pairs for _, pairs in totals.values())
            seen.update(found)
    graph.distinct = len(seen)
    graph.edges = minimal_masks(v for v in seen if v != graph.full) or [graph.full]
    return graph
