"""The searches the method is compared with: all pairs, the column lattice, position lists, and relatives."""

from __future__ import annotations

import random
from collections.abc import Sequence
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyscout.functions.masks import bits, difference_words, join_words, minimal_delta, minimal_masks, words_of
from keyscout.operators import evidence, validate
from keyscout.operators.discover import DiscoveryOptions, DiscoveryResult, Report, discover_keys
from keyscout.operators.prepare import Relation, encode_columns
from keyscout.operators.profile import relation_stats
from keyscout.plans.hitting import minimal_hitting_sets, refined_hitting_sets
from keyscout.plans.lineage import release, snapshot, tidy

#: most columns whose sets are counted one and all, sets whose groupings share one job, rows from which shuffle files
#: are cleared after a job of a search
COUNTED_COLUMNS, SETS_PER_JOB, TIDY_ROWS = 12, 8, 2_000_000


def agreeing_pairs(rows: DataFrame, masks: list[int]) -> dict[int, int]:
    """{column set: row pairs that agree on all of it} of the sets that have such a pair."""
    out: dict[int, int] = {}
    n = F.col("cnt").cast("decimal(19,0)")
    for s in range(0, len(masks), SETS_PER_JOB):
        part = masks[s : s + SETS_PER_JOB]
        counts = [validate.conflict_groups(rows, [f"c{i}" for i in bits(v)]).agg(F.sum(n * (n - 1) / 2).cast("decimal(38,0)").alias("pairs")).select(F.lit(p).alias("place"), "pairs") for p, v in enumerate(part)]
        out |= {part[r.place]: int(r.pairs) for r in reduce(DataFrame.unionAll, counts).collect() if r.pairs}
        tidy(rows.sparkSession)
    return out


def all_pair_masks(relation: Relation) -> DataFrame:
    """Difference masks of every row pair, with the number of pairs.

    No pair is formed: the pairs that agree at least on a column set are counted from the sizes of
    its groups, level by level (a set without such a pair has none above it), and inclusion and
    exclusion over the supersets leaves those that agree on it and nothing else.  That takes up to
    2^m groupings, so beyond COUNTED_COLUMNS columns the pairs are compared in blocks, quadratic as they are.
    """
    m, n, spark = relation.m, relation.n, relation.rows.sparkSession
    if m > COUNTED_COLUMNS:
        rows = snapshot(relation.rows.withColumn("_all", F.lit(0)))
        return evidence.tiled_pairs(rows, ["_all"], relation.columns, tile=512)
    full = (1 << m) - 1
    pairs = [0] * (full + 1)
    pairs[0] = n * (n - 1) // 2
    level = [1 << i for i in range(m)] if pairs[0] else []
    while level:
        found = agreeing_pairs(relation.rows, level)
        for v, k in found.items():
            pairs[v] = k
        wider = {v | 1 << c for v in found for c in range(v.bit_length(), m)}
        level = sorted(w for w in wider if all(w & ~(1 << d) in found for d in bits(w)))
    for i in range(m):
        for v in range(full + 1):
            if not v >> i & 1:
                pairs[v] -= pairs[v | 1 << i]
    return spark.createDataFrame([(full & ~v, k) for v, k in enumerate(pairs) if k], "mask long, pairs long")


def discover_keys_exhaustive(df: DataFrame) -> DiscoveryResult:
    """Every row pair counted: the full hypergraph, then its minimal hitting sets."""
    report, relation = Report(), encode_columns(df)
    if relation.n <= 1:
        return DiscoveryResult(relation.names, [0], [], [], report)
    with report.timed("generate"):
        masks, totals = evidence.gather(all_pair_masks(relation), relation.m)
    report |= {"pairs": sum(pairs for _, pairs in totals.values()), "distinct_masks": sum(n for n, _ in totals.values())}
    full = (1 << relation.m) - 1
    edges = minimal_masks(v for v in masks if v != full) or [full]
    with report.timed("enumerate"):
        keys = minimal_hitting_sets(edges, relation.m)
    return DiscoveryResult(relation.names, keys, edges, [], report)


def discover_keys_lattice(df: DataFrame, method: str = "clustered") -> DiscoveryResult:
    """Level-wise search of the column lattice: supersets of found keys are never tested."""
    report, relation = Report(), encode_columns(df)
    if relation.n <= 1:
        return DiscoveryResult(relation.names, [0], [], [], report)
    keys: list[int] = []
    level, tested = [1 << i for i in range(relation.m)], 0
    with report.timed("validate"):
        while level:
            tested += len(level)
            groups: dict[int, list[int]] = {}
            for v in level:
                groups.setdefault(v & -v, []).append(v)
            rejected: set[int] = set()
            for masks in [level] if method != "clustered" else groups.values():
                rejected |= set(validate.validate_batch(relation, masks, method))
            keys += [v for v in level if v not in rejected]
            bad = rejected
            level = []
            for v in bad:
                for c in range(v.bit_length(), relation.m):
                    w = v | 1 << c
                    # every subset one smaller must be a known non-key
                    if all(w & ~(1 << d) in bad for d in bits(w)):
                        level.append(w)
            level.sort()
    report |= {"validations": tested}
    return DiscoveryResult(relation.names, sorted(keys, key=lambda k: (k.bit_count(), k)), [], [], report)


def stripped_partition(rows: DataFrame, columns: Sequence[str]) -> DataFrame:
    """(cluster, rid): rows that share their values on ``columns`` with another row."""
    groups = rows.groupBy(*columns).agg(F.count("*").alias("_n"), F.min("rid").alias("cluster")).where("_n > 1")
    on = None
    for i, c in enumerate(columns):
        groups = groups.withColumnRenamed(c, f"_p{i}")
        same = F.col(c).eqNullSafe(F.col(f"_p{i}"))
        on = same if on is None else on & same
    return rows.join(groups, on).select("cluster", "rid")


def intersect_partitions(a: DataFrame, b: DataFrame) -> DataFrame:
    """Stripped partition of the union of two column sets from their stripped partitions."""
    both = a.join(b.withColumnRenamed("cluster", "_b"), "rid")
    groups = both.groupBy("cluster", "_b").agg(F.count("*").alias("_n"), F.min("rid").alias("_c")).where("_n > 1")
    return both.join(groups, ["cluster", "_b"]).select(F.col("_c").alias("cluster"), "rid")


def discover_keys_pli(df: DataFrame, sampling_exponent: float = 0.3, seed: int = 0) -> DiscoveryResult:
    """The in-memory competitor: position lists, pair samples and validation in place.

    Every column's position lists are kept as stripped partitions in Spark (rows with a
    partner only).  Each column gives about (cluster pairs) ** sampling_exponent sampled
    pairs; a depth-first hitting-set search validates every leaf by intersecting the
    lists of its columns, smallest first, and pairs of colliding rows refine the masks
    while the search goes on.  Details beyond the exponent follow public literature.
    """
    report, relation = Report(), encode_columns(df)
    m, n = relation.m, relation.n
    if n <= 1:
        return DiscoveryResult(relation.names, [0], [], [], report)
    full = (1 << m) - 1
    with report.timed("decompose"):
        stats = relation_stats(relation)
        lists = {i: snapshot(stripped_partition(relation.rows, [f"c{i}"])) for i in range(m) if stats[i].agree_pairs}
    words = words_of(m)

    def masks_of(pairs: DataFrame) -> set[int]:
        a, b = relation.rows.alias("a"), relation.rows.alias("b")
        joined = pairs.join(a, F.col("x") == F.col("a.rid")).join(b, F.col("y") == F.col("b.rid"))
        return {join_words(r) for r in joined.select(*difference_words("a", "b", relation.columns)).distinct().select(*words).collect()}

    seen: set[int] = set()
    pairs = 0
    with report.timed("generate"):
        for i, part in lists.items():
            want = max(1, round(stats[i].agree_pairs**sampling_exponent))
            picked = part.orderBy(F.xxhash64(F.lit(seed), "rid")).limit(want).select("cluster", F.col("rid").alias("x"))
            # partner: the cluster's least row (its name), or for that row itself the greatest one
            tops = part.groupBy("cluster").agg(F.max("rid").alias("top"))
            sampled = picked.join(tops, "cluster").select("x", F.when(F.col("x") == F.col("cluster"), F.col("top")).otherwise(F.col("cluster")).alias("y"))
            seen |= masks_of(sampled)
            pairs += want
    validations = 0

    def collisions(h: int) -> set[int]:
        nonlocal pairs, validations
        validations += 1
        order = sorted(bits(h), key=lambda i: stats[i].agree_pairs)
        if any(i not in lists for i in order):
            return set()  # a column without a repeated value
        part = lists[order[0]]
        for i in order[1:]:
            part = intersect_partitions(part, lists[i])
        # every row against the least one of its cluster
        new = masks_of(part.where("rid <> cluster").select(F.col("cluster").alias("x"), F.col("rid").alias("y")))
        pairs += len(new)
        return new

    with report.timed("validate"):
        keys, edges = refined_hitting_sets(minimal_masks(v for v in seen if v != full) or [full], m, collisions)
    keys.sort(key=lambda k: (k.bit_count(), k))
    report |= {"pairs": pairs, "validations": validations, "list_rows": sum(p.count() for p in lists.values())}
    return DiscoveryResult(relation.names, keys, edges, stats, report)


def _split(rows: DataFrame, column: str) -> DataFrame:
    """Rows of the groups ``_g`` that share their value of ``column`` with another row of theirs; ``_g`` names the new groups."""
    groups = rows.groupBy("_g", column).agg(F.count("*").alias("_n"), F.min("rid").alias("_new")).where("_n > 1")
    groups = groups.select(F.col("_g").alias("_old"), F.col(column).alias("_v"), "_new")
    on = (F.col("_g") == F.col("_old")) & F.col(column).eqNullSafe(F.col("_v"))
    return rows.join(groups, on).select(F.col("_new").alias("_g"), *[c for c in rows.columns if c not in ("_g", column)])


def discover_keys_prefix_tree(df: DataFrame) -> DiscoveryResult:
    """Row-based search over a prefix tree of the rows: maximal non-keys, complemented to keys.

    Walking the tree, rows below one node agree on the chosen columns; a branch ends
    when a single row is left, and columns are merged away where one is skipped.  A node's
    groups are a DataFrame of the rows that still have a partner, written once and removed
    when its branch is left, so the driver holds column sets only.
    """
    report, relation = Report(), encode_columns(df)
    names, m = relation.names, relation.m
    if relation.n <= 1:
        return DiscoveryResult(names, [0], [], [], report)
    non_keys: list[int] = []

    def covered(mask: int) -> bool:
        return any(mask & ~v == 0 for v in non_keys)

    def walk(rows: DataFrame, column: int, mask: int) -> None:
        """rows: all with a partner that agrees on ``mask``; columns before ``column`` are decided."""
        rest = mask | ((1 << m) - 1) >> column << column
        if covered(rest):
            return
        if column == m:
            non_keys[:] = [v for v in non_keys if v & ~mask] + [mask]
            return
        split = snapshot(_split(rows, f"c{column}"))
        if split.limit(1).count():
            walk(split, column + 1, mask | 1 << column)
        release(split)
        if relation.n >= TIDY_ROWS:
            tidy(df.sparkSession)
        walk(rows.drop(f"c{column}"), column + 1, mask)

    with report.timed("enumerate"):
        walk(relation.rows.withColumn("_g", F.lit(0).cast("long")), 0, 0)
        full = (1 << m) - 1
        edges = minimal_masks(full & ~v for v in non_keys) or [full]
        keys = minimal_hitting_sets(edges, m)
    return DiscoveryResult(names, keys, edges, [], report)


def discover_keys_random_walk(df: DataFrame, seed: int = 0) -> DiscoveryResult:
    """Random walks between keys and non-keys of the lattice, closed by the duality test.

    A walk climbs from a non-key to a maximal one or descends from a key to a minimal
    one.  When the complements of the maximal non-keys found so far have exactly the
    minimal keys found so far as hitting sets, nothing is missing; otherwise a hitting
    set that is not yet known starts the next walk.  A column set is tested by grouping
    the rows, unless a tested subset or superset settles it.
    """
    report, relation = Report(), encode_columns(df)
    names, m, draw = relation.names, relation.m, random.Random(seed)
    if relation.n <= 1:
        return DiscoveryResult(names, [0], [], [], report)
    full = (1 << m) - 1
    checks: dict[int, bool] = {0: False}  # the empty set is no key of two rows or more

    def unique(mask: int) -> bool:
        if any(good and v & ~mask == 0 for v, good in checks.items()):
            return True
        if any(not good and mask & ~v == 0 for v, good in checks.items()):
            return False
        checks[mask] = not validate.conflict_groups(relation.rows, [f"c{i}" for i in bits(mask)]).limit(1).count()
        if relation.n >= TIDY_ROWS:
            tidy(df.sparkSession)
        return checks[mask]

    if not unique(full):
        return DiscoveryResult(names, [], [0], [], report)
    keys: set[int] = set()
    edges: list[int] = []
    with report.timed("validate"):
        starts = [0]
        while starts:
            for v in starts:
                order = draw.sample(range(m), m)
                if unique(v):
                    for c in order:
                        if v >> c & 1 and unique(v & ~(1 << c)):
                            v &= ~(1 << c)
                    keys.add(v)
                else:
                    for c in order:
                        if not v >> c & 1 and not unique(v | 1 << c):
                            v |= 1 << c
                    edges = minimal_delta(edges, [full & ~v])
            starts = [h for h in minimal_hitting_sets(edges, m) if h not in keys]
    report |= {"validations": len(checks) - 1}
    return DiscoveryResult(names, sorted(keys, key=lambda k: (k.bit_count(), k)), edges, [], report)


def discover_keys_hybrid(df: DataFrame, switch_threshold: float = 0.1, seed: int = 0) -> DiscoveryResult:
    """Row phase and column phase in turn: sampled evidence, then validation of the candidates it leaves.

    The phases swap when more than ``switch_threshold`` of the candidates checked fail:
    then a larger row sample is compared before the next validation.
    """
    report, relation = Report(), encode_columns(df)
    m, n = relation.m, relation.n
    if n <= 1:
        return DiscoveryResult(relation.names, [0], [], [], report)
    full, size, edges = (1 << m) - 1, max(32, int(n**0.5)), [(1 << m) - 1]
    accepted: set[int] = set()
    while True:
        with report.timed("generate"):
            masks, _ = evidence.gather(evidence.sample_pair_masks(relation, evidence.supplement_sample(relation, size, seed)), m)
            edges = minimal_delta([e for e in edges if e != full], [v for v in masks if v != full]) or [full]
        while edges != [0]:
            fresh = [h for h in minimal_hitting_sets(edges, m) if h not in accepted]
            if not fresh:
                return DiscoveryResult(relation.names, sorted(accepted, key=lambda k: (k.bit_count(), k)), edges, [], report)
            with report.timed("validate"):
                rejected = validate.validate_batch(relation, fresh, "naive")
                accepted |= set(fresh) - set(rejected)
                if rejected:
                    masks, _ = validate.conflict_masks(relation, rejected, "all")
                    edges = minimal_delta([e for e in edges if e != full], [v for v in masks if v != full]) or [full]
            if len(rejected) > switch_threshold * len(fresh) and size < n:
                size = min(n, size * 2)
                break
        if edges == [0]:
            return DiscoveryResult(relation.names, [], edges, [], report)


#: switches of the method, each minus one saving
ABLATIONS = {
    "no_sampling": {"sampling": "off"},
    "sample_only": {"compare_covered": False},
    "no_free_acceptance": {"free_acceptance": False},
    "whole_table_validation": {"validation": "naive"},
    "grouping_sets_validation": {"validation": "grouping_sets"},
    "star_conflicts": {"pair_mode": "star"},
    "no_ownership": {"ownership": False},
    "first_edge_branching": {"edge_choice": "first"},
}


def discover_keys_ablated(df: DataFrame, name: str, **options) -> DiscoveryResult:
    return discover_keys(df, DiscoveryOptions(**ABLATIONS[name], **options))
