"""Phase 3: free acceptance and batched validation on shared clusterings."""

from __future__ import annotations

import math
from collections.abc import Iterable
from functools import reduce

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyscout.functions.masks import bits, join_words, words_of
from keyscout.operators.evidence import JOB_ROWS, TIDY_ROWS, TILE, tiled_pairs
from keyscout.operators.prepare import Relation
from keyscout.operators.profile import ColumnStats
from keyscout.plans.lineage import release, snapshot, tidy

#: most candidates whose duplicate tests share one job, cells of all clusterings held, conflict groups of one candidate
#: that are compared in one round, colliding rows whose ids are broadcast
PER_JOB, MOST_CELLS, MOST_GROUPS, BROADCAST_ROWS = 24, 200_000_000, 20_000, 2_000_000


def split_free(candidates: Iterable[int], covered: int) -> tuple[list[int], list[int]]:
    """(free, to check): all agreeing pairs of a covered column were compared, so a candidate with one is a key."""
    free, check = [], []
    for c in candidates:
        (free if c & covered else check).append(c)
    return free, check


def anchor_order(stats: list[ColumnStats], covered: int) -> list[int]:
    """Uncovered columns, shortest longest run first."""
    return [s.index for s in sorted((s for s in stats if not covered >> s.index & 1), key=lambda s: (s.longest_run, s.index))]


def plan_batches(candidates: Iterable[int], order: list[int]) -> list[tuple[int, list[int]]]:
    """(anchor, candidates): each candidate once, under its first anchor; a batch is sorted so
    that neighbours share many columns."""
    batches: dict[int, list[int]] = {}
    for c in candidates:
        batches.setdefault(next(a for a in order if c >> a & 1), []).append(c)
    return [(a, sorted(batches[a])) for a in order if a in batches]


class Spread:
    """Whether rows dealt by a column set spread over all tasks, judged from column statistics.

    Columns count as independent: a set has about the product of their cardinalities as values, and
    its longest run shrinks by every column's share.  Enough is ten values for each task
    and no run above one task's part of the rows.
    """

    def __init__(self, stats: list[ColumnStats], n: int, tasks: int):
        self.stats, self.n, self.tasks = stats, max(1, n), max(1, tasks)

    def enough(self, mask: int) -> bool:
        values, run = 1, float(self.n)
        for i in bits(mask):
            values = min(self.n, values * self.stats[i].cardinality)
            run *= self.stats[i].longest_run / self.n
        return values >= min(self.n, 10 * self.tasks) and run <= max(1.0, self.n / self.tasks)


def split_batch(masks: list[int], order: list[int], spread: Spread, most: int = 1 << 30) -> tuple[list[list[int]], list[int]]:
    """(batches whose shared columns spread the rows, candidates left alone).

    Candidates are sorted by their columns in anchor order, so neighbours share the
    columns with the shortest runs; a batch ends where one more candidate would leave
    too little in common or the batch with more than ``most`` columns.  Candidates that share too little with any neighbour need no
    clustering: partial aggregation on the map side serves them.
    """
    place = {c: k for k, c in enumerate(order)}
    batches: list[list[int]] = []
    shared = used = 0
    for v in sorted(masks, key=lambda v: sorted(place[c] for c in bits(v))):
        if batches and spread.enough(shared & v) and (used | v).bit_count() <= most:
            batches[-1].append(v)
            shared, used = shared & v, used | v
        else:
            batches.append([v])
            shared = used = v
    return [b for b in batches if len(b) > 1], [b[0] for b in batches if len(b) == 1]


class Clusterings:
    """Clustered copies of a relation's columns, kept for later rounds of one run."""

    def __init__(self, relation: Relation, spread: Spread):
        self.relation, self.spread = relation, spread
        self.held: list[tuple[int, int, DataFrame]] = []  # (clustered on, columns, rows)
        self.groups: dict[int, tuple[DataFrame, int]] = {}  # rejected candidate: snapshot of its conflict groups, place there
        self.made = self.read = 0

    def serving(self, mask: int) -> DataFrame | None:
        """Rows clustered on a part of the candidate that spreads them, if an earlier batch left them."""
        for key, columns, rows in self.held:
            if key & ~mask == 0 and mask & ~columns == 0:
                return rows
        return None

    def plan(self, masks: list[int], order: list[int]) -> tuple[list[tuple[DataFrame, int]], list[list[int]], list[int]]:
        """(candidates served by an earlier clustering, batches that each deserve a new one, candidates left alone)."""
        out = [(self.serving(v), v) for v in masks]
        batches, alone = split_batch([v for rows, v in out if rows is None], order, self.spread, MOST_CELLS // max(1, self.relation.n))
        return [(rows, v) for rows, v in out if rows is not None], batches, alone

    def cells(self, columns: int) -> int:
        return columns.bit_count() * self.relation.n

    def fits(self, batch: list[int]) -> bool:
        """Whether one more clustering stays within MOST_CELLS beside those held."""
        return sum(self.cells(c) for _, c, _ in self.held) + self.cells(reduce(int.__or__, batch)) <= MOST_CELLS

    def make(self, batch: list[int]) -> DataFrame:
        rows = clustered_by(self.relation, batch)
        self.held.append((shared_columns(batch), reduce(int.__or__, batch), rows))
        self.made += 1
        return rows

    def forget_groups(self) -> None:
        for frame in {id(f): f for f, _ in self.groups.values()}.values():
            release(frame)
        self.groups.clear()

    def release(self) -> None:
        for _, _, rows in self.held:
            rows.unpersist()
        self.held.clear()


def validate_round(clusterings: Clusterings, check: list[int], order: list[int]) -> dict[int, tuple[int, int]]:
    """{rejected candidate: (conflict groups, rows in them)} of one round.

    A job takes PER_JOB candidates, or fewer where its exchanges would carry more than JOB_ROWS rows; a new
    clustering beyond MOST_CELLS waits until the job before has run and takes the place of those held.
    """
    relation, out = clusterings.relation, {}
    pending: list[tuple[DataFrame, int]] = []
    load = 0

    def run() -> None:
        nonlocal load
        if pending:
            groups = snapshot(reduce(DataFrame.unionAll, [_groups(rows, v, p) for p, (rows, v) in enumerate(pending)]))
            for r in groups.groupBy("_x").agg(F.count("*").alias("n_groups"), F.sum("cnt").alias("n_rows")).collect():
                out[pending[r._x][1]] = (r.n_groups, r.n_rows)
                clusterings.groups[pending[r._x][1]] = (groups, r._x)
            pending.clear()
            if load >= TIDY_ROWS:
                tidy(relation.rows.sparkSession)
        load = 0

    def add(rows: DataFrame, v: int, exchanged: int) -> None:
        nonlocal load
        if len(pending) == PER_JOB or pending and load + exchanged > JOB_ROWS:
            run()
        pending.append((rows, v))
        load += exchanged
        clusterings.read += 1

    for _, masks in plan_batches(check, order):
        known, batches, alone = clusterings.plan(masks, order)
        for rows, v in known:
            add(rows, v, 0)
        for batch in batches:
            if not clusterings.fits(batch):
                run()
                clusterings.release()
            rows = clusterings.make(batch)
            for k, v in enumerate(batch):
                add(rows, v, 0 if k else relation.n)
        for v in alone:
            add(relation.rows, v, relation.n)
    run()
    return out


def shared_columns(masks: list[int]) -> int:
    """Columns common to a whole batch: colliding rows agree on all of them, so they may cluster together."""
    return reduce(int.__and__, masks)


def clustered_by(relation: Relation, masks: list[int]) -> DataFrame:
    """The batch's columns, clustered once on what all its candidates share, and kept for reuse."""
    used = bits(reduce(int.__or__, masks))
    key = [f"c{i}" for i in bits(shared_columns(masks))]
    rows = relation.rows.select(*[f"c{i}" for i in used])
    return (rows.repartition(*key) if key else rows).persist(StorageLevel.DISK_ONLY)


def conflict_groups(rows: DataFrame, columns: list[str]) -> DataFrame:
    """Projections that occur more than once, with their counts."""
    return rows.groupBy(*columns).agg(F.count("*").alias("cnt")).where("cnt > 1")


def conflict_rows(relation: Relation, mask: int) -> DataFrame:
    """Whole rows of the conflict groups of a candidate."""
    keys = [f"c{i}" for i in bits(mask)]
    groups = conflict_groups(relation.rows, keys).select(*[F.col(k).alias(f"_{k}") for k in keys])
    on = reduce(lambda a, b: a & b, [F.col(k).eqNullSafe(F.col(f"_{k}")) for k in keys])
    return relation.rows.join(groups, on, "left_semi")


def conflict_pair_masks(relation: Relation, mask: int, pair_mode: str = "all", tile: int = TILE) -> DataFrame:
    """Mask words and pair counts of rows that collide on a candidate.

    ``star`` compares each row with the least row of its group only: one edge at least,
    which is all that progress needs.
    """
    keys = [f"c{i}" for i in bits(mask)]
    if pair_mode == "all":
        return tiled_pairs(relation.rows, keys, relation.columns, tile=tile)
    from keyscout.functions.masks import difference_words

    rows = conflict_rows(relation, mask)
    first = rows.groupBy(*keys).agg(F.min("rid").alias("rid")).select("rid")
    heads = rows.join(first, "rid", "left_semi").alias("a")
    on = reduce(lambda a, b: a & b, [F.col(f"a.{k}").eqNullSafe(F.col(f"b.{k}")) for k in keys]) & (F.col("a.rid") < F.col("b.rid"))
    return heads.join(rows.alias("b"), on).select(*difference_words("a", "b", relation.columns)).groupBy(*words_of(relation.m)).agg(F.count("*").alias("pairs"))


def validate_batch(relation: Relation, masks: list[int], method: str = "clustered") -> dict[int, tuple[int, int]]:
    """{rejected candidate: (conflict groups, rows in them)}.

    ``clustered`` tests every candidate over one shared clustering (no exchange above
    it); ``grouping_sets`` expands rows once per candidate into one aggregation;
    ``naive`` hashes the whole table anew for each candidate.
    """
    out: dict[int, tuple[int, int]] = {}
    rows = clustered_by(relation, masks) if method == "clustered" else relation.rows
    try:
        for s in range(0, len(masks), PER_JOB):
            part = masks[s : s + PER_JOB]
            verdicts = _grouping_sets(rows, part) if method == "grouping_sets" else _union(rows, part)
            for r in verdicts.collect():
                if r.n_groups:
                    out[part[r.place]] = (r.n_groups, r.n_rows)
    finally:
        if method == "clustered":
            rows.unpersist()
    return out


def _verdict(rows: DataFrame, mask: int, place: int) -> DataFrame:
    return conflict_groups(rows, [f"c{i}" for i in bits(mask)]).agg(F.count("*").alias("n_groups"), F.sum("cnt").alias("n_rows")).select(F.lit(place).alias("place"), "n_groups", "n_rows")


def _union(rows: DataFrame, masks: list[int]) -> DataFrame:
    return reduce(DataFrame.unionAll, [_verdict(rows, v, p) for p, v in enumerate(masks)])


def _grouping_sets(rows: DataFrame, masks: list[int]) -> DataFrame:
    used = [f"c{i}" for i in bits(reduce(int.__or__, masks))]
    sets = [[F.col(f"c{i}") for i in bits(v)] for v in masks]
    code = {sum(1 << (len(used) - 1 - k) for k, c in enumerate(used) if not v >> int(c[1:]) & 1): p for p, v in enumerate(masks)}
    grouped = rows.groupingSets(sets, *used).agg(F.count("*").alias("cnt"), F.grouping_id().alias("gid")).where("cnt > 1")
    places = F.create_map(*[x for g, p in code.items() for x in (F.lit(g).cast("long"), F.lit(p))])
    return grouped.groupBy("gid").agg(F.count("*").alias("n_groups"), F.sum("cnt").alias("n_rows")).select(places[F.col("gid")].alias("place"), "n_groups", "n_rows")


def conflict_masks(relation: Relation, rejected: dict[int, tuple[int, int]], pair_mode: str = "all", clusterings: Clusterings | None = None) -> tuple[set[int], int]:
    """(difference masks, pairs) over the conflict groups of rejected candidates, given with their groups and rows.

    Candidates share a job: the hashes of their groups (kept by the validation round) are broadcast, so that of
    the relation only rows that collide are written, and meet by (candidate, hash of the projection).  The mask
    itself tells whether a pair really agrees on the candidate, so a hash collision only costs a comparison.
    All pairs of a group are compared; of a candidate with more than MOST_GROUPS groups about so many of them,
    by least hash, since one mask disjoint from each rejected candidate is all that exactness needs: what the other
    groups would tell is asked again when the next candidates are validated, on all rows.
    """
    words, found, pairs = words_of(relation.m), set(), 0
    spark = relation.rows.sparkSession

    def take(frame: DataFrame) -> None:
        nonlocal pairs
        for r in frame.groupBy(*words).agg(F.sum("pairs").alias("pairs")).collect():
            found.add(join_words([r[w] for w in words]))
            pairs += r.pairs

    if pair_mode == "star":
        masks = sorted(rejected)
        size = max(1, min(PER_JOB, JOB_ROWS // max(1, relation.n)))
        for s in range(0, len(masks), size):
            take(reduce(DataFrame.unionByName, [conflict_pair_masks(relation, v, pair_mode) for v in masks[s : s + size]]))
            if relation.n >= TIDY_ROWS:
                tidy(spark)
        return found, pairs
    masks = sorted(rejected)
    for whole in (False, True):
        for s in range(0, len(masks), PER_JOB):
            part = masks[s : s + PER_JOB]
            rows = snapshot(_colliding(relation, part, rejected, clusterings, whole))
            agrees = F.lit(False)
            for p, v in enumerate(part):
                same = reduce(lambda a, b: a & b, [F.col(f"a.c{i}").eqNullSafe(F.col(f"b.c{i}")) for i in bits(v)])
                agrees = agrees | ((F.col("a._x") == p) & same)
            take(tiled_pairs(rows, ["_x", "_h"], relation.columns, agrees))
            release(rows)
            if relation.n >= TIDY_ROWS:
                tidy(spark)
        masks = [v for v in masks if all(v & e for e in found)]  # none, unless no group's print was small enough
    return found, pairs


def _print(mask: int) -> Column:
    return F.xxhash64(*[F.col(f"c{i}") for i in bits(mask)])


def _groups(rows: DataFrame, mask: int, place: int) -> DataFrame:
    """(_x, _h, cnt): place of the candidate, hash of the projection and rows of every conflict group."""
    return conflict_groups(rows, [f"c{i}" for i in bits(mask)]).select(F.lit(place).alias("_x"), _print(mask).alias("_h"), "cnt")


def _colliding(relation: Relation, masks: list[int], rejected: dict[int, tuple[int, int]], clusterings: Clusterings | None, whole: bool) -> DataFrame:
    """Rows of the conflict groups of some candidates, with _x (place of the candidate) and _h (hash of the projection)."""
    groups = []
    for p, v in enumerate(masks):
        frame, place = clusterings.groups.get(v, (None, 0)) if clusterings else (None, 0)
        found = _groups(relation.rows, v, p) if frame is None else frame.where(F.col("_x") == place)
        if not whole and rejected[v][0] > MOST_GROUPS:
            found = found.where(F.pmod("_h", F.lit(1 << 30)) < F.lit(math.ceil(MOST_GROUPS / rejected[v][0] * (1 << 30))))
        groups.append(found.select(F.lit(p).alias("_x"), "_h"))
    wanted = reduce(DataFrame.unionAll, groups)
    marks = F.explode(F.array(*[F.struct(F.lit(p).alias("_x"), _print(v).alias("_h")) for p, v in enumerate(masks)]))
    few = relation.rows.select("rid", marks.alias("_m")).select("rid", "_m._x", "_m._h").join(wanted if whole else F.broadcast(wanted), ["_x", "_h"], "left_semi")
    share = lambda v: rejected[v][1] * min(1, MOST_GROUPS / rejected[v][0])
    if not whole and sum(map(share, masks)) <= BROADCAST_ROWS:
        few = F.broadcast(few)
    return relation.rows.join(few, "rid")


def maintained_rows(stats: list[ColumnStats], anchors: Iterable[int]) -> int:
    """Most rows one run brings together over the anchors used."""
    return max((stats[a].longest_run for a in anchors), default=0)
