"""The discovery loop, its options and results, and questions about keys."""

from __future__ import annotations

import time
from collections import defaultdict
from collections.abc import Iterator, Sequence
from contextlib import contextmanager
from dataclasses import dataclass, field
from decimal import Decimal

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyscout.functions.masks import bits, mask_columns, mask_of, split_words, words_of
from keyscout.operators import evidence, profile, validate
from keyscout.operators.prepare import Relation, encode_columns
from keyscout.plans.hitting import minimal_hitting_sets


@dataclass
class DiscoveryOptions:
    factor: float = 3.0
    budget: int | str | None = None  # an absolute pair budget, or "gap"
    fallback_multiplier: int = 5
    sampling: str | int = "sqrt"
    seed: int = 0
    max_sample_rows: int | None = None  # a bound on the uniform sample; the method has none
    null_policy: str = "null_equal"
    encoding: str = "native"
    on_duplicates: str = "no_keys"  # or "error", "dedup"
    ownership: bool = True
    pair_strategy: str = "tiled"
    tile: int = evidence.TILE
    compare_covered: bool = True
    free_acceptance: bool = True
    validation: str = "clustered"  # or "grouping_sets", "naive"
    pair_mode: str = "all"  # or "star"
    edge_choice: str | None = "smallest"


class DuplicateRows(ValueError):
    pass


class Report(dict):
    """Counters and seconds of one run."""

    def __init__(self):
        super().__init__(seconds=defaultdict(float), rounds=[])

    @contextmanager
    def timed(self, part: str) -> Iterator[None]:
        began = time.perf_counter()
        try:
            yield
        finally:
            self["seconds"][part] += time.perf_counter() - began


@dataclass
class DiscoveryResult:
    names: list[str]
    keys: list[int]
    edges: list[int]
    stats: list[profile.ColumnStats]
    report: Report
    how: dict[int, tuple[str, int]] = field(default_factory=dict)

    def key_names(self) -> list[tuple[str, ...]]:
        return [tuple(mask_columns(k, self.names)) for k in self.keys]

    def keys_df(self, spark: SparkSession) -> DataFrame:
        """(key, n_columns, how, round); ``key`` joins column names in schema order."""
        rows = [(",".join(mask_columns(k, self.names)), k.bit_count(), *self.how.get(k, ("enumerated", 0))) for k in self.keys]
        return spark.createDataFrame(rows, "key string, n_columns int, how string, round int")

    def edges_df(self, spark: SparkSession) -> DataFrame:
        m = len(self.names)
        return spark.createDataFrame([split_words(e, m) for e in self.edges], ", ".join(f"{w} long" for w in words_of(m)))

    def stats_df(self, spark: SparkSession) -> DataFrame:
        rows = [(s.index, s.name, s.cardinality, Decimal(s.agree_pairs), s.longest_run, s.nulls) for s in self.stats]
        return spark.createDataFrame(rows, "col_ix int, col string, cardinality long, agree_pairs decimal(38,0), longest_run long, nulls long")

    def maximal_non_keys(self) -> list[int]:
        """Complements of the final minimal masks; exact, since those are the masks of the full hypergraph."""
        full = (1 << len(self.names)) - 1
        return [full & ~e for e in self.edges]

    def register(self, spark: SparkSession, prefix: str = "ks") -> None:
        """Temporary views <prefix>_keys, <prefix>_masks and <prefix>_columns."""
        self.keys_df(spark).createOrReplaceTempView(f"{prefix}_keys")
        self.edges_df(spark).createOrReplaceTempView(f"{prefix}_masks")
        self.stats_df(spark).createOrReplaceTempView(f"{prefix}_columns")


def choose_budget(stats: list[profile.ColumnStats], n: int, options: DiscoveryOptions) -> int:
    """The pair budget, raised where it would cover no column at all."""
    if isinstance(options.budget, int):
        budget = options.budget
    else:
        budget = profile.pair_budget(n, options.factor)
        if options.budget == "gap":
            budget = profile.gap_budget(stats, budget)
    if options.fallback_multiplier and not profile.covered_mask(stats, budget):
        budget = profile.fallback_budget(stats, options.fallback_multiplier)
    return budget


def discover_keys(df: DataFrame, options: DiscoveryOptions | None = None, relation: Relation | None = None) -> DiscoveryResult:
    """All minimal keys of ``df``, exactly.

    A table of at most one row has the empty key (mask 0).  Duplicate rows leave no key:
    ``on_duplicates`` decides between an empty result, an error and dropping them first.
    Each round adds at least one mask disjoint from a rejected candidate, so it ends.
    """
    options = options or DiscoveryOptions()
    report = Report()
    with report.timed("decompose"):
        if options.on_duplicates == "dedup" and relation is None:
            df = df.dropDuplicates()
        relation = relation or encode_columns(df, options.encoding, options.null_policy)
    names, m, n = relation.names, relation.m, relation.n
    report |= {"rows": n, "columns": m}
    if n <= 1:
        return DiscoveryResult(names, [0], [], [], report, {0: ("empty", 0)})
    with report.timed("type"):
        stats = profile.relation_stats(relation)
        budget = choose_budget(stats, n, options)
        covered = profile.covered_mask(stats, budget)
    graph = evidence.build_initial_hypergraph(
        relation, stats, bits(covered), options.sampling, options.seed, options.max_sample_rows, options.ownership, options.compare_covered, report.timed, strategy=options.pair_strategy, tile=options.tile)
    if not options.compare_covered or not options.free_acceptance:
        free_columns = 0
    else:
        free_columns = covered
    report |= {"budget": budget, "covered_columns": covered.bit_count(), "pairs_phase1": graph.pairs, "sample_rows": graph.sampled_rows, "sample_pairs": graph.sample_pairs, "distinct_masks": graph.distinct, "pairs_phase3": 0, "scans": 2 + 2 * covered.bit_count()}
    order = validate.anchor_order(stats, free_columns)
    accepted: dict[int, tuple[str, int]] = {}
    anchors: set[int] = set()
    tasks = int(relation.rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    clusterings = validate.Clusterings(relation, validate.Spread(stats, n, tasks))
    try:
        return _rounds(relation, options, report, stats, graph, free_columns, order, accepted, anchors, clusterings)
    finally:
        clusterings.release()


def _rounds(relation: Relation, options: DiscoveryOptions, report: Report, stats, graph, free_columns: int, order: list[int], accepted: dict[int, tuple[str, int]], anchors: set[int], clusterings: validate.Clusterings) -> DiscoveryResult:
    """Enumerates, validates and refines until nothing new appears."""
    names, m = relation.names, relation.m
    while True:
        if graph.edges and graph.edges[0] == 0:
            if options.on_duplicates == "error":
                raise DuplicateRows("the table holds duplicate rows, so no column set is a key")
            return DiscoveryResult(names, [], [0], stats, _finished(report, graph, stats, anchors, accepted))
        with report.timed("enumerate"):
            found = minimal_hitting_sets(graph.edges, m, options.edge_choice)
        fresh = [c for c in found if c not in accepted]
        free, check = validate.split_free(fresh, free_columns)
        turn = len(report["rounds"]) + 1
        accepted |= {c: ("free", turn) for c in free}
        row = {"enumerated": len(fresh), "free": len(free), "checked": len(check), "rejected": 0}
        report["rounds"].append(row)
        if not check:
            break
        rejected: dict[int, tuple[int, int]] = {}
        with report.timed("validate"):
            batches = validate.plan_batches(check, order)
            anchors.update(anchor for anchor, _ in batches)
            if options.validation == "clustered":
                made, read = clusterings.made, clusterings.read
                rejected = validate.validate_round(clusterings, check, order)
                report["scans"] += clusterings.made - made + clusterings.read - read
            else:
                for _, masks in batches:
                    report["scans"] += len(masks) if options.validation == "naive" else 1
                    rejected |= validate.validate_batch(relation, masks, options.validation)
            accepted |= {c: ("validated", turn) for c in check if c not in rejected}
            if rejected:
                report["scans"] += 2  # marked rows, and whole rows of those that collide
                found_masks, pairs = validate.conflict_masks(relation, rejected, options.pair_mode, clusterings)
                report["pairs_phase3"] += pairs
                graph.absorb(sorted(found_masks))
                clusterings.forget_groups()
        row["rejected"] = len(rejected)
        if not rejected:
            break
    keys = sorted(accepted, key=lambda k: (k.bit_count(), k))
    return DiscoveryResult(names, keys, graph.edges, stats, _finished(report, graph, stats, anchors, accepted), accepted)


def _finished(report: Report, graph, stats, anchors, accepted) -> Report:
    s, rounds = report["seconds"], report["rounds"]
    report["phase_seconds"] = {"evidence": sum(s[k] for k in ("decompose", "type", "generate", "supplement")), "enumerate": s["enumerate"], "validate": s["validate"]}
    report["total_seconds"] = sum(report["phase_seconds"].values())
    report["pairs"] = report["pairs_phase1"] + report["sample_pairs"] + report["pairs_phase3"]
    total = sum(r["enumerated"] for r in rounds)
    report["free_share_first"] = rounds[0]["free"] / rounds[0]["enumerated"] if rounds and rounds[0]["enumerated"] else 1.0
    report["free_share"] = sum(r["free"] for r in rounds) / total if total else 1.0
    report["validation_rounds"] = sum(r["checked"] > 0 for r in rounds)
    report["maintained_rows"] = validate.maintained_rows(stats, anchors)
    report |= {"keys": len(accepted), "edges": len(graph.edges), "largest_key": max((k.bit_count() for k in accepted), default=0)}
    report["per_column"] = {i: {"masks": a, "pairs": b} for i, (a, b) in graph.per_column.items()}
    return report


def is_key(df: DataFrame, columns: Sequence[str]) -> bool:
    """No two rows agree on all of ``columns``; the empty set is a key of at most one row."""
    if not columns:
        return df.limit(2).count() <= 1
    return not validate.conflict_groups(df, [f"`{c}`" for c in columns]).limit(1).count()


def is_minimal_key(df: DataFrame, columns: Sequence[str]) -> bool:
    """A key none of whose columns can go."""
    return is_key(df, columns) and all(not is_key(df, [c for c in columns if c != d]) for d in columns)


def implies_key(columns: Sequence[str], keys: Sequence[Sequence[str]]) -> bool:
    """Whether the minimal keys show ``columns`` to be a key."""
    return any(set(k) <= set(columns) for k in keys)


def why_not_key(df: DataFrame, columns: Sequence[str], groups: int = 5) -> DataFrame:
    """Rows of the first few conflict groups, with the group's size: why ``columns`` is no key."""
    names = [f"`{c}`" for c in columns]
    top = validate.conflict_groups(df, names).orderBy(F.col("cnt").desc(), *names).limit(groups).select(*[F.col(c).alias(f"_{i}") for i, c in enumerate(names)], F.col("cnt").alias("group_rows"))
    on = F.lit(True)
    for i, c in enumerate(names):
        on = on & F.col(c).eqNullSafe(F.col(f"_{i}"))
    return df.join(F.broadcast(top), on).drop(*[f"_{i}" for i in range(len(names))])


_WIDTH = {"boolean": 1, "tinyint": 1, "smallint": 2, "int": 4, "date": 4, "float": 4, "bigint": 8, "double": 8, "timestamp": 8, "timestamp_ntz": 8}


def rank_keys(result: DiscoveryResult, df: DataFrame) -> DataFrame:
    """(key, n_columns, null_columns, width, rank): fewest columns, then no nulls, then narrowest types."""
    kind = dict(df.dtypes)
    rows = []
    for k in result.keys:
        cols = mask_columns(k, result.names)
        rows.append((",".join(cols), len(cols), sum(result.stats[i].nulls > 0 for i in bits(k)), sum(_WIDTH.get(kind.get(c, ""), 32) for c in cols)))
    rows.sort(key=lambda r: (r[1], r[2], r[3], r[0]))
    return df.sparkSession.createDataFrame([(*r, i + 1) for i, r in enumerate(rows)], "key string, n_columns int, null_columns int, width int, rank int")


def key_diff(a: DiscoveryResult, b: DiscoveryResult, spark: SparkSession) -> DataFrame:
    """(key, side): keys held by one of two results only, or by both."""
    x = a.keys_df(spark).select("key", F.lit(True).alias("first"))
    y = b.keys_df(spark).select("key", F.lit(True).alias("second"))
    side = F.when(F.col("first") & F.col("second"), "both").when(F.col("first"), "first").otherwise("second")
    return x.join(y, "key", "full_outer").select("key", side.alias("side"))


def key_mask(result: DiscoveryResult, columns: Sequence[str]) -> int:
    return mask_of(columns, result.names)
