import decimal
import itertools
import random

import pytest
from pyspark.sql import functions as F

from keyscout.functions.masks import bits, minimal_masks
from keyscout.operators import baselines, evidence, measures, prepare, profile, validate
from keyscout.operators.discover import DiscoveryOptions, DuplicateRows, discover_keys, implies_key, is_key, is_minimal_key, rank_keys, why_not_key
from keyscout.plans.hitting import minimal_hitting_sets
from keyscout.queries import part_example, running_conflict
from keyscout.sources import tables



def by_definition(rows, m):
    """Minimal keys of distinct rows by testing every column set."""
    found = [s for s in range(1 << m) if len({tuple(r[i] for i in bits(s)) for r in rows}) == len(rows)]
    return sorted(minimal_masks(found), key=lambda x: (x.bit_count(), x))


def random_rows(seed, n, m, size):
    draw = random.Random(seed)
    return sorted({tuple(draw.randrange(size) for _ in range(m)) for _ in range(n)})


@pytest.mark.parametrize("seed,n,m,size", [(1, 40, 5, 3), (2, 40, 7, 3), (3, 25, 8, 2), (4, 12, 4, 4)])
def test_random_relations(spark, seed, n, m, size):
    rows = random_rows(seed, n, m, size)
    df = spark.createDataFrame(rows, [f"x{i}" for i in range(m)])
    want = by_definition(rows, m)
    for options in (DiscoveryOptions(), DiscoveryOptions(factor=0.1, sampling="off", fallback_multiplier=1), DiscoveryOptions(factor=0.05, pair_mode="star", fallback_multiplier=1)):
        result = discover_keys(df, options)
        assert result.keys == want
        assert all(r["rejected"] == 0 or r["checked"] for r in result.report["rounds"])
    # the final masks are those of the full hypergraph
    full = (1 << m) - 1
    pairs = [sum(1 << i for i in range(m) if a[i] != b[i]) for a, b in itertools.combinations(rows, 2)]
    assert sorted(result.edges) == sorted(minimal_masks(v for v in pairs if v != full) or [full])


def test_worked_example(spark):
    df = part_example(spark)
    result = discover_keys(df)
    assert set(result.key_names()) == {("PKEY",), ("NAME",), ("PRICE",), ("MFGR", "TYPE"), ("BRAND", "TYPE")}
    assert [(int(s.agree_pairs), s.longest_run) for s in profile.column_stats(df).orderBy("col_ix").collect()] == [(0, 1), (0, 1), (7, 3), (1, 2), (8, 3), (0, 1)]
    assert sorted(result.edges) == [0b101111, 0b110011] and result.report["rounds"][0]["checked"] == 0


def test_running_conflict(spark, sf):
    rows = running_conflict(spark, sf).collect()
    assert rows and all(r.mask & ~0b10001 == 0 for r in rows)


def test_budgets():
    assert profile.pair_budget(10) == 99 and profile.pair_budget(20, 1) == 86
    # budgets reported for six relation sizes (fixed values)
    for n, want in ((6001215, 405384891), (11997996, 846445064), (29999795, 2235445161), (59986052, 4649781104), (89987373, 7133268257), (119994608, 9661387823)):
        assert profile.pair_budget(n) == want
    stats = [profile.ColumnStats(i, str(i), 1, p, 1, 0) for i, p in enumerate((50, 10, 900))]
    assert profile.fallback_budget(stats) == 50 and profile.covered_mask(stats, 50) == 0b011
    assert profile.gap_budget(stats, 1000) == 50


def test_lineitem_figures(spark, sf01):
    df = tables.sf_table(spark, sf01, "lineitem")
    r = discover_keys(df, DiscoveryOptions(ownership=False))
    assert len(r.keys) == 45 and len(r.edges) == 44
    assert r.report["pairs_phase1"] == 1738991 and r.report["covered_columns"] == 4
    masks = {r.names[i]: v["masks"] for i, v in r.report["per_column"].items()}
    assert masks == {"l_extendedprice": 29, "l_orderkey": 136, "l_partkey": 163, "l_shipdate": 161}
    assert len(discover_keys(df).keys) == 45


def test_covered_count_moves_with_the_factor(spark, sf01):
    stats = profile.relation_stats(prepare.encode_columns(tables.sf_table(spark, sf01, "lineitem")))
    counts = [profile.covered_mask(stats, profile.pair_budget(60000, f)).bit_count() for f in (0.1, 0.5, 0.9, 1, 3, 20)]
    assert counts == [1, 2, 3, 4, 4, 5]


def test_small_budget_moves_work_to_validation(spark, sf):
    df = tables.sf_table(spark, sf, "lineitem")
    few, many = (discover_keys(df, DiscoveryOptions(factor=f)).report for f in (0.05, 20))
    checked = lambda r: sum(x["checked"] for x in r["rounds"])
    assert few["pairs_phase1"] < many["pairs_phase1"] and checked(few) > checked(many)
    assert few["free_share_first"] < many["free_share_first"]


def test_free_candidates_pass_validation(spark, sf):
    df = tables.sf_table(spark, sf, "orders")
    result = discover_keys(df)
    free = [k for k, (how, _) in result.how.items() if how == "free"]
    assert free and not validate.validate_batch(prepare.encode_columns(df), free, "naive")


def test_sizes_and_duplicates(spark):
    one = spark.createDataFrame([(1, 2)], "a int, b int")
    assert discover_keys(one).keys == [0] and discover_keys(one.limit(0)).keys == [0]
    two = spark.createDataFrame([(1, 2), (1, 3)], "a int, b int")
    assert discover_keys(two).key_names() == [("b",)]
    unique = spark.createDataFrame([(i, i) for i in range(5)], "a int, b int")
    assert discover_keys(unique).key_names() == [("a",), ("b",)]
    same = spark.createDataFrame([(1, 2), (1, 2), (3, 4)], "a int, b int")
    assert discover_keys(same).keys == [] and prepare.has_duplicate_rows(same)
    assert discover_keys(same, DiscoveryOptions(on_duplicates="dedup")).key_names() == [("a",), ("b",)]
    with pytest.raises(DuplicateRows):
        discover_keys(same, DiscoveryOptions(on_duplicates="error"))


def test_values_and_types(spark):
    rows = [(0.0, float("nan"), decimal.Decimal("1.0"), 1), (-0.0, 1.0, decimal.Decimal("1.0"), 2), (1.0, float("nan"), decimal.Decimal("2.0"), 2)]
    df = spark.createDataFrame(rows, "a double, b double, c decimal(5,1), d int")
    assert set(discover_keys(df).key_names()) == {("a", "b"), ("a", "d"), ("b", "c"), ("b", "d"), ("c", "d")}
    nested = df.select(F.struct("a", "b").alias("s"), "d")
    assert set(discover_keys(nested).names) == {"s_a", "s_b", "d"}
    with pytest.raises(TypeError):
        discover_keys(df.select(F.create_map(F.lit(1), "a").alias("m")))


@pytest.mark.parametrize("mode", ["native", "rank", "hash128"])
def test_nulls(spark, mode):
    rows = [(1, None), (1, 2), (None, None), (None, 3)]
    df = spark.createDataFrame(rows, "a int, b int")
    assert discover_keys(df, DiscoveryOptions(encoding=mode)).key_names() == [("a", "b")]
    if mode == "native":
        assert discover_keys(df, DiscoveryOptions(null_policy="null_distinct")).key_names() == [("b",)]


def test_many_columns(spark):
    """70 columns: masks of two words."""
    rows = [tuple((r >> (c - 63)) & 1 if c >= 63 else 0 for c in range(70)) for r in range(100)]
    result = discover_keys(spark.createDataFrame(rows, [f"x{i}" for i in range(70)]), DiscoveryOptions(fallback_multiplier=1))
    assert result.key_names() == [tuple(f"x{i}" for i in range(63, 70))]


def test_tiles_do_not_change_masks(spark, sf):
    relation = prepare.encode_columns(tables.sf_table(spark, sf, "lineitem"))
    frames = [evidence.pair_masks_for_column(relation, 3, tile=t) for t in (100, 5000)]
    a, b = (sorted(map(tuple, f.collect())) for f in frames)
    assert a == b


def test_validation_methods_agree(spark, sf):
    relation = prepare.encode_columns(tables.sf_table(spark, sf, "lineitem"))
    masks = [0b1100, 0b11100, 0b111100, 0b1000011, 0b1010001]
    got = [validate.validate_batch(relation, masks, m) for m in ("clustered", "grouping_sets", "naive")]
    assert got[0] == got[1] == got[2]


def test_no_exchange_above_the_clustering(spark, sf):
    relation = prepare.encode_columns(tables.sf_table(spark, sf, "lineitem"))
    rows = validate.clustered_by(relation, [0b1100, 0b11100])
    rows.count()
    plan = validate.conflict_groups(rows, ["c2", "c3"])._jdf.queryExecution().executedPlan().toString()
    above = plan[: plan.index("InMemoryTableScan")]
    rows.unpersist()
    assert "Exchange hashpartitioning" not in above


def test_no_python_in_the_pair_join(spark, sf):
    relation = prepare.encode_columns(tables.sf_table(spark, sf, "orders"))
    plan = evidence.pair_masks_for_column(relation, 1)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "CartesianProduct" not in plan and "NestedLoop" not in plan


def test_baselines_agree(spark, sf):
    df = tables.sf_table(spark, sf, "part").limit(120)
    rows = [tuple(r) for r in df.collect()]
    df = spark.createDataFrame(rows, df.schema)
    want = by_definition(rows, 6)
    for finder in (discover_keys, baselines.discover_keys_exhaustive, baselines.discover_keys_lattice, baselines.discover_keys_pli, baselines.discover_keys_prefix_tree, baselines.discover_keys_random_walk, baselines.discover_keys_hybrid):
        assert finder(df).keys == want, finder.__name__


@pytest.mark.parametrize("finder", [baselines.discover_keys_prefix_tree, baselines.discover_keys_random_walk])
def test_searches_beyond_the_driver(spark, finder):
    """More rows than the driver may hold, and nulls and repeated rows among few."""
    n = 300_000
    many = spark.range(n).select((F.col("id") % 1000).alias("a"), (F.col("id") / 1000).cast("int").alias("b"), (F.col("id") % 7).alias("c"), F.col("id").alias("d"))
    assert finder(many).keys == [0b1000, 0b0011]
    assert finder(spark.createDataFrame([(None, 1), (None, 2), (1, 1)], "a int, b int")).keys == [0b11]
    assert finder(spark.createDataFrame([(None, 1), (None, 1), (1, 1)], "a int, b int")).keys == []


def test_all_pairs_are_counted(spark):
    """Every pair of more rows than could be compared in blocks; few rows against the comparison itself."""
    rows = random_rows(5, 60, 5, 2) + [(None, None, 0, 0, 1), (None, None, 0, 1, 1)]
    relation = prepare.encode_columns(spark.createDataFrame(rows + rows[:3], "a int, b int, c int, d int, e int"))
    want = evidence.tiled_pairs(relation.rows.withColumn("_all", F.lit(0)), ["_all"], relation.columns)
    assert sorted(map(tuple, baselines.all_pair_masks(relation).collect())) == sorted(map(tuple, want.collect()))
    n = 400_000
    many = spark.range(n).select("id", (F.col("id") % 7).alias("x"), F.lit(1).alias("y"))
    found = {r.mask: r.pairs for r in baselines.all_pair_masks(prepare.encode_columns(many)).collect()}
    same = sum(k * (k - 1) // 2 for k in ((n - r + 6) // 7 for r in range(7)))
    assert found == {0b001: same, 0b011: n * (n - 1) // 2 - same}
    assert baselines.discover_keys_exhaustive(many).keys == [1]


def test_stripped_partitions(spark):
    df = spark.createDataFrame([(1, 1), (1, 1), (1, 2), (2, 1), (2, 2)], "a int, b int")
    rows = prepare.encode_columns(df).rows
    a, b = (baselines.stripped_partition(rows, [c]) for c in ("c0", "c1"))
    assert sorted(r["count"] for r in a.groupBy("cluster").count().collect()) == [2, 3]
    assert [r["count"] for r in baselines.intersect_partitions(a, b).groupBy("cluster").count().collect()] == [2]


def test_questions_about_keys(spark, sf):
    df = tables.sf_table(spark, sf, "orders")
    assert is_key(df, ["o_orderkey"]) and not is_key(df, ["o_custkey"]) and not is_key(df, [])
    assert is_minimal_key(df, ["o_orderkey"]) and not is_minimal_key(df, ["o_orderkey", "o_custkey"])
    assert implies_key(["o_orderkey", "o_custkey"], [("o_orderkey",)])
    assert why_not_key(df, ["o_orderstatus"], 1).select("o_orderstatus").distinct().count() == 1
    assert rank_keys(discover_keys(df), df).orderBy("rank").first().n_columns == 1


def test_measures(spark, sf):
    result = discover_keys(tables.sf_table(spark, sf, "orders"))
    assert measures.exactness(result.key_names(), result.key_names()) == (1.0, 1.0)
    assert abs(sum(r.share for r in measures.phase_shares(result, spark).collect()) - 1) < 1e-6
    assert measures.size_summary(result, spark).first()["keys"] == len(result.keys)
    assert measures.memory_peak(spark)["jvm_heap"] > 0
    assert len(minimal_hitting_sets(result.edges, len(result.names))) == len(result.keys)


def test_sources_and_sinks(spark, sf, tmp_path):
    df = tables.sf_table(spark, sf, "part")
    for kind in ("parquet", "orc", "json", "csv"):
        path = f"{tmp_path}/{kind}"
        writer = df.write.option("header", True) if kind == "csv" else df.write
        writer.format(kind).save(path)
        back = tables.read_table(spark, path, kind, ["p_partkey", "p_name"])
        assert back.columns == ["p_partkey", "p_name"] and back.count() == df.count()
    df.createOrReplaceTempView("part_view")
    assert tables.read_table(spark, "part_view", "table").count() == tables.read_table(spark, "SELECT * FROM part_view", "sql").count()
    result = discover_keys(df)
    tables.write_result(result, spark, f"{tmp_path}/result")
    assert spark.read.parquet(f"{tmp_path}/result/keys").count() == len(result.keys)
    tables.write_encoded(df, f"{tmp_path}/codes")
    assert spark.read.parquet(f"{tmp_path}/codes").columns == [*(f"c{i}" for i in range(6)), "rid"]
    result.register(spark)
    assert spark.table("ks_keys").count() == len(result.keys)


def test_pairs_are_counted_where_masks_are_minimised(spark, sf, monkeypatch):
    df = spark.read.parquet(f"{sf}/customer.parquet")
    whole = discover_keys(df)
    monkeypatch.setattr(evidence, "MANY_MASKS", 1)
    small = discover_keys(df)
    assert set(small.keys) == set(whole.keys)
    assert small.report["per_column"] == whole.report["per_column"] and small.report["pairs_phase1"] == whole.report["pairs_phase1"] > 0
    assert small.report["sample_pairs"] == whole.report["sample_pairs"]


def test_batches_spread_the_rows():
    """A batch ends where its shared columns would hold too few values or too long a run for all tasks."""
    stats = [profile.ColumnStats(i, f"x{i}", *v) for i, v in enumerate([(20, 0, 400, 0), (20, 0, 400, 0), (20, 0, 400, 0), (20, 0, 400, 0), (5000, 0, 4000, 0)])]
    spread = validate.Spread(stats, 8000, 8)
    assert not spread.enough(0b1) and spread.enough(0b11)
    assert not spread.enough(0b10000)  # one value holds half of the rows
    masks = [0b00111, 0b01011, 0b10011, 0b11100, 0b11010]
    batches, alone = validate.split_batch(masks, [0, 1, 2, 3, 4], spread)
    assert sorted([*sum(batches, []), *alone]) == sorted(masks)
    assert all(spread.enough(validate.shared_columns(b)) for b in batches) and [0b00111, 0b01011, 0b10011] in map(sorted, batches)


def test_clusterings_are_reused(spark, sf):
    relation = prepare.encode_columns(tables.sf_table(spark, sf, "lineitem"))
    kept = validate.Clusterings(relation, validate.Spread(profile.relation_stats(relation), relation.n, 4))
    order = list(range(relation.m))
    first, second = [0b10011, 0b100011, 0b1000011], [0b110011, 0b1100011]
    rejected = validate.validate_round(kept, first, order)
    assert kept.made == 1
    rejected |= validate.validate_round(kept, second, order)
    kept.release()
    assert kept.made == 1 and rejected == validate.validate_batch(relation, first + second, "naive")


def test_bounded_validation_is_exact(spark, sf, monkeypatch):
    """Few groups a candidate, small jobs and one clustering at a time: more rounds, the same keys and masks."""
    df = tables.sf_table(spark, sf, "lineitem")
    want = discover_keys(df)
    held = []
    make = validate.Clusterings.make

    def watched(self, batch):
        rows = make(self, batch)
        held.append(sum(self.cells(c) for _, c, _ in self.held))
        return rows

    monkeypatch.setattr(validate.Clusterings, "make", watched)
    for name, value in (("MOST_GROUPS", 2), ("PER_JOB", 5), ("JOB_ROWS", 20_000), ("TIDY_ROWS", 1000), ("MOST_CELLS", 50_000)):
        monkeypatch.setattr(validate, name, value)
    got = discover_keys(df, DiscoveryOptions(factor=0.1, sampling=60))
    assert got.keys == want.keys and sorted(got.edges) == sorted(want.edges)
    assert max(held, default=0) <= 50_000 and sum(r["rejected"] for r in got.report["rounds"]) > 0
