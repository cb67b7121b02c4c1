"""Cost and accuracy measures of a discovery run."""

from __future__ import annotations

import resource
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyscout.operators.discover import DiscoveryResult


def phase_shares(result: DiscoveryResult, spark: SparkSession) -> DataFrame:
    """(phase, seconds, share) of evidence, enumeration and validation."""
    parts = result.report["phase_seconds"]
    total = sum(parts.values()) or 1.0
    return spark.createDataFrame([(k, float(v), float(v / total)) for k, v in parts.items()], "phase string, seconds double, share double")


def phase_one_parts(result: DiscoveryResult, spark: SparkSession) -> DataFrame:
    """(part, seconds) of decomposing, typing, comparing (sorting included: Spark clusters inside the join) and sampling."""
    s = result.report["seconds"]
    return spark.createDataFrame([(k, float(s[k])) for k in ("decompose", "type", "generate", "supplement")], "part string, seconds double")


def candidate_history(result: DiscoveryResult, spark: SparkSession) -> DataFrame:
    """(round, enumerated, free, checked, rejected)."""
    rows = [(i + 1, r["enumerated"], r["free"], r["checked"], r["rejected"]) for i, r in enumerate(result.report["rounds"])]
    return spark.createDataFrame(rows, "round int, enumerated long, free long, checked long, rejected long")


def mask_yield(result: DiscoveryResult, spark: SparkSession) -> DataFrame:
    """(col, pairs, masks, pairs_per_mask) of every covered column."""
    rows = [(result.names[i], v["pairs"], v["masks"], v["pairs"] / max(1, v["masks"])) for i, v in result.report["per_column"].items() if i >= 0]
    return spark.createDataFrame(rows, "col string, pairs long, masks long, pairs_per_mask double")


def io_ratio(result: DiscoveryResult) -> float:
    """Logical reads in table sizes: statistics and snapshot once, two reads per covered column, validation scans."""
    return float(result.report["scans"])


def size_summary(result: DiscoveryResult, spark: SparkSession) -> DataFrame:
    """One row: rows, columns, budget, covered columns, pairs, masks, edges, keys, largest key, rounds, maintained rows, free shares."""
    r = result.report
    row = (r["rows"], r["columns"], r["budget"], r["covered_columns"], r["pairs"], r["distinct_masks"], r["edges"], r["keys"], r["largest_key"], r["validation_rounds"], r["maintained_rows"], r["free_share_first"], r["free_share"], io_ratio(result))
    return spark.createDataFrame([row], "n_rows long, n_columns long, budget long, covered_columns long, pairs long, distinct_masks long, edges long, keys long, largest_key long, validation_rounds long, maintained_rows long, free_share_first double, free_share double, io_ratio double")


def exactness(found: Sequence[tuple[str, ...]], truth: Sequence[tuple[str, ...]]) -> tuple[float, float]:
    """(precision, recall) of a key set."""
    a, b = {frozenset(k) for k in found}, {frozenset(k) for k in truth}
    return (len(a & b) / len(a) if a else 1.0, len(a & b) / len(b) if b else 1.0)


def memory_peak(spark: SparkSession) -> dict[str, int]:
    """Bytes in use: JVM heap of the driver process after a collection, and the driver Python's peak resident set."""
    runtime = spark.sparkContext._jvm.java.lang.Runtime.getRuntime()
    runtime.gc()
    return {"jvm_heap": runtime.totalMemory() - runtime.freeMemory(), "python_peak": resource.getrusage(resource.RUSAGE_SELF).ru_maxrss * 1024}


def list_footprint(df: DataFrame) -> DataFrame:
    """(col, listed_rows, bytes): what position lists hold per column - row ids and cluster ids of all
    rows that have a partner, and the inverse array over every row (8 bytes each)."""
    from keyscout.operators.profile import column_stats

    stats = column_stats(df)
    n = df.count()
    out = []
    for c in df.columns:
        out.append(df.groupBy(f"`{c}`").agg(F.count("*").alias("n")).where("n > 1").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("listed_rows")).select(F.lit(c).alias("col"), "listed_rows"))
    rows = out[0]
    for o in out[1:]:
        rows = rows.unionAll(o)
    return rows.join(stats.select("col", "cardinality"), "col").select("col", "listed_rows", (F.col("listed_rows") * 16 + F.lit(n) * 8).alias("bytes"))


def speed_up(first: Callable[[], DiscoveryResult], second: Callable[[], DiscoveryResult]) -> tuple[float, float, float]:
    """(seconds of first, seconds of second, second / first)."""
    import time

    began = time.perf_counter()
    first()
    middle = time.perf_counter()
    second()
    end = time.perf_counter()
    return middle - began, end - middle, (end - middle) / max(1e-9, middle - began)
