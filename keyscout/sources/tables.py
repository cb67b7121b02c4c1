"""Readers and sinks around a discovery run."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession

from keyscout.operators.discover import DiscoveryResult


def read_table(spark: SparkSession, place: str, kind: str = "parquet", columns: list[str] | None = None) -> DataFrame:
    """A table by format (parquet, orc, json, csv with inferred types), catalog name ("table") or SQL ("sql")."""
    if kind == "table":
        df = spark.table(place)
    elif kind == "sql":
        df = spark.sql(place)
    elif kind == "csv":
        df = spark.read.csv(place, header=True, inferSchema=True)
    elif kind in ("parquet", "orc", "json"):
        df = spark.read.format(kind).load(place)
    else:
        raise ValueError(f"unknown source {kind}")
    return df.select(*[f"`{c}`" for c in columns]) if columns else df


def sf_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def wide16(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with its order's columns."""
    line, orders = sf_table(spark, sf_dir, "lineitem"), sf_table(spark, sf_dir, "orders")
    return line.join(orders, line.l_orderkey == orders.o_orderkey).drop("o_orderkey")


def wide28(spark: SparkSession, sf_dir: str) -> DataFrame:
    """wide16 with customer, part and supplier columns, join keys once."""
    w = wide16(spark, sf_dir)
    c, p, s = (sf_table(spark, sf_dir, t) for t in ("customer", "part", "supplier"))
    return w.join(c, w.o_custkey == c.c_custkey).drop("c_custkey").join(p, w.l_partkey == p.p_partkey).drop("p_partkey").join(s, w.l_suppkey == s.s_suppkey).drop("s_suppkey")


def embedding_columns(spark: SparkSession, sf_dir: str, size: int = 64) -> DataFrame:
    """embeddings with one column per component (66 columns: masks of two words)."""
    from pyspark.sql import functions as F

    e = sf_table(spark, sf_dir, "embeddings")
    return e.select("vec_id", *[F.col("embedding")[i].alias(f"e{i}") for i in range(size)], "label")


def write_encoded(df: DataFrame, path: str, mode: str = "rank") -> None:
    """Dictionary-encoded snapshot: fixed-width codes c0.. and rid, as parquet."""
    from keyscout.operators.prepare import encode_columns

    encode_columns(df, mode).rows.write.mode("overwrite").parquet(path)


def write_clustered(df: DataFrame, table: str, columns: list[str], buckets: int) -> None:
    """Table bucketed and sorted by the clustering columns, so later validations need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, *columns).sortBy(*columns).saveAsTable(table)


def write_result(result: DiscoveryResult, spark: SparkSession, path: str) -> None:
    """keys, edges and column statistics as parquet, the report as JSON."""
    result.keys_df(spark).write.mode("overwrite").parquet(f"{path}/keys")
    result.edges_df(spark).write.mode("overwrite").parquet(f"{path}/edges")
    result.stats_df(spark).write.mode("overwrite").parquet(f"{path}/stats")
    spark.createDataFrame([(json.dumps(result.report, default=str),)], "report string").write.mode("overwrite").json(f"{path}/report")
