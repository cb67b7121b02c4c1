"""Lineage cuts that survive lost executors, and connected components as DataFrame rounds."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """The folder ``spark.checkpoint.dir`` names; a temporary one only for a local master that names none."""
    place = spark.conf.get("spark.checkpoint.dir", None)
    if place is None and not (spark.sparkContext.master + "[").startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    return (place or tempfile.mkdtemp(prefix="checkpoints")).rstrip("/")


_FREE = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def durable(df: DataFrame, once: bool = False) -> DataFrame:
    """Eager checkpoint in the shared folder of the session.

    ``once``: the exchanges below serve this checkpoint alone, so their files leave the
    disk when it is written, whatever still refers to ``df``.
    """
    spark = df.sparkSession
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(shared_folder(spark))
    if not once:
        return df.checkpoint(eager=True)
    before = spark.conf.get(_FREE, None)
    spark.conf.set(_FREE, "true")
    try:
        return df.select("*").checkpoint(eager=True)  # a plan keeps the setting that it was made under
    finally:
        spark.conf.unset(_FREE) if before is None else spark.conf.set(_FREE, before)


def connected_components(edges: DataFrame) -> DataFrame:
    """(node, component): the smallest id reachable over undirected ``edges(a, b)``.

    Each round takes the least label among a node's neighbours (aggregated before
    the shuffle, so a hub costs one row per task) and then jumps to the label's own
    label, which halves chains.  Only nodes with an edge appear in the result; an
    empty edge table gives an empty result.  Labels only fall, so the loop ends.
    """
    both = durable(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct())
    labels = both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("low")).select("node", F.least("node", "low").alias("component"))
    labels = durable(labels)
    while True:
        around = both.join(labels.select(F.col("node").alias("b"), "component"), "b").groupBy(F.col("a").alias("node")).agg(F.min("component").alias("near"))
        pulled = labels.join(around, "node").select("node", F.col("component").alias("old"), F.least("component", "near").alias("component"))
        up = labels.select(F.col("node").alias("component"), F.col("component").alias("top"))
        # a label is always the id of a node, so the inner join keeps every row
        jumped = pulled.join(up, "component").select("node", F.least("component", "top").alias("component"), (F.least("component", "top") < F.col("old")).alias("moved"))
        jumped = durable(jumped)
        labels = jumped.select("node", "component")
        if jumped.where("moved").limit(1).count() == 0:
            return labels
