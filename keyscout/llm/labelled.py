"""Bounded, repeatable samples of labelled rows, and the held-out rule of the contracts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def fold(doc_id: Column | str, folds: int) -> Column:
    """crc32 of the id as text, modulo ``folds`` (null for a null id)."""
    return F.crc32(F.col(doc_id).cast("string") if isinstance(doc_id, str) else doc_id.cast("string")) % folds


def class_sample(labels: DataFrame, label: str, per_class: int, folds: int, held: int) -> DataFrame:
    """(doc_id, label, class_rows): up to ``per_class`` training rows of every label value.

    Training rows are those whose fold is not ``held``; the sample goes by id hashes, so
    it is the same on every run.  ``class_rows`` counts all
    training rows of the class.  Rows with a null id or label are left out; a repeated
    id counts once per label value, and once overall (its least label) in the sample.
    """
    rows = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).alias("label")).where("doc_id is not null and label is not null").where(fold("doc_id", folds) != held)
    counts = rows.groupBy("label").agg(F.count("*").alias("class_rows"))
    order = Window.partitionBy("label").orderBy("h", "doc_id")
    # about twice the rows wanted reach the ranking of a class, however large it is
    near = rows.join(F.broadcast(counts), "label").withColumn("h", F.xxhash64("doc_id"))
    near = near.where(F.pmod("h", F.lit(1 << 20)) * F.col("class_rows") <= F.lit((1 << 20) * (2 * per_class + 200)))
    first = near.withColumn("place", F.row_number().over(order)).where(F.col("place") <= per_class).groupBy("doc_id").agg(F.min(F.struct("label", "class_rows")).alias("s"))
    return first.select("doc_id", "s.label", "s.class_rows")


def sample_texts(documents: DataFrame, sample: DataFrame) -> DataFrame:
    """(doc_id, text, label, class_rows) of a class sample, whose size is bounded by construction."""
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("text is not null")
    return docs.join(F.broadcast(sample), "doc_id").select("doc_id", "text", "label", "class_rows")
