"""Corpus preparation in five stages: language, toxicity, repeated lines, near duplicates, packing.

Every stage but the last returns the columns of ``documents``; between stages the rows
are written as Parquet in the session's shared checkpoint folder and read again.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyscout.llm.cluster import shared_folder
from keyscout.llm.language import keep_identified, train_language_model
from keyscout.llm.lines import apply_keep_bitmaps, line_keep_bitmaps
from keyscout.llm.neardup import keep_first_of_groups
from keyscout.llm.packing import pack_documents
from keyscout.llm.queries import tokenizer_path
from keyscout.llm.toxicity import keep_below, train_toxicity


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops texts without letters (null and empty ones too) and texts in which no language holds two fifths.

    Repeated rows are judged each; an empty table stays empty.
    """
    return keep_identified(docs, train_language_model(docs), least=0.4)


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops texts whose calibrated toxicity is 0.7 or more.

    Null and empty texts are scored as texts without words; without labels of both classes all stay
    or go by the base rate.
    """
    model = train_toxicity(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return keep_below(docs, model, most=0.7)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Takes repeated lines out of all but the largest document; ``n_chars`` follows the text.

    Every row stays, null texts as empty ones.
    """
    out = apply_keep_bitmaps(docs, line_keep_bitmaps(docs), counts=False)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.char_length("text").cast(docs.schema["n_chars"].dataType))
    return out.select(*[F.col(f"`{c}`") for c in docs.columns])


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of every near-duplicate group (five-word shingles, similarity 0.8).

    Texts without words belong to no group and stay; rows repeated with id and text stay once.
    """
    return keep_first_of_groups(docs, percent=80, width=5)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs the kept documents into sequences of 2048 tokens; null and empty texts take one end token."""
    return pack_documents(docs, tokenizer_path("word_bpe_49k.json"))


STAGES = [("language_id", language_id), ("toxicity", toxicity), ("line_dedup", line_dedup), ("near_dedup", near_dedup), ("packing", packing)]

#: the stages' models and token ids have no SQL; tests compare the stages with brute force
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the whole documents table."""
    place = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    rows = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        stage(spark, rows, sf_dir).write.parquet(f"{place}/{k}-{name}")
        rows = spark.read.parquet(f"{place}/{k}-{name}")
    return rows
