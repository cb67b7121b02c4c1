"""The contract queries of the operators: thin wrappers over whole tables."""

from __future__ import annotations

import hashlib
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyscout.llm.labelled import fold
from keyscout.llm.language import identify_languages, train_language_model
from keyscout.llm.lines import apply_keep_bitmaps, line_keep_bitmaps
from keyscout.llm.mixing import score_documents
from keyscout.llm.neardup import minhash_near_duplicates
from keyscout.llm.packing import pack_documents
from keyscout.llm.quality import score_quality, train_quality_vote
from keyscout.llm.topk import exact_top_k
from keyscout.llm.toxicity import score_toxicity, train_toxicity
from keyscout.llm.transducer import encoding_digests
from keyscout.llm.vectors import near_duplicate_vectors


def tokenizer_path(name: str) -> str:
    """Place of a public tokenizer's file on this machine (the same on every machine of the cluster)."""
    import public_tokenizers

    return str(public_tokenizers.path(name))


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash_near_duplicates(_table(spark, sf_dir, "documents"), percent=85)


def op2_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(_table(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"))


def op3_context_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_documents(_table(spark, sf_dir, "documents"), folds=7, held=2)


def op4_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    found = identify_languages(docs.select("doc_id", "text"), train_language_model(docs, folds=4, held=2))
    return found.select("doc_id", F.coalesce(fold("doc_id", 4) == 2, F.lit(False)).alias("held_out"), "lang_pred", "score", "lang_shares")


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")

    def digests(batches):
        for batch in batches:
            texts = batch.column(1).to_pylist()
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), batch.column(3), pa.array([hashlib.sha256(t.encode()).hexdigest() for t in texts], pa.string())], names=["doc_id", "n_lines", "n_dropped", "kept_sha256"])

    return apply_keep_bitmaps(docs, line_keep_bitmaps(docs)).mapInArrow(digests, "doc_id long, n_lines long, n_dropped long, kept_sha256 string")


def op6_subword_transducer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encoding_digests(_table(spark, sf_dir, "documents"), tokenizer_path("piece_bpe_32k.model"))


def op7_quality_vote(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    return score_quality(docs, train_quality_vote(docs, _table(spark, sf_dir, "labels"), folds=3, held=1), folds=3, held=1)


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    scored = score_toxicity(docs, train_toxicity(docs, _table(spark, sf_dir, "labels"), folds=3, held=1))
    return scored.select("doc_id", F.coalesce(fold("doc_id", 3) == 1, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def op9_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicate_vectors(_table(spark, sf_dir, "embeddings"), least=0.95)


def op10_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = _table(spark, sf_dir, "embeddings")
    return exact_top_k(vectors, vectors.where(F.col("vec_id") % 100 == 0), k=10)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_minhash_near_dedup": op1_minhash_near_dedup,
        "op2_best_fit_packing": op2_best_fit_packing,
        "op3_context_mixing": op3_context_mixing,
        "op4_language_id": op4_language_id,
        "op5_line_dedup": op5_line_dedup,
        "op6_subword_transducer": op6_subword_transducer,
        "op7_quality_vote": op7_quality_vote,
        "op8_toxicity": op8_toxicity,
        "op9_embedding_near_dedup": op9_embedding_near_dedup,
        "op10_exact_top_k": op10_exact_top_k,
    }
