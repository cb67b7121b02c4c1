"""Quality by voting of nearest labelled neighbours in a latent space (operator 7).

Texts become idf-weighted counts of hashed byte pairs, projected on the main singular
directions of a bounded labelled sample.  The labelled vectors are broadcast (their
number is a parameter) and every text meets all of them in exact blocked products.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyscout.llm.labelled import class_sample, fold, sample_texts
from keyscout.llm.text import Words, chunks, string_buffers

#: hashed byte-pair features, latent dimensions, labelled documents per class, voters
BINS, DIMENSIONS, PER_CLASS, VOTERS = 4096, 48, 1500, 25


#: pseudo-terms of form behind the byte pairs, and their weight beside a byte pair's
FORMS, FORM_WEIGHT = 6, 12.0
#: terms in all, and texts whose terms are held at a time
TERMS, ROWS = BINS + FORMS, 1024


def _forms(column: pa.Array) -> np.ndarray:
    """(texts, FORMS) shares that repeated or run-together text raises."""
    words = Words(column)
    n = words.n_texts
    out = np.zeros((n, FORMS))
    if not len(words.hash):
        return out
    count = np.maximum(words.count, 1)
    order = np.lexsort((words.hash, words.owner))
    h, o = words.hash[order], words.owner[order]
    for k in (1, 2):
        if len(h) > k:
            same = (words.hash[k:] == words.hash[:-k]) & (words.owner[k:] == words.owner[:-k])
            out[:, k - 1] = np.bincount(words.owner[k:][same], minlength=n) / count
    repeated = np.bincount(o[1:][(h[1:] == h[:-1]) & (o[1:] == o[:-1])], minlength=n) / count
    size = words.end - words.start
    out[:, 2] = np.maximum(repeated - 0.5, 0)
    out[:, 3] = np.bincount(words.owner[size > 14], minlength=n) / count
    out[:, 4] = np.bincount(words.owner[size == 1], minlength=n) / count
    out[:, 5] = np.bincount(words.owner[size > 40], minlength=n) / count
    return np.sqrt(out)


def _counts(column: pa.Array) -> np.ndarray:
    """(texts, TERMS) term weights: byte pairs, then the pseudo-terms of form."""
    return np.hstack([_pair_counts(column), (FORM_WEIGHT * _forms(column)).astype(np.float32)])


def _pair_counts(column: pa.Array) -> np.ndarray:
    """(texts, BINS) log-scaled counts of byte pairs; digits count as one digit."""
    raw, at = string_buffers(column)
    n = len(at) - 1
    if len(raw) < 2:
        return np.zeros((n, BINS), np.float32)
    b = raw.astype(np.uint32)
    b[(b >= 48) & (b < 58)] = 48
    code = ((b[:-1] << 8 | b[1:]) * np.uint32(2654435761)) >> np.uint32(20)
    owner = np.repeat(np.arange(n), np.diff(at))
    inside = owner[:-1] == owner[1:]
    counts = np.bincount(owner[:-1][inside] * BINS + code[inside], minlength=n * BINS)
    return np.log1p(counts.reshape(n, BINS)).astype(np.float32)


def _unit(x: np.ndarray) -> np.ndarray:
    norm = np.sqrt((x * x).sum(1, keepdims=True))
    return x / np.where(norm > 0, norm, 1)


class NeighbourVote:
    """Projection, labelled unit vectors, their labels and class weights."""

    def __init__(self, counts: np.ndarray, labels: np.ndarray, weights: np.ndarray, voters: int = VOTERS):
        df = (counts > 0).sum(0)
        self.idf = np.log((len(counts) + 1) / (df + 1)).astype(np.float32) + 0.1
        x = _unit(counts * self.idf)
        self.basis = self._directions(x)
        self.vectors, self.labels, self.weights, self.voters = _unit(x @ self.basis), labels, weights, voters
        self.base = float((weights * labels).sum() / weights.sum()) if len(labels) else 0.5

    @staticmethod
    def _directions(x: np.ndarray) -> np.ndarray:
        """Leading right singular vectors by subspace iteration from a fixed start."""
        if not len(x):
            return np.zeros((TERMS, 1), np.float32)
        k = min(DIMENSIONS, len(x), TERMS)
        q = np.random.default_rng(7).standard_normal((x.shape[1], k + 8)).astype(np.float32)
        for _ in range(4):
            q, _ = np.linalg.qr(x.T @ (x @ q))
        _, _, v = np.linalg.svd(x @ q, full_matrices=False)
        return np.ascontiguousarray((q @ v.T)[:, :k], np.float32)

    def score(self, counts: np.ndarray) -> np.ndarray:
        """Similarity-weighted share of label 1 among the nearest; the base rate without any similar one."""
        if not len(self.labels):
            return np.full(len(counts), self.base)
        y = _unit(_unit(counts * self.idf) @ self.basis)
        near = y @ self.vectors.T
        k = min(self.voters, near.shape[1])
        at = np.argpartition(-near, k - 1, axis=1)[:, :k]
        sim = np.maximum(np.take_along_axis(near, at, 1), 0).astype(np.float64) ** 8 * self.weights[at]
        total = sim.sum(1)
        return np.where(total > 0, (sim * self.labels[at]).sum(1) / np.where(total > 0, total, 1), self.base)


def train_quality_vote(documents: DataFrame, labels: DataFrame, label: str = "quality", folds: int = 3, held: int = 1, per_class: int = PER_CLASS) -> NeighbourVote:
    """Vectors of up to ``per_class`` labelled training documents of each class."""
    texts = sample_texts(documents, class_sample(labels, label, per_class, folds, held))

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in chunks(batch, rows=ROWS):
                rows = _counts(part.column(1)).astype(np.float16)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2).cast(pa.float64()), part.column(3).cast(pa.float64()), pa.array([r.tobytes() for r in rows], pa.binary())], names=["doc_id", "label", "class_rows", "counts"])

    # bounded: per_class rows for each class
    rows = texts.mapInArrow(features, "doc_id long, label double, class_rows double, counts binary").toArrow().sort_by("doc_id")
    y = rows.column("label").to_numpy()
    counts = np.frombuffer(b"".join(rows.column("counts").to_pylist()), np.float16).reshape(-1, TERMS).astype(np.float32)
    drawn = {v: (y == v).sum() for v in np.unique(y)}
    weight = np.array([n / drawn[v] for n, v in zip(rows.column("class_rows").to_pylist(), y)])
    return NeighbourVote(counts, y, weight)


def score_quality(documents: DataFrame, model: NeighbourVote, folds: int = 3, held: int = 1) -> DataFrame:
    """(doc_id, held_out, score, predicted): score in 0..1, predicted = score >= 0.5.

    Only ``text`` feeds the score.  Null and empty texts have no terms and get the base
    rate; a null ``doc_id`` is scored and counts as not held out.
    """
    shared = documents.sparkSession.sparkContext.broadcast(model)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in chunks(batch, rows=ROWS):
                score = np.clip(shared.value.score(_counts(part.column(1))), 0, 1)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(score, pa.float64())], names=["doc_id", "score"])

    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    scored = docs.mapInArrow(work, "doc_id long, score double")
    return scored.select("doc_id", F.coalesce(fold("doc_id", folds) == held, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
