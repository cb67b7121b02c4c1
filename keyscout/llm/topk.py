"""Exact integer top-k search by tiled matrix products (operator 10).

Queries go out in blocks of fixed size (so what is broadcast is bounded), every row
is scored against the block tile by tile, each task keeps one running top list per
query, and lists merge in a tree: within a task, within groups of tasks, overall.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: queries broadcast at once, queries and rows of one matrix product
BLOCK, QUERIES, ROWS = 8192, 512, 4096


def _vectors(column: pa.Array, ids: pa.Array) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """Usable vectors by length: {length: (ids, floor(1024 x))}; null, empty-of-numbers or non-finite ones are left out."""
    out: dict[int, tuple[list, list]] = {}
    lengths = np.array([len(x) if x.is_valid else -1 for x in column]) if column.null_count else np.diff(column.offsets.to_numpy())
    flat = column.flatten()
    at = np.r_[0, np.cumsum(np.maximum(lengths, 0))]
    values = flat.cast(pa.float64()).fill_null(np.nan).to_numpy(zero_copy_only=False)
    names = ids.cast(pa.int64()).fill_null(0).to_numpy(zero_copy_only=False)
    known = ids.is_valid().to_numpy(zero_copy_only=False)
    for size in np.unique(lengths):
        if size < 0:
            continue
        rows = np.flatnonzero((lengths == size) & known)
        if not len(rows):
            continue
        matrix = values[at[rows][:, None] + np.arange(size)] if size else np.zeros((len(rows), 0))
        good = np.isfinite(matrix).all(1)
        out[int(size)] = (names[rows][good], np.floor(1024 * matrix[good]))
    return out


def _products(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Exact inner products: doubles while every partial sum fits 53 bits, else whole numbers held to the long range."""
    if not q.size or not x.size:
        return np.zeros((len(q), len(x)))
    bound = np.abs(q).max() * np.abs(x).max() * q.shape[1]
    if bound < 2.0**53:
        return q @ x.T
    if bound < 2.0**63:
        return q.astype(np.int64) @ x.astype(np.int64).T
    whole = np.vectorize(int, otypes=[object])
    return np.clip(whole(q) @ whole(x).T, 1 - (1 << 63), (1 << 63) - 1).astype(np.int64)


def _best(scores: np.ndarray, ids: np.ndarray, k: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """Per row the k best (score, id), ties to the smaller id."""
    out = []
    n = scores.shape[1]
    cut = np.partition(scores, n - k, axis=1)[:, n - k] if n > k else None
    for i, row in enumerate(scores):
        own = ids if ids.ndim == 1 else ids[i]
        at = np.flatnonzero(row >= cut[i]) if cut is not None else np.arange(n)
        at = at[np.lexsort((own[at], -row[at]))][:k]
        out.append((row[at].astype(np.int64), own[at]))
    return out


def exact_top_k(vectors: DataFrame, queries: DataFrame, k: int = 10, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score): each query's k best rows by integer inner product.

    A component x counts as floor(1024 x); a query's own id is no candidate; fewer than
    k candidates give all.  Vectors that are null, hold null or non-finite components,
    or have a null id take no part; a query meets only vectors of its own length.
    Repeated rows are candidates each; a repeated query id is asked once (its first row
    in vector order).  Scores beyond the long range are held to it.  Empty tables give
    an empty result; other columns are ignored.
    """
    spark = vectors.sparkSession
    asked = queries.select(F.col(id_col).cast("long").alias("query_id"), F.col(vector_col).alias("vector")).where("query_id is not null and vector is not null").groupBy("query_id").agg(F.min("vector").alias("vector"))
    data = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).alias("vector"))
    blocks = asked.select(F.count("*")).first()[0] // BLOCK + 1
    asked = asked.withColumn("block", F.pmod(F.xxhash64("query_id"), F.lit(blocks)))
    schema = "query_id long, task int, vec_id long, score long"
    out = None
    for block in range(blocks):
        rows = asked.where(F.col("block") == block).select("query_id", "vector").toArrow().combine_chunks()
        wanted = {n: v for b in rows.to_batches() for n, v in _vectors(b.column(1), b.column(0)).items() if len(v[0])}
        shared = spark.sparkContext.broadcast(wanted)
        part = data.mapInArrow(_scan(shared, k), schema)
        out = part if out is None else out.unionByName(part)

    def merged(df: DataFrame, *group: str) -> DataFrame:
        best = Window.partitionBy(*group).orderBy(F.col("score").desc(), "vec_id")
        return df.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)

    middle = merged(out.withColumn("branch", F.pmod("task", F.lit(32))), "query_id", "branch").drop("rank", "branch")
    return merged(middle, "query_id").select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def _scan(shared, k: int):
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        wanted = shared.value
        top = {n: [(np.zeros(0, np.int64), np.zeros(0, np.int64))] * len(v[0]) for n, v in wanted.items()}
        for batch in batches:
            for size, (ids, matrix) in _vectors(batch.column(1), batch.column(0)).items():
                if size not in wanted:
                    continue
                names, asked = wanted[size]
                lists = top[size]
                for r in range(0, len(ids), ROWS):
                    own, tile = ids[r : r + ROWS], matrix[r : r + ROWS]
                    for q in range(0, len(names), QUERIES):
                        scores = _products(asked[q : q + QUERIES], tile)
                        valid = names[q : q + QUERIES, None] != own[None, :]
                        for i, (s, v) in enumerate(_best_valid(scores, own, valid, k)):
                            have = lists[q + i]
                            s, v = np.r_[have[0], s], np.r_[have[1], v]
                            at = np.lexsort((v, -s))[:k]
                            lists[q + i] = (s[at], v[at])
        task = TaskContext.get().partitionId()
        for size, lists in top.items():
            n = [len(s) for s, _ in lists]
            if sum(n):
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.repeat(wanted[size][0], n)), pa.array(np.full(sum(n), task, np.int32)), pa.array(np.concatenate([v for _, v in lists])), pa.array(np.concatenate([s for s, _ in lists]))],
                    names=["query_id", "task", "vec_id", "score"],
                )

    return work


def _best_valid(scores, ids, valid, k):
    if valid.all():
        return _best(scores, ids, k)
    return [_best(scores[i : i + 1, ok], ids[ok], k)[0] if not (ok := valid[i]).all() else _best(scores[i : i + 1], ids, k)[0] for i in range(len(scores))]
