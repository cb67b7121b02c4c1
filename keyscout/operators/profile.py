"""Column statistics, the pair budget and covered columns."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from keyscout.operators.prepare import Relation


#: characters from which a value is counted by its print
LONG_VALUE = 64


@dataclass(frozen=True)
class ColumnStats:
    index: int
    name: str
    cardinality: int
    agree_pairs: int
    longest_run: int
    nulls: int


def column_stats(df: DataFrame, columns: list[str] | None = None) -> DataFrame:
    """(col_ix, col, cardinality, agree_pairs, longest_run, nulls), nulls counting as one value.

    One pass and one shuffle for all columns: cells become (column, typed value) rows
    that are counted before the exchange.  Whole numbers and doubles keep their types;
    other types travel as their exact string form, forms of more than LONG_VALUE characters
    as their SHA-256 (which no two values are known to share) behind a mark.  agree_pairs is a decimal, since a
    value with billions of rows overflows a long.
    """
    columns = columns or df.columns
    kinds = {f.name: f.dataType for f in df.schema.fields}
    cells = []
    for i, c in enumerate(columns):
        kind, x = kinds[c], F.col(f"`{c}`")
        whole = isinstance(kind, (T.LongType, T.IntegerType, T.ShortType, T.ByteType, T.BooleanType))
        real = isinstance(kind, (T.DoubleType, T.FloatType))
        text = F.to_json(x) if isinstance(kind, (T.StructType, T.ArrayType)) else F.hex(x) if isinstance(kind, T.BinaryType) else x.cast("string")
        if isinstance(kind, (T.StructType, T.ArrayType, T.BinaryType, T.StringType)):
            text = F.when(F.length(text) > LONG_VALUE, F.concat(F.lit("h"), F.sha2(text, 256))).otherwise(F.concat(F.lit("t"), text))
        cells.append(F.struct(F.lit(i).alias("col_ix"), (x.cast("long") if whole else F.lit(None).cast("long")).alias("whole"), (x.cast("double") if real else F.lit(None).cast("double")).alias("real"), (F.lit(None).cast("string") if whole or real else text).alias("text")))
    counted = df.select(F.explode(F.array(*cells)).alias("cell")).select("cell.*").groupBy("col_ix", "whole", "real", "text").agg(F.count("*").alias("n"))
    n = F.col("n").cast("decimal(19,0)")
    empty = F.col("whole").isNull() & F.col("real").isNull() & F.col("text").isNull()
    out = counted.groupBy("col_ix").agg(
        F.count("*").alias("cardinality"), F.sum(n * (n - 1) / 2).cast("decimal(38,0)").alias("agree_pairs"),
        F.max("n").alias("longest_run"), F.sum(F.when(empty, F.col("n")).otherwise(0)).alias("nulls"),
    )
    names = F.element_at(F.array(*[F.lit(c) for c in columns]), F.col("col_ix") + 1)
    return out.select("col_ix", names.alias("col"), "cardinality", "agree_pairs", "longest_run", "nulls")


def run_histogram(df: DataFrame, column: str) -> DataFrame:
    """(run_length, n_values): how many values have how many rows."""
    return df.groupBy(column).agg(F.count("*").alias("run_length")).groupBy("run_length").agg(F.count("*").alias("n_values"))


def pair_budget(n: int, factor: float = 3.0) -> int:
    """floor(factor * n * log2 n)."""
    return math.floor(factor * n * math.log2(n)) if n > 1 else 0


def fallback_budget(stats: list[ColumnStats], multiplier: int = 5) -> int:
    """Budget for a relation where no column is within the usual one."""
    return multiplier * min(s.agree_pairs for s in stats)


def gap_budget(stats: list[ColumnStats], most: int) -> int:
    """Budget inside the widest ratio between neighbouring pair counts not above ``most``.

    Nothing changes while a budget moves within such a gap, so the widest one is the
    most stable choice.
    """
    pairs = sorted(max(1, s.agree_pairs) for s in stats)
    options = [(b / a, a) for a, b in zip(pairs, [*pairs[1:], 10 * most + 10]) if a <= most]
    return max(options)[1] if options else most


def relation_stats(relation: Relation) -> list[ColumnStats]:
    rows = column_stats(relation.rows, relation.columns).collect()
    return [ColumnStats(r.col_ix, relation.names[r.col_ix], r.cardinality, int(r.agree_pairs), r.longest_run, r.nulls) for r in sorted(rows, key=lambda r: r.col_ix)]


def covered_mask(stats: list[ColumnStats], budget: int) -> int:
    return sum(1 << s.index for s in stats if s.agree_pairs <= budget)


def classify_columns(stats: DataFrame, budget: int) -> DataFrame:
    return stats.withColumn("covered", F.col("agree_pairs") <= F.lit(budget))
