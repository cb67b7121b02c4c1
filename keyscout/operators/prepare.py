"""Phase 0: relation snapshots, encodings, duplicate rows and the null policy."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from keyscout.plans.lineage import snapshot


@dataclass
class Relation:
    """An encoded relation: columns c0..c{m-1} and ``rid``, with the names they stand for."""

    rows: DataFrame
    names: list[str]
    n: int

    @property
    def m(self) -> int:
        return len(self.names)

    @property
    def columns(self) -> list[str]:
        return [f"c{i}" for i in range(self.m)]


def flatten_structs(df: DataFrame) -> DataFrame:
    """Struct columns replaced by their fields, named parent_field (with a number behind where that name is taken).

    A null struct gives null fields.
    """
    while any(isinstance(f.dataType, T.StructType) for f in df.schema.fields):
        # by position, since two columns may have one name
        plain = df.toDF(*[f"_f{i}" for i in range(len(df.columns))])
        taken = {f.name for f in df.schema.fields if not isinstance(f.dataType, T.StructType)}
        out = []
        for i, f in enumerate(df.schema.fields):
            if not isinstance(f.dataType, T.StructType):
                out.append(F.col(f"_f{i}").alias(f.name))
                continue
            for k, g in enumerate(f.dataType.fields):
                name, n = f"{f.name}_{g.name}", 2
                while name in taken:
                    name, n = f"{f.name}_{g.name}_{n}", n + 1
                taken.add(name)
                out.append(F.col(f"_f{i}").getField(g.name).alias(name))
        df = plain.select(*out)
    return df


def reject_maps(df: DataFrame) -> None:
    """Maps have no equality in Spark: refused with the way out named."""
    for f in df.schema.fields:
        if isinstance(f.dataType, T.MapType):
            raise TypeError(f"column {f.name} is a map; pass to_json(array_sort(map_entries({f.name}))) instead")


def project_prefix(df: DataFrame, k: int) -> DataFrame:
    return df.select(*[f"`{c}`" for c in df.columns[:k]])


def attach_row_id(df: DataFrame) -> DataFrame:
    """Row ids fixed by a snapshot, so both sides of a self-join see the same ones."""
    return snapshot(df.withColumn("rid", F.monotonically_increasing_id()))


def drop_duplicate_rows(df: DataFrame) -> DataFrame:
    return df.dropDuplicates()


def has_duplicate_rows(df: DataFrame) -> bool:
    return bool(df.groupBy(*[f"`{c}`" for c in df.columns]).count().where("count > 1").limit(1).count())


def _rank_codes(df: DataFrame, column: str) -> DataFrame:
    """(value, code): consecutive whole numbers by value order, without a single-task sort.

    Distinct values are dealt by range; a code is the place within the range plus the
    sizes of the ranges before it.
    """
    values = snapshot(df.select(F.col(column).alias("value")).where(F.col(column).isNotNull()).distinct().repartitionByRange("value").withColumn("part", F.spark_partition_id()))
    before = values.groupBy("part").count().withColumn("before", F.coalesce(F.sum("count").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    place = F.row_number().over(Window.partitionBy("part").orderBy("value"))
    return values.withColumn("place", place).join(F.broadcast(before.select("part", "before")), "part").select("value", (F.col("place") + F.col("before") - 1).alias("code"))


def encode_columns(df: DataFrame, mode: str = "native", null_policy: str = "null_equal", cast_to_string: bool = False) -> Relation:
    """Snapshot of ``df`` as c0..c{m-1}, rid.

    ``native`` keeps the values (equality is all that matters, and Spark's join and
    aggregate keys agree on NaN and negative zero); ``rank`` maps each column to
    consecutive whole numbers; ``hash128`` to two seeded 64-bit hashes packed as a
    string (probabilistic).  ``null_policy`` null_equal treats nulls as one value,
    null_distinct makes every null differ from everything.
    """
    df = flatten_structs(df)
    reject_maps(df)
    names = df.columns
    df = df.toDF(*[f"_f{i}" for i in range(len(names))])
    columns = [F.col(c) for c in df.columns]
    if cast_to_string:
        columns = [c.cast("string") for c in columns]
    # negative zero becomes zero, so that value comparisons see what keys see
    kinds = [f.dataType for f in df.schema.fields]
    columns = [c + F.lit(0.0).cast(k) if isinstance(k, (T.DoubleType, T.FloatType)) and not cast_to_string else c for c, k in zip(columns, kinds)]
    if mode == "hash128":
        columns = [F.when(c.isNotNull(), F.concat(F.hex(F.xxhash64(c)), F.hex(F.xxhash64(F.lit(1), c)))) for c in columns]
    rows = df.select(*[c.alias(f"c{i}") for i, c in enumerate(columns)])
    rows = attach_row_id(rows)
    if mode == "rank":
        for i in range(len(names)):
            codes = _rank_codes(rows, f"c{i}").withColumnRenamed("code", f"code{i}")
            rows = rows.join(codes, F.col(f"c{i}") == F.col("value"), "left").drop("value")
        rows = snapshot(rows.select(*[F.col(f"code{i}").alias(f"c{i}") for i in range(len(names))], "rid"))
    elif mode not in ("native", "hash128"):
        raise ValueError(f"unknown encoding {mode}")
    relation = Relation(rows, names, rows.count())
    return apply_null_policy(relation, null_policy)


def apply_null_policy(relation: Relation, policy: str) -> Relation:
    """null_distinct replaces every null by a token of its own row."""
    if policy == "null_equal":
        return relation
    if policy != "null_distinct":
        raise ValueError(f"unknown null policy {policy}")
    # a value and a token never meet: values move under a struct field of their own
    columns = [F.struct(F.col(c).alias("value"), F.when(F.col(c).isNull(), F.col("rid")).alias("token")).alias(c) for c in relation.columns]
    return Relation(relation.rows.select(*columns, "rid"), relation.names, relation.n)


def decode(keys: DataFrame, names: Sequence[str]) -> DataFrame:
    """key_mask with its column names."""
    from keyscout.functions.masks import mask_names

    return keys.withColumn("columns", mask_names(F.col("key_mask"), list(names)))
