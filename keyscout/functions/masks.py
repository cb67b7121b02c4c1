"""Column sets as bit masks: bit i is the i-th column.

Driver code uses Python ints of any width.  In DataFrames a mask is one BIGINT named
``mask`` for up to 63 columns, and several words ``mask, mask1, ...`` beyond that.
"""

from __future__ import annotations

from collections.abc import Iterable, Sequence
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WORD = 63


def mask_of(columns: Iterable[str], schema: Sequence[str]) -> int:
    place = {c: i for i, c in enumerate(schema)}
    return sum({1 << place[c] for c in columns})


def bits(mask: int) -> list[int]:
    out = []
    while mask:
        low = mask & -mask
        out.append(low.bit_length() - 1)
        mask ^= low
    return out


def mask_columns(mask: int, schema: Sequence[str]) -> list[str]:
    return [schema[i] for i in bits(mask)]


def words_of(m: int) -> list[str]:
    """Names of the mask words of an m-column relation."""
    return ["mask" if w == 0 else f"mask{w}" for w in range(max(1, -(-m // WORD)))]


def join_words(row: Sequence[int]) -> int:
    return sum(int(v) << (WORD * w) for w, v in enumerate(row))


def split_words(mask: int, m: int) -> tuple[int, ...]:
    return tuple((mask >> (WORD * w)) & ((1 << WORD) - 1) for w in range(len(words_of(m))))


# Column expressions on single-word masks; all of them stay inside generated code.
def mask_size(mask: Column | str) -> Column:
    return F.bit_count(mask)


def mask_subset(a: Column, b: Column) -> Column:
    """a is contained in b."""
    return a.bitwiseAND(b) == a


def mask_hits(a: Column, b: Column) -> Column:
    return a.bitwiseAND(b) != 0


def mask_union(a: Column, b: Column) -> Column:
    return a.bitwiseOR(b)


def mask_minus(a: Column, b: Column) -> Column:
    return a.bitwiseAND(F.bitwise_not(b))


def mask_names(mask: Column, schema: Sequence[str]) -> Column:
    """Comma-joined column names in schema order."""
    return F.concat_ws(",", *[F.when(mask.bitwiseAND(F.lit(1 << i)) != 0, F.lit(c)) for i, c in enumerate(schema)])


def difference_words(left: str, right: str, columns: Sequence[str]) -> list[Column]:
    """Mask words of the columns on which two aliased rows differ (null equals null)."""
    out = []
    for w, name in enumerate(words_of(len(columns))):
        part = columns[WORD * w : WORD * (w + 1)]
        terms = [F.when(F.col(f"{left}.{c}").eqNullSafe(F.col(f"{right}.{c}")), F.lit(0)).otherwise(F.lit(1 << i)).cast("long") for i, c in enumerate(part)]
        out.append(reduce(lambda a, b: a + b, terms, F.lit(0).cast("long")).alias(name))
    return out


def minimal_masks(masks: Iterable[int]) -> list[int]:
    """Masks that contain no other mask, smallest first."""
    found = sorted(set(masks), key=lambda x: (x.bit_count(), x))
    if not found:
        return []
    if max(found).bit_length() <= 63:
        rows = np.array(found, np.int64)
        kept = np.zeros(len(rows), np.int64)
        n = 0
        for v in rows:
            if not ((kept[:n] & v) == kept[:n]).any():
                kept[n] = v
                n += 1
        return [int(v) for v in kept[:n]]
    out: list[int] = []
    for v in found:
        if not any(k & v == k for k in out):
            out.append(v)
    return out


def minimal_delta(old: Sequence[int], new: Iterable[int]) -> list[int]:
    """minimal_masks(old + new) for an ``old`` that is minimal already: old pairs are not compared."""
    fresh = [v for v in minimal_masks(new) if not any(k & v == k for k in old)]
    kept = [k for k in old if not any(v & k == v for v in fresh)]
    return sorted(kept + fresh, key=lambda x: (x.bit_count(), x))


def minimize_df(masks: DataFrame) -> DataFrame:
    """Single-word masks without those that contain another one (anti join; for many masks)."""
    a, b = masks.select("mask").distinct().alias("a"), masks.select("mask").distinct().alias("b")
    inside = (F.col("b.mask").bitwiseAND(F.col("a.mask")) == F.col("b.mask")) & (F.col("a.mask") != F.col("b.mask"))
    return a.join(b, inside, "left_anti")


def minimize_partitions(masks: DataFrame, m: int = WORD) -> DataFrame:
    """Partition-local minimisation: shrinks a large mask table before it is gathered."""
    import pandas as pd

    words = words_of(m)

    def work(frames):
        held: list[int] = []
        for frame in frames:
            held = minimal_masks([*held, *(join_words(r) for r in frame[words].itertuples(index=False))])
        rows = [split_words(v, m) for v in held]
        yield pd.DataFrame({w: pd.Series([r[i] for r in rows], dtype="int64") for i, w in enumerate(words)})

    return masks.select(*words).mapInPandas(work, ", ".join(f"{w} long" for w in words))
