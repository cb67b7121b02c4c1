"""MinHash near-duplicate detection with min-max signatures (operator 1).

Every permutation contributes both its least and its greatest value, so half the
hash evaluations give a full signature; minima and maxima fill separate bands.
Banding only proposes pairs: each link is confirmed on the full shingle sets.

Scale: exact copies collapse to one class before banding.  A bucket first compares
every member with its least member (linear in the bucket); after components are
known, only buckets that still span several components are searched further, in
square tiles of bounded size, by signature.  No group is ever collected whole.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyscout.llm.cluster import connected_components, durable
from keyscout.llm.text import U, chunks, make_room, mix, shingle_sets, unused_names

PERMUTATIONS, ROWS = 63, 5
BANDS = 2 * PERMUTATIONS // ROWS
VALUES = BANDS * ROWS
#: expected members on one side of a tile
TILE = 256
_draw = np.random.default_rng(20240501)
_MULTIPLY = _draw.integers(1, 1 << 63, PERMUTATIONS, dtype=U) * U(2) + U(1)
_ADD = _draw.integers(0, 1 << 63, PERMUTATIONS, dtype=U)
_TOP = (1 << 32) - 1


def minmax_signatures(owner: np.ndarray, value: np.ndarray, n: int) -> np.ndarray:
    """(n, 2 * PERMUTATIONS) uint32: minima, then maxima (complemented so that both are minima-like)."""
    out = np.zeros((n, 2 * PERMUTATIONS), np.uint32)
    if len(value):
        first = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
        rows = owner[first]
        with np.errstate(over="ignore"):
            for p in range(PERMUTATIONS):
                x = value * _MULTIPLY[p] + _ADD[p]
                x = ((x ^ (x >> U(29))) * U(0x9FB21C651E98DF25)) >> U(32)
                out[rows, p] = np.minimum.reduceat(x, first)
                out[rows, PERMUTATIONS + p] = U(_TOP) - np.maximum.reduceat(x, first)
    return out


def _bands(signature: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        part = signature[:, :VALUES].astype(U).reshape(len(signature), BANDS, ROWS)
        key = np.broadcast_to(np.arange(BANDS, dtype=U) * U(0xD6E8FEB86659FD93) + U(7), part.shape[:2]).copy()
        for r in range(ROWS):
            key = mix(key * U(0xFF51AFD7ED558CCD) + part[:, :, r])
        return key.view(np.int64)


_SKETCH = "doc_id long, n_shingles long, hi long, lo long, bands array<long>, signature binary"


def _sketch(width: int):
    schema = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("hi", pa.int64()), ("lo", pa.int64()), ("bands", pa.list_(pa.int64())), ("signature", pa.binary())])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make_room()
        for batch in batches:
            for part in chunks(batch):
                n = part.num_rows
                owner, value = shingle_sets(part.column(1), width)
                signature = minmax_signatures(owner, value, n)
                size = np.bincount(owner, minlength=n).astype(np.int64)
                with np.errstate(over="ignore"):
                    total = np.zeros((2, len(value) + 1), U)
                    np.cumsum(mix(value), out=total[0, 1:])
                    np.cumsum(mix(value ^ U(0xA5A5A5A5A5A5A5A5)), out=total[1, 1:])
                    at = np.r_[0, np.cumsum(size)]
                    print_ = mix(total[:, at[1:]] - total[:, at[:-1]] + size.astype(U)).view(np.int64)
                bands = _bands(signature)
                short = np.ascontiguousarray((signature[:, :VALUES] & 0xFFFF).astype(np.uint16))
                raw = pa.py_buffer(short.tobytes())
                ends = pa.py_buffer((np.arange(n + 1, dtype=np.int32) * (2 * VALUES)).tobytes())
                yield pa.RecordBatch.from_arrays(
                    [part.column(0).cast(pa.int64()), pa.array(size), pa.array(print_[0]), pa.array(print_[1]), pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * BANDS), pa.array(bands.ravel())), pa.Array.from_buffers(pa.binary(), n, [None, ends, raw])],
                    schema=schema,
                )

    return work


def _sets(width: int):
    schema = pa.schema([("doc_id", pa.int64()), ("items", pa.binary())])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make_room()
        for batch in batches:
            for part in chunks(batch):
                owner, value = shingle_sets(part.column(1), width)
                at = np.r_[0, np.cumsum(np.bincount(owner, minlength=part.num_rows))]
                yield pa.RecordBatch.from_arrays([part.column(0).cast(pa.int64()), pa.array([value[a:b].tobytes() for a, b in zip(at[:-1], at[1:])], pa.binary())], schema=schema)

    return work


def _meets(x: np.ndarray, y: np.ndarray, percent: int) -> bool:
    """100 * |x & y| >= percent * |x | y| of two sorted sets."""
    if 100 * min(len(x), len(y)) < percent * max(len(x), len(y)):
        return False
    if len(x) > len(y):
        x, y = y, x
    at = np.searchsorted(y, x)
    at[at == len(y)] = 0
    both = int((y[at] == x).sum())
    return 100 * both >= percent * (len(x) + len(y) - both)


def _verify(percent: int):
    """Keep the pairs whose full sets meet the bound: 100 * intersection >= percent * union."""
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make_room()
        for batch in batches:
            keep = np.zeros(batch.num_rows, bool)
            left, right = batch.column(2), batch.column(3)
            for i in range(batch.num_rows):
                keep[i] = _meets(np.frombuffer(left[i].as_buffer(), U), np.frombuffer(right[i].as_buffer(), U), percent)
            if keep.any():
                mask = pa.array(keep)
                yield pa.RecordBatch.from_arrays([batch.column(0).filter(mask), batch.column(1).filter(mask)], schema=schema)

    return work


#: candidate pairs per member from which a tile is dense
DENSE = 4
_TILE_ROWS = "a long, b long, key long, ti int, tj int, band int, side int"


def _tile_pairs(percent: int, exact: bool):
    """Pairs of different components in one tile whose signatures leave the bound possible.

    A pair shows up in the tile of the first band it agrees on, and only there.  The
    signature test allows five standard deviations, so a true link passes it.  A tile
    with few such pairs gives the pairs; a dense one gives its members instead (b is
    null), to be searched again with their full sets at hand (``exact``), where only
    confirmed links come out.
    """
    schema = pa.schema([(n, pa.int64() if t == "long" else pa.int32()) for n, t in (x.split() for x in _TILE_ROWS.split(", "))])
    share = percent / 100
    least = int(VALUES * (share - 5 * (share * (1 - share) / VALUES) ** 0.5))

    def tile(rows: pa.Table) -> list[pa.RecordBatch]:
        ids = rows.column("doc_id").to_numpy()
        order = np.argsort(ids, kind="stable")
        ids = ids[order]
        side = rows.column("side").to_numpy()[order]
        key, ti, tj, band = (rows.column(c)[0].as_py() for c in ("key", "ti", "tj", "band"))
        component, size = rows.column("component").to_numpy()[order], rows.column("n_shingles").to_numpy()[order]
        keys = np.array(rows.column("bands").combine_chunks().flatten().to_numpy()).reshape(-1, BANDS)[order]
        marks = np.frombuffer(b"".join(rows.column("signature").to_pylist()), np.uint16).reshape(-1, VALUES)[order]
        items = [np.frombuffer(x.as_buffer(), U) for x in rows.column("items").combine_chunks()] if exact else []
        items = [items[i] for i in order] if exact else []
        a, b = [], []
        for i in range(len(ids) - 1):
            rest = np.flatnonzero(component[i + 1 :] != component[i]) + i + 1
            if ti != tj:
                rest = rest[side[rest] != side[i]]
            rest = rest[100 * np.minimum(size[rest], size[i]) >= percent * np.maximum(size[rest], size[i])]
            if len(rest):
                rest = rest[(marks[rest] == marks[i]).sum(1) >= least]
            if len(rest) and band:
                rest = rest[~(keys[rest, :band] == keys[i, :band]).any(1)]
            if exact:
                rest = rest[[_meets(items[i], items[j], percent) for j in rest]] if len(rest) else rest
            if len(rest):
                a.append(np.full(len(rest), i))
                b.append(rest)
        if not a:
            return []
        a, b = np.concatenate(a), np.concatenate(b)
        if not exact and len(a) > DENSE * len(ids):
            a = np.unique(np.r_[a, b])
            place = [pa.array(np.full(len(a), v), t) for v, t in ((key, pa.int64()), (ti, pa.int32()), (tj, pa.int32()), (band, pa.int32()))]
            return [pa.RecordBatch.from_arrays([pa.array(ids[a]), pa.nulls(len(a), pa.int64()), *place, pa.array(side[a])], schema=schema)]
        return [pa.RecordBatch.from_arrays([pa.array(ids[a]), pa.array(ids[b]), *(pa.nulls(len(a), f.type) for f in list(schema)[2:])], schema=schema)]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        last = None

        def flush():
            if held:
                found = tile(pa.Table.from_batches(held))
                held.clear()
                yield from found

        make_room()
        for batch in batches:
            key = np.stack([batch.column(batch.schema.get_field_index(c)).to_numpy() for c in ("key", "ti", "tj")], 1)
            cut = [0, *(np.flatnonzero((key[1:] != key[:-1]).any(1)) + 1).tolist(), batch.num_rows]
            for s, e in zip(cut[:-1], cut[1:]):
                if s == e:
                    continue
                if (now := tuple(key[s])) != last:
                    yield from flush()
                    last = now
                held.append(batch.slice(s, e - s))
        yield from flush()

    return work


def keep_first_of_groups(documents: DataFrame, percent: int = 80, width: int = 5) -> DataFrame:
    """One row of every group of near duplicates (its least doc_id), columns as they are.

    Rows with a null ``doc_id`` stay; rows repeated with id and text stay once, whatever
    their other columns hold.  Of an id with several texts all stay if one is kept.
    """
    found = minhash_near_duplicates(documents, percent, width)
    (kept,) = unused_names(documents.columns, "kept")
    first = found.where("kept and doc_id is not null").select(F.col("doc_id").alias(kept)).distinct()
    rows = documents.join(first, F.col("doc_id") == F.col(kept), "left_semi").dropDuplicates(["doc_id", "text"])
    return rows.unionByName(documents.where("doc_id is null"))


def minhash_near_duplicates(documents: DataFrame, percent: int = 80, width: int = 5) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row of ``documents(doc_id, text)``.

    Links need ``100 * |intersection| >= percent * |union|`` of the distinct
    ``width``-word shingles; a component is everything reachable over links.

    Edge cases: a null or wordless text has no shingle and links with nothing; one
    with fewer words has the whole sequence as its shingle; a null ``doc_id`` links
    with nothing, has a null component and is kept; repeated rows are answered row
    by row with the same class; other columns of the input are ignored.
    """
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    sketch = durable(docs.mapInArrow(_sketch(width), _SKETCH))
    linked = sketch.where("doc_id is not null and n_shingles > 0")
    classes = linked.groupBy("hi", "lo").agg(F.min("doc_id").alias("doc_id"))
    leaders = durable(classes.join(linked, ["doc_id", "hi", "lo"]).dropDuplicates(["doc_id", "hi", "lo"]))

    spread = leaders.select("doc_id", F.posexplode("bands").alias("band", "key"))
    buckets = durable(spread.groupBy("key").agg(F.min("doc_id").alias("leader"), F.count("*").alias("members")).where("members > 1"))
    star = durable(spread.join(buckets, "key").where("doc_id <> leader").select(F.col("leader").alias("a"), F.col("doc_id").alias("b")).distinct())
    wanted = star.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct()
    sets = durable(docs.where("doc_id is not null").join(wanted, "doc_id", "left_semi").mapInArrow(_sets(width), "doc_id long, items binary").dropDuplicates(["doc_id", "items"]))

    def confirmed(pairs: DataFrame) -> DataFrame:
        left, right = sets.select(F.col("doc_id").alias("a"), F.col("items").alias("x")), sets.select(F.col("doc_id").alias("b"), F.col("items").alias("y"))
        return durable(pairs.join(right, "b").join(left, "a").select("a", "b", "x", "y").mapInArrow(_verify(percent), "a long, b long"))

    links = confirmed(star)
    labels = connected_components(links)

    # buckets that still hold several components: tiles of their members
    placed = leaders.select("doc_id", "n_shingles", "bands", "signature").join(labels.withColumnRenamed("node", "doc_id"), "doc_id", "left").withColumn("component", F.coalesce("component", "doc_id"))
    at = placed.select("doc_id", "component", F.posexplode("bands").alias("band", "key")).join(buckets.select("key", "members"), "key")
    mixed = at.groupBy("key").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.first("members").alias("members")).where("low < high").select("key", F.ceil(F.col("members") / TILE).cast("int").alias("tiles"))
    rows = at.join(mixed, "key").select("doc_id", "band", "key", "tiles", F.pmod(F.xxhash64("doc_id"), F.col("tiles")).cast("int").alias("side"))
    other = F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)).alias("other")
    rows = rows.select("doc_id", "band", "key", "side", other).select("doc_id", "band", "key", "side", F.least("side", "other").alias("ti"), F.greatest("side", "other").alias("tj"))
    columns = ["key", "ti", "tj", "band", "side", "doc_id", "component", "n_shingles", "bands", "signature"]

    def searched(rows: DataFrame, exact: bool) -> DataFrame:
        tiles = rows.repartition("key", "ti", "tj").sortWithinPartitions("key", "ti", "tj")
        return durable(tiles.mapInArrow(_tile_pairs(percent, exact), _TILE_ROWS))

    first = searched(rows.join(placed, "doc_id").select(columns), False)
    rest = first.where("b is not null").select("a", "b").join(star, ["a", "b"], "left_anti").distinct()
    dense = first.where("b is null").select(F.col("a").alias("doc_id"), "key", "ti", "tj", "band", "side")
    dense = searched(dense.join(placed, "doc_id").join(sets, "doc_id").select(*columns, "items"), True).select("a", "b")
    more = durable(confirmed(rest).unionByName(dense))
    if more.limit(1).count():
        # the first components stand for their links: only new links between them are added
        root = labels.select(F.col("node"), "component")
        labels = connected_components(more.unionByName(root.where("node <> component").select(F.col("component").alias("a"), F.col("node").alias("b"))))
    found = classes.join(labels.withColumnRenamed("node", "doc_id"), "doc_id", "left").select("hi", "lo", F.coalesce("component", "doc_id").alias("component_id"))
    # the keys are renamed: both sides may come from one checkpoint
    found = found.select(F.col("hi").alias("h"), F.col("lo").alias("l"), "component_id")
    alone = F.col("doc_id").isNull() | (F.col("n_shingles") == 0)
    out = sketch.select("doc_id", "n_shingles", "hi", "lo").join(found, (F.col("hi") == F.col("h")) & (F.col("lo") == F.col("l")) & ~alone, "left")
    out = out.withColumn("component_id", F.when(alone, F.col("doc_id")).otherwise(F.coalesce("component_id", "doc_id")))
    return out.select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"))
