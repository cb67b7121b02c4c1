"""Near-duplicate vectors: every row hung on its nearest nodes of a small-world graph (operator 9).

The graph's nodes are a bounded sample of the rows, thinned so that none is within twice
the bound of another: a dense group has one node, however large it is.  Every row walks
the graph once and hangs on the nearest nodes that its beam ends with; rows on a common
node are compared.  An audit beforehand compares a sample of rows with all rows by brute
force and sets how many nodes a row hangs on; where no number of them reaches the least
recall, all rows hang on one.  Links are confirmed by cosine in double precision and count
under the least common node alone.  A task gives link counts and a spanning forest of its
links, so what leaves it is linear in its rows however dense a group is.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F

from keyscout.llm.cluster import connected_components, durable
from keyscout.llm.hnsw import SmallWorld

#: rows for each node of the graph, least and most nodes, highest cosine between two nodes
NODE_ROWS, LEAST_NODES, MOST_NODES, APART = 4096, 64, 8192, 0.8
#: beam of a walk, nodes that a row hangs on at first and at most, recall that ends the widening, recall below which all rows are compared
BEAM, CELLS, MOST_CELLS, GOAL, LEAST_RECALL = 24, 4, 8, 0.98, 0.9
#: audited rows, rows that tell the sizes of cells, rows of a part of a large cell, most groups of copies collapsed beforehand
AUDITED, SIZED, PART, HEAVY = 512, 8192, 65_536, 20_000
#: rows walked or compared at once
BATCH = 1024


def _lists(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(values, first place and length of every list; length -1: null, empty, zero, or with null or non-finite components)."""
    start = column.offsets.to_numpy()
    start, size = start[:-1].astype(np.int64), np.diff(start).astype(np.int64)
    values = column.values.slice(start[0], start[-1] + size[-1] - start[0]) if len(start) else column.values
    start -= start[0] if len(start) else 0
    flat = values.to_numpy(zero_copy_only=False)  # nulls become nan
    bad, some = (np.r_[0, np.cumsum(x)] for x in (~np.isfinite(flat), flat != 0))
    good = column.is_valid().to_numpy(zero_copy_only=False) & (bad[start + size] == bad[start]) & (some[start + size] > some[start])
    return flat, start, np.where(good, size, -1)


def _by_length(batch: pa.RecordBatch) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(length, places in the batch, matrix; negative zero made zero) of the usable vectors with an id."""
    flat, start, size = _lists(batch.column(1))
    size[batch.column(0).is_null().to_numpy(zero_copy_only=False)] = -1
    for shape in np.unique(size[size >= 0]).tolist():
        rows = np.flatnonzero(size == shape)
        yield shape, rows, flat[start[rows, None] + np.arange(shape)] + flat.dtype.type(0)


def _unit(x: np.ndarray) -> np.ndarray:
    x = x.astype(np.float64)
    x = x / np.abs(x).max(1, keepdims=True)  # no overflow of squares
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def _prints(x: np.ndarray) -> np.ndarray:
    """A 128-bit print of every row's bytes."""
    import xxhash

    raw, width = x.tobytes(), x.shape[1] * x.itemsize
    return np.frombuffer(b"".join(xxhash.xxh3_128_digest(raw[i : i + width]) for i in range(0, len(raw), width)), np.int64).reshape(-1, 2)


def _binary(x: np.ndarray) -> pa.Array:
    """The rows' bytes."""
    x = np.ascontiguousarray(x)
    offsets = np.arange(len(x) + 1, dtype=np.int32) * np.int32(x.shape[1] * x.itemsize)
    return pa.Array.from_buffers(pa.binary(), len(x), [None, pa.py_buffer(offsets), pa.py_buffer(x)])


def _matrix(column: pa.Array | pa.ChunkedArray, dtype: type) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = pa.concat_arrays(column.chunks)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int32)[column.offset : column.offset + len(column) + 1]
    return np.frombuffer(data, np.uint8)[at[0] : at[-1]].view(dtype).reshape(len(column), -1)


_MARKS = "vec_id long, shape int, hi long, lo long, drawn int, vector binary"


def _marks(share: float):
    """Every row's length (-1: not usable) and print, with the vectors of a share of the rows."""
    schema = pa.schema([("vec_id", pa.int64()), ("shape", pa.int32()), ("hi", pa.int64()), ("lo", pa.int64()), ("drawn", pa.int32()), ("vector", pa.binary())])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            shapes, both, vectors = np.full(batch.num_rows, -1, np.int32), np.zeros((batch.num_rows, 2), np.int64), [None] * batch.num_rows
            drawn = np.zeros(batch.num_rows, np.int32)
            for shape, rows, x in _by_length(batch):
                shapes[rows], both[rows] = shape, _prints(x)
                # the draw follows the print and the id, so it is the same in every run
                mixed = (both[rows, 0].view(np.uint64) ^ batch.column(0).take(pa.array(rows)).to_numpy().astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) * np.uint64(0xD6E8FEB86659FD93)
                drawn[rows] = (mixed >> np.uint64(33)).astype(np.int32)
                for i, row in zip(*(a.tolist() for a in (np.flatnonzero(drawn[rows] < share * 2.0**31), rows[drawn[rows] < share * 2.0**31]))):
                    vectors[row] = x[i].tobytes()
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(shapes), pa.array(both[:, 0].copy()), pa.array(both[:, 1].copy()), pa.array(drawn), pa.array(vectors, pa.binary())], schema=schema)

    return work


def thinned(unit: np.ndarray, most: int) -> np.ndarray:
    """Places of at most ``most`` rows, none with a cosine above APART to one before it."""
    kept: list[int] = []
    for s in range(0, len(unit), BATCH):
        block = unit[s : s + BATCH]
        free = (block @ unit[kept].T <= APART).all(1) if kept else np.ones(len(block), bool)
        among, own = block @ block.T > APART, []
        for i in np.flatnonzero(free).tolist():
            if not among[i, own].any():
                own.append(i)
        kept += [s + i for i in own]
        if len(kept) >= most:
            break
    return np.array(kept[:most], np.int64)


def hung(graph: SmallWorld, unit: np.ndarray, cells: int) -> np.ndarray:
    """(rows, cells): the nearest nodes that a walk of every row ends with, nearest first; -1 where there are no more."""
    out = np.full((len(unit), cells), -1, np.int32)
    width = min(BEAM, len(graph.x))
    for s in range(0, len(unit), BATCH):
        ids = graph.search(unit[s : s + BATCH], width)[0][:, :cells]
        out[s : s + BATCH, : ids.shape[1]] = ids
    return out


def _exact(unit: np.ndarray, q: np.ndarray, least: float) -> list[np.ndarray]:
    """Places of ``unit`` with cosine >= least for every query, by products with every row, block by block."""
    out: list[list[np.ndarray]] = [[np.zeros(0, np.int64)] for _ in q]
    for s in range(0, len(q), BATCH):
        for b in range(0, len(unit), 8192):
            r, c = np.nonzero(q[s : s + BATCH] @ unit[b : b + 8192].T >= least - 1e-5)
            same = np.einsum("nd,nd->n", q[s + r], unit[b + c]) >= least
            r, c = r[same], b + c[same]
            cut = np.searchsorted(r, np.arange(len(q[s : s + BATCH]) + 1))
            for i in np.unique(r).tolist():
                out[s + i].append(c[cut[i] : cut[i + 1]])
    return [np.concatenate(o) for o in out]


def needed(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """How many nodes each of two rows must hang on to share one, for pairs of rows' nodes (nearest first); their number + 1: more."""
    k = a.shape[1]
    rank = np.maximum(np.arange(k)[:, None], np.arange(k)[None, :])
    same = (a[:, :, None] == b[:, None, :]) & (a >= 0)[:, :, None]
    return np.where(same, rank, k).min((1, 2)) + 1


def _audit(shared, least: float):
    """Of the links of the audited rows: how many nodes would find them."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(MOST_CELLS + 2, np.int64)
        for batch in batches:
            ids = batch.column(0)
            for shape, rows, x in _by_length(batch):
                if shape not in shared.value:
                    continue
                graph, asked, q, lists = shared.value[shape]
                unit, own = _unit(x), ids.take(pa.array(rows)).to_numpy()
                near = np.flatnonzero((unit.astype(np.float32) @ q.T.astype(np.float32)).max(1) >= least - 1e-4)
                if not len(near):
                    continue
                found = _exact(unit[near], q, least)
                r, c = np.repeat(np.arange(len(q)), [len(f) for f in found]), np.concatenate(found)
                other = own[near[c]] != asked[r]
                walked = hung(graph, unit[near], MOST_CELLS)
                for s in range(0, len(r), 65_536):
                    ok = other[s : s + 65_536]
                    total += np.bincount(needed(lists[r[s : s + 65_536][ok]], walked[c[s : s + 65_536][ok]]), minlength=len(total))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total)), pa.int32()), pa.array(total)], names=["cells", "n"])

    return work


_HUNG = "shape int, cell int, tile long, vec_id long, copies long, cells binary, vector binary"


def _hang(shared, heavy, cells: int):
    """Rows with each of their cells and tiles; of a group of very many copies its least id alone, with their number."""
    schema = pa.schema([("shape", pa.int32()), ("cell", pa.int32()), ("tile", pa.int64()), ("vec_id", pa.int64()), ("copies", pa.int64()), ("cells", pa.binary()), ("vector", pa.binary())])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in (whole.slice(s, 4096) for s in range(0, whole.num_rows, 4096)):
                for shape, rows, x in _by_length(batch):
                    ids, copies = batch.column(0).take(pa.array(rows)).to_numpy(), np.zeros(len(rows), np.int64)
                    if heavy.value:
                        named = [heavy.value.get((shape, *p)) for p in _prints(x).tolist()]
                        keep = np.array([n is None or n[0] == i for n, i in zip(named, ids.tolist())])
                        copies = np.array([0 if n is None else n[1] for n in named], np.int64)[keep]
                        ids, x = ids[keep], x[keep]
                    if not len(ids):
                        continue
                    graph, parts = shared.value[shape]
                    lists = np.zeros((len(ids), 1), np.int32) if graph is None else np.sort(hung(graph, _unit(x), cells), 1)
                    at, k = np.nonzero(lists >= 0)
                    cell = lists[at, k]
                    # a large cell: its rows are dealt in parts, every two of which meet in a tile
                    n = parts[cell]
                    own = ((ids[at].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)).astype(np.int64) % n
                    again = np.repeat(np.arange(len(at)), n)
                    other = np.arange(len(again)) - np.repeat(np.cumsum(n) - n, n)
                    own = own[again]
                    tile = np.minimum(own, other) << 40 | np.maximum(own, other) << 20 | own
                    at, cell = at[again], cell[again]
                    for s in range(0, len(at), 32_768):
                        a = at[s : s + 32_768]
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(a), shape, np.int32)), pa.array(cell[s : s + 32_768]), pa.array(tile[s : s + 32_768]), pa.array(ids[a]), pa.array(copies[a]), _binary(lists[a]), _binary(x[a])], schema=schema)

    return work


class _Forest:
    """Components of a tile's classes, and the links that joined two of them."""

    def __init__(self, n: int):
        self.label, self.links = np.arange(n), []

    def join(self, r: np.ndarray, c: np.ndarray) -> None:
        """Links r[i] - c[i]; each round joins every component with one neighbour, as long as links lead out of one."""
        while True:
            a, b = self.label[r], self.label[c]
            out = a != b
            if not out.any():
                return
            r, c, a, b = r[out], c[out], a[out], b[out]
            first = np.union1d(*(np.unique(x, return_index=True)[1] for x in (a, b)))
            roots: dict[int, int] = {}

            def find(v: int) -> int:
                while (up := roots.setdefault(v, v)) != v:
                    roots[v] = v = roots[up]
                return v

            for i in first.tolist():
                x, y = find(int(a[i])), find(int(b[i]))
                if x != y:
                    roots[max(x, y)] = min(x, y)
                    self.links.append((int(r[i]), int(c[i])))
            old = np.array(list(roots))
            to = np.arange(len(self.label))
            to[old] = [find(v) for v in old.tolist()]
            self.label = to[self.label]


def _earlier(lists: np.ndarray, r: np.ndarray, c: np.ndarray, cell: int) -> np.ndarray:
    """Whether two rows share a node below the cell's."""
    out = np.zeros(len(r), bool)
    k = lists.shape[1]
    below = np.where((lists >= 0) & (lists < cell), lists, -1)
    left, right = [below[r, i] for i in range(k)], [below[c, i] for i in range(k)]
    for x in left:
        for y in right:
            out |= (x == y) & (x >= 0)
    return out


_FOUND = "a long, b long, links long"
_FOUND_SCHEMA = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("links", pa.int64())])


def _compared(table: pa.Table, cell: int, i: int, j: int, least: float, dtype: type) -> pa.RecordBatch:
    """Links among a cell's rows (or between two parts of it) that no lower cell has, counted per id, and a forest of them."""
    ids, copies = table.column("vec_id").to_numpy(), table.column("copies").to_numpy()
    own = table.column("tile").to_numpy() & 0xFFFFF
    x, lists = _matrix(table.column("vector"), dtype), _matrix(table.column("cells"), np.int32)
    # equal rows collapse to a class; the rows of part i come first
    order = np.lexsort((ids, own))
    ids, copies, own, x, lists = ids[order], copies[order], own[order], x[order], lists[order]
    joined = np.concatenate([x.view(np.uint8).reshape(len(x), -1), lists.view(np.uint8).reshape(len(x), -1), own.astype(np.int32)[:, None].view(np.uint8)], 1)
    _, first, kind = np.unique(_prints(np.ascontiguousarray(joined)), axis=0, return_index=True, return_inverse=True)
    rank = np.argsort(np.argsort(first, kind="stable"), kind="stable")  # classes in order of their first rows
    kind, first = rank[kind.ravel()], np.sort(first)
    size = np.bincount(kind)
    np.maximum.at(size, kind, copies)  # a collapsed group brings its number along
    unit = _unit(x[first])
    near, lists, names = unit.astype(np.float32), lists[first], ids[first]
    cut = len(first) if i == j else int(np.searchsorted(own[first], i, "right"))
    slack = max(1e-5, 2.5e-7 * x.shape[1])  # of products in single precision
    counts, forest = np.zeros(len(first), np.int64), _Forest(len(first))
    for s in range(0, cut, BATCH):
        e = min(s + BATCH, cut)
        base = s if i == j else cut
        for b in range(base, len(first), 8192):
            product = near[s:e] @ near[b : b + 8192].T
            hit = np.flatnonzero(product.ravel() >= least - slack)
            for h in (hit[v : v + 1_000_000] for v in range(0, len(hit), 1_000_000)):
                r, c = s + h // product.shape[1], b + h % product.shape[1]
                sure = product.ravel()[h] >= least + slack
                ok = c > r if i == j else np.ones(len(r), bool)
                close = np.flatnonzero(ok & ~sure)
                for v in (close[w : w + 65_536] for w in range(0, len(close), 65_536)):
                    ok[v] = np.einsum("nd,nd->n", unit[r[v]], unit[c[v]]) >= least
                r, c = r[ok], c[ok]
                new = ~_earlier(lists, r, c, cell)
                r, c = r[new], c[new]
                counts += np.bincount(r, size[c], len(counts)).astype(np.int64) + np.bincount(c, size[r], len(counts)).astype(np.int64)
                forest.join(r, c)
    if i == j:  # copies are linked with each other, in their lowest cell
        lowest = np.where(lists >= 0, lists, np.iinfo(np.int32).max).min(1) == cell
        counts += np.where(lowest, size - 1, 0)
    some = np.flatnonzero(counts[kind] > 0)
    # each id of a class once, tied to the class's first
    pair = np.unique(np.stack([kind[some], ids[some]], 1), axis=0)
    tied = pair[pair[:, 1] != names[pair[:, 0]]]
    a = np.concatenate([pair[:, 1], tied[:, 1], names[[l[0] for l in forest.links]] if forest.links else tied[:0, 1]])
    b = np.concatenate([names[tied[:, 0]], names[[l[1] for l in forest.links]] if forest.links else tied[:0, 1]])
    none = pa.nulls(len(pair), pa.int64())
    columns = [pa.array(a), pa.concat_arrays([none, pa.array(b)]), pa.concat_arrays([pa.array(counts[pair[:, 0]]), pa.nulls(len(b), pa.int64())])]
    return pa.RecordBatch.from_arrays(columns, schema=_FOUND_SCHEMA)


def _compare(least: float, dtype: type):
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by cell and tile."""
        now, held = None, []

        def answer() -> pa.RecordBatch:
            return _compared(pa.Table.from_batches(held), now[1], now[2] >> 20, now[2] & 0xFFFFF, least, dtype)

        for batch in batches:
            key = np.stack([batch.column(0).to_numpy(), batch.column(1).to_numpy(), batch.column(2).to_numpy() >> 20], 1)
            cut = [0, *(np.flatnonzero((key[1:] != key[:-1]).any(1)) + 1).tolist(), batch.num_rows]
            for s, e in zip(cut[:-1], cut[1:]):
                if s == e:
                    continue
                if (place := tuple(key[s].tolist())) != now:
                    if held:
                        yield answer()
                    now, held = place, []
                held.append(batch.slice(s, e - s))
        if held:
            yield answer()

    return work


def _planned(drawn: list[Row], n: int, dtype: type) -> tuple[SmallWorld | None, np.ndarray, np.ndarray]:
    """(graph or None for few rows, unit vectors and ids of the drawn rows) of one length."""
    unit, ids = _unit(np.stack([np.frombuffer(r.vector, dtype) for r in drawn])), np.array([r.vec_id for r in drawn])
    nodes = thinned(unit, _nodes(n))
    return (SmallWorld.build(unit[nodes]) if len(nodes) > 1 else None), unit, ids


def _nodes(n: int) -> int:
    return min(max(n // NODE_ROWS, min(LEAST_NODES, n // 16)), MOST_NODES)


def _parts(rows: np.ndarray) -> np.ndarray:
    """Parts that cells of so many rows are dealt in."""
    return np.where(rows > 1.5 * PART, np.ceil(rows / PART), 1).astype(np.int64)


def near_duplicate_vectors(vectors: DataFrame, least: float = 0.95, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row.

    Links join vectors of one length whose cosine in double precision is ``least`` or
    more.  Vectors that are null, zero, empty or hold null or non-finite components link
    with nothing, and so does a null id (component null, kept).  Repeated rows count as
    vectors of their own.  An empty table gives an empty result; other columns are
    ignored.
    """
    spark = vectors.sparkSession
    single = dict(vectors.dtypes)[vector_col] == "array<float>"
    dtype = np.float32 if single else np.float64
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).cast("array<float>" if single else "array<double>").alias("vector"))
    n = rows.count()
    marks = durable(rows.mapInArrow(_marks(max(2 * _nodes(n), SIZED, AUDITED) / max(n, 1)), _MARKS))
    usable = marks.where("shape >= 0")
    sizes = {r.shape: r.n for r in usable.groupBy("shape").agg(F.count("*").alias("n")).collect()}
    groups = usable.groupBy("shape", "hi", "lo").agg(F.min("vec_id").alias("first"), F.count("*").alias("copies")).where(F.col("copies") >= max(1000, n // HEAVY))
    heavy = {(r.shape, r.hi, r.lo): (r.first, r.copies) for r in groups.collect()}
    drawn: dict[int, list[Row]] = {}
    for r in marks.where("vector is not null").select("shape", "hi", "lo", "vec_id", "drawn", "vector").collect():
        drawn.setdefault(r.shape, []).append(r)
    plans = {}
    for shape, own in drawn.items():
        own.sort(key=lambda r: (r.drawn, r.vec_id))
        plans[shape] = _planned(own, sizes[shape], dtype)

    # audit: how many nodes a row must hang on
    asked = {s: (graph, ids[:AUDITED], unit[:AUDITED], hung(graph, unit[:AUDITED], MOST_CELLS)) for s, (graph, unit, ids) in plans.items() if graph}
    need = np.zeros(MOST_CELLS + 2, np.int64)
    if asked:
        shared = spark.sparkContext.broadcast(asked)
        for r in rows.mapInArrow(_audit(shared, least), "cells int, n long").groupBy("cells").agg(F.sum("n").alias("n")).collect():
            need[r.cells] = r.n
    recall = np.cumsum(need) / max(1, need.sum())
    cells = CELLS
    while need.any() and cells < MOST_CELLS and recall[cells] < GOAL:
        cells += 1
    exact = need.any() and recall[cells] < LEAST_RECALL  # the graph does not serve these vectors: all are compared

    # sizes of the cells, from the drawn rows
    placed = {}
    for shape, count in sizes.items():
        graph, unit, _ = plans.get(shape, (None, None, None))
        light = count - sum(copies - 1 for key, (_, copies) in heavy.items() if key[0] == shape)
        if graph is None or exact:
            placed[shape] = None, _parts(np.array([light]))
            continue
        some = np.array([i for i, r in enumerate(drawn[shape][:SIZED]) if (shape, r.hi, r.lo) not in heavy], np.int64)
        lists = hung(graph, unit[some], cells)
        share = np.bincount(lists[lists >= 0], minlength=len(graph.x)) / max(1, len(some))
        placed[shape] = graph, _parts(share * light)
    work = _hang(spark.sparkContext.broadcast(placed), spark.sparkContext.broadcast(heavy), cells)
    dealt = rows.mapInArrow(work, _HUNG).repartition("shape", "cell", F.shiftright("tile", 20)).sortWithinPartitions("shape", "cell", "tile")
    found = durable(dealt.mapInArrow(_compare(least, dtype), _FOUND), once=True)

    links = found.where("links is not null").groupBy(F.col("a").alias("alias")).agg(F.sum("links").alias("links"))
    labels = connected_components(found.where("b is not null").select("a", "b")).withColumnRenamed("node", "alias")
    whole = marks.select("vec_id", "shape", "hi", "lo")
    if heavy:
        rest = spark.createDataFrame([(*key, first) for key, (first, _) in heavy.items()], "s int, h long, l long, first long")
        whole = whole.join(F.broadcast(rest), (F.col("shape") == F.col("s")) & (F.col("hi") == F.col("h")) & (F.col("lo") == F.col("l")), "left")
    else:
        whole = whole.withColumn("first", F.lit(None).cast("long"))
    whole = whole.select("vec_id", F.when(F.col("shape") >= 0, F.coalesce("first", "vec_id")).alias("alias"))
    whole = whole.join(links, "alias", "left").join(labels, "alias", "left")
    return whole.select("vec_id", F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component", "alias", "vec_id").alias("component_id")).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))
