"""Line deduplication by range-partitioned key hashes (operator 5).

Line keys are dealt by range over (key hash, document) and sorted by document from
the largest down, so the first occurrence of a run is the one that stays.  A key held
by a third of all documents spreads over many ranges; only the first and last run of
a range can continue elsewhere, and those boundary runs (two per partition at most)
are the only thing gathered.  What comes out is a zlib-compressed keep bitmap per
document that loses lines; texts are never grouped.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyscout.llm.cluster import durable
from keyscout.llm.text import chunks, make_room, unused_names

BLANK = " \t\n\x0b\x0c\r"
_UPPER = {c: c + 32 for c in range(65, 91)}


def line_key(line: str) -> str:
    return line.strip(BLANK).translate(_UPPER)


def _mark(text: str) -> int:
    """Fingerprint of a text as a signed long; tells rows with one doc_id but two texts apart."""
    value = xxhash.xxh3_64_intdigest(text.encode())
    return value - (1 << 64) if value >= 1 << 63 else value


_LINES = pa.schema([("high", pa.int64()), ("low", pa.int64()), ("doc_id", pa.int64()), ("mark", pa.int64()), ("position", pa.int32())])
_DROPS = pa.schema([("doc_id", pa.int64()), ("mark", pa.int64()), ("position", pa.int32())])
_ENDS = pa.schema([("high", pa.int64()), ("low", pa.int64()), ("docs", pa.int64()), ("top", pa.int64())])


def _occurrences(shortest: int):
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make_room()
        for batch in batches:
            for part in chunks(batch, limit=4 << 20):
                keys, docs, marks, places = bytearray(), [], [], []
                for doc, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    if doc is None or not text or len(text) < shortest:
                        continue
                    mark = _mark(text)
                    for at, line in enumerate(text.split("\n")):
                        if len(line) >= shortest and len(key := line.strip(BLANK)) >= shortest:
                            keys += xxhash.xxh3_128_digest(key.translate(_UPPER).encode())
                            docs.append(doc)
                            marks.append(mark)
                            places.append(at)
                pair = np.frombuffer(bytes(keys), np.int64).reshape(-1, 2)
                yield pa.RecordBatch.from_arrays([pa.array(pair[:, 0]), pa.array(pair[:, 1]), pa.array(docs, pa.int64()), pa.array(marks, pa.int64()), pa.array(places, pa.int32())], schema=_LINES)

    return work


class _Run:
    """State of the run being streamed: its key, documents so far, and rows not yet decided."""

    __slots__ = ("key", "docs", "top", "last", "held", "first")

    def __init__(self, key, doc, first):
        self.key, self.docs, self.top, self.last, self.held, self.first = key, 0, doc, None, [], first


def _count(run, doc, s, e):
    part = doc[s:e]
    run.docs += int((part[1:] != part[:-1]).sum()) + int(run.last is None or part[0] != run.last)
    run.last = part[-1]


def _boundaries(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Summary of the first and the last run of a range; every other run is complete here."""
    found = []

    def rows(run, batch, s, e, doc):
        _count(run, doc, s, e)

    def end(run, last):
        if run.first or last:
            found.append((*run.key, run.docs, run.top))

    for _ in _step(batches, rows, end):
        pass
    yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in found], pa.int64()) for i in range(4)], schema=_ENDS)


def _drops(least_docs: int, shared):
    """Rows to drop: lines of a key with enough documents, outside its largest document.

    A row waits only until its run has ``least_docs`` documents; later rows leave at once.
    """

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = shared.value
        out: list[pa.RecordBatch] = []

        def give(run, part):
            top = known.get(run.key, (0, run.top))[1]
            part = part.filter(pa.array(part.column(2).to_numpy() != top))
            if part.num_rows:
                out.append(pa.RecordBatch.from_arrays([part.column(2), part.column(3), part.column(4)], schema=_DROPS))

        def rows(run, batch, s, e, doc):
            _count(run, doc, s, e)
            run.held.append(batch.slice(s, e - s))
            if known.get(run.key, (run.docs, 0))[0] >= least_docs:
                for part in run.held:
                    give(run, part)
                run.held.clear()

        def end(run, last):
            run.held.clear()

        # results leave batch by batch: the generator below drains ``out`` as it fills
        for _ in _step(batches, rows, end):
            if len(out) >= 256:
                yield from _packed(out)
        yield from _packed(out)

    return work


def _step(batches, rows, end):
    """Streams sorted rows run by run: rows(run, batch, start, end, doc), end(run, is_last); pauses after every batch."""
    run = None
    make_room()
    for batch in batches:
        n = batch.num_rows
        if n:
            high, low, doc = (batch.column(i).to_numpy() for i in range(3))
            new = np.ones(n, bool)
            new[1:] = (high[1:] != high[:-1]) | (low[1:] != low[:-1])
            if run is not None and run.key == (high[0], low[0]):
                new[0] = False
            starts = np.flatnonzero(new)
            ends = np.r_[starts[1:], n]
            head = int(starts[0]) if len(starts) else n
            if head:
                rows(run, batch, 0, head, doc)
            for s, e in zip(starts.tolist(), ends.tolist()):
                if run is not None:
                    end(run, False)
                run = _Run((int(high[s]), int(low[s])), int(doc[s]), run is None)
                rows(run, batch, s, e, doc)
        yield
    if run is not None:
        end(run, True)


def _packed(out):
    if out:
        table = pa.Table.from_batches(out).combine_chunks()
        out.clear()
        yield from table.to_batches()


def _bitmaps(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Dropped positions of a document as a compressed keep bitmap (1: the line stays).

    Lines behind the last dropped one are not part of the bitmap: they stay.
    """
    make_room()
    for batch in batches:
        maps = []
        for places in batch.column(2).to_pylist():
            keep = np.ones((max(places) // 8 + 1) * 8, bool)
            keep[places] = False
            maps.append(zlib.compress(np.packbits(keep).tobytes(), 1))
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([len(p) for p in batch.column(2).to_pylist()], pa.int64()), pa.array(maps, pa.binary())], names=["doc_id", "mark", "n_dropped", "keep"])


def line_keep_bitmaps(documents: DataFrame, shortest: int = 40, least_docs: int = 5) -> DataFrame:
    """(doc_id, mark, n_dropped, keep) for every document that loses a line.

    Keys of at least ``shortest`` code points found in ``least_docs`` or more documents
    stay only in the largest ``doc_id`` that holds them.  ``mark`` fingerprints the text
    (rows may share a ``doc_id``; they count as one document).  Rows with a null
    ``doc_id`` are not counted and lose nothing; null or empty texts have one empty line.
    """
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    # narrow rows, kept: dealing by range reads them twice, and texts should be split once
    lines = durable(docs.mapInArrow(_occurrences(shortest), "high long, low long, doc_id long, mark long, position int"))
    ranged = durable(lines.repartitionByRange("high", "low", F.col("doc_id").desc()).sortWithinPartitions("high", "low", F.col("doc_id").desc(), "mark", "position"))
    # two rows per partition at most: a bound that follows the partition count, not the rows
    ends = ranged.mapInArrow(_boundaries, "high long, low long, docs long, top long").groupBy("high", "low").agg(F.sum("docs").alias("docs"), F.max("top").alias("top")).collect()
    shared = documents.sparkSession.sparkContext.broadcast({(r.high, r.low): (r.docs, r.top) for r in ends})
    drops = ranged.mapInArrow(_drops(least_docs, shared), "doc_id long, mark long, position int")
    each = drops.groupBy("doc_id", "mark").agg(F.collect_set("position").alias("positions"))
    return each.mapInArrow(_bitmaps, "doc_id long, mark long, n_dropped long, keep binary")


def _kept_text(text: str | None, keep: bytes | None) -> tuple[str, int, int]:
    lines = (text or "").split("\n")
    if keep is None:
        return text or "", len(lines), 0
    bits = np.unpackbits(np.frombuffer(zlib.decompress(keep), np.uint8))
    stays = [line for i, line in enumerate(lines) if i >= len(bits) or bits[i]]
    return "\n".join(stays), len(lines), len(lines) - len(stays)


def apply_keep_bitmaps(documents: DataFrame, bitmaps: DataFrame, counts: bool = True) -> DataFrame:
    """documents with ``text`` cut to its kept lines, plus n_lines and n_dropped (in place of
    input columns of these names; without ``counts`` the columns stay as they are).

    Null texts count as empty.  A document keeps its row even if all its lines go.
    """
    documents = documents.drop("n_lines", "n_dropped") if counts else documents
    names = documents.columns
    added = ["n_lines", "n_dropped"] * counts
    mark, doc, own, kept = unused_names(names, "mark", "doc", "text", "keep")

    def marks(batches):
        make_room()
        for batch in batches:
            texts = batch.column(batch.schema.get_field_index("text")).to_pylist()
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([_mark(t or "") for t in texts], pa.int64())], names=[*batch.schema.names, mark])

    def cut(batches):
        make_room()
        for batch in batches:
            for part in chunks(batch, limit=16 << 20):
                at = part.schema.get_field_index("text")
                done = [_kept_text(t, k) for t, k in zip(part.column(at).to_pylist(), part.column(part.schema.get_field_index(kept)).to_pylist())]
                columns = [pa.array([d[0] for d in done], pa.string()) if n == "text" else part.column(part.schema.get_field_index(n)) for n in names]
                columns += [pa.array([d[1] for d in done], pa.int64()), pa.array([d[2] for d in done], pa.int64())] * counts
                yield pa.RecordBatch.from_arrays(columns, names=[*names, *added])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in documents.schema.fields)
    marked = documents.mapInArrow(marks, f"{schema}, `{mark}` long")
    sides = bitmaps.select(F.col("doc_id").alias(doc), F.col("mark").alias(own), F.col("keep").alias(kept))
    joined = marked.join(sides, (F.col("doc_id") == F.col(doc)) & (F.col(mark) == F.col(own)), "left").drop(doc, own, mark)
    return joined.mapInArrow(cut, ", ".join([schema, *(f"{n} long" for n in added)]))
