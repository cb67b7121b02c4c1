"""Subword encoding as a shortest path through composed transducers (operator 6).

Three machines: the normaliser (white space to the piece mark, and one mark in front),
the lexicon (pieces, and byte pieces for characters without one), and an acceptor of
piece pairs.  A merge-based vocabulary is a constraint on neighbours - two pieces may
stand side by side only if merging their joined text gives just the two - so the
composition accepts exactly one path per input and that path is its tropical shortest
one.  The search takes long pieces first, remembers dead states, and is therefore
linear in the text.  Texts are cut where no piece can cross: before a run of marks and
around characters without a piece.
"""

from __future__ import annotations

import heapq
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyscout.llm.text import chunks

MARK = "▁"
#: spans and neighbour pairs kept per worker, longest span kept
SPANS, PAIRS, LONGEST = 500_000, 2_000_000, 48


class SubwordTransducer:
    """Encoder and decoder of one merge-based subword model with byte fallback."""

    _kept: dict[str, SubwordTransducer] = {}

    def __init__(self, path: str):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        size = model.get_piece_size()
        plain = [i for i in range(size) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i) or model.is_unused(i))]
        self.text = [model.id_to_piece(i) for i in range(size)]
        self.lexicon = {self.text[i]: i for i in plain}
        self.rank = {self.text[i]: model.get_score(i) for i in plain}
        self.byte = [model.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
        self.byte_of = {i: b for b, i in enumerate(self.byte)}
        # bytes of every id that is text
        self.raw = {i: self.text[i].encode() for i in plain} | {i: bytes([b]) for i, b in self.byte_of.items()}
        self.is_byte = np.isin(np.arange(size), self.byte)
        self.longest = max(map(len, self.lexicon))
        if any(MARK in t.lstrip(MARK) for t in self.lexicon):
            raise ValueError("a piece crosses a space; texts cannot be cut before spaces")
        self.pairs: dict[int, bool] = {}
        # a piece that its own merges never reach is no arc
        self.halves: dict[str, tuple[str, str]] = {}
        self.lexicon = {t: i for t, i in self.lexicon.items() if self._merged(t) == [t]}
        # arcs of the lexicon by three leading characters: lengths, longest first
        lengths: dict[str, set[int]] = {}
        for t in self.lexicon:
            if len(t) > 2:
                lengths.setdefault(t[:3], set()).add(len(t))
        self.arcs = {t: (*sorted(n, reverse=True), 2, 1) for t, n in lengths.items()}
        alphabet = "".join(re.escape(t) for t in self.lexicon if len(t) == 1 and t != MARK)
        self.cut = re.compile(f"{MARK}*[{alphabet}]+|{MARK}+|[^{alphabet}{MARK}]").findall
        self.spans: dict[str, tuple[int, ...]] = {}

    @classmethod
    def of(cls, path: str) -> SubwordTransducer:
        if path not in cls._kept:
            cls._kept[path] = cls(path)
        return cls._kept[path]

    def _merged(self, text: str) -> list[str]:
        """Pieces by merging: best score first, then leftmost (the definition; for short texts)."""
        parts: list[str | None] = list(text)
        right = [*range(1, len(parts)), -1]
        left = list(range(-1, len(parts) - 1))
        rank, heap = self.rank, []

        def offer(i: int) -> None:
            j = right[i]
            if j >= 0 and (joined := parts[i] + parts[j]) in rank:
                heapq.heappush(heap, (-rank[joined], i, joined))

        for i in range(len(parts) - 1):
            offer(i)
        while heap:
            _, i, joined = heapq.heappop(heap)
            j = right[i] if parts[i] is not None else -1
            if j < 0 or parts[i] + parts[j] != joined:
                continue
            if joined == text:
                self.halves[joined] = parts[i], parts[j]
            parts[i], parts[j], right[i] = joined, None, right[j]
            if right[j] >= 0:
                left[right[j]] = i
            offer(i)
            if left[i] >= 0:
                offer(left[i])
        return [p for p in parts if p is not None]

    def _side_by_side(self, a: int, b: int) -> bool:
        """Whether merging the joined text of two pieces gives just the two."""
        key = a << 20 | b
        found = self.pairs.get(key)
        if found is None:
            if len(self.pairs) >= PAIRS:
                self.pairs.clear()
            found = self.pairs[key] = self._border(self.text[a], self.text[b])
        return found

    def _border(self, left: str, right: str) -> bool:
        """No merge across the border comes before the merges that built both pieces.

        The later of the two last merges is undone step by step; what then touches the
        border must not form a piece that would have been merged earlier.  Runs of marks
        share one score, so there the merging itself decides.
        """
        if MARK + MARK in left + right:
            return self._merged(left + right) == [left, right]
        rank, halves, before = self.rank, self.halves, float("inf")
        while True:
            joined = rank.get(left + right)
            if joined is not None and -joined < before:
                return False
            x = -rank[left] if len(left) > 1 else -1.0
            y = -rank[right] if len(right) > 1 else -1.0
            if x < 0 and y < 0:
                return True
            if x > y:
                before, left = x, halves[left][1]
            else:  # at one score the leftmost merge goes first
                before, right = y + 0.5, halves[right][0]

    def _path(self, span: str) -> list[int]:
        """The accepted path over one span of characters that all have pieces."""
        lookup, arcs, pairs, n = self.lexicon.get, self.arcs, self.pairs, len(span)
        path: list[int] = []
        ends: list[int] = [0]
        dead: set[tuple[int, int]] = set()
        below = n + 1
        while (at := ends[-1]) < n:
            for size in arcs.get(span[at : at + 3], (2, 1)):
                if size >= below or at + size > n:
                    continue
                piece = lookup(span[at : at + size])
                if piece is None or (dead and (at + size, piece) in dead):
                    continue
                if path:
                    fits = pairs.get(path[-1] << 20 | piece)
                    if not (self._side_by_side(path[-1], piece) if fits is None else fits):
                        continue
                path.append(piece)
                ends.append(at + size)
                below = n + 1
                break
            else:  # nothing follows: the state is dead, try a shorter piece before it
                if not path:  # no accepted path at all: merging decides
                    return [i for p in self._merged(span) for i in ([lookup(p)] if p in self.lexicon else [self.byte[b] for b in p.encode()])]
                end = ends.pop()
                dead.add((end, path.pop()))
                below = end - ends[-1]
        return path

    def _arcs(self, span: str) -> tuple[int, ...]:
        if len(span) == 1 and span not in self.lexicon:
            return tuple(self.byte[b] for b in span.encode())
        return tuple(self._path(span))

    def encode(self, text: str) -> list[int]:
        """Ids of a text; the empty text has none."""
        if not text:
            return []
        out: list[int] = []
        known = self.spans
        for span in self.cut(MARK + text.replace(" ", MARK)):
            ids = known.get(span)
            if ids is None:
                ids = self._arcs(span)
                if len(span) <= LONGEST:
                    if len(known) >= SPANS:
                        known.clear()
                    known[span] = ids
            out += ids
        return out

    def decode(self, ids: list[int]) -> str:
        """Text of ids: byte pieces as UTF-8 (bad sequences replaced), marks as spaces, the first mark dropped."""
        try:
            # pieces are whole characters, so bytes on both sides of one never join
            text = b"".join(map(self.raw.__getitem__, ids)).decode("utf-8", "replace")
        except (KeyError, TypeError):
            text = self._decode_runs(ids)
        if ids and ids[0] not in self.byte_of and text.startswith(MARK):
            text = text[1:]
        return text.replace(MARK, " ")

    def _decode_runs(self, ids: list[int]) -> str:
        """Ids of which some are no text (they part the bytes around them)."""
        out, held = [], bytearray()
        for i in ids:
            b = self.byte_of.get(i)
            if b is not None:
                held.append(b)
                continue
            if held:
                out.append(held.decode("utf-8", "replace"))
                held.clear()
            if i in self.raw:
                out.append(self.text[i])
        if held:
            out.append(held.decode("utf-8", "replace"))
        return "".join(out)


def encode_documents(documents: DataFrame, model: str) -> DataFrame:
    """(doc_id, ids array<int>) of every row; null and empty texts have no ids.

    Repeated rows are encoded each, a null ``doc_id`` is kept, other columns are
    ignored.  A text that itself holds the piece mark encodes like one with a space
    there (as the vocabulary's own normaliser does), so only such texts do not come
    back as they were.
    """

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = SubwordTransducer.of(model)
        for batch in batches:
            for part in chunks(batch, limit=4 << 20):
                rows = [machine.encode(t) for t in pc.fill_null(part.column(1), "").to_pylist()]
                at = np.r_[0, np.cumsum([len(r) for r in rows])].astype(np.int32)
                flat = np.fromiter((i for r in rows for i in r), np.int32, int(at[-1]))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(pa.array(at), pa.array(flat))], names=["doc_id", "ids"])

    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return docs.mapInArrow(work, "doc_id long, ids array<int>")


def decode_documents(encoded: DataFrame, model: str) -> DataFrame:
    """(doc_id, text) from (doc_id, ids); null ids decode to the empty text."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = SubwordTransducer.of(model)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([machine.decode(i or []) for i in batch.column(1).to_pylist()], pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(work, "doc_id long, text string")


def encoding_digests(documents: DataFrame, model: str) -> DataFrame:
    """(doc_id, n_ids, n_byte_ids, ids_crc32, round_trip): encoding and decoding of every row in one pass.

    ``ids_crc32`` covers the ids as little-endian unsigned 32-bit numbers.  Null and empty
    texts have no ids; repeated rows and null ids keep a row each.
    """

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = SubwordTransducer.of(model)
        for batch in batches:
            for part in chunks(batch, limit=4 << 20):
                rows = []
                for doc, text in zip(part.column(0).to_pylist(), pc.fill_null(part.column(1), "").to_pylist()):
                    ids = machine.encode(text)
                    raw = np.array(ids, "<u4")
                    n_bytes = int(np.count_nonzero(machine.is_byte[raw]))
                    rows.append((doc, len(ids), n_bytes, zlib.crc32(raw.tobytes()), machine.decode(ids) == text.replace(MARK, " ")))
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.bool_()))], names=["doc_id", "n_ids", "n_byte_ids", "ids_crc32", "round_trip"])

    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return docs.mapInArrow(work, "doc_id long, n_ids long, n_byte_ids long, ids_crc32 long, round_trip boolean")
