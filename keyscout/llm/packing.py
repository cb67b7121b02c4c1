"""Best-fit packing of token sequences with swap-based local search (operator 2).

Lengths are whole numbers up to the capacity, so the global packing problem is its
length histogram: at most ``capacity`` counters, whatever the corpus size.  Best fit
(longest first) and the local search run on bin *classes* - a pattern of lengths with
the number of bins that share it - and the resulting slots are then dealt out to the
pieces by their rank among pieces of the same length.
"""

from __future__ import annotations

import re
import zlib
from bisect import bisect_left, insort
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from keyscout.llm.cluster import durable
from keyscout.llm.text import chunks, kept_tables


def best_fit(histogram: dict[int, int], capacity: int) -> Counter:
    """Bin classes {pattern (lengths, longest first): bins} of best-fit decreasing."""
    open_: dict[int, list[list]] = {}
    spaces: list[int] = []
    done: Counter = Counter()

    def put(pattern: tuple[int, ...], space: int, bins: int) -> None:
        if bins and space:
            if space not in open_:
                open_[space] = []
                insort(spaces, space)
            open_[space].append([pattern, bins])
        elif bins:
            done[pattern] += bins

    for length in sorted((n for n, c in histogram.items() if c), reverse=True):
        left = histogram[length]
        while left:
            at = bisect_left(spaces, length)
            if at == len(spaces):
                each = capacity // length
                put((length,) * each, capacity - length * each, left // each)
                put((length,) * (left % each), capacity - length * (left % each), int(left % each > 0))
                break
            space = spaces[at]
            pattern, bins = open_[space].pop()
            if not open_[space]:
                del open_[space], spaces[at]
            # a bin that can take several of this length stays the tightest fit after each
            each = min(space // length, left)
            used = min(bins, left // each)
            put(pattern, space, bins - used)
            put(pattern + (length,) * each, space - length * each, used)
            left -= used * each
    for space, rows in open_.items():
        for pattern, bins in rows:
            done[pattern] += bins
    return done


def _improvement(donor: tuple[int, ...], target: tuple[int, ...], capacity: int) -> tuple[tuple[int, ...], tuple[int, ...]] | None:
    """Best move, one-for-one or two-for-one exchange that makes the fuller bin fuller: (given, taken)."""
    space, best, gain = capacity - sum(target), None, 0
    pieces = sorted(set(donor))
    for a in pieces:
        if gain < a <= space:
            best, gain = ((a,), ()), a
        for b in set(target):
            if gain < a - b <= space:
                best, gain = ((a,), (b,)), a - b
    counts = Counter(donor)
    for i, a in enumerate(pieces):
        for c in pieces[i:]:
            if a == c and counts[a] < 2:
                continue
            for b in set(target):
                if gain < a + c - b <= space:
                    best, gain = ((a, c), (b,)), a + c - b
    return best


def _changed(pattern: tuple[int, ...], out: tuple[int, ...], into: tuple[int, ...]) -> tuple[int, ...]:
    left = list(pattern)
    for x in out:
        left.remove(x)
    return tuple(sorted([*left, *into], reverse=True))


def local_search(classes: Counter, capacity: int) -> Counter:
    """Moves and exchanges between underfull bins while the sum of squared fills grows.

    The emptiest bins give first; the search ends when the bin count meets the volume
    bound or no exchange improves.  Whole classes move together, so the work follows
    the number of different patterns.
    """
    classes = Counter({p: c for p, c in classes.items() if c})
    volume = sum(sum(p) * c for p, c in classes.items())
    bound = -(-volume // capacity)
    stuck: set[tuple[int, ...]] = set()
    while sum(classes.values()) > bound:
        under = sorted((p for p in classes if sum(p) < capacity), key=sum)
        donor = next((p for p in under if p not in stuck), None)
        if donor is None:
            break
        best = None
        for target in under:
            if sum(target) < sum(donor) or target == donor and classes[donor] < 2:
                continue
            found = _improvement(donor, target, capacity)
            if found and (best is None or sum(found[0]) - sum(found[1]) > best[0]):
                best = (sum(found[0]) - sum(found[1]), target, *found)
        if best is None:
            stuck.add(donor)
            continue
        _, target, given, taken = best
        bins = classes[donor] // 2 if target == donor else min(classes[donor], classes[target])
        for old in (donor, target):
            classes[old] -= bins
        for new in (_changed(donor, given, taken), _changed(target, taken, given)):
            if new:
                classes[new] += bins
        classes = Counter({p: c for p, c in classes.items() if c})
        stuck.clear()  # new patterns may take what the old ones could not
    return classes


def slots(classes: Counter) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Per length: (first rank, first sequence, offset) of every run of slots, ranks ascending."""
    found: dict[int, list] = {}
    base = 0
    for pattern, bins in sorted(classes.items(), reverse=True):
        at = 0
        for length in pattern:
            found.setdefault(length, []).append((bins, base, at))
            at += length
        base += bins
    out = {}
    for length, rows in found.items():
        bins, first, at = (np.array(c, np.int64) for c in zip(*rows))
        out[length] = (np.r_[0, np.cumsum(bins)[:-1]], first, at)
    return out


def _room(x: np.ndarray, n: int) -> np.ndarray:
    return x if n <= len(x) else np.concatenate([x, np.zeros(max(n - len(x), len(x)), x.dtype)])


class Encoder:
    """Ids of whole texts, equal to the tokenizer's own; one per Python worker.

    The tokenizer drops white space and encodes what stands between it alone, so ids
    are looked up by such a span.  A span of Latin letters that is not yet known is
    lower-cased, cut by the tokenizer's pattern and merged by the same ranks with a
    word-end byte (0xFF never occurs in UTF-8); every other span goes to the tokenizer.
    The table of known spans starts afresh when it is full, which bounds memory, and when
    the worker goes over to another operator.
    """

    SPANS, LONGEST = 350_000, 64
    _kept: dict[str, Encoder] = {}

    def __init__(self, path: str):
        import json

        import regex
        import tiktoken
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_padding()
        self.tokenizer.no_truncation()
        with open(path, encoding="utf-8") as f:
            data = json.load(f)
        suffix = data["model"]["end_of_word_suffix"]
        steps = data["pre_tokenizer"]["pretokenizers"]
        self.pieces = regex.compile(next(x["pattern"]["Regex"] for x in steps if x["type"] == "Split")).findall
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]  # bytes that stand for themselves
        letter = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in set(shown))}
        special = {x["content"] for x in data["added_tokens"]}
        ranks = {}
        for token, i in data["model"]["vocab"].items():
            if token not in special:
                end = token.endswith(suffix) and token != suffix
                ranks[bytes(letter[c] for c in (token[: -len(suffix)] if end else token)) + b"\xff" * end] = i
        self.merge = tiktoken.Encoding("spans", pat_str=r"[\s\S]+", mergeable_ranks=ranks, special_tokens={})._core_bpe.encode_single_piece
        self._clear()

    def _clear(self) -> None:
        self.known: dict[str, int] = {}
        self.ids, self.size = np.zeros(1 << 20, np.uint32), 0
        self.first, self.length = np.zeros(1 << 16, np.int64), np.zeros(1 << 16, np.int64)

    @classmethod
    def of(cls, path: str) -> Encoder:
        if path not in cls._kept:
            cls._kept[path] = cls(path)
            kept_tables["packing"] = cls._drop
        return cls._kept[path]

    @classmethod
    def _drop(cls) -> bool:
        """Known spans are forgotten (and learnt again when needed); the vocabulary stays."""
        full = [e for e in cls._kept.values() if e.known]
        for e in full:
            e._clear()
        return bool(full)

    def _learn(self, spans: set[str]) -> None:
        rest, names, ids, ends = [], [], [], []
        merge, pieces, longest = self.merge, self.pieces, self.LONGEST
        for span in spans:
            if len(span) <= longest and (span.isascii() or max(span) < "\u0250") and "<|" not in span:
                small = span.lower()
                if small.isalpha():
                    ids += merge(small.encode() + b"\xff")
                else:
                    for piece in pieces(small):
                        ids += merge(piece.encode() + b"\xff")
                names.append(span)
                ends.append(len(ids))
            else:
                rest.append(span)
        for span, e in zip(rest, self.tokenizer.encode_batch_fast(rest, add_special_tokens=False) if rest else ()):
            ids += e.ids
            names.append(span)
            ends.append(len(ids))
        at, n = len(self.known), len(ids)
        self.ids = _room(self.ids, self.size + n)
        self.ids[self.size : self.size + n] = ids
        self.first, self.length = _room(self.first, at + len(names)), _room(self.length, at + len(names))
        edges = np.array([0, *ends], np.int64)
        self.first[at : at + len(names)], self.length[at : at + len(names)] = edges[:-1] + self.size, np.diff(edges)
        self.known.update(zip(names, range(at, at + len(names))))
        self.size += n

    def __call__(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of each text.  Control characters that only Python takes for white space send a text to the tokenizer whole."""
        odd = [i for i, t in enumerate(texts) if _ODD(t)]
        spans = [t.split() for t in texts]
        for i in odd:
            spans[i] = []
        new = set().union(*spans).difference(self.known)
        if new:
            if len(self.known) > self.SPANS:  # the table starts afresh: all of these spans are needed again
                self._clear()
                new = set().union(*spans)
            self._learn(new)
        known = self.known
        at = np.fromiter((known[s] for row in spans for s in row), np.int64, sum(map(len, spans)))
        length = self.length[at]
        ends = np.cumsum(length)
        ids = self.ids[np.repeat(self.first[at] - ends + length, length) + np.arange(ends[-1] if len(ends) else 0)]
        cut = np.r_[0, ends][np.cumsum([0, *map(len, spans)])]
        out = [ids[a:b] for a, b in zip(cut[:-1], cut[1:])]
        for i in odd:
            out[i] = np.array(self.tokenizer.encode(texts[i], add_special_tokens=False).ids, np.uint32)
        return out


_ODD = re.compile("[\x1c-\x1f]").search


_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def _cut(path: str, capacity: int, end_id: int):
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        encode = Encoder.of(path)
        for batch in batches:
            for part in chunks(batch):
                docs, rows = part.column(0).to_pylist(), []
                for doc, ids in zip(docs, encode(pc.fill_null(part.column(1), "").to_pylist())):
                    ids = np.append(ids, np.uint32(end_id)).astype("<u4")
                    for k in range(0, len(ids), capacity):
                        piece = ids[k : k + capacity]
                        rows.append((doc, k // capacity, k, len(piece), zlib.crc32(piece.tobytes())))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()))], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return work


def pack_documents(documents: DataFrame, tokenizer: str, capacity: int = 2048, end_id: int = 0) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, sequence_id, offset) for every piece.

    A document is its ids and ``end_id``; longer ones are cut every ``capacity`` ids.
    Every piece gets a place in a sequence of at most ``capacity`` ids, without gaps.

    Edge cases: null and empty texts are the end id alone; a null ``doc_id`` is packed
    like any other and returned as null; repeated rows are packed each; an empty table
    gives an empty result; other columns are ignored.
    """
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    pieces = durable(docs.mapInArrow(_cut(tokenizer, capacity, end_id), _PIECES).withColumn("task", F.spark_partition_id()))
    counts = pieces.groupBy("length", "task").agg(F.count("*").alias("n"))
    # at most ``capacity`` rows reach the driver
    histogram = {r.length: r.n for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    table = slots(local_search(best_fit(histogram, capacity), capacity))
    shared = documents.sparkSession.sparkContext.broadcast(table)
    # rank within a length: rank within the task that cut the piece, plus the tasks before
    before = counts.withColumn("before", F.sum("n").over(Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1))).select(F.col("length").alias("len"), F.col("task").alias("by"), F.coalesce("before", F.lit(0)).alias("before"))
    local = pieces.withColumn("row", F.row_number().over(Window.partitionBy("task", "length").orderBy("doc_id", "piece", "ids_crc32")) - 1)
    ranked = local.join(before, (F.col("length") == F.col("len")) & (F.col("task") == F.col("by"))).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("row") + F.col("before")).alias("rank"))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        where = shared.value
        for batch in batches:
            length, rank = batch.column(3).to_numpy(), batch.column(5).to_numpy()
            sequence, offset = np.zeros(len(rank), np.int64), np.zeros(len(rank), np.int64)
            order = np.argsort(length, kind="stable")
            cut = np.flatnonzero(np.r_[True, np.diff(length[order]) != 0]) if len(order) else []
            for rows in np.split(order, cut[1:]) if len(order) else []:
                first, base, at = where[int(length[rows[0]])]
                run = np.searchsorted(first, rank[rows], "right") - 1
                sequence[rows], offset[rows] = base[run] + rank[rows] - first[run], at[run]
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(sequence), pa.array(offset)], names=["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return ranked.mapInArrow(place, f"{_PIECES}, sequence_id long, offset long")
