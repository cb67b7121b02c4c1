"""Vectorised text kernels shared by the operators (numpy over Arrow buffers).

All kernels work on a *chunk*: the UTF-8 bytes of consecutive texts plus their
offsets.  Chunks are cut by bytes, so one Arrow batch with many long texts never
inflates into a batch-sized set of 8-byte temporaries; a single text longer than
the limit is a chunk of its own (its whole content is always processed).
"""

from __future__ import annotations

import contextlib
import ctypes
import gc
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U = np.uint64
#: ASCII white space of the word contract: 0x20 and 0x09-0x0D.
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
LOWER_TABLE = bytes(_LOWER)
_BASE = U(0x9E3779B97F4A7C15 | 1)
_INVERSE = U(pow(int(_BASE), -1, 1 << 64))
_powers: dict[str, np.ndarray] = {}


def _power(which: str, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64, grown by doubling and kept per process."""
    have = _powers.get(which)
    if have is None or len(have) < n:
        size = 1 << max(12, (n - 1).bit_length())
        row = np.full(size, _BASE if which == "up" else _INVERSE, U)
        row[0] = 1
        have = _powers[which] = np.multiply.accumulate(row, dtype=U)
    return have[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every input bit over the 64-bit word."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
        return x ^ (x >> U(31))


def string_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; null counts as the empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "")
    wide = pa.types.is_large_string(column.type)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def unused_names(columns: list[str], *wanted: str) -> list[str]:
    """``wanted`` behind a prefix of underscores that no name of ``columns`` starts with."""
    prefix = "_"
    while any(c.startswith(prefix) for c in columns):
        prefix += "_"
    return [prefix + w for w in wanted]


def chunks(batch: pa.RecordBatch, column: str = "text", limit: int = 1 << 18, rows: int | None = None) -> Iterator[pa.RecordBatch]:
    """Slices of a batch of at most ``limit`` text bytes and ``rows`` rows each (one row at least)."""
    if not batch.num_rows:
        return
    _, at = string_buffers(batch.column(batch.schema.get_field_index(column)))
    row = 0
    while row < batch.num_rows:
        end = max(row + 1, int(np.searchsorted(at, at[row] + limit, "right")) - 1)
        end = end if rows is None else min(end, row + rows)
        yield batch.slice(row, end - row)
        row = end


#: by operator: drops the tables that it keeps in a Python worker for its next tasks, and says whether there were any
kept_tables: dict[str, Callable[[], bool]] = {}


def make_room() -> None:
    """Called where tasks of an operator without such tables begin: a worker outlives its stage, the tables of others must not."""
    if any([drop() for drop in kept_tables.values()]):
        gc.collect()
        pa.default_memory_pool().release_unused()
        with contextlib.suppress(OSError, AttributeError):  # freed pages go back where the C library can do that
            ctypes.CDLL(None).malloc_trim(0)


class Words:
    """Words of a chunk: byte spans, owner text, and a 64-bit hash of each."""

    def __init__(self, column: pa.Array | tuple[np.ndarray, np.ndarray], hashes: bool = True, blanks: np.ndarray = _SPACE):
        raw, self.offsets = column if isinstance(column, tuple) else string_buffers(column)
        self.bytes = _LOWER[raw]
        self.n_texts = len(self.offsets) - 1
        blank = blanks[raw]
        n = len(raw)
        first = np.zeros(n + 1, bool)
        first[self.offsets] = True  # a text's first byte never continues a word of the text before
        inside = ~blank
        starts = inside.copy()
        starts[1:] &= blank[:-1] | first[1:n]
        ends = inside.copy()
        ends[:-1] &= blank[1:] | first[1:n]
        self.start = np.flatnonzero(starts)
        self.end = np.flatnonzero(ends) + 1
        self.owner = np.searchsorted(self.offsets, self.start, "right") - 1
        self.count = np.bincount(self.owner, minlength=self.n_texts) if len(self.owner) else np.zeros(self.n_texts, np.int64)
        if hashes:
            self.hash = self._hashes(n)

    def _hashes(self, n: int) -> np.ndarray:
        with np.errstate(over="ignore"):
            total = np.zeros(n + 1, U)
            np.cumsum((self.bytes.astype(U) + U(1)) * _power("up", n), out=total[1:])
            self._total = total
            return self._span_hash(self.end)

    def _span_hash(self, end: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            value = (self._total[end] - self._total[self.start]) * _power("down", len(self._total))[self.start]
            return mix(value + (end - self.start).astype(U) * U(0xD6E8FEB86659FD93))

    def prefix_hash(self, size: int) -> np.ndarray:
        """Hash of each word's first ``size`` bytes (of the whole word where it is shorter)."""
        return self._span_hash(np.minimum(self.start + size, self.end))

    def strings(self) -> list[bytes]:
        data = self.bytes.tobytes()
        return [data[a:b] for a, b in zip(self.start.tolist(), self.end.tolist())]


def shingle_sets(column: pa.Array, width: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Distinct word shingles of every text of a chunk: (owner, hash), sorted by both.

    A text with fewer than ``width`` words but at least one has the whole sequence
    as its only shingle; a text without words has none.
    """
    words = Words(column)
    n = len(words.hash)
    with np.errstate(over="ignore"):
        if n >= width:
            value = words.hash[: n - width + 1].copy()
            for k in range(1, width):
                value = value * U(0xFF51AFD7ED558CCD) + words.hash[k : n - width + 1 + k]
            whole = words.owner[: n - width + 1] == words.owner[width - 1 :]
            value, owner = mix(value[whole] + U(width)), words.owner[: n - width + 1][whole]
        else:
            value, owner = np.zeros(0, U), np.zeros(0, np.int64)
        short = np.flatnonzero((words.count > 0) & (words.count < width))
        if len(short):
            at = np.concatenate([[0], np.cumsum(words.count)])
            extra = []
            for t in short.tolist():
                h = int(words.hash[at[t]])
                for w in words.hash[at[t] + 1 : at[t + 1]].tolist():
                    h = (h * 0xFF51AFD7ED558CCD + w) & 0xFFFFFFFFFFFFFFFF
                extra.append((h + int(words.count[t])) & 0xFFFFFFFFFFFFFFFF)
            value = np.concatenate([value, mix(np.array(extra, U))])
            owner = np.concatenate([owner, short])
    order = np.lexsort((value, owner))
    value, owner = value[order], owner[order]
    if len(value):
        keep = np.ones(len(value), bool)
        keep[1:] = (value[1:] != value[:-1]) | (owner[1:] != owner[:-1])
        value, owner = value[keep], owner[keep]
    return owner, value
