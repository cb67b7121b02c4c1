"""Language-model scores by online logistic context mixing (operator 3).

Every token is spelled bit by bit: each byte and the end of the token are binary decisions
of a code over the byte's rank among those that came after the two bytes before it.  A decision is predicted by several hashed contexts - the bytes before it
in the word, the whole beginning of the word, the same inside the text's class (one of the
commonest ``lang`` values, guessed from the blocks read so far), and, over the word border,
the end of the word before - whose tables hold how often either branch was taken in training,
every occurrence counted.  Their opinions are mixed in the logistic domain; a gate (which
contexts have one) picks the starting weights, which Newton steps over all training words
have set, and every block of the scored text moves them on.

Over the bits stands a refinement by exact word sequences: a token may follow the two
tokens before it, or the one before it, as it did in training.  Whether such a context is
followed is a binary decision too, mixed from how often the context occurred and how long
it has just been right, with weights that move with every block.  What a token costs
depends on earlier tokens of the same text only, so the bits of a text add up to its code
length; divided by its bytes that is the model's bits per byte.  A training text is not told by its
own word sequences: they are taken out of the counts.

Corpus statistics never meet in one place: documents are dealt in groups, a group
sends each of its distinct words and word sequences (hashes whose length follows the
corpus) with its training counts once, word shards add them up and answer every group with
its words' counts; the training words of the shards, with their frequencies, fill the
context tables.  Tables are added up in a tree; only they (their slots follow the
distinct training words up to what a broadcast holds), gate weights and totals reach the driver.
"""

from __future__ import annotations

import heapq
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyscout.llm.cluster import durable
from keyscout.llm.labelled import fold
from keyscout.llm.text import U, Words, _power, chunks, mix

#: contexts inside a word: place, the 1 to 4 bytes before, the whole beginning, the whole beginning within the class;
#: one more reaches over the border.  Least and most slots of one as bits, slots per distinct training word, slots of the border's
INSIDE, SLOT_BITS, MOST_SLOT_BITS, ROOM, BORDER_BITS = 7, 16, 21, 8, 18
GATES = 2 * INSIDE
#: group of each inside context (short, long, whole, class), inputs of the second layer (the groups and the border)
GROUP, LAYER = (0, 0, 0, 1, 1, 2, 3), 5
#: slices that tables are added up in, tables one task adds up, Newton steps of a piece of words on the gate weights
SLICES, FAN_IN, STEPS = 64, 32, 4
#: text classes beside the rest
CLASSES = 7
#: text bytes of a group, tokens of a document's first block and of its largest
GROUP_BYTES, FIRST_BLOCK, LAST_BLOCK = 8 << 20, 4, 64
#: learning rates of a document's mixing weights and of its word-context weights, and where the latter start
#: (per context: bias, log count of the context, whether it knew the token before, log of how many in a row it knew)
RATE, TRUST_RATE = 0.02, 0.05
TRUST = np.array([[-2.0, 0.1, 1.0, 1.0], [-2.0, 0.1, 0.5, 0.5]])
#: weight of the border context before a text moves it, count that stands for none
BORDER_WEIGHT, NONE = 0.3, 0.4
#: tokens that a step of the scoring takes on, decisions whose contexts are looked up at once: both stay in a core's cache
PIECE_TOKENS, AT_ONCE = 4096, 1 << 16
_END_WORD, _END_TEXT = 0x20, 0xFF  # neither occurs inside a UTF-8 word


class ByteCode:
    """Prefix code over 256 symbols: per symbol its inner nodes and the branches taken there.

    A byte's symbol is its rank among the bytes that came after the two bytes before it in the word (``rank``, by rows
    that ``row`` names for every two bytes); without ranks it is the byte.  Ranks are spelled in fewer decisions.
    """

    def __init__(self, counts: np.ndarray, row: np.ndarray | None = None, rank: np.ndarray | None = None):
        self.row, self.rank = row, rank
        heap = [(int(n) + 1, v) for v, n in enumerate(counts)]
        heapq.heapify(heap)
        children: dict[int, tuple[int, int]] = {}
        for node in range(256, 511):
            (a, x), (b, y) = heapq.heappop(heap), heapq.heappop(heap)
            children[node] = (x, y)
            heapq.heappush(heap, (a + b, node))
        paths: dict[int, list[tuple[int, int]]] = {510: []}
        for node in range(510, 255, -1):
            for bit, child in enumerate(children[node]):
                paths[child] = [*paths[node], (node - 256, bit)]
        self.size = np.array([len(paths[v]) for v in range(256)])
        self.first = np.r_[0, np.cumsum(self.size)[:-1]]
        self.node = np.array([n for v in range(256) for n, _ in paths[v]], np.int64)
        self.bit = np.array([b for v in range(256) for _, b in paths[v]], np.int8)

    @classmethod
    def ranking(cls, before: np.ndarray, byte: np.ndarray, counts: np.ndarray) -> ByteCode:
        """From counts of bytes after two bytes; bytes that never came there rank behind, in the order of all counts."""
        overall = np.argsort(-np.bincount(byte, counts, 256), kind="stable")
        behind = np.empty(256)
        behind[overall] = np.arange(256) / -256
        seen, at = np.unique(before, return_inverse=True)
        row, rank = np.zeros(1 << 16, np.int32), np.empty((len(seen) + 1, 256), np.uint8)
        row[seen] = np.arange(1, len(seen) + 1)
        rank[0] = np.argsort(overall)
        for s in range(0, len(seen), 4096):
            mine = (at >= s) & (at < s + 4096)
            table = np.zeros((min(4096, len(seen) - s), 256)) + behind
            table[at[mine] - s, byte[mine]] += counts[mine]
            rank[s + 1 : s + 1 + len(table)] = np.argsort(np.argsort(-table, axis=1), axis=1)
        return cls(np.bincount(rank[row[before], byte], counts, 256).astype(np.int64), row, rank)

    def symbols(self, raw: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Symbols of the bytes of tokens spelled in raw[at[i]:at[i+1]]."""
        if self.rank is None:
            return raw.astype(np.int64)
        return self.rank.ravel().take(self.row.take(two_before(raw, at)) * 256 + raw).astype(np.int64)

    def lead(self, byte: np.ndarray) -> np.ndarray:
        """Symbols of first bytes of tokens."""
        return byte if self.rank is None else self.rank[self.row[0]].take(byte).astype(np.int64)


def two_before(raw: np.ndarray, at: np.ndarray) -> np.ndarray:
    """The byte before and, above it, the one before that, of the same token; 0 for none."""
    one, two = np.zeros(len(raw), np.int32), np.zeros(len(raw), np.int32)
    one[1:], two[2:] = raw[:-1], raw[:-2]
    one[at[:-1]] = 0
    two[at[:-1]] = 0
    two[np.minimum(at[:-1] + 1, len(raw) - 1)] = 0
    return one | two << 8


def _spread(first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """first[i], first[i]+1, .. size[i] values for every i."""
    ends = np.cumsum(size)
    return np.repeat(first - ends + size, size) + np.arange(ends[-1] if len(ends) else 0)


def slot_bits(words: int) -> int:
    """Slots of a context as bits: they follow the number of distinct training words, up to what a broadcast holds."""
    return min(max(SLOT_BITS, int(words * ROOM).bit_length()), MOST_SLOT_BITS)


_MULTIPLY = np.uint32(0x85EBCA6B)


class Decisions:
    """Binary decisions of tokens spelled in raw[at[i]:at[i+1]]: slots of the contexts inside the word, bits, decisions per token.

    ``chosen``: places of the bytes whose decisions are wanted (all, if not given).
    """

    def __init__(self, raw: np.ndarray, at: np.ndarray, code: ByteCode, bits: int, chosen: np.ndarray | None = None):
        self.shift = np.uint32(32 - bits)
        owner = np.repeat(np.arange(len(at) - 1), np.diff(at))
        place = np.arange(len(raw)) - at[owner]
        padded = np.concatenate([np.zeros(4, np.uint8), raw]).astype(U)
        with np.errstate(over="ignore"):
            near, hashes = np.zeros(len(raw), U), [mix(np.minimum(place, 12).astype(U) + U(77))]
            for k in range(1, 5):
                near = near << U(8) | np.where(place >= k, padded[4 - k : len(padded) - k], U(0))
                hashes.append(mix(near * U(0x9E3779B97F4A7C15) + U(k)))
            # hash of the whole beginning, however long: a polynomial sum from the token's first byte on
            total = np.zeros(len(raw) + 1, U)
            np.cumsum((raw.astype(U) + U(1)) * _power("up", len(raw)), out=total[1:])
            start = at[:-1][owner]
            whole = mix((total[:-1] - total[start]) * _power("down", len(raw))[start] + place.astype(U) * U(0xD6E8FEB86659FD93))
            hashes.append(mix(whole + U(99)))
        byte = code.symbols(raw, at)
        if chosen is not None:
            byte, owner, whole, hashes = byte[chosen], owner[chosen], whole[chosen], [h[chosen] for h in hashes]
        size = code.size[byte]
        steps = _spread(code.first[byte], size)
        self.bit = code.bit[steps]
        self.salt = (code.node[steps] + 1).astype(np.uint32) * np.uint32(0x9E3779B1)
        self.each = np.bincount(owner, size, len(at) - 1).astype(np.int64)
        self.slots = np.empty((INSIDE - 1, len(steps)), np.int32)
        for k, h in enumerate(hashes):
            spread = np.repeat((h >> U(32)).astype(np.uint32), size)
            self.slots[k] = ((spread ^ self.salt) * _MULTIPLY) >> self.shift
        self.whole = spread

    def in_class(self, kind: int | np.ndarray, rows: np.ndarray | slice = slice(None)) -> np.ndarray:
        """Slots of the whole beginning within a class (one, or one for each of the chosen decisions)."""
        other = (np.atleast_1d(np.asarray(kind, np.uint32)) + np.uint32(1)) * np.uint32(0xC2B2AE35)
        return ((((self.whole[rows] ^ other) * np.uint32(0x27D4EB2F)) ^ self.salt[rows]) * _MULTIPLY >> self.shift).astype(np.int32)


def beginnings(raw: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(places of the bytes to spell, for every byte the one of them that stands for it).

    What the contexts inside a word say of a byte follows from the word's bytes up to it alone, so words with the
    same beginning share it.  Tokens in the order of their first eight bytes share theirs with the one before.
    """
    n, size = len(at) - 1, np.diff(at)
    head = np.zeros(n, U)
    for k in range(8):
        head |= np.where(size > k, raw[np.minimum(at[:-1] + k, len(raw) - 1)], 0).astype(U) << U(56 - 8 * k)
    order = np.argsort(head, kind="stable")
    differ = np.r_[U(0), head[order][1:] ^ head[order][:-1]]
    stands = np.arange(len(raw))
    for k in range(8):
        same = (differ >> U(56 - 8 * k)) == 0
        same[0] = False
        same &= size[order] > k
        # the last token in front that begins anew here
        begun = np.maximum.accumulate(np.where(same, 0, np.arange(n)))
        mine = order[same]
        stands[at[:-1][mine] + k] = at[:-1][order[begun[same]]] + k
    chosen = np.flatnonzero(stands == np.arange(len(raw)))
    place = np.zeros(len(raw), np.int64)
    place[chosen] = np.arange(len(chosen))
    return chosen, place[stands]


def border_slots(before: np.ndarray, byte: np.ndarray, code: ByteCode) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(slots, bits, decisions) of first bytes of tokens after a word that ends in two given bytes (as one number)."""
    byte = code.lead(byte)
    size = code.size[byte]
    steps = _spread(code.first[byte], size)
    key = np.repeat(before.astype(np.uint32) * np.uint32(0x9E3779B1), size) ^ (code.node[steps] + 1).astype(np.uint32) * np.uint32(0xC2B2AE35)
    return ((key * _MULTIPLY) >> np.uint32(32 - BORDER_BITS)).astype(np.int64), code.bit[steps], size


def borders(words: Words | Spans) -> tuple[np.ndarray, np.ndarray]:
    """(last two bytes of the word before, first byte) of all tokens, end tokens included; 0 before a text's first."""
    n = words.n_texts
    ends = np.cumsum(words.count + 1) - 1
    inside = np.ones(len(words.start) + n, bool)
    inside[ends] = False
    first = np.full(len(inside), _END_TEXT, np.int64)
    first[inside] = words.bytes[words.start]
    last = words.bytes[words.end - 1].astype(np.int64)
    last |= np.where(words.end - words.start > 1, words.bytes[np.maximum(words.end - 2, 0)].astype(np.int64), 0) << 8
    own = np.zeros(len(inside), np.int64)
    own[inside] = last
    before = np.r_[0, own[:-1]]
    before[np.r_[0, ends[:-1] + 1]] = 0
    return before, first


# a slot's two counts as one number: 256 levels each, exact up to 64 and then seven to an octave
_STEP = 191 / np.log2(2.0**32 / 64)
_VALUES = np.r_[np.arange(65), 64 * 2 ** (np.arange(1, 192) / _STEP)]


def levels(counts: np.ndarray) -> np.ndarray:
    """States of slots from their (zeros, ones)."""
    n = np.where(counts <= 64, counts, 64 + np.rint(np.log2(np.maximum(counts, 64) / 64) * _STEP)).astype(np.uint16)
    return n[0] << np.uint16(8) | n[1]


def _stretched(own: int | None) -> np.ndarray:
    """log odds of a one by state; ``own`` (0 or 1) takes one such count out."""
    zero, one = (np.maximum(_VALUES - (own == b), 0) for b in (0, 1))
    return (np.log(one[None, :] + NONE) - np.log(zero[:, None] + NONE)).astype(np.float32).ravel()


_ODDS, _LEFT = _stretched(None), (_stretched(0), _stretched(1))


def grams(words: Words) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(text, hash, hash with the token before, hash with the two before) of all tokens, end tokens included."""
    owner = np.repeat(np.arange(words.n_texts), words.count + 1)
    ends = np.cumsum(words.count + 1) - 1
    token = np.full(len(owner), U(0x656E64))
    inside = np.ones(len(owner), bool)
    inside[ends] = False
    token[inside] = words.hash
    # before a text's first token stand two that no word equals
    one, two = np.full(len(owner), U(0x7374)), np.full(len(owner), U(0x7374))
    one[1:] = np.where(owner[1:] == owner[:-1], token[:-1], U(0x7374))
    two[2:] = np.where(owner[2:] == owner[:-2], token[:-2], U(0x7374))
    with np.errstate(over="ignore"):
        pair = mix(mix(one + U(1)) * U(0x9E3779B97F4A7C15) + token)
        # 63 bits: the last one is free for a flag while they are sorted
        return owner, token, pair >> U(1), mix(mix(two + U(2)) * U(0xD6E8FEB86659FD93) + pair) >> U(1)


def ranked(values: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """(distinct values ascending, place of every value among them) of whole numbers below 2 ** ``bits``.

    Where value and place fit one word together, they are sorted as one: that is several times faster than sorting places.
    """
    n = len(values)
    values, low = values.astype(U, copy=False), max(1, (n - 1).bit_length())
    if bits + low <= 64:
        both = values << U(low)
        both |= np.arange(n, dtype=U)
        both.sort()
        order, values = (both & U((1 << low) - 1)).view(np.int64), both >> U(low)
    else:
        order = np.argsort(values)
        values = values[order]
    new = np.ones(n, bool)
    new[1:] = values[1:] != values[:-1]
    inverse = np.empty(n, np.int32)
    inverse[order] = np.cumsum(new, dtype=np.int32) - np.int32(1)
    return values[new], inverse


def _repeats(owner: np.ndarray, h: np.ndarray) -> np.ndarray:
    """How often the token's text has the same number or hash."""
    if not len(h):
        return np.zeros(0, np.int64)
    bits, own_bits = int(h.max()).bit_length(), int(owner.max()).bit_length()
    with np.errstate(over="ignore"):
        if bits + own_bits <= 64:
            key, bits = owner.astype(U) << U(min(bits, 63)) | h.astype(U), bits + own_bits
        else:
            key, bits = mix(h + owner.astype(U) * U(0x9E3779B97F4A7C15)), 64
    inverse = ranked(key, bits)[1]
    return np.bincount(inverse)[inverse]


def contexts(words: Words | Spans, known: np.ndarray, pair: np.ndarray, triple: np.ndarray, texts: int, train: np.ndarray, same: tuple[np.ndarray, ...] | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(share (tokens, 2), evidence (tokens, 2, 4)) of the two tokens before and the one before.

    From training counts of every token and of it with the one and the two before, the text's own
    taken out.  A context occurs as often as the shorter sequence that it is.  ``same``: what
    ``grams`` gives, with any numbers that are equal where the hashes are.
    """
    owner, token, h1, h2 = grams(words) if same is None else same
    own = train[owner]
    known, pair, triple = (n - own * _repeats(owner, h) for n, h in ((known, token), (pair, h1), (triple, h2)))
    first = np.r_[True, owner[1:] != owner[:-1]]
    texts = texts - train[owner].astype(np.int64)
    seen1 = np.where(first, texts, np.r_[0, known[:-1]])
    seen2 = np.where(first, texts, np.r_[0, pair[:-1]])
    share, evidence = np.zeros((len(owner), 2)), np.zeros((len(owner), 2, 4), np.float32)
    start = np.flatnonzero(first)[owner]
    at = np.arange(len(owner))
    for k, (n, seen) in enumerate(((triple, seen2), (pair, seen1))):
        share[:, k] = np.maximum(n, 0) / np.maximum(seen, 1)
        miss = np.maximum.accumulate(np.where(n > 0, -1, at))
        run = at - np.maximum(miss, start - 1)
        run = np.where(first, 0, np.r_[0, run[:-1]])
        mine = evidence[:, k]
        mine[:, 0] = seen > 0
        np.log(np.maximum(seen, 0).astype(np.float32) + np.float32(1), out=mine[:, 1])
        mine[:, 2] = run > 0
        np.log(run.astype(np.float32) + np.float32(1), out=mine[:, 3])
        mine[:, 2:] *= mine[:, :1]  # nothing to draw from
    return share, evidence


def _joined(tokens: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    return np.frombuffer(b"".join(tokens), np.uint8), np.r_[0, np.cumsum([len(t) for t in tokens], dtype=np.int64)]


class Spans:
    """Words of some texts of a group: spans in the bytes of all of it."""

    def __init__(self, raw: np.ndarray, start: np.ndarray, end: np.ndarray, count: np.ndarray):
        self.bytes, self.start, self.end, self.count, self.n_texts = raw, start, end, count, len(count)


class Mixer:
    """Byte code, states of the context tables, gate weights and corpus totals.

    ``tables``: (INSIDE, slots) states; ``border``: states of the border context; ``tokens``
    and ``types``: training tokens and distinct ones per class; ``distinct``: of all classes.
    """

    def __init__(self, code: ByteCode, tables: np.ndarray, border: np.ndarray, tokens: np.ndarray, distinct: int):
        self.code, self.tables, self.border = code, tables, border
        self.bits = tables.shape[1].bit_length() - 1
        self.per_class, self.tokens, self.distinct = tokens.astype(np.float64), int(tokens.sum()), distinct
        self.weights = np.full((GATES, INSIDE), 0.3, np.float32)

    # learning

    def _by_gate(self, spelled: list[bytes], counts: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
        """(signed inputs, weight) of training words' decisions by gate, one occurrence of the word taken out."""
        raw, at = _joined(spelled)
        kind, total = counts.argmax(1), counts.sum(1)
        # words of one class that begin alike share the beginning's decisions
        chosen, often = [], []
        for c in np.unique(kind).tolist():
            mine = np.flatnonzero(kind == c)
            size = np.diff(at)[mine]
            bytes_ = _spread(at[mine], size)
            picked, place = beginnings(raw[bytes_], np.r_[0, np.cumsum(size)])
            chosen.append(bytes_[picked])
            often.append(np.bincount(place, np.repeat(total[mine], size)))
        chosen, often = np.concatenate(chosen), np.concatenate(often)
        order = np.argsort(chosen)
        chosen, often = chosen[order], often[order].astype(np.float32)
        d = Decisions(raw, at, self.code, self.bits, chosen)
        size = self.code.size[self.code.symbols(raw, at)[chosen]]
        kind, often = np.repeat(kind, d.each), np.repeat(often, size)
        x = np.zeros((len(d.bit), INSIDE), np.float32)
        for k in range(INSIDE):
            state = self.tables[k][d.slots[k] if k < INSIDE - 1 else d.in_class(kind)]
            x[:, k] = np.where(d.bit, _LEFT[1].take(state), -_LEFT[0].take(state))
        gate = 2 * (x[:, :-1] != 0).sum(1) + (x[:, -1] != 0)
        order = np.argsort(gate.astype(np.int8), kind="stable")
        cut = np.cumsum(np.bincount(gate, minlength=GATES))[:-1]
        return list(zip(np.split(x[order], cut), np.split(often[order], cut)))

    def learned(self, spelled: list[bytes], counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Per gate: (curvature times weights, curvature) where Newton steps over the words settle, piece by piece."""
        pull, total, ridge = np.zeros((GATES, INSIDE)), np.zeros((GATES, INSIDE, INSIDE)), np.eye(INSIDE)
        for s in range(0, len(spelled), 8192):
            for g, (v, n) in enumerate(self._by_gate(spelled[s : s + 8192], counts[s : s + 8192])):
                if not len(v):
                    continue
                w = self.weights[g].astype(np.float64)
                for _ in range(STEPS):
                    slope, curve = _slope(v, n, w)
                    w += np.clip(np.linalg.solve(curve + ridge, slope), -0.5, 0.5)
                pull[g] += curve @ w
                total[g] += curve
        return pull, total

    def settle(self, pull: np.ndarray, curve: np.ndarray) -> None:
        """Weights of all pieces averaged by curvature; a little ridge holds gates that few decisions reach."""
        for g in range(GATES):
            self.weights[g] = np.linalg.solve(curve[g] + np.eye(INSIDE), pull[g] + self.weights[g])

    # scoring

    def opinions(self, d: Decisions, kind: int) -> tuple[np.ndarray, np.ndarray]:
        """First layer, (LAYER - 1, decisions): the inside contexts' weighted opinions by group, signed so that more
        makes the bit that came likelier."""
        out = np.zeros((LAYER - 1, len(d.bit)), np.float32)
        for s in range(0, len(d.bit), AT_ONCE):
            rows = slice(s, s + AT_ONCE)
            sign = np.where(d.bit[rows], np.float32(1), np.float32(-1))
            x = np.empty((INSIDE, len(sign)), np.float32)
            for k in range(INSIDE):
                np.take(_ODDS, self.tables[k].take(d.slots[k, rows] if k < INSIDE - 1 else d.in_class(kind, rows)), out=x[k], mode="clip")
                x[k] *= sign
            gate = 2 * (x[:-1] != 0).sum(0, dtype=np.int8) + (x[-1] != 0)
            for k in range(INSIDE):
                x[k] *= np.ascontiguousarray(self.weights[:, k])[gate]
                out[GROUP[k], rows] += x[k]
        return out

    def spelled(self, raw: np.ndarray, at: np.ndarray, kind: int = 0) -> np.ndarray:
        """Natural log probabilities of spelled tokens in a class, before any text has moved the weights and without a word before."""
        d = Decisions(raw, at, self.code, self.bits)
        logit = self.opinions(d, kind).sum(0)
        return np.add.reduceat(-np.log1p(np.exp(-np.clip(logit, -30, 30))), np.r_[0, np.cumsum(d.each)[:-1]], dtype=np.float64)

    def classes(self, owner: np.ndarray, texts: int, count: np.ndarray, word: np.ndarray) -> np.ndarray:
        """The class that would draw a text's words likeliest, from the words' texts, the distinct words' training counts in
        every class and the number of the distinct one that a word is; naming it costs log10(classes)."""
        likely = np.log((count.T + 0.1) / (self.per_class + 0.1 * (self.distinct + 1))[:, None])
        likely[self.per_class == 0] = -1e3
        return np.stack([np.bincount(owner, row.take(word), texts) for row in likely], 1).argmax(1)

    def score(self, words: Words | Spans, count: np.ndarray, kind: int = 0, before: tuple[np.ndarray, np.ndarray] | None = None, word: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Per text: log10 probability, base log10 score, known tokens, for texts of one class; ``count`` is the training
        count of every word in every class (rows: words, then the end token), ``before`` what ``contexts`` gives, ``word``
        numbers of the words (their hashes, if not given)."""
        n, code = words.n_texts, self.code
        distinct, inverse = ranked(words.hash, 64) if word is None else ranked(word, int(word.max(initial=0)).bit_length())
        first = np.empty(len(distinct), np.int64)
        first[inverse] = np.arange(len(inverse))  # any of its places
        token = np.full(len(inverse) + n, len(distinct))
        ends = np.cumsum(words.count + 1)
        is_end = np.zeros(len(token), bool)
        is_end[ends - 1] = True
        token[~is_end] = inverse
        counts = np.concatenate([count[:-1][first], count[-1:]]).sum(1)
        base = np.log10((counts + 1) / (self.tokens + self.distinct + 1))
        starts = ends - words.count - 1
        base_score = np.add.reduceat(base[token], starts)
        known = np.add.reduceat((counts > 0)[token].astype(np.int64), starts)
        # the distinct tokens spelled once: words in hash order, then the end of the text
        size = (words.end - words.start)[first]
        at = np.r_[0, np.cumsum(size + 1)]
        raw = np.full(int(at[-1]) + 1, _END_WORD, np.uint8)
        raw[_spread(at[:-1], size)] = words.bytes[_spread(words.start[first], size)]
        raw[-1] = _END_TEXT
        at = np.r_[at, at[-1] + 1]
        chosen, place = beginnings(raw, at)
        d = Decisions(raw, at, code, self.bits, chosen)
        size = code.size[code.symbols(raw, at)]
        each = np.add.reduceat(size, at[:-1])
        begin = np.cumsum(each) - each
        # a decision's four inputs side by side, moved as one value
        shared = np.ascontiguousarray(self.opinions(d, kind).T).view(np.complex128).ravel()
        inside = shared.take(_spread((np.cumsum(size[chosen]) - size[chosen])[place], size))
        lead = size[at[:-1]]  # decisions of a token's first byte
        del d, shared, chosen, place
        slots, bit, size = border_slots(*borders(words), code)
        border = _ODDS.take(self.border.take(slots)) * np.where(bit, np.float32(BORDER_WEIGHT), np.float32(-BORDER_WEIGHT))
        border_at = np.cumsum(size) - size
        del slots, bit
        scale, trust = np.ones((n, LAYER), np.float32), np.tile(TRUST, (n, 1, 1))
        score, done, block = np.full(n, -np.log10(max(1, int((self.per_class > 0).sum())))), np.zeros(n, np.int64), FIRST_BLOCK
        live = np.arange(n)
        while len(live):
            m = np.minimum(block, words.count[live] + 1 - done[live])
            for s, e in _pieces(m, PIECE_TOKENS):
                own, size = live[s:e], m[s:e]
                where = _spread(starts[own] + done[own], size)
                t = token[where]
                per = each[t]
                rows = _spread(begin[t], per)
                head = np.cumsum(per) - per
                cut = np.cumsum(size) - size
                edge = head[cut]
                bits = np.diff(edge, append=len(rows))
                # second layer: the text's own weights on the groups' opinions; the border speaks on a token's first byte
                x = inside.take(rows).view(np.float32).reshape(-1, LAYER - 1)
                first = lead[t]
                lane, b = _spread(head, first), border.take(_spread(border_at[where], first))
                first = np.add.reduceat(first, cut)
                miss, spans = np.empty(len(rows), np.float32), list(zip(own.tolist(), edge.tolist(), (edge + bits).tolist()))
                for i, f, g in spans:
                    np.dot(x[f:g], scale[i, :-1], out=miss[f:g])
                miss[lane] += b * np.repeat(scale[own, -1], first)
                np.clip(miss, -30, 30, out=miss)
                np.exp(np.negative(miss, out=miss), out=miss)
                less = miss + 1  # one through the probability of the bit that came
                miss /= less  # one minus that probability
                log_spelled = -np.add.reduceat(np.log(less, out=less), head, dtype=np.float64)
                if before is None:
                    log_whole = log_spelled
                else:
                    log_whole, rest = _followed(before[0][where], before[1][where], log_spelled, np.repeat(np.arange(len(own)), size), cut, trust, own)
                    miss *= np.repeat(rest.astype(np.float32), per)
                score[own] += np.add.reduceat(log_whole, cut) / np.log(10)
                # refinement: the spelled tokens of the block pull the weights
                pull = np.empty((len(own), LAYER), np.float32)
                for k, (_, f, g) in enumerate(spans):
                    np.dot(miss[f:g], x[f:g], out=pull[k, :-1])
                pull[:, -1] = np.add.reduceat(miss[lane] * b, np.cumsum(first) - first)
                pull /= np.sqrt(bits)[:, None]
                scale[own] = np.clip(scale[own] + RATE * pull, 0.2, 2.5)
            done[live] += m
            live = live[done[live] <= words.count[live]]
            block = min(2 * block, LAST_BLOCK)
        return score, base_score, known


def _followed(share: np.ndarray, evidence: np.ndarray, log_spelled: np.ndarray, text: np.ndarray, cut: np.ndarray, trust: np.ndarray, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(log probability, share of the spelling in it) of a block's tokens that may follow the words before; moves ``trust``."""
    q = 1 / (1 + np.exp(-np.clip(np.einsum("nkf,nkf->nk", evidence, trust[own].take(text, axis=0)), -12, 12)))
    q *= evidence[:, :, 0]  # a context that never occurred is not trusted
    two, one = q[:, 0] * share[:, 0], (1 - q[:, 0]) * q[:, 1] * share[:, 1]
    left = np.log((1 - q[:, 0]) * (1 - q[:, 1])) + log_spelled
    with np.errstate(divide="ignore"):
        log_whole = np.logaddexp(left, np.log(two + one))
    back = np.exp(-np.maximum(log_whole, -700))  # where less, both are 0
    two, one = two * back, one * back
    slope = np.stack([two - q[:, 0], one - q[:, 1] * (1 - two)], 1)
    step = np.add.reduceat(slope[:, :, None] * evidence, cut, axis=0)
    trust[own] = np.clip(trust[own] + TRUST_RATE * step, -8, 8)
    return log_whole, np.exp(left - log_whole)


def _slope(v: np.ndarray, n: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Gradient and curvature of the log probability of weighted decisions."""
    p = 1 / (1 + np.exp(-np.clip(v @ w.astype(np.float32), -30, 30)))
    miss = (1 - p) * n
    return (miss @ v).astype(np.float64), ((v * (miss * p)[:, None]).T @ v).astype(np.float64)


def _pieces(m: np.ndarray, most: int) -> Iterator[tuple[int, int]]:
    """Runs of texts whose blocks hold about ``most`` tokens."""
    total, s = np.cumsum(m), 0
    while s < len(m):
        e = max(s + 1, int(np.searchsorted(total, (total[s - 1] if s else 0) + most, "right")))
        yield s, e
        s = e


def _joined_words(words: list[bytes], counts: np.ndarray) -> bytes:
    return zlib.compress(counts.astype("<u4").T.tobytes() + b"\n".join(words), 1)


def _split_words(blob: bytes, n: int, classes: int) -> tuple[list[bytes], np.ndarray]:
    """(words, counts (words, classes))"""
    raw = zlib.decompress(blob)
    cut = 4 * n * classes
    return raw[cut:].split(b"\n") if n else [], np.frombuffer(raw[:cut], "<u4").reshape(classes, n).T.astype(np.int64)


def _word_hash(words: list[bytes]) -> np.ndarray:
    """The kernel's hash of whole words."""
    if not words:
        return np.zeros(0, U)
    return Words(_joined(words), blanks=np.zeros(256, bool)).hash


def _planes(x: np.ndarray) -> bytes:
    """Whole numbers byte plane by byte plane, in as many bytes as the largest needs (said in front); planes of noise stay as they are."""
    size = next(s for s in (1, 2, 4, 8) if not len(x) or int(x.max()) < 1 << 8 * s)
    out = [bytes([size])]
    for plane in np.ascontiguousarray(x.astype(f"<u{size}").view(np.uint8).reshape(-1, size).T):
        some = plane[:4096].tobytes()
        dense = len(zlib.compress(some, 1)) > 0.9 * len(some)
        raw = plane.tobytes()
        blob = raw if dense else zlib.compress(raw, 1)
        out += [bytes([dense]), len(blob).to_bytes(8, "little"), blob]
    return b"".join(out)


def _numbers(blob: bytes) -> np.ndarray:
    size, at, planes = blob[0], 1, []
    for _ in range(size):
        end = at + 9 + int.from_bytes(blob[at + 1 : at + 9], "little")
        planes.append(np.frombuffer(blob[at + 9 : end] if blob[at] else zlib.decompress(blob[at + 9 : end]), np.uint8))
        at = end
    raw = np.empty((len(planes[0]), size), np.uint8)
    for k, plane in enumerate(planes):
        raw[:, k] = plane
    return raw.view(f"<u{size}").ravel().astype(np.int64)


def _pack_grams(h: np.ndarray, n: np.ndarray, shards: int) -> bytes:
    """Ascending hashes of word sequences of one shard (all the same modulo ``shards``), and training counts."""
    first = _planes(np.diff((h // U(shards)).astype(np.int64), prepend=0))
    return len(first).to_bytes(4, "little") + first + _planes(n)


def _unpack_grams(blob: bytes) -> tuple[np.ndarray, np.ndarray]:
    """(hashes divided by the number of shards, counts)"""
    cut = 4 + int.from_bytes(blob[:4], "little")
    return np.cumsum(_numbers(blob[4:cut])), _numbers(blob[cut:])


def gram_bits(size: int) -> int:
    """Bits of a word sequence's hash: 64 values for each sequence that texts of ``size`` bytes can hold."""
    return min(63, max(24, int(size).bit_length() + 5))


_ASK = "shard int, grp long, n int, words binary, grams binary"


def _asks(shards: int, classes: int, keep: int):
    """Per group and word shard: the group's distinct words in hash order and its word sequences, with their training counts."""
    schema = pa.schema([("shard", pa.int32()), ("grp", pa.int64()), ("n", pa.int32()), ("words", pa.binary()), ("grams", pa.binary())])

    def work(table: pa.Table) -> pa.Table:
        grp = table.column("grp")[0].as_py()
        seen, spans, text = np.zeros(0, U), [], []  # distinct hashes so far; bytes of the words new in every chunk
        hashes, kinds, sequences, trains = [], [], [], []
        for batch in table.combine_chunks().to_batches():
            for part in chunks(batch):
                words = Words(part.column(part.schema.get_field_index("text")))
                kind = part.column(part.schema.get_field_index("kind")).to_numpy(zero_copy_only=False)
                owner, _, pair, triple = grams(words)
                sequences += [pair >> U(63 - keep), triple >> U(63 - keep)]
                trains += [kind[owner] >= 0] * 2
                own, first, inverse = np.unique(words.hash, return_index=True, return_inverse=True)
                learn = kind[words.owner] >= 0
                hashes.append(own)
                kinds.append(np.bincount(inverse[learn] * classes + kind[words.owner][learn], minlength=len(own) * classes).reshape(-1, classes))
                at = np.searchsorted(seen, own)
                new = np.ones(len(own), bool)
                new[at < len(seen)] = seen[at[at < len(seen)]] != own[at < len(seen)]
                size = (words.end - words.start)[first[new]]
                spans.append((own[new], size))
                text.append(words.bytes[_spread(words.start[first[new]], size)])
                seen = np.insert(seen, at[new], own[new])
        # training counts of the distinct words, in hash order
        place = np.searchsorted(seen, np.concatenate(hashes))
        every = np.concatenate(kinds)
        counts = np.stack([np.bincount(place, every[:, c], len(seen)) for c in range(classes)], 1).astype(np.int64)
        raw = np.concatenate(text).tobytes()
        size = np.concatenate([s for _, s in spans])
        end = np.cumsum(size)
        order = np.argsort(np.concatenate([h for h, _ in spans]))
        begin, end = (end - size)[order].tolist(), end[order].tolist()
        # places by shard: numbers of two bytes are sorted fastest
        small = np.uint16 if shards <= 1 << 16 else np.int64
        shard = (seen % U(shards)).astype(small)
        flagged = np.sort(np.concatenate(sequences) << U(1) | np.concatenate(trains).astype(U))
        del sequences[:], trains[:], hashes[:], kinds[:], place, every
        every = flagged >> U(1)
        new = np.flatnonzero(np.r_[True, every[1:] != every[:-1]])
        every, trained = every[new], np.add.reduceat((flagged & U(1)).astype(np.int64), new)
        del flagged
        gram_shard = (every % U(shards)).astype(small)
        by_word, by_gram = np.argsort(shard, kind="stable"), np.argsort(gram_shard, kind="stable")
        word_cut, gram_cut = (np.searchsorted(s[o], np.arange(shards + 1)) for s, o in ((shard, by_word), (gram_shard, by_gram)))
        rows = []
        for s in range(shards):
            own, mine = by_word[word_cut[s] : word_cut[s + 1]], by_gram[gram_cut[s] : gram_cut[s + 1]]
            if len(own) or len(mine):
                rows.append((s, grp, len(own), _joined_words([raw[begin[i] : end[i]] for i in own.tolist()], counts[own]), _pack_grams(every[mine], trained[mine], shards)))
        return pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), schema)], schema=schema)

    return work


PIECE = 20_000  # words of a blob
_TOLD = "kind string, a long, b long, blob binary, tokens long, types long"
_TOLD_SCHEMA = pa.schema([("kind", pa.string()), ("a", pa.int64()), ("b", pa.int64()), ("blob", pa.binary()), ("tokens", pa.int64()), ("types", pa.int64())])


def _tell(classes: int):
    """A word shard: answers to every group, totals, and its training words with their counts."""

    def work(table: pa.Table) -> pa.Table:
        shard = table.column("shard")[0].as_py()
        hashes, counts, names = [], [], []
        sizes = table.column("n").to_pylist()
        groups = table.column("grp").to_pylist()
        for blob, n in zip((b for c in table.column("words").chunks for b in c), sizes):
            words, c = _split_words(blob.as_buffer().to_pybytes(), n, classes)
            hashes.append(_word_hash(words))
            counts.append(c)
            names += words
        distinct, inverse = ranked(np.concatenate(hashes), 64)
        first = np.empty(len(distinct), np.int64)
        first[inverse] = np.arange(len(inverse))
        every = np.concatenate(counts)
        total = np.stack([np.bincount(inverse, every[:, k], len(distinct)) for k in range(classes)], 1).astype(np.int64)
        rows, at = [], 0
        for g, n in zip(groups, sizes):
            rows.append(("answer", g, shard, _planes(total[inverse[at : at + n]].T.ravel()), None, None))
            at += n
        seen = total.any(1)
        # class -1: words of any class
        rows.append(("total", -1, shard, None, int(total.sum()), int(seen.sum())))
        rows += [("total", k, shard, None, int(total[:, k].sum()), int((total[:, k] > 0).sum())) for k in range(classes)]
        trained, often = [names[i] for i in first[seen].tolist()], total[seen]
        rows += [("words", len(trained[s : s + PIECE]), shard, _joined_words(trained[s : s + PIECE], often[s : s + PIECE]), None, None) for s in range(0, len(trained), PIECE)]
        del hashes, counts, names, every, inverse, trained, often
        # word sequences: the same for hashes
        asked = [_unpack_grams(blob.as_buffer().to_pybytes()) for c in table.column("grams").chunks for blob in c]
        every = np.concatenate([h for h, _ in asked])
        inverse = ranked(every, int(every.max(initial=0)).bit_length())[1]
        often = np.bincount(inverse, np.concatenate([n for _, n in asked])).astype(np.int64)
        at = 0
        for g, (h, _) in zip(groups, asked):
            rows.append(("grams", g, shard, _planes(often[inverse[at : at + len(h)]]), None, None))
            at += len(h)
        return pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), _TOLD_SCHEMA)], schema=_TOLD_SCHEMA)

    return work


def _trained(batches: Iterator[pa.RecordBatch], classes: int) -> Iterator[tuple[list[bytes], np.ndarray]]:
    """(words as they are spelled, counts (words, classes)) of (n, blob) rows."""
    for batch in batches:
        for n, blob in zip(batch.column(0).to_pylist(), batch.column(1)):
            words, counts = _split_words(blob.as_buffer().to_pybytes(), n, classes)
            yield [w + b" " for w in words], counts


_SUMS = "part int, branch int, blob binary"
_SUMS_SCHEMA = pa.schema([("part", pa.int32()), ("branch", pa.int32()), ("blob", pa.binary())])


def _sliced(cells: np.ndarray, slices: int) -> pa.RecordBatch:
    """The cells that are not zero, in slices; every FAN_IN tasks share a branch of the tree that adds them up."""
    from pyspark import TaskContext

    width, blobs = len(cells) // slices, []
    for part in range(slices):
        mine = cells[part * width : (part + 1) * width]
        at = np.flatnonzero(mine)
        first = _planes(np.diff(at, prepend=0))
        blobs.append(len(first).to_bytes(4, "little") + first + _planes(mine[at]))
    branch = TaskContext.get().partitionId() // FAN_IN
    return pa.RecordBatch.from_arrays([pa.array(range(slices), pa.int32()), pa.array([branch] * slices, pa.int32()), pa.array(blobs, pa.binary())], schema=_SUMS_SCHEMA)


def _added(width: int, last: bool):
    """Adds up slices of ``width`` cells; at ``last``, states of the cells in pairs."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[int, int], np.ndarray] = {}
        for batch in batches:
            for part, branch, blob in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                at, n = _unpack_grams(blob)
                total = held.setdefault((part, 0 if last else branch), np.zeros(width, np.int64))
                total[at] += n
        for (part, branch), total in held.items():
            if last:
                blob = zlib.compress(levels(total.reshape(-1, 2).T).tobytes(), 1)
            else:
                at = np.flatnonzero(total)
                first = _planes(np.diff(at, prepend=0))
                blob = len(first).to_bytes(4, "little") + first + _planes(total[at])
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([branch // FAN_IN], pa.int32()), pa.array([blob], pa.binary())], schema=_SUMS_SCHEMA)

    return work


def _summed(counted: DataFrame, cells: int, slices: int, tasks: int) -> np.ndarray:
    """States of pairs of cells from sliced counts of ``tasks`` tasks, added up in a tree whose nodes read FAN_IN rows or fewer."""
    width = cells // slices
    while tasks > FAN_IN:
        tasks = -(-tasks // FAN_IN)
        counted = counted.repartition(slices * min(tasks, 8), "part", "branch").mapInArrow(_added(width, False), _SUMS)
    out = np.zeros(cells // 2, np.uint16)
    for r in counted.repartition(slices, "part").mapInArrow(_added(width, True), _SUMS).toLocalIterator():
        out[r.part * width // 2 : (r.part + 1) * width // 2] = np.frombuffer(zlib.decompress(r.blob), np.uint16)
    return out


def _bit_counts(code: ByteCode, bits: int, classes: int):
    """Branches taken when the training words are spelled, every occurrence counted: one table a task, whatever arrives."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells = np.zeros(INSIDE * 2 << bits, np.uint32)
        for spelled, counts in _trained(batches, classes):
            raw, at = _joined(spelled)
            chosen, place = beginnings(raw, at)
            d = Decisions(raw, at, code, bits, chosen)
            size, each = code.size[code.symbols(raw, at)[chosen]], np.diff(at)
            often = [np.bincount(place, np.repeat(counts[:, c], each), len(chosen)).astype(np.uint32) for c in range(classes)]
            total = np.repeat(np.sum(often, axis=0, dtype=np.uint32), size)
            for k in range(INSIDE - 1):
                np.add.at(cells, (k * 2 << bits) + 2 * d.slots[k].astype(np.int64) + d.bit, total)
            for c in range(classes):
                mine = np.flatnonzero(np.repeat(often[c] > 0, size))
                at_class = ((INSIDE - 1) * 2 << bits) + 2 * d.in_class(c, mine).astype(np.int64) + d.bit[mine]
                np.add.at(cells, at_class, np.repeat(often[c], size)[mine])
        if cells.any():
            yield _sliced(cells, SLICES)

    return work


def _border_counts(code: ByteCode):
    """Branches taken by first bytes of training tokens after the end of the word before."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells = np.zeros(2 << BORDER_BITS, np.int64)
        for batch in batches:
            for part in chunks(batch):
                slots, bit, _ = border_slots(*borders(Words(part.column(0), hashes=False)), code)
                cells += np.bincount(2 * slots + bit, minlength=len(cells))
        if cells.any():
            yield _sliced(cells, 8)

    return work


def _learned(shared, classes: int):
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(GATES * INSIDE * (INSIDE + 1))
        for spelled, counts in _trained(batches, classes):
            total += np.concatenate([part.ravel() for part in shared.value.learned(spelled, counts)])
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total)), pa.int32()), pa.array(total)], names=["at", "sum"])

    return work


_SCORED = "doc_id long, n_tokens long, n_known long, base_score double, score double, n_bytes long"
_SCORED_SCHEMA = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64()), ("n_bytes", pa.int64())])
#: text bytes scored at once
SCORED_BYTES = 1 << 21


def _scores(shared, shards: int, keep: int):
    def work(docs: pa.Table, answers: pa.Table) -> pa.Table:
        learnt, weights, ends = shared.value
        model = learnt.value
        model.weights = weights
        if not docs.num_rows:
            return _SCORED_SCHEMA.empty_table()
        told, often = {}, {}
        for kind, s, blob in zip(*(answers.column(c).to_pylist() for c in ("kind", "b", "blob"))):
            (told if kind == "answer" else often)[s] = blob
        docs = docs.combine_chunks()
        # the group's words again, in the order they were asked in
        held, hashes, sequences, size = [], [], [[], []], 0
        for b in docs.to_batches():
            for p in chunks(b):
                words = Words(p.column(p.schema.get_field_index("text")))
                for into, h in zip(sequences, grams(words)[2:]):
                    into.append(h >> U(63 - keep))
                hashes.append(words.hash)
                held.append((words.bytes, words.start + size, words.end + size, words.count, np.diff(words.offsets)))
                size += len(words.bytes)
        raw, start, end, count, n_bytes = (np.concatenate(x) for x in zip(*held))
        del held, words
        every, word = ranked(np.concatenate(hashes), 64)
        del hashes
        counts = np.zeros((len(every), len(ends)), np.int64)
        shard = (every % U(shards)).astype(np.int64)
        for s, blob in told.items():
            counts[np.flatnonzero(shard == s)] = _numbers(blob).reshape(len(ends), -1).T
        asked, sequence = ranked(np.concatenate(sequences[0] + sequences[1]), keep)
        del sequences, every
        found = np.zeros(len(asked), np.int64)
        shard = (asked % U(shards)).astype(np.int64)
        for s, blob in often.items():
            found[shard == s] = _numbers(blob)
        del asked, shard, told, often
        texts, total = len(count), int(ends.sum())
        kind = model.classes(np.repeat(np.arange(texts), count), texts, counts, word)
        single = counts.sum(1)
        del counts
        ids, train = docs.column("doc_id"), docs.column("train").to_numpy()
        word_at, token_at = np.cumsum(count) - count, np.cumsum(count + 1) - count - 1
        pair, triple = sequence[: len(word) + texts], sequence[len(word) + texts :]
        out = []
        # texts of one class are scored together
        order = np.argsort(kind, kind="stable")
        bounds = np.flatnonzero(np.diff(kind[order], prepend=-1, append=-1))
        for f, g in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
            for s, e in _pieces(n_bytes[order[f:g]], SCORED_BYTES):
                own = order[f + s : f + e]
                at, tokens = _spread(word_at[own], count[own]), _spread(token_at[own], count[own] + 1)
                words = Spans(raw, start[at], end[at], count[own])
                mine, one, two = word[at], pair[tokens], triple[tokens]
                owner = np.repeat(np.arange(len(own), dtype=np.int32), count[own] + 1)
                inside = np.ones(len(tokens), bool)
                inside[np.cumsum(count[own] + 1) - 1] = False
                known, token = np.full(len(tokens), total), np.full(len(tokens), len(single), np.int32)
                known[inside], token[inside] = single[mine], mine
                before = contexts(words, known, found[one], found[two], total, train[own], (owner, token, one, two))
                score, base, n_known = model.score(words, np.r_[known[inside], total][:, None], int(kind[own[0]]), before, mine)
                out.append(pa.RecordBatch.from_arrays([ids.take(pa.array(own)).combine_chunks(), pa.array(count[own] + 1), pa.array(n_known), pa.array(base), pa.array(score), pa.array(n_bytes[own])], schema=_SCORED_SCHEMA))
        return pa.Table.from_batches(out)

    return work


def score_documents(documents: DataFrame, folds: int = 7, held: int = 2) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, bits_per_byte).

    Tokens are the lower-cased (A-Z) words and one end token.  Training rows are those
    whose fold is not ``held``; ``base_score`` is their add-one unigram score, ``score``
    the mixing model's log10 probability, both of the whole text.

    Edge cases: null and empty texts are the end token alone (bits_per_byte null); a
    null ``doc_id`` is scored but neither trains nor counts as held out; repeated rows
    train and are scored each; without training rows all tokens are spelled from empty
    tables; an empty table gives an empty result; other columns are ignored.
    """
    spark = documents.sparkSession
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    lang = F.col("lang").cast("string") if "lang" in documents.columns else F.lit(None).cast("string")
    train = F.coalesce(fold("doc_id", folds) != held, F.lit(False))
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"), train.alias("train"), lang.alias("lang"))
    # the commonest languages of the training rows: a fixed number, the rest share one class
    names = [r.lang for r in docs.where("train and lang is not null").groupBy("lang").agg(F.count("*").alias("n")).orderBy(F.col("n").desc(), "lang").limit(CLASSES).collect()]
    classes = len(names) + 1
    kind = F.lit(classes - 1)
    for k, name in enumerate(names):
        kind = F.when(F.col("lang") == name, k).otherwise(kind)
    docs = docs.select("doc_id", "text", "train", F.when(F.col("train"), kind).otherwise(-1).cast("int").alias("kind"))
    ends, size = np.zeros(classes, np.int64), 0
    for r in docs.groupBy("kind").agg(F.count("*").alias("n"), F.sum(F.octet_length("text")).alias("bytes")).collect():
        size += r.bytes
        if r.kind >= 0:
            ends[r.kind] = r.n
    groups = max(8, size // GROUP_BYTES)
    shards, keep = max(8, groups // 2), gram_bits(size)
    docs = docs.withColumn("grp", F.pmod(F.xxhash64("doc_id", F.octet_length("text")), F.lit(groups)))
    asks = docs.groupBy("grp").applyInArrow(_asks(shards, classes, keep), _ASK)
    # once the asks are answered, nothing needs the two exchanges of texts and asks
    told = durable(asks.groupBy("shard").applyInArrow(_tell(classes), _TOLD), once=True)
    tokens, distinct = ends.copy(), int(ends.any())
    for r in told.where("kind = 'total'").groupBy("a").agg(F.sum("tokens").alias("tokens"), F.sum("types").alias("types")).collect():
        if r.a < 0:
            distinct += r.types
        else:
            tokens[r.a] += r.tokens
    bits = slot_bits(distinct)
    trained = told.where("kind = 'words'").select("a", "blob")
    code = _byte_code(trained, classes, int(ends.sum()))
    tasks = max(1, size // (32 << 20))
    border = _summed(docs.where("train").select("text").mapInArrow(_border_counts(code), _SUMS), 2 << BORDER_BITS, 8, 4 * tasks)
    counted = trained.mapInArrow(_bit_counts(code, bits, classes), _SUMS)
    tables = _summed(counted, INSIDE * 2 << bits, SLICES, shards).reshape(INSIDE, 1 << bits)
    model = Mixer(code, tables, border, tokens, distinct)
    # gate weights: every training word of every shard pulls them
    learning = spark.sparkContext.broadcast(model)
    sums = np.zeros(GATES * INSIDE * (INSIDE + 1))
    for r in trained.mapInArrow(_learned(learning, classes), "at int, sum double").groupBy("at").agg(F.sum("sum").alias("sum")).collect():
        sums[r.at] = r.sum
    cut = GATES * INSIDE
    model.settle(sums[:cut].reshape(GATES, INSIDE), sums[cut:].reshape(GATES, INSIDE, INSIDE))
    shared = spark.sparkContext.broadcast((learning, model.weights, ends))
    answers = told.where("kind in ('answer', 'grams')").select("kind", F.col("a").alias("grp"), "b", "blob")
    work = _scores(shared, shards, keep)
    scored = docs.groupBy("grp").cogroup(answers.groupBy("grp")).applyInArrow(lambda d, a: work(d, a), _SCORED)
    per_byte = F.when(F.col("n_bytes") > 0, -F.col("score") * float(np.log2(10)) / F.col("n_bytes"))
    return scored.select("doc_id", F.coalesce(fold("doc_id", folds) == held, F.lit(False)).alias("held_out"), "n_tokens", "n_known", F.lit(int(tokens.sum())).cast("long").alias("train_tokens"), "base_score", "score", per_byte.alias("bits_per_byte"))


def _followers(classes: int):
    """How often a byte came after two bytes in training words, every occurrence counted."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, often = np.zeros(0, U), np.zeros(0)
        for spelled, counts in _trained(batches, classes):
            raw, at = _joined(spelled)
            key = two_before(raw, at).astype(U) << U(8) | raw
            weight = np.repeat(counts.sum(1), np.diff(at))
            keys, place = ranked(np.concatenate([keys, key]), 24)
            often = np.bincount(place, np.concatenate([often, weight]))
        yield pa.RecordBatch.from_arrays([pa.array(keys.astype(np.int64)), pa.array(often.astype(np.int64))], names=["key", "n"])

    return work


def _byte_code(trained: DataFrame, classes: int, ends: int) -> ByteCode:
    """Code of all training words' bytes and the texts' ends: what follows two bytes, which does not grow with the corpus and only shapes the code."""
    rows = trained.mapInArrow(_followers(classes), "key long, n long").groupBy("key").agg(F.sum("n").alias("n")).toArrow()
    key = np.r_[rows.column("key").to_numpy(), _END_TEXT]
    return ByteCode.ranking(key >> 8, key & 255, np.r_[rows.column("n").to_numpy(), ends])
