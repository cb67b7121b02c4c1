"""Toxicity by boosted trees over dense features, with isotonic calibration (operator 8).

The lexicon - words and word beginnings far commoner in toxic texts - is learned from
one half of a bounded labelled sample; trees and calibration use the other half, so
lexicon densities are as honest there as on unseen texts.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyscout.llm.boosting import BoostedTrees, Isotonic
from keyscout.llm.labelled import class_sample, fold, sample_texts
from keyscout.llm.text import U, Words, chunks, make_room, mix, string_buffers

#: labelled documents per class, lexicon size, bytes of word beginnings, words around a pronoun
PER_CLASS, TERMS, STEMS, NEAR = 4000, 1500, (4, 5, 6), 4
#: second-person pronouns (fixed values)
SECOND_PERSON = "you your yours yourself u ur du dich dir dein deine deiner ihr euch euer tu te toi ton ta tes vous votre vos ti tú usted ustedes vosotros".split()
FEATURES = (
    "words", "hits", "density", "weight", "weight_density", "top_weight", "stem_hits", "near_person", "person_rate",
    "hidden_hits", "hidden_rate", "digit_in_word", "mark_in_word", "capitals", "shouted", "exclaim", "question",
    "punctuation", "digits", "wide", "word_length", "long_repeat", "lines",
)
_MARKS = np.ones(256, bool)  # blank table: words are letters, digits and bytes of other scripts
_MARKS[48:58] = _MARKS[65:91] = _MARKS[97:123] = _MARKS[128:] = False
_ALPHA = np.zeros(256, bool)
_ALPHA[65:91] = _ALPHA[97:123] = _ALPHA[128:] = True
_DIGIT = np.zeros(256, bool)
_DIGIT[48:58] = True
#: look-alike digits and signs (fixed values)
_LEET = np.arange(256, dtype=np.uint8)
for _sign, _letter in zip(b"013457@$!|", b"oieastasil"):
    _LEET[_sign] = _letter
_SIGNS = np.zeros(256, bool)
_SIGNS[[ord(c) for c in "*.-_+~'`^#"]] = True


def _word_table(words: list[str]) -> np.ndarray:
    column = pa.array(words, pa.string())
    return np.unique(Words(column, blanks=_MARKS).hash)


_PERSON = _word_table(SECOND_PERSON)


def _found(table: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(hit, place in the sorted table) of every value."""
    if not len(table):
        return np.zeros(len(values), bool), np.zeros(len(values), np.int64)
    at = np.searchsorted(table, values)
    at[at == len(table)] = 0
    return table[at] == values, at


def _terms(words: Words) -> list[np.ndarray]:
    """Term hashes of every word: the word, then its beginnings (told apart by a salt)."""
    out = [words.hash]
    for size in STEMS:
        with np.errstate(over="ignore"):
            out.append(np.where(words.end - words.start > size, mix(words.prefix_hash(size) + U(size)), U(0)))
    return out


class Lexicon:
    """Sorted term hashes and their log-odds."""

    def __init__(self, terms: np.ndarray, weights: np.ndarray):
        order = np.argsort(terms)
        self.terms, self.weights = terms[order], weights[order]

    def __call__(self, hashes: np.ndarray) -> np.ndarray:
        hit, at = _found(self.terms, hashes)
        return np.where(hit, self.weights[at], 0.0) if len(self.weights) else np.zeros(len(hashes))


def _shown(raw: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Texts with look-alikes undone and signs between two letters taken out."""
    plain = _LEET[raw]
    keep = np.ones(len(raw), bool)
    if len(raw) > 2:
        keep[1:-1] = ~(_SIGNS[raw[1:-1]] & _ALPHA[raw[:-2]] & _ALPHA[raw[2:]])
    return plain[keep], np.r_[0, np.cumsum(keep)][at]


def features(column: pa.Array, lexicon: Lexicon) -> np.ndarray:
    """(texts, FEATURES) of a chunk."""
    raw, at = string_buffers(column)
    n = len(at) - 1
    words = Words((raw, at), blanks=_MARKS)
    size = np.diff(at)

    def per_text(mask: np.ndarray) -> np.ndarray:
        return np.diff(np.r_[0, np.cumsum(mask)][at]).astype(np.float64)

    def per_word(x: np.ndarray, own: Words = words) -> np.ndarray:
        return np.bincount(own.owner, x, n) if len(own.owner) else np.zeros(n)

    whole, *stems = _terms(words)
    stem = np.max([lexicon(s) for s in stems], axis=0) if len(whole) else np.zeros(0)
    weight = np.maximum(lexicon(whole), stem)
    hit = weight > 0
    person = _found(_PERSON, whole)[0]
    close = np.zeros(len(whole), bool)
    for d in range(1, NEAR + 1):
        if len(whole) > d:
            same = words.owner[d:] == words.owner[:-d]
            close[d:] |= same & person[:-d]
            close[:-d] |= same & person[d:]
    bare, bare_at = _shown(raw, at)
    shown = Words((bare, bare_at), blanks=_MARKS)
    hidden = np.maximum(lexicon(shown.hash), np.max([lexicon(s) for s in _terms(shown)[1:]], axis=0)) > 0 if len(shown.hash) else np.zeros(0)
    count = np.maximum(words.count, 1)
    hits, all_hits = per_word(hit), per_word(hidden, shown)
    top = np.zeros(n)
    if len(whole):
        np.maximum.at(top, words.owner[hit], weight[hit])
    letters = np.maximum(per_text(_ALPHA[raw]), 1)
    upper = (raw >= 65) & (raw < 91)
    total_up = np.r_[0, np.cumsum(upper)]
    shouted = (total_up[words.end] - total_up[words.start] == words.end - words.start) & (words.end - words.start > 2) if len(whole) else np.zeros(0)
    inner = np.zeros((3, len(raw)), bool)
    if len(raw) > 2:
        between = _ALPHA[raw[:-2]] & _ALPHA[raw[2:]]
        inner[0, 1:-1], inner[1, 1:-1] = _DIGIT[raw[1:-1]] & between, _SIGNS[raw[1:-1]] & between
        inner[2, 2:] = (raw[2:] == raw[1:-1]) & (raw[1:-1] == raw[:-2]) & _ALPHA[raw[2:]]
    length = np.maximum(size, 1)
    columns = (
        np.log1p(words.count), np.minimum(hits, 50), hits / count, np.minimum(per_word(weight * hit), 200), per_word(weight * hit) / count, top,
        np.minimum(per_word(stem > 0), 50), per_word(hit & close) / np.maximum(hits, 1), per_word(person) / count,
        np.clip(all_hits - hits, 0, 50), np.maximum(all_hits - hits, 0) / count, per_text(inner[0]) / count, per_text(inner[1]) / count,
        per_text(upper) / letters, per_word(shouted) / count, per_text(raw == 33) / count, per_text(raw == 63) / count,
        per_text((raw < 128) & _MARKS[raw] & (raw > 32)) / length, per_text(_DIGIT[raw]) / length, per_text(raw >= 128) / letters, letters / count, per_text(inner[2]) / length, per_text(raw == 10) / length,
    )
    return np.stack(columns, 1)


class ToxicityModel:
    def __init__(self, lexicon: Lexicon, trees: BoostedTrees | None, curve: Isotonic | None, base: float):
        self.lexicon, self.trees, self.curve, self.base = lexicon, trees, curve, base

    def score(self, column: pa.Array) -> np.ndarray:
        if self.trees is None:
            return np.full(len(column), self.base)
        return np.clip(self.curve(self.trees.raw(features(column, self.lexicon))), 0, 1)


def _half(doc_id: str = "doc_id"):
    return F.pmod(F.xxhash64(F.lit("half"), F.col(doc_id)), F.lit(2))


def train_toxicity(documents: DataFrame, labels: DataFrame, label: str = "toxic", folds: int = 3, held: int = 1, per_class: int = PER_CLASS) -> ToxicityModel:
    """Lexicon, trees and calibration from up to ``per_class`` labelled training documents of each class."""
    texts = sample_texts(documents, class_sample(labels, label, per_class, folds, held))

    def terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make_room()
        for batch in batches:
            for part in chunks(batch):
                words = Words(part.column(1), blanks=_MARKS)
                y = part.column(2).cast(pa.int64()).to_numpy()
                term = np.concatenate(_terms(words))
                owner = np.tile(words.owner, 1 + len(STEMS))
                pair = np.unique(np.stack([term.view(np.int64), owner], 1), axis=0) if len(term) else np.zeros((0, 2), np.int64)
                pair = pair[pair[:, 0] != 0]
                yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(pair[:, 0])), pa.array(y[pair[:, 1]])], names=["term", "label"])

    counts = texts.where(_half() == 0).mapInArrow(terms, "term long, label long").groupBy("term").agg(F.sum((F.col("label") == 1).cast("long")).alias("toxic"), F.sum((F.col("label") == 0).cast("long")).alias("clean"))
    sizes = {r.label: r.n for r in texts.where(_half() == 0).groupBy("label").agg(F.count("*").alias("n")).collect()}
    n1, n0 = sizes.get(1, 0), sizes.get(0, 0)
    odds = F.log((F.col("toxic") + 0.5) / (n1 + 1)) - F.log((F.col("clean") + 0.5) / (n0 + 1))
    sure = odds / F.sqrt(1 / (F.col("toxic") + 0.5) + 1 / (F.col("clean") + 0.5))
    # a fixed number of the surest terms
    best = counts.where("toxic >= 4").select("term", odds.alias("odds"), sure.alias("sure")).where("odds > 1.6 and sure > 2.2").orderBy(F.col("sure").desc(), "term").limit(TERMS).toPandas()
    lexicon = Lexicon(best["term"].to_numpy(np.int64).view(U), best["odds"].to_numpy(float))
    shared = documents.sparkSession.sparkContext.broadcast(lexicon)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make_room()
        for batch in batches:
            for part in chunks(batch):
                x = features(part.column(1), shared.value)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2).cast(pa.float64()), part.column(3).cast(pa.float64()), pa.array([r.tobytes() for r in x], pa.binary())], names=["doc_id", "label", "class_rows", "x"])

    data = texts.where(_half() == 1).mapInArrow(rows, "doc_id long, label double, class_rows double, x binary").toArrow().sort_by("doc_id")
    y = data.column("label").to_numpy()
    if len(np.unique(y)) < 2:
        return ToxicityModel(lexicon, None, None, float(y.mean()) if len(y) else 0.0)
    x = np.frombuffer(b"".join(data.column("x").to_pylist()), np.float64).reshape(len(y), -1)
    drawn = {v: (y == v).sum() for v in np.unique(y)}
    w = np.array([n / drawn[v] for n, v in zip(data.column("class_rows").to_pylist(), y)])
    w *= len(w) / w.sum()
    out = np.zeros(len(y))
    part = np.arange(len(y)) % 4
    for k in range(4):  # out-of-fold scores calibrate
        out[part == k] = BoostedTrees().fit(x[part != k], y[part != k], w[part != k]).raw(x[part == k])
    return ToxicityModel(lexicon, BoostedTrees().fit(x, y, w), Isotonic().fit(out, y, w), float(np.average(y, weights=w)))


def keep_below(documents: DataFrame, model: ToxicityModel, most: float = 0.7) -> DataFrame:
    """Rows whose score stays below ``most``; columns stay as they are."""
    shared = documents.sparkSession.sparkContext.broadcast(model)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make_room()
        for batch in batches:
            for part in chunks(batch):
                yield part.filter(pa.array(shared.value.score(part.column(part.schema.get_field_index("text"))) < most))

    return documents.mapInArrow(work, documents.schema)


def score_toxicity(documents: DataFrame, model: ToxicityModel) -> DataFrame:
    """Input columns plus ``score`` (0..1) from ``text`` alone.

    Null and empty texts are scored like any text without words; without labelled rows
    of both classes every score is the base rate.  A ``score`` column of the input is
    replaced.
    """
    shared = documents.sparkSession.sparkContext.broadcast(model)
    base = documents.drop("score")
    names = base.columns

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make_room()
        for batch in batches:
            for part in chunks(batch):
                score = shared.value.score(part.column(part.schema.get_field_index("text")))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(score, pa.float64())], names=[*names, "score"])

    return base.mapInArrow(work, ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in base.schema.fields), "score double"]))
