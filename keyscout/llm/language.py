"""Language identification by expectation-maximisation over a mixture (operator 4).

Every word of a text is drawn from one of the languages; a word's likelihood under a
language is that of its letter trigrams.  EM finds the text's language proportions,
and languages leave one by one while the penalised likelihood rises.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from keyscout.llm.labelled import fold
from keyscout.llm.text import U, Words, chunks, make_room, mix

#: bins of hashed trigrams, documents learned from per language, EM rounds per language set
BINS, PER_LANGUAGE, ROUNDS = 1 << 17, 2000, 6
_LETTERS = np.ones(256, bool)  # blank table: only ASCII letters and bytes of other scripts are inside words
_LETTERS[65:91] = _LETTERS[97:123] = _LETTERS[128:] = False
_has_letter = regex.compile(r"\p{L}").search  # letters only: no digits, fractions or other numerals


def _trigrams(words: Words) -> tuple[np.ndarray, np.ndarray]:
    """(bin, word) of every byte trigram of every word, borders included."""
    size = words.end - words.start
    word = np.repeat(np.arange(len(size)), size)
    at = np.arange(size.sum()) + np.repeat(words.start - np.r_[0, np.cumsum(size)[:-1]], size)
    b = np.concatenate([words.bytes, np.zeros(1, np.uint8)]).astype(np.uint32)
    here = b[at]
    before = np.where(at > words.start[word], b[at - 1], 0)
    after = np.where(at + 1 < words.end[word], b[np.minimum(at + 1, len(b) - 1)], 0)
    code = (before << 16 | here << 8 | after) * np.uint32(2654435761)
    return (code >> np.uint32(15)).astype(np.int64), word


_COUNTS = "lang string, bin int, n long"


def _learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total: dict[str, np.ndarray] = {}
    make_room()
    for batch in batches:
        for part in chunks(batch):
            words = Words(part.column(0), hashes=False, blanks=_LETTERS)
            bins, word = _trigrams(words)
            langs = np.array(part.column(1).to_pylist(), object)
            owner = words.owner[word]
            for lang in set(langs.tolist()):
                mine = (langs == lang)[owner]
                total[lang] = total.get(lang, 0) + np.bincount(bins[mine], minlength=BINS)
    for lang, n in total.items():
        at = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.string()), pa.array(at, pa.int32()), pa.array(n[at], pa.int64())], names=["lang", "bin", "n"])


class LanguageModel:
    """Trigram log-likelihoods (bins x languages), languages in order of name."""

    def __init__(self, languages: list[str], logs: np.ndarray):
        self.languages, self.logs = languages, logs

    def mixtures(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Per text: language proportions, and mean log-likelihood of a trigram under the mixture."""
        k = len(self.languages)
        words = Words(column, hashes=False, blanks=_LETTERS)
        n = words.n_texts
        if not len(words.start) or not k:
            return np.zeros((n, k)), np.zeros(n)
        bins, word = _trigrams(words)
        size = words.end - words.start
        like = np.add.reduceat(self.logs[bins], np.r_[0, np.cumsum(size)[:-1]], axis=0)
        some = np.flatnonzero(words.count)
        first = np.r_[0, np.cumsum(words.count[some])[:-1]]
        owner = np.repeat(np.arange(len(some)), words.count[some])
        count = words.count[some].astype(np.float64)
        penalty = np.log(count + 1)  # half a parameter's description length, twice: share and choice

        def settle(share: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            for _ in range(ROUNDS):
                with np.errstate(divide="ignore"):
                    x = like + np.log(share).astype(np.float32)[owner]
                top = x.max(1, keepdims=True)
                x = np.exp(x - top)
                whole = x.sum(1, keepdims=True)
                share = np.add.reduceat(x / whole, first, axis=0) / count[:, None]
            fit = np.add.reduceat((top + np.log(whole))[:, 0].astype(np.float64), first)
            return share, fit

        best, fit = settle(np.full((len(some), k), 1 / k))
        value = fit - penalty * (best > 0).sum(1)
        for _ in range(k - 1):
            trial = best.copy()
            live = (trial > 0).sum(1) > 1
            if not live.any():
                break
            low = np.where(trial > 0, trial, np.inf).argmin(1)
            trial[live, low[live]] = 0
            trial /= trial.sum(1, keepdims=True)
            trial, new = settle(trial)
            gain = live & (new - penalty * (trial > 0).sum(1) >= value)
            if not gain.any():
                break
            best[gain], value[gain], fit[gain] = trial[gain], (new - penalty * (trial > 0).sum(1))[gain], new[gain]
        share, mean = np.zeros((n, k)), np.zeros(n)
        share[some] = best
        mean[some] = fit / np.add.reduceat(size[: len(owner)].astype(np.float64), first)
        return share, mean


def train_language_model(documents: DataFrame, folds: int = 4, held: int = 2, per_language: int = PER_LANGUAGE) -> LanguageModel:
    """Trigram counts of up to ``per_language`` training documents per language (least id hashes)."""
    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang")).where("text is not null and lang is not null and doc_id is not null").where(fold("doc_id", folds) != held)
    order = Window.partitionBy("lang").orderBy("h", "doc_id")
    # about twice the rows wanted reach the ranking of a language, however many it has
    sizes = rows.groupBy("lang").agg(F.count("*").alias("lang_rows"))
    near = rows.select("doc_id", "lang", F.xxhash64("doc_id").alias("h")).join(F.broadcast(sizes), "lang")
    near = near.where(F.pmod("h", F.lit(1 << 20)) * F.col("lang_rows") <= F.lit((1 << 20) * (2 * per_language + 200)))
    chosen = near.withColumn("place", F.row_number().over(order)).where(F.col("place") <= per_language).select("doc_id").distinct()
    texts = rows.join(F.broadcast(chosen), "doc_id", "left_semi").select("text", "lang")
    counts = texts.mapInArrow(_learn, _COUNTS).groupBy("lang", "bin").agg(F.sum("n").alias("n")).toPandas()
    languages = sorted(counts["lang"].unique())
    table = np.zeros((BINS, len(languages)))
    for i, lang in enumerate(languages):
        mine = counts[counts["lang"] == lang]
        table[mine["bin"].to_numpy(), i] = mine["n"].to_numpy()
    seen = max(1, int((table > 0).any(1).sum())) if len(languages) else 1
    total = table.sum(0, keepdims=True)
    return LanguageModel(languages, np.log((table + 0.1) / (total + 0.1 * seen)).astype(np.float32))


def keep_identified(documents: DataFrame, model: LanguageModel, least: float = 0.4) -> DataFrame:
    """Rows whose text has letters and whose first language holds a share of ``least`` or more; columns stay as they are."""
    shared = documents.sparkSession.sparkContext.broadcast(model)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make_room()
        for batch in batches:
            for part in chunks(batch):
                column = part.column(part.schema.get_field_index("text"))
                share, _ = shared.value.mixtures(column)
                top = share.max(1) if share.size else np.zeros(len(share))
                letters = np.array([t is not None and _has_letter(t) is not None for t in column.to_pylist()], bool)
                yield part.filter(pa.array((top >= least) & letters))

    return documents.mapInArrow(work, documents.schema)


def identify_languages(documents: DataFrame, model: LanguageModel) -> DataFrame:
    """Input columns plus lang_pred, score, lang_shares (map of the selected set), fit.

    ``score`` is the share of the predicted language; ``fit`` the mean log-likelihood of
    a trigram.  A null or letterless text is ``und`` with score 0 and no shares; a text
    with letters of scripts the model never saw gets the likeliest language all the
    same.  Without training rows every text is ``und``.  Only ``text`` is read.
    Output columns replace input columns of the same names.
    """
    shared = documents.sparkSession.sparkContext.broadcast(model)
    added = {"lang_pred": "string", "score": "double", "lang_shares": "map<string,double>", "fit": "double"}
    base = documents.drop(*added)
    names = base.columns

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        make_room()
        for batch in batches:
            for part in chunks(batch):
                column = part.column(part.schema.get_field_index("text"))
                share, mean = model.mixtures(column)
                pred, score, shares = [], [], []
                for text, row in zip(column.to_pylist(), share):
                    if text is None or not row.size or not row.any() or not _has_letter(text):
                        pred.append("und"), score.append(0.0), shares.append([])
                        continue
                    top = int(row.argmax())
                    pred.append(model.languages[top])
                    score.append(min(1.0, float(row[top])))
                    shares.append([(model.languages[i], float(row[i])) for i in np.flatnonzero(row)])
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(pred, pa.string()), pa.array(score, pa.float64()), pa.array(shares, pa.map_(pa.string(), pa.float64())), pa.array(mean, pa.float64())], names=[*names, *added])

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in base.schema.fields), *(f"{n} {t}" for n, t in added.items())])
    return base.mapInArrow(work, schema)
