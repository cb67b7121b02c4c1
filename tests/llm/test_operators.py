"""Operators against SQL, brute force, public libraries and held-out rows."""

import collections
import hashlib
import math
import random
import re
import sys
import time
import zlib

import numpy as np
import pyarrow as pa
import pytest
from oracle import compare
from pyspark.sql import functions as F

from keyscout.llm import oracles, queries
from keyscout.llm.cluster import durable
from keyscout.llm.language import identify_languages, keep_identified, train_language_model
from keyscout.llm.lines import apply_keep_bitmaps, line_keep_bitmaps
from keyscout.llm.mixing import score_documents
from keyscout.llm.neardup import _sketch, keep_first_of_groups
from keyscout.llm.packing import Encoder, best_fit, local_search, pack_documents, slots
from keyscout.llm.quality import score_quality, train_quality_vote
from keyscout.llm.topk import exact_top_k
from keyscout.llm.toxicity import score_toxicity, train_toxicity
from keyscout.llm.transducer import SubwordTransducer, decode_documents, encode_documents
from keyscout.llm.vectors import near_duplicate_vectors

WORD = queries.tokenizer_path("word_bpe_49k.json")
PIECE = queries.tokenizer_path("piece_bpe_32k.model")
ODD = [(1, None), (2, ""), (3, " \n\t "), (4, "x"), (5, "Ünï çødé 日本 \x00 end"), (5, "Ünï çødé 日本 \x00 end"), (None, "no id here"), (7, "long " * 60_000)]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, "doc_id long, text string").selectExpr("*", "'en' as lang", "0.5 as score", "1 as n_lines", "2 as length")


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], "doc_id long, text string, lang string")


@pytest.mark.parametrize("name", sorted(oracles.oracle_sql()))
def test_against_sql(spark, sf, name):
    compare(spark, queries.queries()[name], oracles.oracle_sql()[name], sf)


def crc(i, m):
    return zlib.crc32(str(i).encode()) % m


# packing


def test_pack_plan_is_whole_and_tight():
    draw = random.Random(5)
    lengths = collections.Counter(min(2048, int(draw.expovariate(1 / 500)) + 1) for _ in range(5000))
    plan = local_search(best_fit(lengths, 2048), 2048)
    got = collections.Counter()
    for pattern, bins in plan.items():
        assert sum(pattern) <= 2048
        for n in pattern:
            got[n] += bins
    assert got == lengths
    assert sum(plan.values()) <= math.ceil(sum(k * v for k, v in lengths.items()) / 2048) + 1


def test_local_search_empties_bins():
    # best fit leaves three bins; two hold everything after an exchange
    start = collections.Counter({(6, 2): 1, (5, 4): 1, (3,): 1})
    done = local_search(start, 10)
    assert sum(done.values()) == 2 and sum(sum(p) * c for p, c in done.items()) == 20


def test_slots_are_gapless():
    for length, (rank, _, _) in slots(collections.Counter({(5, 3, 2): 4, (7, 3): 2})).items():
        assert rank[0] == 0 and (np.diff(rank) > 0).all()


def test_packing_matches_tokenizer(spark, sf, odd):
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(WORD)
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    for frame in (docs, odd):
        rows = pack_documents(frame, WORD).collect()
        bins = collections.defaultdict(list)
        for r in rows:
            bins[r.sequence_id].append((r.offset, r.length))
        for parts in bins.values():
            parts.sort()
            assert parts[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(parts, parts[1:])) and sum(parts[-1]) <= 2048
        want = collections.Counter()
        for r in frame.select("doc_id", "text").collect():
            ids = [*tokenizer.encode(r.text or "", add_special_tokens=False).ids, 0]
            for k in range(0, len(ids), 2048):
                piece = np.array(ids[k : k + 2048], "<u4")
                want[(r.doc_id, k // 2048, k, len(piece), zlib.crc32(piece.tobytes()))] += 1
        assert collections.Counter((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in rows) == want


def test_encoder_equals_tokenizer_on_noise():
    draw = random.Random(1)
    signs = list("aAbB'sSéÉßΣςİıtT 12²½ªº\n\t \u0085\x1c\x00<|>_-!?.日本語ー한́èﬁ🙂‍") + ["<|endoftext|>", "'s", "'re", "</w>", "ll"]
    texts = ["".join(draw.choice(signs) for _ in range(draw.randint(0, 40))) for _ in range(3000)]
    encoder = Encoder.of(WORD)
    for got, want in zip(encoder(texts), encoder.tokenizer.encode_batch(texts, add_special_tokens=False)):
        assert got.tolist() == want.ids


# subword transducer


def test_transducer_equals_library(spark, sf, odd):
    import sentencepiece

    library = sentencepiece.SentencePieceProcessor(model_file=PIECE)
    draw = random.Random(2)
    signs = list("abehinorst \n\t  ▁") + ["ing", "the", " a", "  ", "é", "한", "😀", "\x00", "<s>", "<0x0A>", "ll", "aaa", "1234", "ﬁ"]
    machine = SubwordTransducer.of(PIECE)
    for _ in range(3000):
        text = "".join(draw.choice(signs) for _ in range(draw.randint(0, 40)))
        ids = library.encode(text)
        assert machine.encode(text) == ids and machine.decode(ids) == library.decode(ids)
    for frame in (spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text"), odd):
        encoded = encode_documents(frame, PIECE)
        back = collections.Counter((r.doc_id, r.text) for r in decode_documents(encoded, PIECE).collect())
        assert back == collections.Counter((r.doc_id, r.text or "") for r in frame.select("doc_id", "text").collect())
        assert collections.Counter((r.doc_id, tuple(r.ids)) for r in encoded.collect()) == collections.Counter((r.doc_id, tuple(library.encode(r.text or ""))) for r in frame.select("doc_id", "text").collect())


def test_decoding_takes_no_step_for_each_id():
    machine = SubwordTransducer.of(PIECE)
    ids, calls = machine.encode("the café is 東 open \U0001f600 " * 500), []
    sys.setprofile(lambda frame, event, arg: calls.append(event))
    try:
        text = machine.decode(ids)
    finally:
        sys.setprofile(None)
    assert text == "the café is 東 open \U0001f600 " * 500 and len(calls) < 100 < len(ids)


def test_decoding_parts_bytes_at_ids_without_text():
    machine = SubwordTransducer.of(PIECE)
    half = [machine.byte[b] for b in "é".encode()]
    control = next(i for i in range(len(machine.text)) if i not in machine.raw)
    assert machine.decode(half) == "é"
    assert machine.decode([half[0], control, half[1]]) == "\ufffd\ufffd"
    assert machine.decode([half[0], machine.lexicon["a"], half[1]]) == "\ufffda\ufffd"


def test_neighbour_rule_equals_merging():
    machine = SubwordTransducer.of(PIECE)
    draw = random.Random(3)
    ids = sorted(machine.lexicon.values())
    for _ in range(4000):
        a, b = draw.choice(ids), draw.choice(ids)
        x, y = machine.text[a], machine.text[b]
        assert machine._border(x, y) == (machine._merged(x + y) == [x, y])


# line dedup


def test_line_edge_cases(spark, odd):
    line = "This very line is repeated in many of the documents here"
    rows = [(i, f"own {i}\n  {line.upper()}\t\n{line}") for i in range(1, 8)] + [(8, line), (8, line), (None, line), (9, None), (10, "")]
    got = apply_keep_bitmaps(*(lambda d: (d, line_keep_bitmaps(d)))(spark.createDataFrame(rows, "doc_id long, text string"))).collect()
    by = collections.Counter((r.doc_id, r.text, r.n_lines, r.n_dropped) for r in got)
    assert all(by[(i, f"own {i}", 3, 2)] == 1 for i in range(1, 8))
    assert by[(8, line, 1, 0)] == 2 and by[(None, line, 1, 0)] == 1 and by[(9, "", 1, 0)] == 1 and by[(10, "", 1, 0)] == 1
    assert apply_keep_bitmaps(odd, line_keep_bitmaps(odd)).count() == len(ODD)


def test_line_dedup_over_many_ranges(spark):
    """A key that spreads over every range, and keys at range borders."""
    rows = [(i, "\n".join(f"line number {j:05d} padded with more text to be long" for j in range(i % 7, 40, 3)) + "\nthe same long line stands in every one of these") for i in range(300)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        got = {r.doc_id: r.text for r in apply_keep_bitmaps(docs, line_keep_bitmaps(docs)).collect()}
    finally:
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")
    holders = collections.defaultdict(set)
    for i, text in rows:
        for key in text.split("\n"):
            holders[key].add(i)
    for i, text in rows:
        assert got[i] == "\n".join(k for k in text.split("\n") if len(holders[k]) < 5 or max(holders[k]) == i)


# top-k and vectors


def brute_top(vectors, ask, k):
    out = {}
    for q in ask:
        scores = sorted((-int(sum(math.floor(1024 * a) * math.floor(1024 * b) for a, b in zip(vectors[q], v))), i) for i, v in vectors.items() if i != q)
        out[q] = [(i, -s) for s, i in scores[:k]]
    return out


def test_top_k_ties_and_odd_vectors(spark):
    draw = random.Random(4)
    vectors = {i: [float(draw.randint(-2, 2)) / 1024 for _ in range(4)] for i in range(300)}
    rows = [*vectors.items(), (400, None), (500, [None, 1.0, 1.0, 1.0]), (600, [float("nan")] * 4), (700, [float("inf"), 0.0, 0.0, 0.0]), (None, [1.0] * 4)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>").selectExpr("*", "1 as score", "2 as rank")
    got = collections.defaultdict(list)
    for r in exact_top_k(frame, frame.where("vec_id % 100 = 0"), 10).orderBy("query_id", "rank").collect():
        got[r.query_id].append((r.vec_id, r.score))
    assert dict(got) == brute_top(vectors, [0, 100, 200], 10)
    few = frame.where("vec_id in (0, 1, 2)")
    assert exact_top_k(few, few, 10).count() == 6
    assert exact_top_k(frame.where("vec_id < 0"), frame.where("vec_id < 0"), 3).count() == 0


def test_vector_groups(spark):
    rng = np.random.default_rng(6)
    centre = rng.standard_normal((20, 16))
    rows = [(i, (centre[i % 20] + 0.12 * rng.standard_normal(16)).tolist()) for i in range(1200)]
    rows += [(2000 + i, rows[0][1]) for i in range(50)]
    unit = np.array([v for _, v in rows])
    unit /= np.linalg.norm(unit, axis=1, keepdims=True)
    near = unit @ unit.T >= 0.95
    ids = np.array([i for i, _ in rows])
    low = ids.copy()
    while True:
        new = np.array([low[n].min() for n in near])
        if (new == low).all():
            break
        low = new
    odd = [(5000, None), (5001, [0.0] * 16), (5002, [float("nan")] * 16), (5003, []), (5004, [1.0, 2.0]), (None, [1.0] * 16)]
    frame = spark.createDataFrame(rows + odd, "vec_id long, embedding array<double>").selectExpr("*", "1 as shard", "2 as links")
    got = near_duplicate_vectors(frame).collect()
    by = {r.vec_id: (r.n_links, r.component_id) for r in got}
    assert len(got) == len(rows) + len(odd)
    assert {i: by[i] for i in ids.tolist()} == {i: (int(n.sum()) - 1, int(c)) for i, n, c in zip(ids.tolist(), near, low)}
    assert all(by[i] == (0, i) for i in range(5000, 5005)) and by[None] == (0, None)
    assert near_duplicate_vectors(frame.where("vec_id < 0")).count() == 0


# language model


def test_base_score_by_definition(spark, odd):
    rows = odd.select("doc_id", "text").collect() + [(i, f"the cat {i % 5} sat On the mat{'!' * (i % 3)}") for i in range(40)]
    frame = spark.createDataFrame([tuple(r) for r in rows], "doc_id long, text string")
    got = score_documents(frame).collect()
    assert len(got) == len(rows)

    def tokens(text):
        return [*re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or "")), None]

    count = collections.Counter()
    for d, t in rows:
        if d is not None and crc(d, 7) != 2:
            count.update(tokens(t))
    total, kinds = sum(count.values()), len(count)
    want = collections.Counter()
    for d, t in rows:
        row = tokens(t)
        want[(d, d is not None and crc(d, 7) == 2, len(row), sum(count[w] > 0 for w in row), round(sum(math.log10((count[w] + 1) / (total + kinds + 1)) for w in row), 4))] += 1
    assert collections.Counter((r.doc_id, r.held_out, r.n_tokens, r.n_known, round(r.base_score, 4)) for r in got) == want
    assert all(r.train_tokens == total and r.score < 0 for r in got)


def spelling_model(words, classes=1, bits=16):
    """Mixer whose tables hold the words, each once and in the first class."""
    from keyscout.llm.mixing import BORDER_BITS, INSIDE, ByteCode, Decisions, Mixer, _joined, levels

    code = ByteCode(np.ones(256))
    d = Decisions(*_joined(words), code, bits)
    counts = np.zeros((INSIDE, 2, 1 << bits), np.int64)
    for k in range(INSIDE):
        np.add.at(counts[k], (d.bit, d.slots[k] if k < INSIDE - 1 else d.in_class(0)), 1)
    tokens = np.zeros(classes, np.int64)
    tokens[0] = len(words)
    return Mixer(code, np.stack([levels(c) for c in counts]), np.zeros(1 << BORDER_BITS, np.uint16), tokens, len(set(words)))


def test_mixing_is_a_distribution():
    """Probabilities of all next bytes after any beginning sum to one, and adaptation helps repetition."""
    from keyscout.llm.text import Words
    import pyarrow as pa

    model = spelling_model([b"ab ", b"abc ", b"ba "], classes=2)
    assert abs(sum(2.0 ** -int(n) for n in model.code.size) - 1) < 1e-12
    one = np.arange(256, dtype=np.uint8)
    assert abs(np.exp(model.spelled(one, np.arange(257))).sum() - 1) < 1e-4
    for head in (b"a", b"ab", b"zq"):
        raw = np.concatenate([np.r_[np.frombuffer(head, np.uint8), v] for v in one]).astype(np.uint8)
        longer = model.spelled(raw, np.arange(257) * (len(head) + 1))
        shorter = model.spelled(np.frombuffer(head, np.uint8), np.array([0, len(head)]))
        assert abs(np.exp(longer - shorter).sum() - 1) < 1e-4
    text = Words(pa.array(["zzq " * 300]))
    score, _, _ = model.score(text, np.zeros((301, 2), np.int64))
    once, _, _ = model.score(Words(pa.array(["zzq"])), np.zeros((2, 2), np.int64))
    assert score[0] / 300 > once[0]


def test_mixing_learns_from_every_training_word():
    """Slots follow the distinct words, the beginning counts however long, and pulls of shards add up."""
    from keyscout.llm.mixing import MOST_SLOT_BITS, SLOT_BITS, ByteCode, Decisions, _joined, slot_bits

    assert slot_bits(10) == SLOT_BITS < slot_bits(20_000) < slot_bits(100_000) <= MOST_SLOT_BITS
    long = [bytes([97 + k]) + b"x" * 60 + b" " for k in range(2)]
    a, b = (Decisions(*_joined([w]), ByteCode(np.ones(256)), 18).slots for w in long)
    assert (a[4, -8:] == b[4, -8:]).all() and (a[5, -8:] != b[5, -8:]).any()
    rng = np.random.default_rng(4)
    words = [bytes(rng.integers(97, 105, rng.integers(1, 9)).astype(np.uint8)) + b" " for _ in range(3 * 8192)]
    model = spelling_model(words)
    often = rng.integers(1, 5, (len(words), 1))
    whole = model.learned(words, often)
    parts = [model.learned(words[:8192], often[:8192]), model.learned(words[8192:], often[8192:])]
    assert all(np.allclose(w, p + q, rtol=1e-6) for w, p, q in zip(whole, *parts))
    before = model.spelled(*_joined(words)).sum()
    model.settle(*whole)
    assert model.spelled(*_joined(words)).sum() > before


def test_word_order_counts_and_long_words_cost(spark):
    """Held-out texts in training order score better than shuffled; a text's own sequences do not help it."""
    rng = np.random.default_rng(6)
    names = ["".join(map(chr, rng.integers(97, 123, 5))) for _ in range(300)]
    passages = [" ".join(rng.choice(names, 30)) for _ in range(20)]
    train = [i for i in range(400) if crc(i, 7) != 2]
    held = [i for i in range(400) if crc(i, 7) == 2]
    rows = [(i, " ".join(passages[k] for k in rng.integers(0, 20, 3))) for i in train[:150]]
    alone = [(i, " ".join(rng.choice(names, 90))) for i in train[150:200]]
    kept, mixed = held[: len(held) // 2], held[len(held) // 2 :]
    rows += alone
    rows += [(i, passages[i % 20]) for i in kept] + [(i, " ".join(rng.permutation(passages[i % 20].split()))) for i in mixed]
    rows += [(held[0] + 7_000_000, "q" * 3000), (held[0] + 7_000_001, "q" * 6000)]
    score = {r.doc_id: r.score / r.n_tokens for r in score_documents(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    in_order, shuffled, own = (np.mean([score[i] for i in some]) for some in (kept, mixed, [i for i, _ in alone]))
    assert in_order > shuffled + 0.8 and own < in_order - 0.8


def test_tokens_after_a_very_long_word_are_scored():
    """A word whose probability is below the smallest double leaves the weights that follow the words before as numbers."""
    from keyscout.llm.mixing import TRUST, _followed

    trust = TRUST[None].copy()
    whole, rest = _followed(np.array([[0, 0], [0.5, 0.2]]), np.ones((2, 2, 4), np.float32), np.array([-1e5, -2.0]), np.zeros(2, np.int64), np.array([0]), trust, np.array([0]))
    assert np.isfinite(whole).all() and np.isfinite(rest).all() and np.isfinite(trust).all() and whole[0] < -1e5 < whole[1]


def test_contexts_against_a_plain_count():
    from keyscout.llm.mixing import contexts
    from keyscout.llm.text import Words
    import pyarrow as pa

    texts = ["a b a b c", "a b c", "", "b c a b"]
    rows = [["<", "<", *t.split(), ">"] for t in texts]
    count = [collections.Counter(tuple(r[i - k : i + 1]) for r in rows for i in range(2, len(r))) for k in range(3)]
    at = [(r, i) for r in rows for i in range(2, len(r))]
    args = [np.array([count[k][tuple(r[i - k : i + 1])] for r, i in at]) for k in range(3)]
    for own in (False, True):
        share, _ = contexts(Words(pa.array(texts)), *args, len(texts), np.full(len(texts), own))
        want = []
        for r, i in at:
            rest = [q for q in rows if q is not r] if own else rows
            for k in (2, 1):
                follows = [q[j] for q in rest for j in range(2, len(q)) if q[j - k : j] == r[i - k : i]]
                want.append(follows.count(r[i]) / max(1, len(follows)))
        assert np.allclose(share.ravel(), want)


def test_scores_beat_the_base_on_held_out_rows(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = [r for r in score_documents(docs).collect() if r.held_out]
    assert rows and sum(r.score for r in rows) > sum(r.base_score for r in rows)


def test_search_starts_from_the_entry_too():
    """A node that only the entry links to is found, and exact products find what brute force does."""
    from keyscout.llm.hnsw import SmallWorld
    from keyscout.llm.vectors import _exact

    turn = np.array([3.0, 0.0, 0.1, 0.2])
    x = np.stack([np.cos(turn), np.sin(turn)], 1).astype(np.float32)
    graph = SmallWorld(x, np.array([2, 1, 1, 0]))
    for t in graph.tables:
        t[:] = -1
    graph.tables[1][0, :2] = 1, 2
    graph.tables[0][0, 0], graph.entry = 3, 0
    ids, _ = graph.search(x[3:], 4)
    assert set(ids[0].tolist()) >= {1, 2, 3}
    rng = np.random.default_rng(2)
    unit = rng.standard_normal((500, 4)).astype(np.float32)
    unit /= np.linalg.norm(unit, axis=1, keepdims=True)
    assert all(set(f.tolist()) == set(np.flatnonzero(t).tolist()) for f, t in zip(_exact(unit, unit, 0.9), unit @ unit.T >= 0.9))


def test_scores_of_nothing(spark, empty):
    assert score_documents(empty).count() == 0


# trained labellers


def test_languages(spark, sf01, odd, empty):
    docs = spark.read.parquet(f"{sf01}/documents.parquet")
    model = train_language_model(docs)
    lang = {r.doc_id: r.lang for r in docs.collect()}
    held = [r for r in identify_languages(docs.drop("lang"), model).collect() if crc(r.doc_id, 4) == 2]
    assert np.mean([r.lang_pred == lang[r.doc_id] for r in held]) > 0.97
    got = collections.Counter((r.doc_id, r.lang_pred == "und", 0 <= r.score <= 1) for r in identify_languages(odd, model).collect())
    assert sum(got.values()) == len(ODD) and all(ok for _, _, ok in got) and got[(1, True, True)] == got[(2, True, True)] == got[(3, True, True)] == 1
    assert keep_identified(odd, model).count() == len(ODD) - 3
    none = train_language_model(empty)
    assert {r.lang_pred for r in identify_languages(odd, none).collect()} == {"und"}
    half = spark.createDataFrame([(1, " ".join(docs.where("lang = 'en'").first().text.split()[:150] + docs.where("lang = 'fr'").first().text.split()[:150]))], "doc_id long, text string")
    shares = identify_languages(half, model).first().lang_shares
    assert set(shares) == {"en", "fr"} and 0.3 < shares["en"] < 0.7


def test_quality(spark, odd, empty):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    model = train_quality_vote(docs, labels)
    truth = {r.doc_id: r.quality for r in labels.collect()}
    held = [r for r in score_quality(docs, model).collect() if r.held_out and r.doc_id in truth]
    assert np.mean([r.predicted == truth[r.doc_id] for r in held]) > 0.93
    rows = score_quality(odd, model).collect()
    assert len(rows) == len(ODD) and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in rows)
    none = train_quality_vote(docs, labels.where("doc_id < 0"))
    assert score_quality(odd, none).count() == len(ODD) and score_quality(empty, model).count() == 0


def test_toxicity(spark, odd, empty):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    model = train_toxicity(docs, labels)
    truth = {r.doc_id: r.toxic for r in labels.collect()}
    held = [(r.score >= 0.7, truth[r.doc_id]) for r in score_toxicity(docs.select("doc_id", "text"), model).collect() if r.doc_id in truth and crc(r.doc_id, 3) == 1]
    found, toxic = sum(a and b == 1 for a, b in held), sum(b == 1 for _, b in held)
    assert found / toxic > 0.85 and sum(a and b == 0 for a, b in held) < 0.01 * len(held)
    rows = score_toxicity(odd, model).collect()
    assert len(rows) == len(ODD) and all(0 <= r.score <= 1 for r in rows)
    none = train_toxicity(docs, labels.where("doc_id < 0"))
    assert score_toxicity(odd, none).count() == len(ODD) and score_toxicity(empty, model).count() == 0


def test_isotonic_and_trees():
    from keyscout.llm.boosting import BoostedTrees, Isotonic

    rng = np.random.default_rng(8)
    x = rng.standard_normal((2000, 5))
    y = ((x[:, 0] > 0) ^ (x[:, 1] > 0.5)).astype(float)
    raw = BoostedTrees(trees=40).fit(x, y, np.ones(2000)).raw(x)
    assert ((raw > 0) == y).mean() > 0.98
    curve = Isotonic().fit(np.array([1.0, 2, 3, 4]), np.array([0.0, 1, 0, 1]), np.ones(4))
    assert (np.diff(curve.value) >= 0).all() and curve.value.tolist() == [0, 0.5, 1]


# pipeline


def test_pipeline_stage_by_stage(spark, tmp_path):
    import corpus_pipeline

    sf_dir = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    kept = {}
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, sf_dir)
        if k < len(corpus_pipeline.STAGES) - 1:
            assert out.columns == docs.columns
        out.write.parquet(f"{tmp_path}/{k}")
        before, docs = docs, spark.read.parquet(f"{tmp_path}/{k}")
        kept[name] = docs
        if name == "line_dedup":
            rows = {r.doc_id: r.text for r in before.collect()}
            holders = collections.defaultdict(set)
            key = lambda line: re.sub("[A-Z]", lambda m: m[0].lower(), line.strip(" \t\n\x0b\x0c\r"))
            for i, text in rows.items():
                for line in text.split("\n"):
                    holders[key(line)].add(i)
            for r in docs.collect():
                assert r.text == "\n".join(x for x in rows[r.doc_id].split("\n") if len(key(x)) < 40 or len(holders[key(x)]) < 5 or max(holders[key(x)]) == r.doc_id)
        if name == "near_dedup":
            from test_neardup import brute

            want = brute([(r.doc_id, r.text) for r in before.collect()], 80)
            assert {r.doc_id for r in docs.collect()} == {d for d, (_, c) in want.items() if c == d}
    assert {r.doc_id for r in kept["packing"].collect()} == {r.doc_id for r in kept["near_dedup"].collect()}
    assert corpus_pipeline.run(spark, sf_dir).count() == kept["packing"].count()


def test_hash_of_kept_text():
    assert hashlib.sha256(b"").hexdigest().startswith("e3b0c442")


def test_numerals_are_no_letters(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    signs = spark.createDataFrame([(1, "½"), (2, "²"), (3, "Ⅷ"), (4, "12 _ ³"), (5, "ª"), (6, "½ der Hund")], "doc_id long, text string")
    model = train_language_model(docs)
    got = {r.doc_id: (r.lang_pred, r.score) for r in identify_languages(signs, model).collect()}
    assert all(got[i] == ("und", 0.0) for i in (1, 2, 3, 4))
    assert got[6][0] in model.languages


def test_mixtures_equal_a_plain_em(spark, sf):
    """Shares of single-language sets and of the first full set against loops over words."""
    from keyscout.llm.language import _LETTERS, ROUNDS, LanguageModel, _trigrams
    from keyscout.llm.text import Words
    import pyarrow as pa

    logs = train_language_model(spark.read.parquet(f"{sf}/documents.parquet")).logs
    k = logs.shape[1]
    model = LanguageModel([str(i) for i in range(k)], logs)
    for text in ("the house of the river", "und der Hund, aber the house", "x"):
        words = Words(pa.array([text]), hashes=False, blanks=_LETTERS)
        bins, word = _trigrams(words)
        like = [[sum(float(logs[b, c]) for b, w in zip(bins, word) if w == i) for c in range(k)] for i in range(len(words.start))]

        def settle(share):
            for _ in range(ROUNDS):
                parts = []
                for row in like:
                    x = [v + math.log(s) if s else -math.inf for v, s in zip(row, share)]
                    top = max(x)
                    whole = sum(math.exp(v - top) for v in x)
                    parts.append([math.exp(v - top) / whole for v in x])
                    parts[-1].append(top + math.log(whole))
                share = [sum(p[c] for p in parts) / len(parts) for c in range(k)]
            return share, sum(p[-1] for p in parts)

        penalty = math.log(len(like) + 1)
        share, fit = settle([1 / k] * k)
        best, value = share, fit - penalty * sum(s > 0 for s in share)
        for _ in range(k - 1):
            if sum(s > 0 for s in best) <= 1:
                break
            trial = list(best)
            trial[min((c for c in range(k) if trial[c] > 0), key=lambda c: trial[c])] = 0
            trial, fit = settle([s / sum(trial) for s in trial])
            new = fit - penalty * sum(s > 0 for s in trial)
            if new < value:
                break
            best, value = trial, new
        got, _ = model.mixtures(pa.array([text]))
        assert np.allclose(got[0], best, atol=1e-3), text


#: names that the operators use inside, as columns of the input
INSIDE = ["_mark", "_doc", "_text", "_keep", "_kept", "__kept", "mark", "keep", "positions", "key", "hash", "component_id", "kept", "lang_pred", "score"]


def _crowded(spark, rows):
    return spark.createDataFrame([(*r, *range(len(INSIDE))) for r in rows], "doc_id long, text string, " + ", ".join(f"`{n}` int" for n in INSIDE))


def test_filters_keep_clashing_columns(spark):
    long = "a line that is longer than forty characters, and repeated"
    words = " ".join(f"w{i}" for i in range(60))
    docs = _crowded(spark, [(i, f"{long}\nown {i}") for i in range(6)] + [(10, words), (11, words), (12, None), (13, "")])
    cut = apply_keep_bitmaps(docs, line_keep_bitmaps(docs), counts=False)
    assert cut.columns == docs.columns
    assert {r.doc_id: r.text for r in cut.collect()} == {i: f"own {i}" for i in range(5)} | {5: f"{long}\nown 5", 10: words, 11: words, 12: "", 13: ""}
    first = keep_first_of_groups(docs)
    assert first.columns == docs.columns
    got = {r.doc_id: r for r in first.collect()}
    assert 10 in got and 11 not in got and 12 in got and 13 in got
    assert all([r[n] for n in INSIDE] == list(range(len(INSIDE))) for r in got.values())


def test_stage_filters_on_empty_tables(spark, empty):
    assert apply_keep_bitmaps(empty, line_keep_bitmaps(empty), counts=False).collect() == []
    assert keep_first_of_groups(empty).collect() == [] and keep_first_of_groups(empty).columns == empty.columns


def test_path_falls_back_on_merging():
    machine = SubwordTransducer(PIECE)
    want = machine.encode("hello world")
    machine.spans.clear()
    machine._side_by_side = lambda a, b: False
    machine.pairs.clear()
    assert machine.encode("hello world") == want


def test_votes_match_a_plain_count(spark):
    """Every score is the similarity-weighted share of the nearest labelled vectors, worked out text by text."""
    from keyscout.llm import quality

    draw = random.Random(3)
    rows = [(i, " ".join(draw.choice(["good", "fine", "plain", "words"] if i % 2 else ["zz", "qq", "x9", "zz"]) for _ in range(5 + i % 9))) for i in range(90)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i, _ in rows], "doc_id long, quality int")
    model = train_quality_vote(docs, labels, per_class=20)
    got = {r.doc_id: r.score for r in score_quality(docs, model).collect()}
    for i, text in rows:
        terms = quality._counts(pa.array([text]))[0].astype(np.float64) * model.idf
        y = terms / np.linalg.norm(terms) @ model.basis
        near = model.vectors @ (y / np.linalg.norm(y))
        best = sorted(range(len(near)), key=lambda k: -near[k])[: model.voters]
        vote = {k: max(near[k], 0) ** 8 * model.weights[k] for k in best}
        assert math.isclose(got[i], sum(v * model.labels[k] for k, v in vote.items()) / sum(vote.values()), abs_tol=1e-3)


def test_chunks_bound_rows_and_bytes():
    from keyscout.llm.text import chunks

    batch = pa.RecordBatch.from_arrays([pa.array(["", "ab", "c" * 50, "", "d"] * 3)], names=["text"])
    parts = list(chunks(batch, limit=10, rows=2))
    assert max(p.num_rows for p in parts) == 2 and pa.Table.from_batches(parts).column(0).to_pylist() == batch.column(0).to_pylist()


def test_a_checkpoint_that_alone_needs_its_exchanges_frees_them(spark):
    def files():
        tracker = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
        names = tracker.getAllFiles()
        return {names.apply(i).getName() for i in range(names.size()) if names.apply(i).getName().startswith("shuffle_")}

    before = files()
    frame = spark.range(1000).groupBy((F.col("id") % 10).alias("k")).agg(F.count("*").alias("n"))
    kept = durable(frame, once=True)
    end = time.time() + 20
    while files() - before and time.time() < end:  # files go in the background
        time.sleep(0.2)
    assert not files() - before
    assert kept.count() == 10 and sum(r.n for r in kept.collect()) == 1000
    assert frame.count() == 10  # the same rows can still be computed


def test_workers_forget_the_tables_of_an_operator_they_have_left():
    encode, texts = Encoder.of(WORD), ["some words that the packing operator learns", "日本 words"]
    first = [ids.tolist() for ids in encode(texts)]
    assert encode.known
    batch = pa.RecordBatch.from_arrays([pa.array([1]), pa.array(["another operator's text"])], names=["doc_id", "text"])
    assert sum(b.num_rows for b in _sketch(5)(iter([batch]))) == 1
    assert not encode.known and encode.size == 0
    assert [ids.tolist() for ids in encode(texts)] == first


def test_words_share_their_beginnings():
    """A beginning that several words have is looked up once, and every word's decisions are those of it spelled alone."""
    from keyscout.llm.mixing import ByteCode, Decisions, _joined, beginnings

    rng = random.Random(5)
    words = {"".join(rng.choice("abc") for _ in range(rng.randint(1, 14))).encode() + b" " for _ in range(900)} | {b"a ", b"a\0 ", b"\0 ", b"abcdefgh ", b"abcdefghi ", b"abcdefghij "}
    spelled = [*rng.sample(sorted(words), len(words)), b"\xff"]
    raw, at = _joined(spelled)
    code = ByteCode(np.bincount(raw, minlength=256))
    chosen, place = beginnings(raw, at)
    whole, shared = Decisions(raw, at, code, 16), Decisions(raw, at, code, 16, chosen)
    assert len(chosen) < 0.6 * len(raw) and len(shared.bit) < 0.6 * len(whole.bit)
    size = code.size[raw]
    first = np.cumsum(size[chosen]) - size[chosen]
    rows = np.concatenate([np.arange(f, f + n) for f, n in zip(first[place].tolist(), size.tolist())])
    assert (shared.slots[:, rows] == whole.slots).all() and (shared.bit[rows] == whole.bit).all() and (shared.in_class(3)[rows] == whole.in_class(3)).all()


def ranking_code(words):
    from keyscout.llm.mixing import ByteCode, _joined, two_before

    raw, at = _joined(words)
    return ByteCode.ranking(two_before(raw, at), raw.astype(np.int64), np.ones(len(raw), np.int64))


def test_bytes_are_spelled_by_rank():
    """Ranks after the two bytes before take fewer decisions than bytes, and all next bytes' probabilities still sum to one."""
    from keyscout.llm.mixing import BORDER_BITS, INSIDE, ByteCode, Decisions, Mixer, _joined, border_slots, borders, levels, two_before
    from keyscout.llm.text import Words

    rng = random.Random(3)
    words = ["".join(rng.choice("aab" if i % 2 else "xyyz") for i in range(rng.randint(1, 9))).encode() + b" " for _ in range(400)] + [b"\xff"]
    raw, at = _joined(words)
    assert [(b & 255, b >> 8) for b in two_before(*_joined([b"abc", b"d", b"ef"])).tolist()] == [(0, 0), (97, 0), (98, 97), (0, 0), (0, 0), (101, 0)]
    code, plain = ranking_code(words), ByteCode(np.bincount(raw, minlength=256))
    assert all(sorted(r) == list(range(256)) for r in code.rank.tolist())
    assert code.size[code.symbols(raw, at)].sum() < 0.8 * plain.size[raw].sum()
    d = Decisions(raw, at, code, 16)
    counts = np.zeros((INSIDE, 2, 1 << 16), np.int64)
    for k in range(INSIDE):
        np.add.at(counts[k], (d.bit, d.slots[k] if k < INSIDE - 1 else d.in_class(0)), 1)
    model = Mixer(code, np.stack([levels(c) for c in counts]), np.zeros(1 << BORDER_BITS, np.uint16), np.array([len(words)]), len(set(words)))
    one = np.arange(256, dtype=np.uint8)
    assert abs(np.exp(model.spelled(one, np.arange(257))).sum() - 1) < 1e-4
    for head in (b"x", b"xa", b"xay", b"q\0"):
        longer = model.spelled(np.concatenate([np.r_[np.frombuffer(head, np.uint8), v] for v in one]).astype(np.uint8), np.arange(257) * (len(head) + 1))
        shorter = model.spelled(np.frombuffer(head, np.uint8), np.array([0, len(head)]))
        assert abs(np.exp(longer - shorter).sum() - 1) < 1e-4
    # the border's decisions are those of the first bytes
    text = Words(pa.array(["xay b x", ""]))
    first = [b"x", b"b", b"x", b"\xff", b"\xff"]
    assert border_slots(*borders(text), code)[2].tolist() == [int(code.size[code.symbols(*_joined([b]))[0]]) for b in first]


def test_shared_beginnings_learn_as_if_spelled_alone(monkeypatch):
    """Counts and gates' inputs of training words in classes, each beginning spelled once, are those of every word spelled by itself."""
    from keyscout.llm import mixing as m

    rng = np.random.default_rng(8)
    words = sorted({bytes(rng.integers(97, 101, rng.integers(1, 12)).astype(np.uint8)) for _ in range(700)})
    words = [words[i] for i in rng.permutation(len(words))]
    counts = rng.integers(0, 4, (len(words), 3)) + np.eye(3, dtype=np.int64)[rng.integers(0, 3, len(words))]
    code = ranking_code([w + b" " for w in words])
    d = m.Decisions(*m._joined([w + b" " for w in words]), code, 16)
    want = np.zeros((m.INSIDE, 1 << 16, 2), np.int64)
    for c in range(3):
        often = np.repeat(counts[:, c], d.each)
        for k in range(m.INSIDE):
            np.add.at(want[k], (d.slots[k] if k < m.INSIDE - 1 else d.in_class(c), d.bit), often)
    caught, spelled, plain = [], [], m.Decisions

    def counted(raw, at, *rest):
        spelled.append(len(plain(raw, at, *rest).bit))
        return plain(raw, at, *rest)

    monkeypatch.setattr(m, "_sliced", lambda cells, slices: caught.append(cells.copy()))
    monkeypatch.setattr(m, "Decisions", counted)
    batch = pa.RecordBatch.from_arrays([pa.array([len(words)]), pa.array([m._joined_words(words, counts)], pa.binary())], names=["a", "blob"])
    list(m._bit_counts(code, 16, 3)(iter([batch])))
    assert (caught[0].reshape(want.shape) == want).all() and spelled[0] < 0.7 * len(d.bit)
    model = m.Mixer(code, np.stack([m.levels(t.T) for t in want]), np.zeros(1 << m.BORDER_BITS, np.uint16), counts.sum(0), len(words))
    kind = np.repeat(counts.argmax(1), d.each)
    x = np.stack([np.where(d.bit, m._LEFT[1][state], -m._LEFT[0][state]) for state in (model.tables[k][d.slots[k] if k < m.INSIDE - 1 else d.in_class(kind)] for k in range(m.INSIDE))], 1)
    gate, often = 2 * (x[:, :-1] != 0).sum(1) + (x[:, -1] != 0), np.repeat(counts.sum(1), d.each)
    for g, (v, n) in enumerate(model._by_gate([w + b" " for w in words], counts)):
        assert np.isclose(n.sum(), often[gate == g].sum()) and np.allclose(n @ v, often[gate == g] @ x[gate == g], rtol=1e-4, atol=1e-2)


def test_places_and_planes_of_numbers():
    from keyscout.llm.mixing import _numbers, _planes, _repeats, ranked

    rng = np.random.default_rng(2)
    for bits in (1, 20, 44, 62, 64):
        x = rng.integers(0, 1 << min(bits, 63), 3000).astype(np.uint64)[rng.integers(0, 3000, 5000)] << np.uint64(bits == 64)
        values, inverse = ranked(x, bits)
        assert (values == np.unique(x)).all() and (values[inverse] == x).all()
        owner = rng.integers(0, 5, len(x))
        often = collections.Counter(zip(owner.tolist(), x.tolist()))
        assert _repeats(owner, x).tolist() == [often[k] for k in zip(owner.tolist(), x.tolist())]
    assert [len(a) for a in ranked(np.zeros(0, np.uint64), 64)] == [0, 0] and ranked(np.array([7]), 3)[1].tolist() == [0]
    for x in (np.zeros(0, np.int64), np.arange(9000) % 7, rng.integers(0, 1 << 40, 9000), np.array([255]), np.array([1 << 40, 0])):
        assert _numbers(_planes(x)).tolist() == x.tolist()
    assert len(_planes(rng.integers(0, 256, 9000))) < 9050


# vectors hung on the nodes of a graph


def test_vectors_hang_on_few_nodes(spark):
    """The work on a row does not grow with the table: it walks one graph and meets the rows of a few nodes, each link counted once."""
    from keyscout.llm import vectors as v
    from keyscout.llm.hnsw import SmallWorld

    rng = np.random.default_rng(8)
    x = rng.standard_normal((6000, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    z = rng.standard_normal((600, 64))
    z -= (z * x[:600]).sum(1, keepdims=True) * x[:600]
    z /= np.linalg.norm(z, axis=1, keepdims=True)
    c = rng.uniform(0.952, 0.99, (600, 1))
    x[-600:] = c * x[:600] + np.sqrt(1 - c * c) * z
    x[1000:1300] = x[1000] + 0.015 * rng.standard_normal((300, 64))
    x = x.astype(np.float32)
    unit = v._unit(x)
    nodes = v.thinned(unit, 300)
    assert len(nodes) == 300 and (unit[nodes] @ unit[nodes].T - 2 * np.eye(300)).max() <= v.APART  # one node in the dense group at most
    lists = v.hung(SmallWorld.build(unit[nodes]), unit, v.CELLS)
    met = np.bincount(lists[lists >= 0], minlength=300)
    assert (met[np.maximum(lists, 0)].sum(1) < len(x) // 4).mean() > 0.95
    frame = spark.createDataFrame(list(enumerate(x.tolist())), "vec_id long, embedding array<float>")
    near = unit @ unit.T >= 0.95
    got = {r.vec_id: r.n_links for r in v.near_duplicate_vectors(frame.repartition(4)).collect()}
    true = near.sum(1) - 1
    assert len(got) == len(x) and all(got[i] <= true[i] for i in range(len(x)))
    assert sum(got.values()) >= 0.99 * true.sum() and np.mean([got[i] >= 1 for i in np.flatnonzero(true)]) > 0.97


def test_vector_copies_and_tiles(spark, monkeypatch):
    """Very many copies collapse beforehand, repeated rows count, and a large cell is compared in tiles."""
    from keyscout.llm import vectors as v

    rng = np.random.default_rng(9)
    rows = [(i, x) for i, x in enumerate(rng.standard_normal((700, 8)).tolist())]
    rows += [(1000 + i, rows[3][1]) for i in range(1200)] + [rows[3], rows[5]]
    rows += [(5000 + i, (np.array(rows[7][1]) + 0.05 * rng.standard_normal(8)).tolist()) for i in range(40)]
    unit = np.array([x for _, x in rows])
    unit /= np.linalg.norm(unit, axis=1, keepdims=True)
    near = unit @ unit.T >= 0.95
    low = ids = np.array([i for i, _ in rows])
    while not (low == (new := np.array([low[n].min() for n in near]))).all():
        low = new
    want = collections.Counter()
    for i, n in zip(ids.tolist(), near.sum(1).tolist()):
        want[i] = n - 1
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    monkeypatch.setattr(v, "PART", 60)
    monkeypatch.setattr(v, "LEAST_NODES", 0)  # no graph: one cell of many parts
    got = v.near_duplicate_vectors(frame).collect()
    assert len(got) == len(rows)
    assert {r.vec_id: (r.n_links, r.component_id) for r in got} == {int(i): (want[i], int(c)) for i, c in zip(ids, low)}
