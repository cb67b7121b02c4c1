import itertools
import re

from hypothesis import given, settings
from hypothesis import strategies as st

from keyscout.llm.neardup import minhash_near_duplicates


def lowered(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text)


def shingles(text, width=5):
    words = re.findall(r"[^\x20\x09-\x0D]+", lowered(text or ""))
    if not words:
        return set()
    return {tuple(words[i : i + width]) for i in range(len(words) - width + 1)} or {tuple(words)}


def brute(docs, percent):
    """Components by comparing all pairs of different sets (inverted by shared shingles)."""
    sets = {d: shingles(t) for d, t in docs}
    root = {d: d for d in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    owners = {}
    for d, s in sets.items():
        for x in s:
            owners.setdefault(x, []).append(d)
    pairs = {p for o in owners.values() for p in itertools.combinations(sorted(o), 2)}
    for a, b in pairs:
        x, y = sets[a], sets[b]
        if 100 * len(x & y) >= percent * len(x | y):
            a, b = find(a), find(b)
            root[max(a, b)] = min(a, b)
    return {d: (len(s), find(d)) for d, s in sets.items()}


def test_matches_brute_force(spark, sf01):
    docs = spark.read.parquet(f"{sf01}/documents.parquet")
    want = brute([(r.doc_id, r.text) for r in docs.collect()], 85)
    got = minhash_near_duplicates(docs, 85).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == want
    assert all(r.kept == (r.doc_id == r.component_id) for r in got)


def test_edge_cases(spark):
    base = " ".join(f"w{i}" for i in range(200))
    rows = [(1, None), (2, ""), (3, "a b c"), (4, "A  b\tC"), (5, base), (6, base + " x"), (7, base.upper()), (7, base.upper()), (None, base), (8, " \n "), (9, "a b c d"), (10, "é " * 100000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as component_id", "2 as key", "3 as hi")
    got = minhash_near_duplicates(docs, 80).collect()
    assert len(got) == len(rows)
    by = {r.doc_id: r for r in got}
    assert by[1].n_shingles == by[2].n_shingles == by[8].n_shingles == 0
    assert [by[i].component_id for i in (1, 2, 3, 4, 5, 6, 7, 8, 9, 10)] == [1, 2, 3, 3, 5, 5, 5, 8, 9, 10]
    assert by[None].component_id is None and by[None].kept


def test_empty(spark):
    assert minhash_near_duplicates(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_large_near_copy_group_needs_the_tiles(spark):
    """Variants of one text that mostly miss the bound with one another but all meet it with the last."""
    words = [f"w{i}" for i in range(400)]
    rows = []
    for i in range(320):
        w = list(words)
        for k in range(5):
            w[(i * 7 + k * 83) % 400] = f"x{i}_{k}"
        rows.append((i, " ".join(w)))
    rows.append((1000, " ".join(words)))
    want = brute(rows, 85)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in minhash_near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), 85).collect()}
    assert got == want


@settings(max_examples=30, deadline=None)
@given(st.lists(st.text(alphabet="aB \t\nñ", max_size=30), max_size=6))
def test_kernel_counts(texts):
    import numpy as np
    import pyarrow as pa

    from keyscout.llm.text import shingle_sets

    owner, _ = shingle_sets(pa.array(texts, pa.string()))
    assert np.bincount(owner, minlength=len(texts)).tolist() == [len(shingles(t)) for t in texts]
