from hypothesis import given, settings
from hypothesis import strategies as st

from keyscout.functions import masks as M
from keyscout.plans import hitting as H


def one_based(*columns):
    return sum(1 << (c - 1) for c in columns)


RUNNING = [one_based(*e) for e in ((2,), (7,), (8,), (1, 3), (1, 4), (1, 6), (3, 5), (4, 5))]
edge_lists = st.lists(st.integers(1, 1023), max_size=12)


def test_running_example_first_round():
    assert set(H.minimal_hitting_sets(RUNNING, 8)) == {one_based(1, 2, 5, 7, 8), one_based(1, 2, 3, 4, 7, 8), one_based(2, 3, 4, 6, 7, 8)}


def test_running_example_second_round():
    edges = M.minimal_delta(RUNNING, [one_based(1, 5)])
    assert set(H.minimal_hitting_sets(edges, 8)) == {one_based(1, 2, 5, 7, 8), one_based(1, 2, 3, 4, 7, 8), one_based(2, 3, 4, 5, 6, 7, 8)}


def test_columns_before_the_branch_are_not_lost():
    edges = [one_based(3, 4), one_based(1, 3), one_based(2, 4)]
    for choice in ("smallest", "first", None):
        assert set(H.minimal_hitting_sets(edges, 4, choice)) == {one_based(3, 4), one_based(2, 3), one_based(1, 4)}


def test_no_edges_and_empty_edge():
    assert H.minimal_hitting_sets([], 5) == [0]
    assert H.minimal_hitting_sets([0, 3], 5) == []


@settings(max_examples=150, deadline=None)
@given(edge_lists)
def test_enumerators_agree(edges):
    want = sorted(H.hitting_sets_bruteforce(edges, 10))
    for choice in ("smallest", "first", None):
        assert sorted(H.minimal_hitting_sets(edges, 10, choice)) == want
    assert sorted(H.minimal_hitting_sets(edges, 10, order="depth")) == want
    assert sorted(H.hitting_sets_by_edge_product(edges)) == want
    assert all(H.is_minimal_hitting_set(k, edges) for k in want)


@settings(max_examples=100, deadline=None)
@given(edge_lists, edge_lists)
def test_minimising(old, new):
    small = M.minimal_masks(old)
    assert M.minimal_masks(small) == small
    assert M.minimal_delta(small, new) == M.minimal_masks([*old, *new])
    assert H.minimal_hitting_sets(small, 10) == H.minimal_hitting_sets(old, 10)


@settings(max_examples=60, deadline=None)
@given(edge_lists)
def test_duality(edges):
    small = M.minimal_masks(edges)
    if small:
        assert sorted(H.minimal_hitting_sets(H.minimal_hitting_sets(small, 10), 10)) == sorted(small)


def test_wide_masks():
    masks = [1 << 70, (1 << 70) | 1, 1 << 3]
    assert M.minimal_masks(masks) == [1 << 3, 1 << 70]
    assert M.join_words(M.split_words((1 << 70) | 5, 72)) == (1 << 70) | 5
    assert M.words_of(63) == ["mask"] and M.words_of(64) == ["mask", "mask1"]


def test_distributed_enumeration(spark):
    edges = [*RUNNING, one_based(1, 5)]
    got = sorted(r.key_mask for r in H.minimal_hitting_sets_df(spark, edges, 8).collect())
    assert got == sorted(H.minimal_hitting_sets(edges, 8))
    assert [r.key_mask for r in H.minimal_hitting_sets_df(spark, [], 4).collect()] == [0]
    assert H.minimal_hitting_sets_df(spark, [0], 4).count() == 0


def test_dataframe_minimising(spark):
    df = spark.createDataFrame([(m,) for m in (7, 3, 12, 8, 3)], "mask long")
    assert sorted(r.mask for r in M.minimize_df(df).collect()) == [3, 8]
    assert set(r.mask for r in M.minimize_partitions(df).collect()) >= {3, 8}
