"""Minimal hitting sets of a mask hypergraph."""

from __future__ import annotations

import itertools
from collections import deque
from collections.abc import Callable, Iterable, Iterator, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyscout.functions.masks import bits, join_words, minimal_delta, minimal_masks, split_words, words_of
from keyscout.plans.lineage import snapshot


class _Edges:
    """Edges as one incidence bitset per column: every test of a node is a few integer operations."""

    def __init__(self, edges: Sequence[int], m: int):
        self.edges = list(edges)
        self.all = (1 << len(self.edges)) - 1
        self.through = [sum(1 << e for e, v in enumerate(self.edges) if v >> c & 1) for c in range(m)]

    def state(self, chosen: int) -> tuple[int, tuple]:
        """(edges missed, (column, edges only it hits) of every chosen column)"""
        once, more = 0, 0
        for c in bits(chosen):
            more |= once & self.through[c]
            once |= self.through[c]
        return self.all & ~once, tuple((c, self.through[c] & ~more) for c in bits(chosen))


def _children(space: _Edges, node: tuple, choice: str | None) -> Iterator[tuple]:
    chosen, open_, missed, own = node
    if choice is None:
        branch, rest = open_, 0
    else:
        options = (space.edges[e] & open_ for e in bits(missed))
        branch = min(options, key=int.bit_count) if choice == "smallest" else next(options)
        rest = open_ & ~branch
    later = branch
    for c in bits(branch):
        later &= ~(1 << c)
        through = space.through[c]
        fresh = missed & through
        if not fresh:
            continue  # c would hit nothing of its own
        kept = [(a, e & ~through) for a, e in own]
        if all(e for _, e in kept):
            # columns of the branch before c stay out; all others may still come
            yield chosen | 1 << c, rest | later, missed & ~through, (*kept, (c, fresh))


def minimal_hitting_sets(edges: Sequence[int], m: int, edge_choice: str | None = "smallest", order: str = "breadth", counters: dict | None = None) -> list[int]:
    """All inclusion-minimal column sets that meet every edge, sorted by size.

    A node keeps, for each chosen column, the edges only that column hits; a node where
    such a list runs empty can never become minimal again and is dropped at once.  The
    search branches over the missed edge with the fewest open columns; ``edge_choice``
    "first" and None (every open column) are the ablations.  No edges: the empty set.
    An empty edge: nothing.
    """
    edges = minimal_masks(edges)
    if edges and edges[0] == 0:
        return []
    space = _Edges(edges, m)
    todo = deque([(0, (1 << m) - 1, space.all, ())])
    found, visited = [], 0
    take = todo.popleft if order == "breadth" else todo.pop
    while todo:
        node = take()
        visited += 1
        if not node[2]:
            found.append(node[0])
            continue
        todo.extend(_children(space, node, edge_choice))
    if counters is not None:
        counters["nodes"] = visited
    return sorted(set(found), key=lambda x: (x.bit_count(), x))


def minimal_hitting_sets_df(spark: SparkSession, edges: Sequence[int], m: int) -> DataFrame:
    """The same tree level by level as a distributed frontier, for very many results.

    DF(key_mask) up to 63 columns; beyond, the words key_mask, key_mask1, ... of 63 columns each.
    """
    import pandas as pd

    words = range(len(words_of(m)))
    names = ["key_mask" if w == 0 else f"key_mask{w}" for w in words]
    edges = minimal_masks(edges)
    if not edges or edges[0] == 0:
        return spark.createDataFrame([] if edges else [split_words(0, m)], ", ".join(f"{n} long" for n in names))
    shared = spark.sparkContext.broadcast(edges)
    schema = ", ".join([*(f"chosen{w} long" for w in words), *(f"open{w} long" for w in words), "done boolean"])
    columns = [c.split()[0] for c in schema.split(", ")]

    def step(frames):
        space = _Edges(shared.value, m)
        for frame in frames:
            rows = []
            for row in frame.itertuples(index=False):
                chosen, open_ = join_words(row[: len(words)]), join_words(row[len(words) : 2 * len(words)])
                missed, own = space.state(chosen)
                rows += [(*split_words(a, m), *split_words(o, m), not u) for a, o, u, _ in _children(space, (chosen, open_, missed, own), "smallest")]
            yield pd.DataFrame(rows, columns=columns)

    frontier = spark.createDataFrame([(*split_words(0, m), *split_words((1 << m) - 1, m), False)], schema)
    found = None
    while True:
        level = snapshot(frontier.repartition(spark.sparkContext.defaultParallelism, *columns[: len(words)]).mapInPandas(step, schema))
        done = level.where("done").select(*[F.col(f"chosen{w}").alias(n) for w, n in zip(words, names)])
        found = done if found is None else found.unionByName(done)
        frontier = level.where("not done")
        if not frontier.limit(1).count():
            return found.distinct()


def refined_hitting_sets(edges: Sequence[int], m: int, refine: Callable[[int], Iterable[int]]) -> tuple[list[int], list[int]]:
    """(sets that ``refine`` has nothing against, final edges), depth first, while edges arrive.

    ``refine`` gives new edges that a found set misses.  The search goes on in place: nodes
    see the new edges when their turn comes, and nodes left because a column hit nothing
    of its own are parked, since a new edge may be that column's own.
    """
    edges = minimal_masks(edges)
    space, accepted = _Edges(edges, m), []
    todo, parked = [(0, (1 << m) - 1)], []
    while todo and edges[:1] != [0]:
        chosen, open_ = todo.pop()
        missed, own = space.state(chosen)
        if not all(e for _, e in own):
            parked.append((chosen, open_))
            continue
        if not missed:
            new = list(refine(chosen))
            if not new:
                accepted.append(chosen)
                continue
            edges = minimal_delta(edges, new)
            space = _Edges(edges, m)
            todo += [*parked, (chosen, open_)]
            parked = []
            continue
        branch = min((space.edges[e] & open_ for e in bits(missed)), key=int.bit_count)
        later = branch
        for c in bits(branch):
            later &= ~(1 << c)
            todo.append((chosen | 1 << c, open_ & ~branch | later))
    return ([] if edges[:1] == [0] else accepted), edges


def is_minimal_hitting_set(mask: int, edges: Sequence[int]) -> bool:
    return all(mask & e for e in edges) and all(any(mask & e == 1 << c for e in edges) for c in bits(mask))


def hitting_sets_bruteforce(edges: Sequence[int], m: int) -> list[int]:
    """By definition, over all subsets (tests)."""
    hit = [s for s in range(1 << m) if all(s & e for e in edges)]
    return minimal_masks(hit)


def hitting_sets_by_edge_product(edges: Sequence[int]) -> list[int]:
    """Edge by edge: every partial set meets the new edge or takes one of its columns (cross-check)."""
    found = [0]
    for e in minimal_masks(edges):
        found = minimal_masks(itertools.chain((s for s in found if s & e), (s | 1 << c for s in found if not s & e for c in bits(e))))
    return sorted(found, key=lambda x: (x.bit_count(), x))
