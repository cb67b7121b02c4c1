"""Hierarchical navigable small-world graph of one shard, built and searched in numpy batches."""

from __future__ import annotations

import numpy as np

LINKS, BUILD_BEAM = 12, 48


class SmallWorld:
    """Levels of neighbour tables over unit vectors; row -1 entries are empty slots.

    ``levels[l]`` is (nodes of the level, neighbour table in shard positions).  Level 0
    holds every vector, each higher one about 1/LINKS of the level below.
    """

    def __init__(self, vectors: np.ndarray, level: np.ndarray):
        self.x, self.level = np.ascontiguousarray(vectors, np.float32), level
        self.tables = [np.full((len(vectors), LINKS * (2 if k == 0 else 1)), -1, np.int32) for k in range(int(level.max(initial=0)) + 1)]
        self.entry = -1

    @classmethod
    def build(cls, vectors: np.ndarray, seed: int = 11) -> SmallWorld:
        n = len(vectors)
        draw = np.random.default_rng(seed).random(n)
        graph = cls(vectors, np.floor(-np.log(np.maximum(draw, 1e-12)) / np.log(LINKS)).astype(np.int64))
        order = np.argsort(-graph.level, kind="stable")
        at, size = 0, 1
        while at < n:
            graph._insert(order[at : at + size])
            at += size
            size = min(1024, at)
        graph._connect()
        return graph

    def _connect(self) -> None:
        """Every node of level 0 is made reachable from the entry: pruning can leave one without a link to it.

        An unreachable node hangs on its nearest reachable neighbour, in a spare column.
        """
        n = len(self.x)
        if n < 2:
            return
        seen = np.zeros(n, bool)
        front = np.array([self.entry])
        seen[front] = True
        while True:
            while len(front):
                near = self.tables[0][front].ravel()
                near = np.unique(near[near >= 0])
                front = near[~seen[near]]
                seen[front] = True
            lost = np.flatnonzero(~seen)
            if not len(lost):
                return
            out = self.tables[0][lost]
            able = (out >= 0) & seen[np.maximum(out, 0)]
            ready = able.any(1)
            if ready.any():
                lost, holder = lost[ready], out[ready, able[ready].argmax(1)]
            else:  # an island without links out of it
                lost, holder = lost[:1], np.array([self.entry])
            order = np.argsort(holder, kind="stable")
            lost, holder = lost[order], holder[order]
            rank = np.arange(len(holder)) - np.searchsorted(holder, holder)
            free = (self.tables[0] >= 0).sum(1)[holder] + rank
            wide = int(free.max()) + 1 - self.tables[0].shape[1]
            if wide > 0:
                self.tables[0] = np.concatenate([self.tables[0], np.full((n, wide), -1, np.int32)], 1)
            # rows fill from the left once their empty slots are moved to the right
            rows = np.unique(holder)
            self.tables[0][rows] = np.take_along_axis(self.tables[0][rows], np.argsort(self.tables[0][rows] < 0, axis=1, kind="stable"), 1)
            self.tables[0][holder, free] = lost
            front = lost
            seen[front] = True

    def _insert(self, new: np.ndarray) -> None:
        if self.entry < 0:
            self.entry = int(new[0])
            return
        start = np.full((len(new), 1), self.entry)
        among = self.x[new] @ self.x[new].T
        np.fill_diagonal(among, -2)
        for k in range(len(self.tables) - 1, -1, -1):
            ids, sims = self._beam(self.x[new], start, k, BUILD_BEAM if (self.level[new] >= k).any() else 4)
            start = ids[:, :4]
            mine = np.flatnonzero(self.level[new] >= k)
            if not len(mine):
                continue
            # candidates: the beam, and the others of the batch that live on this level
            near = min(16, len(mine) - 1)
            ids, sims = ids[mine], sims[mine]
            if near > 0:
                part = among[np.ix_(mine, mine)]
                top = np.argpartition(-part, near - 1, axis=1)[:, :near]
                ids = np.concatenate([ids, new[mine][top]], 1)
                sims = np.concatenate([sims, np.take_along_axis(part, top, 1)], 1)
            ok = (ids >= 0) & (self.level[np.maximum(ids, 0)] >= k)
            chosen = self._diverse(np.where(ok, ids, -1), np.where(ok, sims, -2), self.tables[k].shape[1])
            self.tables[k][new[mine]] = chosen
            self._answer(new[mine], chosen, k)

    def _diverse(self, ids: np.ndarray, sims: np.ndarray, cap: int) -> np.ndarray:
        """Keep a candidate that is nearer to the node than to any kept one; fill up with the nearest rest."""
        order = np.argsort(-sims, axis=1, kind="stable")[:, :64]
        ids, sims = np.take_along_axis(ids, order, 1), np.take_along_axis(sims, order, 1)
        out = np.full((len(ids), cap), -1, np.int32)
        for s in range(0, len(ids), 256):
            i, q = ids[s : s + 256], sims[s : s + 256]
            v = self.x[np.maximum(i, 0)]
            cross = v @ v.transpose(0, 2, 1)
            keep = np.zeros(i.shape, bool)
            for c in range(i.shape[1]):
                worst = np.where(keep, cross[:, c, :], -2).max(1)
                keep[:, c] = (i[:, c] >= 0) & (q[:, c] > worst) & (keep.sum(1) < cap)
            rank = np.argsort(~keep, axis=1, kind="stable")[:, :cap]
            out[s : s + 256, : rank.shape[1]] = np.take_along_axis(i, rank, 1)
        return out

    def _answer(self, new: np.ndarray, chosen: np.ndarray, k: int) -> None:
        """Links back from the chosen neighbours, chosen anew where a table is full."""
        table = self.tables[k]
        owner, node = np.repeat(new, chosen.shape[1]), chosen.ravel()
        ok = node >= 0
        owner, node = owner[ok], node[ok]
        order = np.argsort(node, kind="stable")
        owner, node = owner[order], node[order]
        targets, first, count = np.unique(node, return_index=True, return_counts=True)
        most = int(count.max(initial=0))
        extra = np.full((len(targets), most), -1, np.int64)
        extra[np.repeat(np.arange(len(targets)), count), np.arange(len(node)) - np.repeat(first, count)] = owner
        both = np.concatenate([table[targets], extra], 1)
        # one place for each neighbour
        both.sort(axis=1)
        both[:, 1:][both[:, 1:] == both[:, :-1]] = -1
        both[both == targets[:, None]] = -1
        for s in range(0, len(targets), 512):
            b = both[s : s + 512]
            sims = np.einsum("nd,nkd->nk", self.x[targets[s : s + 512]], self.x[np.maximum(b, 0)])
            table[targets[s : s + 512]] = self._diverse(b, np.where(b >= 0, sims, -2), table.shape[1])

    def _beam(self, q: np.ndarray, start: np.ndarray, k: int, width: int) -> tuple[np.ndarray, np.ndarray]:
        """Beam search of many queries at once on level k: ids (-1: none) and similarities, best first."""
        n, b = len(self.x), len(q)
        table = self.tables[k]
        width = max(width, start.shape[1])
        ids = np.full((b, width), -1, np.int64)
        sims = np.full((b, width), -2, np.float32)
        done = np.ones((b, width), bool)
        m = start.shape[1]
        ids[:, :m] = start
        sims[:, :m] = np.where(start >= 0, np.einsum("bd,bkd->bk", q, self.x[np.maximum(start, 0)]), -2)
        done[:, :m] = start < 0
        seen = np.zeros((b, n), bool)
        row = np.arange(b)[:, None]
        r, c = np.nonzero(start >= 0)
        seen[r, start[r, c]] = True
        live = np.arange(b)
        while len(live):
            best = np.where(done[live], -3, sims[live])
            pick = best.argmax(1)
            go = best[np.arange(len(live)), pick] > -3
            live, pick = live[go], pick[go]
            if not len(live):
                break
            done[live, pick] = True
            near = table[ids[live, pick]].astype(np.int64)
            fresh = (near >= 0) & ~seen[live[:, None], np.maximum(near, 0)]
            seen[np.broadcast_to(live[:, None], near.shape)[fresh], near[fresh]] = True
            got = np.full(near.shape, -2, np.float32)
            r, c = np.nonzero(fresh)
            got[r, c] = np.einsum("nd,nd->n", q[live[r]], self.x[near[r, c]])
            s = np.concatenate([sims[live], got], 1)
            i = np.concatenate([ids[live], np.where(fresh, near, -1)], 1)
            d = np.concatenate([done[live], ~fresh], 1)
            top = np.argpartition(-s, width - 1, axis=1)[:, :width]
            sims[live], ids[live], done[live] = np.take_along_axis(s, top, 1), np.take_along_axis(i, top, 1), np.take_along_axis(d, top, 1)
        order = np.argsort(-sims, axis=1, kind="stable")
        return ids[row, order], sims[row, order]

    def search(self, q: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
        """(ids, similarities) of the level-0 beam of every query."""
        q = np.ascontiguousarray(q, np.float32)
        start = np.full((len(q), 1), self.entry)
        for k in range(len(self.tables) - 1, 0, -1):
            start = self._beam(q, start, k, 4)[0][:, :2]
        if len(self.tables) > 1:  # every node can be reached from the entry, not from any other start
            entry = np.where((start == self.entry).any(1), -1, self.entry)
            start = np.concatenate([start, entry[:, None]], 1)
        return self._beam(q, start, 0, width)

    def packed(self) -> list[bytes]:
        """Per node its neighbour rows of all its levels, to be carried in a table."""
        return [np.concatenate([t[i] for t in self.tables[: self.level[i] + 1]]).astype(np.int32).tobytes() for i in range(len(self.x))]

    @classmethod
    def unpacked(cls, vectors: np.ndarray, level: np.ndarray, rows: list[bytes]) -> SmallWorld:
        graph = cls(vectors, level)
        if rows:  # level 0 may be wider by its spare columns
            extra = max(len(r) // 4 - v * graph.tables[-1].shape[1] for r, v in zip(rows, level) if len(graph.tables) > 1) if len(graph.tables) > 1 else len(rows[0]) // 4
            graph.tables[0] = np.full((len(rows), extra), -1, np.int32)
        for i, raw in enumerate(rows):
            flat, at = np.frombuffer(raw, np.int32), 0
            for k in range(level[i] + 1):
                size = graph.tables[k].shape[1]
                graph.tables[k][i] = flat[at : at + size]
                at += size
        graph.entry = int(np.argmax(level)) if len(level) else -1
        return graph
