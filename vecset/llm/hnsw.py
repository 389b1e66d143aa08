"""A hierarchical navigable small-world graph in numpy, for many queries at once. Nearness is the inner product of unit vectors.

Points go in by batches that double; each batch is searched in the graph so far, linked to diverse near points (one that is nearer
to an already chosen neighbour than to the point is left out while others remain), and linked back under the same rule.
"""

from __future__ import annotations

import numpy as np

from .common import mix64


class Graph:
    def __init__(self, vectors: np.ndarray, degree: int = 12, beam: int = 48, seed: int = 1):
        self.x = np.ascontiguousarray(vectors, np.float32)
        n = len(self.x)
        self.degree, self.beam = degree, beam
        draw = (mix64(np.arange(n, dtype=np.uint64) + np.uint64(seed)) >> np.uint64(11)).astype(np.float64) / 2**53
        self.level = np.minimum((-np.log(np.maximum(draw, 1e-12)) / np.log(degree)).astype(np.int64), 6)
        order = np.argsort(-self.level, kind="stable")
        self.links = [np.full((n, 2 * degree if k == 0 else degree), -1, np.int32) for k in range((int(self.level.max()) if n else 0) + 1)]
        self.entry, done = (int(order[0]), 1) if n else (-1, 0)
        self.known = np.zeros(n, bool)
        if n:
            self.known[self.entry] = True
        while done < n:
            batch = order[done : done + max(1, min(done, 256))]
            self._insert(batch)
            done += len(batch)

    def _insert(self, batch: np.ndarray) -> None:
        q = self.x[batch]
        at = np.full((len(batch), 1), self.entry)
        for k in range(len(self.links) - 1, -1, -1):
            mine = self.level[batch] >= k
            ids, sims = self._walk(q, at, k, self.beam if mine.any() else 1)
            if mine.any():
                inner = np.argwhere(mine)[:, 0]
                # points of one batch see each other too
                near = q[inner] @ q[inner].T
                np.fill_diagonal(near, -2)
                few = min(self.degree, len(inner) - 1)
                if few:
                    other = np.argpartition(-near, few - 1, axis=1)[:, :few]
                    cand, csim = np.concatenate((ids[inner], batch[inner][other]), 1), np.concatenate((sims[inner], np.take_along_axis(near, other, 1)), 1)
                else:
                    cand, csim = ids[inner], sims[inner]
                chosen = self._diverse(cand, csim, self.links[k].shape[1] // 2 if k == 0 else self.degree)
                self.links[k][batch[inner], : chosen.shape[1]] = chosen
                self._back(batch[inner], chosen, k)
            at = ids[:, :4]
        self.known[batch] = True

    def _diverse(self, ids: np.ndarray, sims: np.ndarray, most: int) -> np.ndarray:
        """Rows of at most `most` ids, -1 padded: nearest first, those not dominated by a chosen one before the rest."""
        order = np.argsort(-np.where(ids < 0, -3, sims), axis=1, kind="stable")[:, : 4 * most]
        ids, sims = np.take_along_axis(ids, order, 1), np.take_along_axis(np.where(ids < 0, -3, sims), order, 1)
        v = self.x[np.maximum(ids, 0)]
        between = np.einsum("qad,qbd->qab", v, v)
        taken, ok = np.zeros(ids.shape, bool), ids >= 0
        for j in range(ids.shape[1]):
            blocked = ((between[:, j, :] > sims[:, j, None]) & taken).any(axis=1)
            taken[:, j] = ok[:, j] & ~blocked & (taken.sum(axis=1) < most)
        rank = np.argsort(np.where(taken, 0, np.where(ok, 1, 2)), axis=1, kind="stable")[:, :most]
        return np.take_along_axis(ids, rank, 1)

    def _back(self, source: np.ndarray, chosen: np.ndarray, k: int) -> None:
        to, back = chosen.ravel(), np.repeat(source, chosen.shape[1])
        to, back = to[to >= 0], back[chosen.ravel() >= 0]
        order = np.argsort(to, kind="stable")
        to, back = to[order], back[order]
        nodes, start, n = np.unique(to, return_index=True, return_counts=True)
        width, most = self.links[k].shape[1], int(n.max()) if len(n) else 0
        if not most:
            return
        extra = np.full((len(nodes), most), -1, np.int64)
        extra[np.repeat(np.arange(len(nodes)), n), np.arange(len(to)) - np.repeat(start, n)] = back
        have = self.links[k][nodes].astype(np.int64)
        extra[(extra[:, :, None] == have[:, None, :]).any(axis=2)] = -1
        both = np.concatenate((have, extra), 1)
        fits = (both >= 0).sum(axis=1) <= width
        self.links[k][nodes[fits]] = np.take_along_axis(both[fits], np.argsort(both[fits] < 0, axis=1, kind="stable"), 1)[:, :width]
        if (~fits).any():
            full = both[~fits]
            sims = np.einsum("qad,qd->qa", self.x[np.maximum(full, 0)], self.x[nodes[~fits]])
            self.links[k][nodes[~fits]] = self._diverse(full, sims, width)

    def _walk(self, q: np.ndarray, start: np.ndarray, k: int, beam: int) -> tuple[np.ndarray, np.ndarray]:
        """Best-first search of a layer: ids and inner products, best first, -1 padded."""
        n_q, links = len(q), self.links[k]
        seen = np.zeros((n_q, len(self.x)), bool)
        row = np.arange(n_q)[:, None]
        start = np.where(start < 0, start[:, :1], start)
        beam = max(beam, start.shape[1])
        ids = np.full((n_q, beam), -1)
        sims, open_ = np.full((n_q, beam), -3.0, np.float32), np.zeros((n_q, beam), bool)
        first = np.einsum("qad,qd->qa", self.x[start], q)
        order = np.argsort(start, axis=1, kind="stable")
        sorted_ = np.take_along_axis(start, order, 1)
        twice = np.concatenate((np.zeros((n_q, 1), bool), sorted_[:, 1:] == sorted_[:, :-1]), 1)
        ids[:, : start.shape[1]], sims[:, : start.shape[1]] = sorted_, np.where(twice, -3, np.take_along_axis(first, order, 1))
        open_[:, : start.shape[1]] = ~twice
        seen[row, start] = True
        live = np.arange(n_q)
        while len(live):
            s = np.where(open_[live], sims[live], -9)
            best = np.argpartition(-s, min(2, beam - 1), axis=1)[:, : min(3, beam)]
            good = np.take_along_axis(s, best, 1) > -4
            go = good.any(axis=1)
            live, best, good = live[go], best[go], good[go]
            if not len(live):
                break
            open_[live[:, None], best] = False
            near = np.where(good[:, :, None], links[np.maximum(ids[live[:, None], best], 0)], -1).reshape(len(live), -1)
            near = np.where(seen[live[:, None], np.maximum(near, 0)], -1, near)
            near = np.sort(near, axis=1)
            near[:, 1:][near[:, 1:] == near[:, :-1]] = -1
            r, c = np.nonzero(near >= 0)
            got = np.full(near.shape, -3.0, np.float32)
            seen[live[r], near[r, c]] = True
            got[r, c] = np.einsum("ad,ad->a", self.x[near[r, c]], q[live[r]])
            all_s, all_i = np.concatenate((sims[live], got), 1), np.concatenate((ids[live], near), 1)
            all_o = np.concatenate((open_[live], got > -3), 1)
            top = np.argpartition(-all_s, beam - 1, axis=1)[:, :beam]
            sims[live], ids[live], open_[live] = (np.take_along_axis(a, top, 1) for a in (all_s, all_i, all_o))
        order = np.argsort(-sims, axis=1, kind="stable")
        sims = np.take_along_axis(sims, order, 1)
        return np.where(sims > -3, np.take_along_axis(ids, order, 1), -1), sims

    def search(self, q: np.ndarray, beam: int, own: np.ndarray | None = None, block: int = 256) -> tuple[np.ndarray, np.ndarray]:
        """own: for queries that are points of the graph, where they are; the search of the lowest layer starts there too."""
        q = np.ascontiguousarray(q, np.float32)
        parts = []
        for a in range(0, len(q), block):
            part = q[a : a + block]
            at = np.full((len(part), 1), self.entry)
            for k in range(len(self.links) - 1, 0, -1):
                at = self._walk(part, at, k, 2)[0][:, :2]
            if own is not None:
                at = np.concatenate((at, own[a : a + block, None]), 1)
            parts.append(self._walk(part, at, 0, beam))
        if not parts:
            return np.zeros((0, beam), np.int64), np.zeros((0, beam), np.float32)
        return np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])

    def lost(self) -> np.ndarray:
        """Points that the links of the lowest layer don't lead to from the entry."""
        seen = np.zeros(len(self.x), bool)
        front = np.array([self.entry] if len(self.x) else [], np.int64)
        while len(front):
            seen[front] = True
            near = np.unique(self.links[0][front])
            near = near[near >= 0]
            front = near[~seen[near]]
        return np.flatnonzero(~seen)

    def parts(self) -> list[bytes]:
        return [self.x.tobytes(), np.int64([self.entry, self.x.shape[1] if self.x.ndim == 2 else 0, self.degree]).tobytes(), *(x.tobytes() for x in self.links)]

    @classmethod
    def of(cls, parts: list[bytes]) -> "Graph":
        g = cls.__new__(cls)
        entry, d, degree = np.frombuffer(parts[1], np.int64)
        g.entry, g.degree = int(entry), int(degree)
        g.x = np.frombuffer(parts[0], np.float32).reshape(-1, int(d))
        g.links = [np.frombuffer(p, np.int32).reshape(len(g.x), -1) for p in parts[2:]]
        return g
