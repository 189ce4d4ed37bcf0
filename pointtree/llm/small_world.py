"""Hierarchical navigable small-world graphs in numpy, built and searched in batches.

Nodes are ordered by falling level, so that a layer is a prefix of them. Insertions and searches run for many vectors
at once: each holds a beam, and every round opens the best unopened node of each beam.
"""

from __future__ import annotations

import io

import numpy as np

LINKS, BEAM, BATCH = 16, 48, 256


class SmallWorld:
    def __init__(self, vectors: np.ndarray, links: int = LINKS, beam: int = BEAM, seed: int = 1):
        n = len(vectors)
        rng = np.random.default_rng([seed, n])
        level = np.minimum((-np.log(1 - rng.random(n)) / np.log(links)).astype(np.int64), 5) if n else np.zeros(0, np.int64)
        self.order = np.argsort(-level, kind="stable")
        self.x = np.ascontiguousarray(vectors[self.order], np.float32)
        level = level[self.order]
        self.sizes = [int((level >= k).sum()) for k in range(int(level.max(initial=0)) + 1)]
        self.layers = [np.full((m, 2 * links), -1, np.int32) for m in self.sizes]
        for k in reversed(range(len(self.sizes))):
            self._build(k, links, beam)

    def _build(self, k: int, links: int, beam: int) -> None:
        near, n = self.layers[k], self.sizes[k]
        far = np.full((n, 2 * links), -np.inf, np.float32)  # similarity of each link
        done = 0
        while done < n:
            size = min(n - done, BATCH, max(2 * links, done))
            rows = np.arange(done, done + size)
            q = self.x[rows]
            ids, sims = np.empty((size, 0), np.int32), np.empty((size, 0), np.float32)
            if done:
                ids, sims = self._beam(k, q, self._enter(k, q), min(beam, done), done)
            inner = q @ q.T  # the batch's own members
            inner[np.tril_indices(size)] = -np.inf  # each looks at members after it; the links go both ways
            own = np.argsort(-inner, 1)[:, : 2 * links]
            ids = np.concatenate([ids, rows[own].astype(np.int32)], 1)
            sims = np.concatenate([sims, np.take_along_axis(inner, own, 1)], 1)
            best = np.argsort(-sims, 1)[:, :links]
            ids, sims = np.take_along_axis(ids, best, 1), np.take_along_axis(sims, best, 1)
            good = np.isfinite(sims) & (ids >= 0)
            a, b, s = np.repeat(rows, good.sum(1)), ids[good], sims[good]
            self._link(near, far, np.concatenate([a, b]), np.concatenate([b, a]), np.concatenate([s, s]))
            done += size

    @staticmethod
    def _link(near: np.ndarray, far: np.ndarray, a: np.ndarray, b: np.ndarray, s: np.ndarray) -> None:
        """Add links a -> b. A full node keeps its nearest ones and, in its last quarter, links at hashed places, which keep clusters joined."""
        touched, width = np.unique(a), near.shape[1]
        rows = np.concatenate([np.repeat(touched, width), a])
        ids, sims = np.concatenate([near[touched].ravel(), b]), np.concatenate([far[touched].ravel(), s])
        keep = ids >= 0
        rows, ids, sims = rows[keep], ids[keep], sims[keep]
        _, one = np.unique(rows.astype(np.int64) << 32 | ids, return_index=True)
        rows, ids, sims = rows[one], ids[one], sims[one]
        order = np.lexsort((-sims, rows))
        rows, ids, sims = rows[order], ids[order], sims[order]
        start = np.searchsorted(rows, rows)
        rank = np.arange(len(rows)) - start
        close = width * 3 // 4
        mixed = (ids.astype(np.int64) * 2654435761 + rows) % 4294967296
        order = np.lexsort((np.where(rank < close, rank, close + 1 + mixed), rows))
        rows, ids, sims = rows[order], ids[order], sims[order]
        rank = np.arange(len(rows)) - np.searchsorted(rows, rows)
        kept = rank < width
        near[touched], far[touched] = -1, -np.inf
        near[rows[kept], rank[kept]], far[rows[kept], rank[kept]] = ids[kept], sims[kept]

    def _enter(self, k: int, q: np.ndarray) -> np.ndarray:
        """Entry nodes of layer k: the best found in the layers above."""
        at = np.zeros((len(q), 1), np.int32)
        for layer in range(len(self.layers) - 1, k, -1):
            at = self._beam(layer, q, at, 4, self.sizes[layer])[0]
        return at

    def _beam(self, k: int, q: np.ndarray, enter: np.ndarray, beam: int, limit: int) -> tuple[np.ndarray, np.ndarray]:
        """The ``beam`` best of the first ``limit`` nodes that are reached from ``enter``."""
        near, n = self.layers[k], len(q)
        seen = np.zeros((n, limit + 1), bool)  # the last column takes what is no node
        seen[:, limit] = True
        enter = np.where((enter >= 0) & (enter < limit), enter, limit)
        ids = np.full((n, beam + near.shape[1]), limit, np.int32)
        sims = np.full(ids.shape, -np.inf, np.float32)
        opened = np.ones(ids.shape, bool)
        m = min(enter.shape[1], beam)
        ids[:, :m] = enter[:, :m]
        at = np.minimum(ids[:, :m], limit - 1)
        sims[:, :m] = np.where(ids[:, :m] < limit, np.einsum("nmd,nd->nm", self.x[at], q), -np.inf)
        opened[:, :m] = ids[:, :m] >= limit
        np.put_along_axis(seen, ids[:, :m].astype(np.int64), True, 1)
        live = np.arange(n)
        while len(live):
            open_sims = np.where(opened[live, :beam], -np.inf, sims[live, :beam])
            best = open_sims.argmax(1)
            going = np.isfinite(open_sims[np.arange(len(live)), best])
            live, best = live[going], best[going]
            if not len(live):
                break
            opened[live, best] = True
            more = near[ids[live, best]]
            more = np.where((more >= 0) & (more < limit), more, limit)
            new = ~seen[live[:, None], more]
            seen[live[:, None], more] = True
            found = np.einsum("nmd,nd->nm", self.x[np.minimum(more, limit - 1)], q[live])
            ids[live, beam:], sims[live, beam:], opened[live, beam:] = more, np.where(new, found, -np.inf), ~new
            some = live[(sims[live, beam:].max(1) > sims[live, :beam].min(1))]
            if len(some):
                top = np.argpartition(-sims[some], beam - 1, 1)
                for c in (ids, sims, opened):
                    c[some] = np.take_along_axis(c[some], top, 1)
        return np.where(np.isfinite(sims[:, :beam]), ids[:, :beam], -1), sims[:, :beam]

    def search(self, q: np.ndarray, beam: int) -> tuple[np.ndarray, np.ndarray]:
        """The ids (in the caller's order, -1 for none) and similarities of the ``beam`` best nodes found."""
        q = np.ascontiguousarray(q, np.float32)
        ids, sims = self._beam(0, q, self._enter(0, q), min(beam, len(self.x)), len(self.x))
        return np.where(ids >= 0, self.order[np.maximum(ids, 0)], -1), sims

    def to_bytes(self) -> bytes:
        out = io.BytesIO()
        np.savez(out, order=self.order, **{f"layer{k}": a for k, a in enumerate(self.layers)})
        return out.getvalue()

    @classmethod
    def from_bytes(cls, raw: bytes, vectors: np.ndarray) -> SmallWorld:
        got, self = np.load(io.BytesIO(raw)), cls.__new__(cls)
        self.order = got["order"]
        self.layers = [got[f"layer{k}"] for k in range(len(got.files) - 1)]
        self.sizes = [len(a) for a in self.layers]
        self.x = np.ascontiguousarray(vectors[self.order], np.float32)
        return self
