"""A hierarchical navigable small-world graph over unit vectors, built and searched in batches with NumPy."""

from __future__ import annotations

import numpy as np

#: Cells of the visited table of one search, and the beam beyond which a crowded query is compared with all nodes.
_VISITED, WIDE = 1 << 25, 384


class Graph:
    """Layers of neighbour lists: 2 * m each on the lowest layer, m above. Levels are drawn from a fixed seed, so rebuilds agree."""

    def __init__(self, x: np.ndarray, m: int = 12, ef: int = 48, seed: int = 1) -> None:
        self.x, self.m, self.ef = np.ascontiguousarray(x, np.float32), m, ef
        n = len(x)
        draws = np.random.default_rng(seed).random(n)
        self.level = np.minimum((-np.log(np.maximum(draws, 1e-12)) / np.log(m)).astype(int), 8) if n else np.zeros(0, int)
        order = np.argsort(-self.level, kind="stable")  # upper layers first: every layer is whole before the ones below use it
        self.layers = []
        for k in range(int(self.level.max(initial=0)) + 1):
            self.layers.append(np.full((n, 2 * m if k == 0 else m), -1, np.int32))
        self.entry = order[:1]
        at = 0
        while at < n:
            batch = order[at : at + max(32, min(512, at))]
            self._insert(batch, order[:at])
            at += len(batch)
        if n:
            self._reach()

    def _reach(self, least: int = 8) -> None:
        """Nodes that few others list, as happens within dense groups, are added to the lists of their own nearest neighbours."""
        layer = self.layers[0]
        n, width = layer.shape
        listed = np.bincount(layer[layer >= 0], minlength=n)
        extra: list[list[int]] = [[] for _ in range(n)]
        few = np.nonzero(listed < least)[0]
        for at in range(0, len(few), 4096):
            part = few[at : at + 4096]
            sims = np.einsum("rd,rmd->rm", self.x[part], self.x[layer[part]])
            sims[layer[part] < 0] = -np.inf
            order = np.argsort(-sims, axis=1, kind="stable")
            for v, row, s in zip(part, np.take_along_axis(layer[part], order, 1), np.take_along_axis(sims, order, 1)):
                due = least - listed[v]
                for t in row[np.isfinite(s)]:
                    if due and len(extra[t]) < width and v not in layer[t]:
                        extra[t].append(int(v))
                        due -= 1
        more = max(map(len, extra))
        wide = np.full((n, width + more), -1, np.int32)
        wide[:, :width] = layer
        for t, own in enumerate(extra):
            wide[t, width : width + len(own)] = own
        self.layers[0] = wide

    def _insert(self, batch: np.ndarray, before: np.ndarray) -> None:
        top = len(self.layers) - 1
        entry = np.repeat(self.entry[None, :], len(batch), 0)
        for k in range(top, -1, -1):
            here = self.level[batch] >= k
            if len(before):
                ids, sims = self._beam(self.x[batch], entry, k, self.ef if here.any() else 1)
                entry = ids[:, :1]
            else:
                ids, sims = np.full((len(batch), 1), -1, np.int64), np.full((len(batch), 1), -np.inf, np.float32)
            rows = np.nonzero(here)[0]
            if not len(rows):
                continue
            own = batch[rows]
            mates = self.x[own] @ self.x[own].T
            np.fill_diagonal(mates, -np.inf)
            few = min(len(own), self.ef)
            near = np.argpartition(-mates, few - 1, axis=1)[:, :few]
            ids = np.concatenate([ids[rows], own[near]], 1)
            sims = np.concatenate([sims[rows], np.take_along_axis(mates, near, 1)], 1)
            chosen = self._choose(own, ids, sims, self.m)
            self.layers[k][own, : self.m] = chosen
            self._link_back(own, chosen, k)

    def _choose(self, own: np.ndarray, ids: np.ndarray, sims: np.ndarray, most: int) -> np.ndarray:
        """For each row the nearest candidates that are nearer to it than to those chosen before; then the nearest of the rest."""
        order = np.argsort(-sims, axis=1, kind="stable")
        ids, sims = np.take_along_axis(ids, order, 1), np.take_along_axis(sims, order, 1)
        ids = np.where(np.isfinite(sims), ids, -1)
        rows, width = ids.shape
        out = np.full((rows, most), -1, np.int64)
        count = np.zeros(rows, int)
        late = np.zeros(ids.shape, bool)
        kept = np.zeros((rows, most, self.x.shape[1]), np.float32)
        for c in range(width):
            due = (ids[:, c] >= 0) & (count < most)
            if not due.any():
                break
            v = self.x[ids[:, c]]
            to_kept = np.einsum("rd,rmd->rm", v, kept)
            to_kept[np.arange(most)[None, :] >= count[:, None]] = -np.inf
            good = due & (sims[:, c] > to_kept.max(axis=1))
            late[:, c] = due & ~good
            r = np.nonzero(good)[0]
            out[r, count[r]] = ids[r, c]
            kept[r, count[r]] = v[r]
            count[r] += 1
        for c in range(width):
            r = np.nonzero(late[:, c] & (count < most))[0]
            out[r, count[r]] = ids[r, c]
            count[r] += 1
        return out

    def _link_back(self, own: np.ndarray, chosen: np.ndarray, k: int) -> None:
        """Adds the reverse links; lists that would overflow are chosen anew."""
        layer = self.layers[k]
        cap = layer.shape[1]
        src = np.repeat(own, chosen.shape[1])[chosen.ravel() >= 0]
        dst = chosen.ravel()[chosen.ravel() >= 0]
        order = np.argsort(dst, kind="stable")
        src, dst = src[order], dst[order]
        heads, first, counts = np.unique(dst, return_index=True, return_counts=True)
        width = int(counts.max(initial=0))
        fresh = np.full((len(heads), width), -1, np.int64)
        place = np.arange(len(dst)) - np.repeat(first, counts)
        fresh[np.repeat(np.arange(len(heads)), counts), place] = src
        fresh[(fresh[:, :, None] == layer[heads][:, None, :]).any(axis=2)] = -1
        have, more = (layer[heads] >= 0).sum(axis=1), (fresh >= 0).sum(axis=1)
        easy = have + more <= cap
        for r in np.nonzero(easy & (more > 0))[0]:
            new = fresh[r][fresh[r] >= 0]
            free = np.nonzero(layer[heads[r]] < 0)[0][: len(new)]
            layer[heads[r], free] = new
        hard = np.nonzero(~easy)[0]
        for at in range(0, len(hard), 512):
            part = hard[at : at + 512]
            h = heads[part]
            ids = np.concatenate([layer[h].astype(np.int64), fresh[part]], 1)
            sims = np.einsum("rd,rmd->rm", self.x[h], self.x[ids])
            sims[ids < 0] = -np.inf
            layer[h] = self._choose(h, ids, sims, cap)

    def _beam(self, q: np.ndarray, entry: np.ndarray, k: int, ef: int, wide: int = 4) -> tuple[np.ndarray, np.ndarray]:
        """The ef best nodes (ids, similarities, falling) that a best-first search of layer k finds from the entry nodes."""
        step = max(1, _VISITED // max(1, len(self.x)))
        if len(q) > step:
            parts = [self._beam(q[i : i + step], entry[i : i + step], k, ef, wide) for i in range(0, len(q), step)]
            return np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
        n, layer = len(q), self.layers[k]
        seen = np.zeros((n, len(self.x)), bool)
        all_rows = np.arange(n)[:, None]
        seen[all_rows, entry] = True
        ids = np.full((n, ef), -1, np.int64)
        sims = np.full((n, ef), -np.inf, np.float32)
        done = np.zeros((n, ef), bool)
        e = min(ef, entry.shape[1])
        ids[:, :e], sims[:, :e] = entry[:, :e], np.einsum("rd,rmd->rm", q, self.x[entry[:, :e]])
        wide = min(wide, ef)
        live = np.arange(n)
        while len(live):
            open_sims = np.where(done[live] | (ids[live] < 0), -np.inf, sims[live])
            pick = np.argpartition(-open_sims, wide - 1, axis=1)[:, :wide] if wide < ef else np.tile(np.arange(ef), (len(live), 1))
            real = np.isfinite(np.take_along_axis(open_sims, pick, 1))
            more = real.any(axis=1)
            live, pick, real = live[more], pick[more], real[more]
            if not len(live):
                break
            r = live[:, None]
            done[r, pick] |= real
            near = np.where(real[:, :, None], layer[ids[r, pick]], -1).reshape(len(live), -1).astype(np.int64)
            fresh = (near >= 0) & ~seen[r, near]
            seen[r, np.where(near >= 0, near, ids[r, pick[:, :1]])] = True
            s = np.einsum("rd,rmd->rm", q[live], self.x[near])
            s[~fresh] = -np.inf
            order = np.argsort(near, axis=1, kind="stable")  # a node reached twice in one step counts once
            twice = np.zeros(near.shape, bool)
            by = np.take_along_axis(near, order, 1)
            np.put_along_axis(twice, order[:, 1:], by[:, 1:] == by[:, :-1], 1)
            s[twice] = -np.inf
            all_ids, all_sims = np.concatenate([ids[live], near], 1), np.concatenate([sims[live], s], 1)
            all_done = np.concatenate([done[live], np.zeros(near.shape, bool)], 1)
            best = np.argpartition(-all_sims, ef - 1, axis=1)[:, :ef]
            ids[live], sims[live], done[live] = np.take_along_axis(all_ids, best, 1), np.take_along_axis(all_sims, best, 1), np.take_along_axis(all_done, best, 1)
        ids[~np.isfinite(sims)] = -1
        order = np.argsort(-sims, axis=1, kind="stable")
        return np.take_along_axis(ids, order, 1), np.take_along_axis(sims, order, 1)

    def search(self, q: np.ndarray, ef: int) -> tuple[np.ndarray, np.ndarray]:
        q = np.ascontiguousarray(q, np.float32)
        entry = np.repeat(self.entry[None, :], len(q), 0)
        for k in range(len(self.layers) - 1, 0, -1):
            entry = self._beam(q, entry, k, 4)[0][:, :1]
        return self._beam(q, entry, 0, min(ef, len(self.x)))

    def within(self, q: np.ndarray, least: float, ef: int) -> list[np.ndarray]:
        """For each query the nodes of similarity least or more that are found. A beam of which such nodes fill more than half is doubled, up to the whole
        graph or WIDE; a query that crowds even that beam, as only one within a large dense group does, is then compared with all nodes."""
        q = np.ascontiguousarray(q, np.float32)
        out: list[np.ndarray] = [np.zeros(0, np.int64)] * len(q)
        due = np.arange(len(q))
        while len(due):
            ids, sims = self.search(q[due], ef)
            near = sims >= least
            full = (2 * near.sum(axis=1) > ids.shape[1]) & (ids.shape[1] < len(self.x))
            for i in np.nonzero(~full & near.any(axis=1))[0]:
                out[due[i]] = ids[i][near[i]]
            due, ef = due[full], ef * 2
            if ef > WIDE:
                break
        for at in range(0, len(due), 256):
            part = due[at : at + 256]
            for i, row in zip(part, q[part] @ self.x.T >= least):
                out[i] = np.nonzero(row)[0]
        return out
