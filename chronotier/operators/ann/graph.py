"""A layered proximity graph in numpy.

Each vector has a top level drawn from a hash of its id. Upper levels are walked
greedily, the ground level by a best-first search whose frontier holds `ef` vectors.
A new vector is linked to neighbours that are nearer to it than to any neighbour taken
before, at most m (2m on the ground). Masked vectors carry traffic but are not returned.
A graph is built one vector after another, or at once from the exact neighbours within it,
which products of matrices give in a fraction of the time.
"""

from __future__ import annotations

import hashlib
import heapq
import math


class LayeredGraph:
    def __init__(self, vectors, ids, m: int = 16, ef_build: int = 200, at_once: bool = False):
        import numpy as np

        x = np.asarray(vectors, np.float64)
        self.x = x / np.maximum(np.linalg.norm(x, axis=1), 1e-300)[:, None]
        self.ids, self.m, self.visited, self.masked = [int(i) for i in ids], m, 0, set()
        self.links: list[dict[int, list[int]]] = []
        self.entry, self.top = -1, -1
        if at_once and len(self.x):
            self._link()
            return
        for i in range(len(self.x)):
            self._add(i, ef_build)

    def _link(self, wide: int = 32) -> None:
        """All levels at once: of the `wide` nearest of each vector those that are nearer to
        it than to any taken before, and the ways back while there is room. Besides, each
        is linked both ways with the nearest of a higher level, so that all can be reached."""
        import numpy as np

        level = np.array([self._level(i) for i in range(len(self.x))], np.int64)
        self.top, self.entry = int(level.max()), int(level.argmax())
        x = self.x.astype(np.float32)
        all_near = x @ x.T
        np.fill_diagonal(all_near, -2)
        above = np.full(len(level), self.entry)
        for lev in range(self.top):
            mine, higher = np.flatnonzero(level == lev), np.flatnonzero(level > lev)
            if len(mine):
                above[mine] = higher[all_near[np.ix_(mine, higher)].argmax(1)]
        place = np.empty(len(level), np.int64)
        for lev in range(self.top + 1):
            here = np.flatnonzero(level >= lev)
            near = all_near[np.ix_(here, here)] if lev else all_near
            n, most, c = len(here), self.m if lev else 2 * self.m, min(wide, len(here) - 1)
            place[here] = np.arange(n)
            low = np.flatnonzero(here != self.entry)
            high = place[above[here[low]]]
            edges = [(low, high, 0), (high, low, 0)]
            for at in range(0, n if c else 0, 500):
                rows = near[at : at + 500]
                found = np.argpartition(rows, n - c, axis=1)[:, n - c :]
                order = np.argsort(-np.take_along_axis(rows, found, 1), axis=1, kind="stable")
                found = np.take_along_axis(found, order, 1)
                own, between = np.take_along_axis(rows, found, 1), near[found[:, :, None], found[:, None, :]]
                kept = np.zeros(found.shape, bool)
                for j in range(c):
                    kept[:, j] = (kept.sum(1) < self.m) & ~(kept[:, :j] & (between[:, j, :j] >= own[:, j, None])).any(1)
                a, b = np.nonzero(kept)
                edges += [(a + at, found[a, b], 1), (found[a, b], a + at, 2)]
            a, b = (np.concatenate([e[i] for e in edges]) for i in (0, 1))
            kind = np.repeat([e[2] for e in edges], [len(e[0]) for e in edges])
            order = np.lexsort((-near[a, b], kind, a))
            order = order[np.sort(np.unique((a * n + b)[order], return_index=True)[1])]
            a, b, kind = a[order], b[order], kind[order]
            some = (kind == 0) | (np.arange(len(a)) - np.searchsorted(a, a) < most)
            a, b = a[some], here[b[some]].tolist()
            ends = np.searchsorted(a, np.arange(n + 1)).tolist()
            self.links.append({i: b[s:e] for i, s, e in zip(here.tolist(), ends[:-1], ends[1:], strict=True)})

    def _level(self, i: int) -> int:
        u = (int.from_bytes(hashlib.md5(str(self.ids[i]).encode()).digest()[:6], "big") + 1) / (1 << 48)
        return int(-math.log(u) / math.log(self.m))

    def _near(self, v, start: list[int], ef: int, level: int) -> list[tuple[float, int]]:
        """The ef nearest that a best-first walk from start finds: (distance, node)."""
        seen = set(start)
        d = 1 - self.x[start] @ v
        open_ = sorted(zip(d.tolist(), start, strict=True))
        best = [(-a, b) for a, b in open_]
        heapq.heapify(best)
        while open_:
            a, i = heapq.heappop(open_)
            if len(best) >= ef and a > -best[0][0]:
                break
            new = [j for j in self.links[level].get(i, ()) if j not in seen]
            if not new:
                continue
            seen.update(new)
            for b, j in zip((1 - self.x[new] @ v).tolist(), new, strict=True):
                if len(best) < ef or b < -best[0][0]:
                    heapq.heappush(open_, (b, j))
                    heapq.heappush(best, (-b, j))
                    if len(best) > ef:
                        heapq.heappop(best)
        self.visited += len(seen)
        return sorted((-a, b) for a, b in best)

    def _pick(self, i: int, found: list[tuple[float, int]], most: int) -> list[int]:
        kept: list[int] = []
        for d, j in found:
            if len(kept) == most:
                break
            if j != i and (not kept or d < (1 - self.x[kept] @ self.x[j]).min()):
                kept.append(j)
        return kept

    def _add(self, i: int, ef: int) -> None:
        level, v = self._level(i), self.x[i]
        while len(self.links) <= level:
            self.links.append({})
        if self.entry < 0:
            for lev in range(level + 1):
                self.links[lev][i] = []
            self.entry, self.top = i, level
            return
        at = [self.entry]
        for lev in range(self.top, level, -1):
            at = [self._near(v, at, 1, lev)[0][1]]
        for lev in range(min(level, self.top), -1, -1):
            found, most = self._near(v, at, ef, lev), self.m if lev else 2 * self.m
            self.links[lev][i] = self._pick(i, found, self.m)
            for j in self.links[lev][i]:
                mine = self.links[lev].setdefault(j, [])
                mine.append(i)
                if len(mine) > most:
                    d = 1 - self.x[mine] @ self.x[j]
                    self.links[lev][j] = self._pick(j, sorted(zip(d.tolist(), mine, strict=True)), most)
            at = [j for _, j in found]
        for lev in range(self.top + 1, level + 1):
            self.links[lev][i] = []
        if level > self.top:
            self.entry, self.top = i, level

    def search(self, v, k: int, ef: int, allow=None) -> list[tuple[int, float]]:
        """(id, cosine) of the k nearest among those not masked and allowed; `visited`
        holds the number of vectors looked at."""
        import numpy as np

        self.visited, v = 0, np.asarray(v, np.float64)
        v = v / max(np.linalg.norm(v), 1e-300)
        at = [self.entry]
        for lev in range(self.top, 0, -1):
            at = [self._near(v, at, 1, lev)[0][1]]
        wide = max(ef, k)
        while True:
            found = [(d, self.ids[j]) for d, j in self._near(v, at, wide, 0) if j not in self.masked and (allow is None or allow(self.ids[j]))]
            if len(found) >= k or wide >= len(self.x):
                return [(i, round(1 - d, 6)) for d, i in sorted(found)[:k]]
            wide *= 4
