"""The contraction index of one cell: topology, customization, and queries, in rank space.

Ranks 0..n-1; up[r] are the sorted higher-ranked neighbours of rank r in the index.
"""

from __future__ import annotations

import heapq
from bisect import bisect_left

import numpy as np

FAR = 1 << 60


def build(n: int, lo: np.ndarray, hi: np.ndarray) -> list[list[int]]:
    """Upward neighbours after contracting all ranks in order. A rank's neighbours all become its lowest one's, which
    hands them on; so each list is merged into one other list only."""
    up: list[set[int]] = [set() for _ in range(n)]
    for a, b in zip(lo.tolist(), hi.tolist(), strict=True):
        up[a].add(b)
    out: list[list[int]] = [[] for _ in range(n)]
    for r in range(n):
        own = sorted(up[r])
        out[r] = own
        if own:
            up[own[0]].update(own[1:])
        up[r] = set()
    return out


def build_block(first: int, last: int, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """`build` for the ranks first .. last - 1, given all their arcs and what lower ranks handed them: lo and hi of their index arcs, and of those that they hand on to later ranks."""
    up: list[set[int]] = [set() for _ in range(first, last)]
    for a, b in zip((lo - first).tolist(), hi.tolist(), strict=True):
        up[a].add(b)
    later: dict[int, set[int]] = {}
    counts, own_hi = [], []
    for r, mine in enumerate(up):
        own = np.array(sorted(mine), np.int64)
        if len(own) > 1:
            p = int(own[0])
            mine.discard(p)
            (up[p - first] if p < last else later.setdefault(p, set())).update(mine)
        up[r] = set()
        counts.append(len(own))
        own_hi.append(own)
    none = np.zeros(0, np.int64)
    handed = [np.fromiter(x, np.int64, len(x)) for x in later.values()]
    tails = np.repeat(np.fromiter(later, np.int64, len(later)), [len(x) for x in handed]) if later else none
    return np.repeat(np.arange(first, last), counts), np.concatenate([none, *own_hi]), tails, np.concatenate([none, *handed])


#: Candidates for later ranks' weights that a block's task holds before it keeps the least of each arc.
CANDIDATES = 1 << 22


def customize_block(first: int, last: int, lo: np.ndarray, hi: np.ndarray, up: np.ndarray, down: np.ndarray) -> tuple[np.ndarray, ...]:
    """Relaxes the triangles whose lowest corner is one of the ranks first .. last - 1, given all their arcs sorted by lo and hi and what lower ranks found for them. Returns the
    arcs' weights up and down, and lo, hi, up, down of the least that was found for arcs of later ranks."""
    up, down = up.astype(np.int64), down.astype(np.int64)
    start = np.searchsorted(lo, np.arange(first, last + 1)).tolist()
    found: list[tuple[np.ndarray, ...]] = []
    waiting = 0
    for w in range(last - first):
        a, b = start[w], start[w + 1]
        own, ups, downs = hi[a:b], up[a:b], down[a:b]
        inner = int(np.searchsorted(own, last))
        for i, u in enumerate(own[:inner].tolist()):
            c, d = start[u - first], start[u - first + 1]
            at = c + np.searchsorted(hi[c:d], own[i + 1 :])
            up[at] = np.minimum(up[at], downs[i] + ups[i + 1 :])
            down[at] = np.minimum(down[at], downs[i + 1 :] + ups[i])
        if b - a - inner > 1:
            i, j = np.triu_indices(b - a - inner, 1)
            i, j = i + inner, j + inner
            found.append((own[i], own[j], downs[i] + ups[j], downs[j] + ups[i]))
            waiting += len(i)
            if waiting > CANDIDATES:
                found = [_least(found)]
                waiting = len(found[0][0])
    return up, down, *_least(found)


def _least(found: list[tuple[np.ndarray, ...]]) -> tuple[np.ndarray, ...]:
    """lo, hi and the least up and down of each arc."""
    if not found:
        return tuple(np.zeros(0, np.int64) for _ in range(4))
    lo, hi, up, down = (np.concatenate(x) for x in zip(*found, strict=True))
    order = np.lexsort((hi, lo))
    lo, hi = lo[order], hi[order]
    new = np.flatnonzero(np.concatenate([[True], (lo[1:] != lo[:-1]) | (hi[1:] != hi[:-1])]))
    return lo[new], hi[new], np.minimum.reduceat(up[order], new), np.minimum.reduceat(down[order], new)


def parents(up: list[list[int]]) -> list[int]:
    return [x[0] if x else -1 for x in up]


def depths(parent: list[int]) -> list[int]:
    """Number of ancestors, the rank itself included."""
    out = [0] * len(parent)
    for r in range(len(parent) - 1, -1, -1):
        out[r] = 1 if parent[r] < 0 else out[parent[r]] + 1
    return out


def measures(up: list[list[int]]) -> dict[str, int]:
    parent = parents(up)
    nodes = depths(parent)
    arcs = [0] * len(up)
    for r in range(len(up) - 1, -1, -1):
        arcs[r] = len(up[r]) + (arcs[parent[r]] if parent[r] >= 0 else 0)
    return {
        "index_arcs": sum(map(len, up)), "triangles": sum(len(x) * (len(x) - 1) // 2 for x in up), "tw_bound": max(map(len, up), default=0),
        "nodes_sum": sum(nodes), "nodes_max": max(nodes, default=0), "arcs_sum": sum(arcs), "arcs_max": max(arcs, default=0), "ranks": len(up),
    }


class Weights:
    """Both directions of each index arc, in the order of `up`; mid is the lower corner that gave the weight, or -1."""

    def __init__(self, up: list[list[int]]):
        self.up = up
        self.w_up = [[FAR] * len(x) for x in up]
        self.w_down = [[FAR] * len(x) for x in up]
        self.far_up, self.far_down = [[] for _ in up], [[] for _ in up]
        self.mid = [[-1] * len(x) for x in up]
        self.mid_down = [[-1] * len(x) for x in up]

    def at(self, lo: int, hi: int) -> int:
        i = bisect_left(self.up[lo], hi)
        return i if i < len(self.up[lo]) and self.up[lo][i] == hi else -1

    def attach(self, tail, head, weight) -> Weights:
        for a, b, w in zip(tail, head, weight, strict=True):
            i = self.at(min(a, b), max(a, b))
            side = self.w_up if a < b else self.w_down
            side[min(a, b)][i] = min(side[min(a, b)][i], w)
        return self

    def customize(self, corner: str = "lower") -> Weights:
        """Weights obey all triangles with a lower third corner. 'upper' walks the same triangles from their lowest corner."""
        if corner == "upper":
            for w in range(len(self.up)):
                own, ups, downs = self.up[w], self.w_up[w], self.w_down[w]
                for i, u in enumerate(own):
                    for j in range(i + 1, len(own)):
                        self._relax(u, self.at(u, own[j]), downs[i] + ups[j], downs[j] + ups[i], w)
            return self
        below: list[list[int]] = [[] for _ in self.up]
        for w, own in enumerate(self.up):
            for u in own:
                below[u].append(w)
        for u in range(len(self.up)):
            for w in below[u]:
                iu = self.at(w, u)
                for j in range(iu + 1, len(self.up[w])):
                    v = self.up[w][j]
                    self._relax(u, self.at(u, v), self.w_down[w][iu] + self.w_up[w][j], self.w_down[w][j] + self.w_up[w][iu], w)
        return self

    def perfect(self) -> int:
        """Makes every weight the distance between its ends, by triangles with an intermediate or upper third corner, from the highest rank down. Directions whose
        weight falls are no shortest path themselves: another path over the index witnesses that, and they leave (FAR). Returns how many arcs keep neither direction."""
        gone = 0
        for x in range(len(self.up) - 1, -1, -1):
            own = self.up[x]
            up, down = list(self.w_up[x]), list(self.w_down[x])
            for i, y in enumerate(own):
                for j in range(i + 1, len(own)):
                    k = self.at(y, own[j])
                    # whole distances between higher ranks, whether or not their arcs have left
                    forth, back = self.far_up[y][k], self.far_down[y][k]
                    up[j], down[j] = min(up[j], up[i] + forth), min(down[j], back + down[i])
                    up[i], down[i] = min(up[i], up[j] + back), min(down[i], forth + down[j])
            self.far_up[x], self.far_down[x] = up, down
            self.w_up[x] = [w if w <= d else FAR for w, d in zip(self.w_up[x], up, strict=True)]
            self.w_down[x] = [w if w <= d else FAR for w, d in zip(self.w_down[x], down, strict=True)]
            gone += sum(a >= FAR and b >= FAR for a, b in zip(self.w_up[x], self.w_down[x], strict=True))
        return gone

    def _relax(self, u: int, i: int, forth: int, back: int, w: int) -> None:
        if forth < self.w_up[u][i]:
            self.w_up[u][i], self.mid[u][i] = forth, w
        if back < self.w_down[u][i]:
            self.w_down[u][i], self.mid_down[u][i] = back, w

    def walk(self, parent: list[int], s: int, forward: bool) -> dict[int, int]:
        """Distances from s to its ancestors over upward arcs (or from them to s)."""
        dist, x = {s: 0}, s
        weights = self.w_up if forward else self.w_down
        while x >= 0:
            d = dist.get(x, FAR)
            if d < FAR:
                for y, w in zip(self.up[x], weights[x], strict=True):
                    if d + w < dist.get(y, FAR):
                        dist[y] = d + w
            x = parent[x]
        return dist

    def tree_query(self, parent: list[int], s: int, t: int, prune: bool = False) -> int:
        """Distance over both root paths; prune skips ancestors that are no nearer than the best meeting so far."""
        a, b = ({s: 0}, self.w_up), ({t: 0}, self.w_down)
        best, x, y = FAR, s, t
        while x >= 0 or y >= 0:
            # the lower of the two goes up, so a common ancestor is complete on both sides when it is met
            both = x == y
            for (dist, weights), (others, _), z in ((a, b, x), (b, a, y)):
                if z < 0 or (z != x or not both) and z != (x if y < 0 or 0 <= x < y else y):
                    continue
                d = dist.get(z, FAR)
                best = min(best, d + others.get(z, FAR))
                if d < FAR and not (prune and d >= best):
                    for q, w in zip(self.up[z], weights[z], strict=True):
                        if d + w < dist.get(q, FAR):
                            dist[q] = d + w
            if both:
                x = y = parent[x]
            elif y < 0 or 0 <= x < y:
                x = parent[x]
            else:
                y = parent[y]
        return best

    def heap_query(self, s: int, t: int) -> int:
        """Distance by two upward searches with heaps."""
        dist = [{s: 0}, {t: 0}]
        for k, weights in enumerate((self.w_up, self.w_down)):
            heap = [(0, s if k == 0 else t)]
            while heap:
                d, x = heapq.heappop(heap)
                if d > dist[k][x]:
                    continue
                for y, w in zip(self.up[x], weights[x], strict=True):
                    if d + w < dist[k].get(y, FAR):
                        dist[k][y] = d + w
                        heapq.heappush(heap, (d + w, y))
        return min((d + dist[1][z] for z, d in dist[0].items() if z in dist[1]), default=FAR)

    def unpack(self, u: int, v: int) -> list[int]:
        """The original nodes of the path that arc u -> v stands for, v left out."""
        lo, hi = min(u, v), max(u, v)
        i = self.at(lo, hi)
        w = (self.mid if u < v else self.mid_down)[lo][i]
        return [u] if w < 0 else self.unpack(u, w) + self.unpack(w, v)


def dijkstra(n: int, near: list[list[tuple[int, int]]], s: int) -> list[int]:
    """Plain shortest paths, the reference for all queries."""
    dist = [FAR] * n
    dist[s] = 0
    heap = [(0, s)]
    while heap:
        d, x = heapq.heappop(heap)
        if d > dist[x]:
            continue
        for y, w in near[x]:
            if d + w < dist[y]:
                dist[y] = d + w
                heapq.heappush(heap, (d + w, y))
    return dist
