"""Dissection orders of one cell's graph: preprocessing, recursion, trees and cliques.

Orders are lists of nodes, first eliminated first. A graph here is (n, u, v, x, y) with nodes 0..n-1 in input order.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np

from .cutter import Cut, SweepParams, band_cuts, choose, directions, front, interleave, pair_cutters, separator_of, split_orders, sweep_cutters, sweep_order
from .flow import Net


@dataclass
class Graph:
    n: int
    u: np.ndarray
    v: np.ndarray
    x: np.ndarray
    y: np.ndarray

    def part(self, nodes: np.ndarray) -> Graph:
        """The induced subgraph of sorted nodes."""
        new = np.full(self.n, -1, np.int64)
        new[nodes] = np.arange(len(nodes))
        a, b = new[self.u], new[self.v]
        own = (a >= 0) & (b >= 0)
        return Graph(len(nodes), a[own], b[own], self.x[nodes], self.y[nodes])

    def lists(self) -> list[list[int]]:
        out: list[list[int]] = [[] for _ in range(self.n)]
        for a, b in zip(self.u.tolist(), self.v.tolist(), strict=True):
            out[a].append(b)
            out[b].append(a)
        return out


def component_labels(n: int, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """The smallest node of each node's component."""
    label = np.arange(n)
    while len(u):
        low = np.minimum(label[u], label[v])
        new = label.copy()
        np.minimum.at(new, u, low)
        np.minimum.at(new, v, low)
        np.minimum.at(new, label[u], low)
        np.minimum.at(new, label[v], low)
        new = new[new]
        if np.array_equal(new, label):
            break
        label = new
    return label


def parts_of(labels: np.ndarray) -> list[np.ndarray]:
    order = np.argsort(labels, kind="stable")
    if not len(order):
        return []
    cuts = np.flatnonzero(np.diff(labels[order])) + 1
    return np.split(order, cuts)


def bicomponents(g: Graph) -> np.ndarray:
    """A number for each edge's biconnected component, by depth-first search with low points."""
    at: list[list[tuple[int, int]]] = [[] for _ in range(g.n)]
    for e, (a, b) in enumerate(zip(g.u.tolist(), g.v.tolist(), strict=True)):
        at[a].append((b, e))
        at[b].append((a, e))
    out, depth, low = np.full(len(g.u), -1, np.int64), [-1] * g.n, [0] * g.n
    stack: list[int] = []
    count = 0
    for root in range(g.n):
        if depth[root] >= 0:
            continue
        depth[root] = low[root] = 0
        work = [(root, -1, iter(at[root]))]
        while work:
            x, entry, rest = work[-1]
            moved = False
            for y, e in rest:
                if e == entry:
                    continue
                if depth[y] < 0:
                    stack.append(e)
                    depth[y] = low[y] = depth[x] + 1
                    work.append((y, e, iter(at[y])))
                    moved = True
                    break
                if depth[y] < depth[x]:
                    stack.append(e)
                    low[x] = min(low[x], depth[y])
            if moved:
                continue
            work.pop()
            if work:
                p = work[-1][0]
                low[p] = min(low[p], low[x])
                if low[x] >= depth[p]:
                    while stack:
                        e = stack.pop()
                        out[e] = count
                        if e == entry:
                            break
                    count += 1
    return out


def tree_order(g: Graph) -> tuple[list[int], int]:
    """A tree's order of least elimination depth, and that depth: each node takes the least rank that keeps any two nodes of
    one rank apart by a higher one; a bitmask holds the ranks visible from above."""
    near = g.lists()
    rank, visible = [0] * g.n, [0] * g.n
    done, best = [False] * g.n, 0
    for root in range(g.n):
        if done[root]:
            continue
        order, parent = [root], {root: -1}
        done[root] = True
        for x in order:
            for y in near[x]:
                if not done[y]:
                    done[y] = True
                    parent[y] = x
                    order.append(y)
        for x in reversed(order):
            once = twice = 0
            for y in near[x]:
                if y != parent[x]:
                    twice |= once & visible[y]
                    once |= visible[y]
            least = twice.bit_length()
            while once >> least & 1:
                least += 1
            rank[x] = least
            visible[x] = (once >> least | 1) << least
            best = max(best, least + 1)
    return sorted(range(g.n), key=lambda x: (rank[x], x)), best


@dataclass(frozen=True)
class Splitter:
    """How cells are cut: kind 'sweep', 'pairs', 'bands' or a function; style 'separator' or 'edgecut'."""

    kind: str = "sweep"
    params: SweepParams = SweepParams()
    pairs: int = 20
    seed: int = 0
    style: str = "separator"
    patience: int = 0
    schedule: str = "flow"
    cut: Callable | None = None

    @property
    def cutters(self) -> int:
        """How many cutters a cell has: directions or pairs."""
        return self.pairs if self.kind == "pairs" else self.params.q


def _mixed(z: int) -> int:
    z = (z + 0x9E3779B97F4A7C15) % 2**64
    z = (z ^ z >> 30) * 0xBF58476D1CE4E5B9 % 2**64
    z = (z ^ z >> 27) * 0x94D049BB133111EB % 2**64
    return z ^ z >> 31


def _random_pairs(n: int, k: int, seed: int) -> list[tuple[list[int], list[int]]]:
    """k pairs of two nodes, by integer mixing that the compiled kernel repeats."""
    out = []
    for i in range(k):
        at = _mixed(_mixed(_mixed(_mixed(seed) ^ n) ^ k) ^ i)
        s, t = (at >> 1) % n, (_mixed(at) >> 1) % (n - 1)
        out.append(([s], [t + (t >= s)]))
    return out


def cuts_of(g: Graph, splitter: Splitter, split: bool, bound: bool = True, seed: int | None = None, numbers: list[int] | None = None, best_only: bool = False) -> tuple[list[Cut], dict]:
    """All cuts that a splitter's cutters (or those of the given numbers) find on the graph, or on its split graph."""
    net = Net.split(g.n, g.u, g.v) if split else Net.undirected(g.n, g.u, g.v)
    ids = list(range(net.n))
    numbers = list(range(splitter.cutters)) if numbers is None else numbers
    if splitter.kind in ("bands", "sweep"):
        fan = directions(splitter.params.q)
        orders = [sweep_order(g.x, g.y, np.arange(g.n), fan[k]) for k in numbers]
        wide = split_orders(orders) if split else orders
        if splitter.kind == "bands":
            cuts, units = band_cuts(net, wide, splitter.params.alpha, numbers, best_only)
            return cuts, {"units": units, "searches": units + len(wide)}
        cutters = sweep_cutters(net, wide, ids, splitter.params, numbers)
        if split:
            cutters = [_whole_seeds(c) for c in cutters]
    else:
        pairs = _random_pairs(g.n, splitter.pairs, splitter.seed if seed is None else seed)
        cutters = pair_cutters(net, [([2 * s[0], 2 * s[0] + 1], [2 * t[0], 2 * t[0] + 1]) if split else (s, t) for s, t in (pairs[k] for k in numbers)], ids, numbers)
    cuts = interleave(cutters, splitter.schedule, bound)
    return cuts, {"units": sum(c.units for c in cutters), "searches": sum(c.searches for c in cutters), "most": max((c.flow for c in cutters), default=0)}


def _whole_seeds(c):
    """On a split graph seeds take both copies of a node."""
    both = lambda seeds: sorted({y for x in seeds for y in (x & ~1, x | 1)})
    return type(c)(c.net, both(c.sources), both(c.targets), c.ids, c.number, c.order, c.params)


def separate(g: Graph, splitter: Splitter, numbers: list[int] | None = None) -> np.ndarray:
    """0 / 1 / 2 by node: blocks and separator of a connected graph, by all cutters or those of the given numbers."""
    if splitter.cut is not None:
        label = splitter.cut(g)
    elif splitter.style == "edgecut" or splitter.kind == "bands":
        best, tries = choose(cuts_of(g, splitter, False)[0]), 0
        while best is not None and tries < splitter.patience:
            tries += 1
            other = choose(cuts_of(g, splitter, False, seed=splitter.seed + tries)[0])
            if other is not None and other.size * best.small < best.size * other.small:
                best, tries = other, 0
        label = np.zeros(g.n, np.int8)
        if best is not None:
            label[:] = np.frombuffer(best.side, np.uint8)
            label = edge_cut_separator(label, g.u, g.v)
    else:
        cuts = [c for c in front(cuts_of(g, splitter, True, numbers=numbers)[0])]
        good = [c for c in cuts if 5 * c.small >= c.n] or cuts
        good.sort(key=lambda c: (c.size / c.small, -c.small))
        label, fall = np.zeros(g.n, np.int8), None
        for c in good:
            label = separator_of(c.side, g.u, g.v)
            small = min((label == 0).sum(), (label == 1).sum())
            if 5 * small >= (label != 2).sum():
                return label
            if fall is None or small > fall[0]:
                fall = (small, label)
        label = fall[1] if fall else label
    return label


def edge_cut_separator(label: np.ndarray, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """A separator from an edge cut: the cut's ends on the side with fewer of them."""
    label = label.astype(np.int8)
    crossing = label[u] != label[v]
    a = np.unique(np.where(label[u[crossing]] == 0, u[crossing], v[crossing]))
    b = np.unique(np.where(label[u[crossing]] == 1, u[crossing], v[crossing]))
    label[a if len(a) <= len(b) else b] = 2
    return label


def dissect(g: Graph, splitter: Splitter) -> list[int]:
    """An elimination order by recursive separators; trees and cliques end the recursion."""
    out: list[int] = []
    work: list[tuple[str, np.ndarray]] = [("cell", np.arange(g.n))]
    while work:
        kind, nodes = work.pop()
        if kind == "done":
            out.extend(nodes.tolist())
            continue
        cell = g.part(nodes)
        parts = parts_of(component_labels(cell.n, cell.u, cell.v))
        if len(parts) > 1:
            work.extend(("cell", nodes[p]) for p in reversed(parts))
            continue
        m = len(cell.u)
        if m == cell.n - 1:
            out.extend(nodes[tree_order(cell)[0]].tolist())
            continue
        if m == cell.n * (cell.n - 1) // 2 or cell.n < 3:
            out.extend(nodes.tolist())
            continue
        label = separate(cell, splitter)
        blocks = [nodes[label == 0], nodes[label == 1]]
        if not len(blocks[0]) or not len(blocks[1]):
            out.extend(nodes.tolist())
            continue
        work.append(("done", nodes[label == 2]))
        work.extend(("cell", b) for b in reversed(blocks))
    return out


def core_split(g: Graph) -> np.ndarray:
    """1 for nodes of the largest biconnected component, else 0."""
    label = np.zeros(g.n, np.int8)
    if len(g.u):
        number = bicomponents(g)
        sizes = np.bincount(number)
        best = int(np.argmax(sizes))
        own = number == best
        label[np.unique(np.concatenate([g.u[own], g.v[own]]))] = 1
    return label


def chains(g: Graph) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Which nodes are of degree 2 or less on chains, and the edges that stand for the chains between nodes of degree 3 or more.

    A chain that ends at a node of degree 1 takes that end along; a component that is one cycle has no chain.
    """
    degree = np.bincount(np.concatenate([g.u, g.v]), minlength=g.n)
    low = degree <= 2
    own = low[g.u] & low[g.v]
    label = component_labels(g.n, g.u[own], g.v[own])
    cross = low[g.u] != low[g.v]
    inner = np.where(low[g.u[cross]], g.u[cross], g.v[cross])
    outer = np.where(low[g.u[cross]], g.v[cross], g.u[cross])
    ends: dict[int, list[int]] = {}
    for c, o in zip(label[inner].tolist(), outer.tolist(), strict=True):
        ends.setdefault(c, []).append(o)
    on_chain = low & np.isin(label, list(ends))
    new = {(min(e), max(e)) for e in ends.values() if len(e) == 2 and e[0] != e[1]}
    return on_chain, np.array([e[0] for e in sorted(new)], np.int64), np.array([e[1] for e in sorted(new)], np.int64)


def stages(g: Graph) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The preprocessing of a connected graph: 0 for nodes outside its largest biconnected component, 1 for chains in it, 2 for the rest; and the edges
    that stand for chains between nodes of the rest."""
    core = core_split(g).astype(bool)
    label = np.zeros(g.n, np.int8)
    inner = np.flatnonzero(core)
    if not len(inner):
        return label, np.zeros(0, np.int64), np.zeros(0, np.int64)
    on_chain, a, b = chains(g.part(inner))
    label[inner] = np.where(on_chain, 1, 2)
    return label, inner[a], inner[b]


def staged(g: Graph, label: np.ndarray, a: np.ndarray, b: np.ndarray) -> Graph:
    """The graph whose components are dissected one by one: edges within a stage, and those for chains."""
    own = label[g.u] == label[g.v]
    lo, hi = np.concatenate([g.u[own], np.minimum(a, b)]), np.concatenate([g.v[own], np.maximum(a, b)])
    pairs = np.unique(np.stack([lo, hi], 1), axis=0)
    return Graph(g.n, pairs[:, 0], pairs[:, 1], g.x, g.y)


def full_order(g: Graph, splitter: Splitter, preprocess: bool = True) -> list[int]:
    """The whole order of a graph: loose parts before the core, chains before the rest of the core."""
    if not preprocess:
        return dissect(g, splitter)
    out: list[int] = []
    for nodes in parts_of(component_labels(g.n, g.u, g.v)):
        whole = g.part(nodes)
        label, a, b = stages(whole)
        made = staged(whole, label, a, b)
        for stage in (0, 1, 2):
            out.extend(_cut_loose(made, nodes, label == stage, splitter))
    return out


def _cut_loose(g: Graph, names: np.ndarray, chosen: np.ndarray, splitter: Splitter) -> list[int]:
    nodes = np.flatnonzero(chosen)
    return names[nodes][dissect(g.part(nodes), splitter)].tolist() if len(nodes) else []
