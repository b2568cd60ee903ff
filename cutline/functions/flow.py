"""Unit-capacity flow on one cell's graph, in memory of one task.

For fixed terminals the nodes reachable from either side in the residual graph are the same for every maximum flow, so this
kernel and the DataFrame flow of operators.flow give the same cuts.
"""

from __future__ import annotations

import numpy as np


class Net:
    """Arcs in CSR form with residual capacities. Node numbers are 0..n-1."""

    def __init__(self, n: int, tail: np.ndarray, head: np.ndarray, cap: np.ndarray, back: np.ndarray):
        """One arc tail -> head of capacity cap per row, and its reverse of capacity back."""
        m = len(tail)
        t, h = np.concatenate([tail, head]).astype(np.int64), np.concatenate([head, tail]).astype(np.int64)
        order = np.argsort(t * n + h, kind="stable") if n else np.zeros(0, np.int64)
        place = np.empty(2 * m, np.int64)
        place[order] = np.arange(2 * m)
        twin = np.concatenate([place[m:], place[:m]])[order] if m else np.zeros(0, np.int64)
        self.n = n
        self.start = np.searchsorted(t[order], np.arange(n + 1)).tolist()
        self.head = h[order].tolist()
        self.twin = twin.tolist()
        self.cap = np.concatenate([cap, back]).astype(np.int8)[order]
        self.res = bytearray(self.cap.astype(np.uint8).tobytes())
        self.tails = t[order]

    @classmethod
    def undirected(cls, n: int, u: np.ndarray, v: np.ndarray) -> Net:
        one = np.ones(len(u), np.int8)
        return cls(n, u, v, one, one)

    @classmethod
    def split(cls, n: int, u: np.ndarray, v: np.ndarray) -> Net:
        """Node capacities: node x is 2x (in) and 2x + 1 (out) with a bridge arc; edges are arcs out -> in."""
        x = np.arange(n)
        tail = np.concatenate([2 * x, 2 * u + 1, 2 * v + 1])
        head = np.concatenate([2 * x + 1, 2 * v, 2 * u])
        one = np.ones(len(tail), np.int8)
        return cls(2 * n, tail, head, one, np.zeros(len(tail), np.int8))

    def copy(self) -> Net:
        other = object.__new__(Net)
        other.__dict__.update(self.__dict__)
        other.res = bytearray(self.res)
        return other

    def flow(self) -> np.ndarray:
        """Flow of each arc, by skew symmetry -1, 0 or 1."""
        return self.cap.astype(np.int16) - np.frombuffer(self.res, np.uint8).astype(np.int16)

    def reach(self, seeds, forward: bool, stop: bytearray | None = None, breadth: bool = False, marks: bytearray | None = None) -> tuple[bytearray, int, dict[int, int]]:
        """Marks what the residual arcs reach from seeds (or what reaches them); ends at the first node with stop.
        Nodes are marked as they are found; those that `marks` has at first are not entered. Returns marks, the stop node or -1, and the arc by which each was found."""
        start, head, twin, res = self.start, self.head, self.twin, self.res
        seen, via = marks if marks is not None else bytearray(self.n), {}
        stack = list(seeds)
        for s in stack:
            seen[s] = 1
        at = 0
        while at < len(stack) if breadth else stack:
            if breadth:
                x = stack[at]
                at += 1
            else:
                x = stack.pop()
            for a in range(start[x], start[x + 1]):
                y = head[a]
                if not seen[y] and (res[a] if forward else res[twin[a]]):
                    seen[y] = 1
                    via[y] = a
                    if stop is not None and stop[y]:
                        return seen, y, via
                    stack.append(y)
        return seen, -1, via

    def push(self, end: int, via: dict[int, int], roots: bytearray, forward: bool = True) -> None:
        """One unit along the arcs that found `end`: from a root to it, or, where the search went backward, from it to a root."""
        head, twin, res = self.head, self.twin, self.res
        while not roots[end]:
            a = via[end]
            if forward:
                res[a] -= 1
                res[twin[a]] += 1
            else:
                res[twin[a]] -= 1
                res[a] += 1
            end = head[twin[a]]

    def units(self, seeds, forward: bool, stop: bytearray, marks: bytearray, near: list[int], whole: bool = True) -> tuple[int, bytearray, list[int]]:
        """Searches from one seed after the other as `reach` does, and pushes a unit along each path to a node with stop. near: hops to where paths should go; of the nodes found from
        one the nearest is gone on from first. Returns the units pushed, marks and the nodes found.

        Where a seed's search fails, what it found stays marked: no later path enters it, so nothing in it ever reaches a stop. In the end all seeds have failed, the flow is maximal and
        marks are all that is reached. Without `whole`, what a successful search left behind stays marked too: quick, but paths may be missed."""
        start, head, twin, res = self.start, self.head, self.twin, self.res
        waiting, found, units = sorted(seeds, key=near.__getitem__, reverse=True), [], 0
        for x in waiting:
            marks[x] = 1
        while waiting:
            root, end, via = waiting.pop(), -1, {}
            stack = [root]
            while stack:
                x = stack.pop()
                had = len(stack)
                for a in range(start[x], start[x + 1]):
                    y = head[a]
                    if not marks[y] and (res[a] if forward else res[twin[a]]):
                        marks[y] = 1
                        via[y] = a
                        if stop[y]:
                            end = y
                            break
                        stack.append(y)
                if end >= 0:
                    break
                if len(stack) > had + 1:
                    best = had
                    for i in range(had + 1, len(stack)):
                        if near[stack[i]] < near[stack[best]]:
                            best = i
                    stack[best], stack[-1] = stack[-1], stack[best]
            if end < 0:
                found += via
                continue
            for y in via if whole else stack:
                marks[y] = 0
            while end != root:
                a = via[end]
                there, back = (a, twin[a]) if forward else (twin[a], a)
                res[there] -= 1
                res[back] += 1
                marks[end] = 0
                end = head[twin[a]]
            units += 1
            waiting.append(root)
        return units, marks, found

    def hops(self, seeds) -> list[int]:
        """Hop distances over arcs of positive capacity either way; n where unreachable."""
        far = [self.n] * self.n
        now = list(seeds)
        for s in now:
            far[s] = 0
        d = 0
        while now:
            d += 1
            new = []
            for x in now:
                for y in self.head[self.start[x] : self.start[x + 1]]:
                    if far[y] == self.n:
                        far[y] = d
                        new.append(y)
            now = new
        return far


def unit_flow(net: Net, sources, targets, breadth: bool = False):
    """Augments net's flow to a maximum one, and yields 1 after each unit."""
    s, t = bytearray(net.n), bytearray(net.n)
    for x in sources:
        s[x] = 1
    for x in targets:
        t[x] = 1
    while True:
        _, end, via = net.reach(sources, True, t, breadth)
        if end < 0:
            return
        net.push(end, via, s)
        yield 1


def max_flow(net: Net, sources, targets, breadth: bool = False) -> int:
    """Augments net's flow to a maximum one; returns the units added."""
    return sum(unit_flow(net, sources, targets, breadth))


def level_flow(net: Net, sources, targets) -> int:
    """Maximum flow by breadth-first levels and all paths that a level graph admits: few rounds, many units each."""
    s, t = bytearray(net.n), bytearray(net.n)
    for x in sources:
        s[x] = 1
    for x in targets:
        t[x] = 1
    units = 0
    start, head, twin, res = net.start, net.head, net.twin, net.res
    while True:
        level, now, d = [-1] * net.n, list(sources), 0
        for x in now:
            level[x] = 0
        found = False
        while now and not found:
            d += 1
            new = []
            for x in now:
                for a in range(start[x], start[x + 1]):
                    if res[a] and level[head[a]] < 0:
                        level[head[a]] = d
                        new.append(head[a])
                        found = found or bool(t[head[a]])
            now = new
        if not found:
            return units
        at = list(start[: net.n])
        for root in sources:
            while True:
                path, x = [], root
                while not t[x]:
                    while at[x] < start[x + 1] and not (res[at[x]] and level[head[at[x]]] == level[x] + 1):
                        at[x] += 1
                    if at[x] < start[x + 1]:
                        path.append(at[x])
                        x = head[at[x]]
                    elif path:
                        x = head[twin[path.pop()]]
                        at[x] += 1
                    else:
                        break
                if not t[x]:
                    break
                for a in path:
                    res[a] -= 1
                    res[twin[a]] += 1
                units += 1
