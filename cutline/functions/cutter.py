"""Cutters: incremental piercing from seeds, with sweep bulk steps, and their interleaving over directions."""

from __future__ import annotations

import heapq
import math
import pickle
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np

from .flow import Net, unit_flow


@dataclass(frozen=True)
class SweepParams:
    """Directions q, seed share alpha, bulk limits gamma_a and gamma_o, step share delta."""

    q: int = 8
    alpha: float = 0.05
    gamma_a: float = 0.4
    gamma_o: float = 0.25
    delta: float = 0.05


@dataclass
class Cut:
    size: int
    small: int
    n: int
    held: bytes | tuple[list[int], int]  # the grown block: 1 by node, or so many first nodes of a list that only grows
    cutter: int
    rule: str = ""
    grown: str = ""
    pierced: tuple = ()

    @property
    def large(self) -> int:
        return self.n - self.small

    @property
    def side(self) -> bytes:
        """1 for nodes of the grown block."""
        if isinstance(self.held, bytes):
            return self.held
        grown, upto = self.held
        marks = np.zeros(self.n, np.uint8)
        marks[grown[:upto]] = 1
        return marks.tobytes()


def directions(q: int) -> list[tuple[int, int]]:
    """Fixed-point unit vectors (times 10**6) at angles k * pi / q."""
    return [(round(1e6 * math.cos(k * math.pi / q)), round(1e6 * math.sin(k * math.pi / q))) for k in range(q)]


def sweep_order(x: np.ndarray, y: np.ndarray, ids: np.ndarray, direction: tuple[int, int]) -> np.ndarray:
    """Nodes along a direction; ties by id."""
    key = x.astype(np.int64) * direction[0] + y.astype(np.int64) * direction[1]
    return np.lexsort((ids, key))


def count_of(share: float, n: int) -> int:
    """floor(share * n) without a float's last bit in the way."""
    return math.floor(share * n + 1e-9)


def trimmed(net: Net, terminals: list[int]) -> list[int]:
    """Terminals with a neighbour outside the set; the others never take part in a path."""
    own = bytearray(net.n)
    for x in terminals:
        own[x] = 1
    return [x for x in terminals if not all(own[y] for y in net.head[net.start[x] : net.start[x + 1]])] or terminals


@dataclass
class Cutter:
    """One incremental cutter. ids order ties; order is the sweep order (None: single piercing only)."""

    net: Net
    sources: list[int]
    targets: list[int]
    ids: list[int]
    number: int = 0
    order: list[int] | None = None
    params: SweepParams = field(default_factory=SweepParams)
    use_distance: bool = True

    def __post_init__(self):
        net, n = self.net, self.net.n
        self.term = bytearray(n)
        for x in self.sources:
            self.term[x] = 1
        for x in self.targets:
            self.term[x] = 2
        self.flow = self.units = self.searches = 0
        self.done = False
        self.from_s = net.hops(self.sources) if self.use_distance else [0] * n
        self.from_t = net.hops(self.targets) if self.use_distance else [0] * n
        self.next = {1: 0, 2: 0}
        self.reached = {1: bytearray(n), 2: bytearray(n)}  # what each side reaches; closed under residual arcs between piercings
        self.waiting: dict[int, list[int]] = {1: [], 2: []}  # reached, but not yet terminals
        self.grown: dict[int, list[int]] = {1: [], 2: []}  # absorbed nodes, in order
        self.edge: dict[int, set[int]] = {1: set(), 2: set()}
        self.mark = {k: bytearray(n) for k in (1, 2)}
        self.begun = False

    def _absorb(self, side: int) -> None:
        """The side's terminals become all that it reaches; its outer neighbours are kept up to date."""
        net, edge, own = self.net, self.edge[side], self.reached[side]
        start, head, term, mark = net.start, net.head, self.term, self.mark[side]
        for x in self.waiting[side]:
            term[x] = side
            mark[x] = 1
            edge.discard(x)
            for a in range(start[x], start[x + 1]):
                y = head[a]
                if not own[y] and (net.cap_list[a] if side == 1 else net.cap_list[net.twin[a]]):
                    edge.add(y)
        self.grown[side] += self.waiting[side]
        self.waiting[side] = []

    def _join(self, side: int, nodes: list[int]) -> list[int]:
        """Makes nodes terminals of a side; returns those that the side doesn't reach yet. What it reaches is closed, so paths can only start there."""
        for x in nodes:
            self.term[x] = side
            self.mark[side][x] = 1
        return [x for x in nodes if not self.reached[side][x]]

    def _fill(self, side: int, new: list[int], marks: bytearray | None = None) -> None:
        """Adds to a side's reach what residual arcs join to it from new nodes."""
        own = self.reached[side]
        seen, _, via = self.net.reach(new, side == 1, marks=own)
        self.reached[side] = seen
        self.waiting[side] += new
        self.waiting[side] += via

    def _augment(self, side: int, new: list[int]) -> Iterator[None]:
        """Units of flow from a side's new terminals until none is left; their reach joins the side's, and the other side's is found anew if flow was pushed.
        A search pushes many units, which are counted one by one: cuts depend on how many there are, not on their paths."""
        net, other, pushed = self.net, 3 - side, 0
        near = self.from_t if side == 1 else self.from_s  # hops to where the other side began
        for whole in (False, True) if len(new) > 1 else (True,):
            self.searches += 1
            units, seen, found = net.units(new, side == 1, self.mark[other], bytearray(self.reached[side]), near, whole)
            for _ in range(units):
                pushed += 1
                self.flow += 1
                self.units += 1
                yield None
        self.reached[side] = seen
        self.waiting[side] += new
        self.waiting[side] += found
        if pushed:
            # absorbed terminals stay closed, so the other side's reach goes out from its later ones only
            rest = [x for x in self.waiting[other] if self.mark[other][x]]
            seen, _, via = net.reach(rest, other == 1, marks=bytearray(self.mark[other]))
            self.reached[other] = seen
            self.waiting[other] = [*rest, *via]

    def steps(self, limit: int | None = None) -> Iterator[Cut | None]:
        """None after each unit of flow, a Cut after each derived cut; free piercing goes on within one step. With a limit it pauses before
        the first cut of at least so much flow, and goes on there when called again.

        What a side reaches is closed under residual arcs, so after a piercing paths can only start at its nodes, and never run through that reach."""
        net, n = self.net, self.net.n
        half = -(-n // 2)
        if not hasattr(net, "cap_list"):
            net.cap_list = net.cap.tolist()
        if not self.begun:
            self.begun = True
            self._fill(2, self._join(2, self.targets))
            yield from self._augment(1, self._join(1, self.sources))
        while not self.done:
            if limit is not None and self.flow >= limit:
                return
            sizes = {k: len(self.grown[k]) + len(self.waiting[k]) for k in (1, 2)}
            side = 1 if sizes[1] <= sizes[2] else 2
            size = sizes[side]
            self._absorb(side)
            rule, pierced, again = self._pierce(side, size, self.reached[3 - side])
            cut = Cut(self.flow, min(size, n - size), n, (self.grown[side], size), self.number, rule, "ST"[side - 1], tuple(pierced))
            if max(size, n - size) <= half:
                cut.rule, cut.pierced, rule = "balanced", (), "balanced"
            yield cut
            if rule in ("balanced", "end"):
                self.done = True
                return
            new = self._join(side, pierced)
            if again:  # free nodes add no augmenting path, so only this side's reach grows
                self._fill(side, new)
            else:
                yield from self._augment(side, new)

    def dump(self) -> bytes:
        """The whole state of a paused cutter, with its graph."""
        net = self.net
        plain = {k: v for k, v in self.__dict__.items() if k != "net"}
        arrays = {k: np.array(getattr(net, k), np.int64 if net.n > 1 << 30 or len(net.head) > 1 << 30 else np.int32) for k in ("start", "head", "twin")}
        return pickle.dumps((plain, net.n, arrays, net.cap.tobytes(), bytes(net.res)), protocol=5)

    @classmethod
    def load(cls, state: bytes) -> Cutter:
        plain, n, arrays, cap, res = pickle.loads(state)
        net = object.__new__(Net)
        net.n, net.cap, net.res = n, np.frombuffer(cap, np.int8), bytearray(res)
        net.start, net.head, net.twin = (arrays[k].tolist() for k in ("start", "head", "twin"))
        net.cap_list, net.tails = net.cap.tolist(), np.repeat(np.arange(n), np.diff(arrays["start"]))
        own = object.__new__(cls)
        own.__dict__.update(plain, net=net)
        return own

    def _pierce(self, side: int, size: int, other: bytearray) -> tuple[str, list[int], bool]:
        """Rule, nodes, and whether they leave the flow maximal."""
        opposite = 3 - side
        found = [y for y in self.edge[side] if self.term[y] != opposite]
        near, far = (self.from_s, self.from_t) if side == 1 else (self.from_t, self.from_s)
        rank = lambda p: (far[p] - near[p], self.ids[p])
        free = [p for p in found if not other[p]]
        if free:
            return "free", [min(free, key=rank)], True
        bulk = self._bulk(side, size)
        if bulk:
            return "bulk", bulk, False
        if found:
            return "single", [min(found, key=rank)], False
        return "end", [], False

    def _bulk(self, side: int, have: int) -> list[int]:
        if self.order is None:
            return []
        n, p = self.net.n, self.params
        if have > p.gamma_a * n:
            return []
        raw = p.delta * ((1 - p.delta) * n / 2 - have)
        if raw <= 0:
            return []
        step, limit, out = max(1, int(raw)), count_of(p.gamma_o, n), []
        at = self.next[side]
        while at < limit and len(out) < step:
            x = self.order[at] if side == 1 else self.order[n - 1 - at]
            if not self.term[x]:
                out.append(x)
            at += 1
        self.next[side] = at
        return out


def interleave(cutters: list[Cutter], schedule: str = "flow", bound: bool = False, least_small: float = 0.2, most_cut: int | None = None, trace: bool = False) -> list[Cut]:
    """All cuts of the cutters. schedule 'flow': the cutter with least flow moves next, by a unit or a cut; 'cut': all with the
    least cut go on to their next cut. bound: cutters that can't improve the best expansion stop."""
    cuts: list[Cut] = []
    best: Cut | None = None
    runs = {c.number: c.steps() for c in cutters}
    by = {c.number: c for c in cutters}
    last = dict.fromkeys(by, 0)
    heap = [(0, k) for k in sorted(by)]
    heapq.heapify(heap)
    while heap:
        _, k = heapq.heappop(heap)
        c = by[k]
        if bound and best is not None and c.flow * best.small >= best.size * (c.net.n // 2):
            continue
        if most_cut is not None and c.flow > most_cut:
            continue
        while True:
            got = next(runs[k], "over")
            if isinstance(got, Cut):
                if not trace and cuts and cuts[-1].cutter == k and cuts[-1].size == got.size and cuts[-1].small <= got.small:
                    cuts[-1] = got  # the same size with better balance
                else:
                    cuts.append(got)
                last[k] = got.size
                if got.small >= least_small * got.n and got.small and (best is None or got.size * best.small < best.size * got.small):
                    best = got
                if got.rule == "free":
                    continue
                break
            if got == "over" or schedule == "flow":
                break
        if got != "over":
            heapq.heappush(heap, (c.flow if schedule == "flow" else last[k], k))
    return cuts


def thinned(steps: Iterator[Cut | None]) -> list[Cut]:
    """A cutter's cuts, of equal sizes in a row only the last, which is the most balanced if blocks grow."""
    cuts: list[Cut] = []
    for got in steps:
        if got is not None:
            if cuts and cuts[-1].size == got.size and cuts[-1].small <= got.small:
                cuts.pop()
            cuts.append(got)
    return cuts


def front(cuts: list[Cut]) -> list[Cut]:
    """Cuts that no other beats: size strictly grows with the smaller block."""
    out: list[Cut] = []
    for c in sorted(cuts, key=lambda c: (-c.small, c.size, c.cutter)):
        if c.small and (not out or c.size < out[-1].size):
            out.append(c)
    return out[::-1]


def choose(cuts: list[Cut], least_small: float = 0.2) -> Cut | None:
    """Least expansion among cuts with at least a fifth on the smaller side; else the most balanced."""
    good = [c for c in cuts if c.small >= least_small * c.n]
    if good:
        best = good[0]
        for c in good[1:]:
            if (c.size * best.small, -c.small) < (best.size * c.small, -best.small):
                best = c
        return best
    some = [c for c in cuts if c.small]
    return max(some, key=lambda c: (c.small, -c.size), default=None)


def band_seeds(order: np.ndarray, alpha: float) -> tuple[list[int], list[int]]:
    n = len(order)
    k = max(1, min(count_of(alpha, n), n // 2))
    return order[:k].tolist(), order[n - k :].tolist()


def sweep_cutters(net: Net, orders: list[np.ndarray], ids: list[int], params: SweepParams, numbers: list[int] | None = None) -> list[Cutter]:
    out = []
    for k, order in zip(numbers if numbers is not None else range(len(orders)), orders, strict=True):
        s, t = band_seeds(order, params.alpha)
        out.append(Cutter(net.copy(), s, t, ids, k, order.tolist(), params))
    return out


def pair_cutters(net: Net, pairs: list[tuple[list[int], list[int]]], ids: list[int], numbers: list[int] | None = None) -> list[Cutter]:
    return [Cutter(net.copy(), list(s), list(t), ids, k) for k, (s, t) in zip(numbers if numbers is not None else range(len(pairs)), pairs, strict=True)]


def band_cuts(net: Net, orders: list[np.ndarray], alpha: float, numbers: list[int] | None = None, best_only: bool = False) -> tuple[list[Cut], int]:
    """One maximum flow per direction, of the direction with least flow a unit at a time; of the source-side and target-side cuts the more
    balanced. best_only: the first direction whose flow is maximal has the smallest cut, and the others stop there."""
    numbers = list(numbers) if numbers is not None else list(range(len(orders)))
    runs = []
    for k, order in zip(numbers, orders, strict=True):
        s, t = band_seeds(order, alpha)
        own = net.copy()
        runs.append((0, k, own, s, t, unit_flow(own, trimmed(own, s), trimmed(own, t))))
    cuts, units = [], 0
    heap = [(0, k, i) for i, (_, k, *_rest) in enumerate(runs)]
    heapq.heapify(heap)
    while heap:
        flow, k, i = heapq.heappop(heap)
        _, _, own, s, t, run = runs[i]
        if next(run, None) is not None:
            units += 1
            heapq.heappush(heap, (flow + 1, k, i))
            continue
        a, _, _ = own.reach(s, True)
        b, _, _ = own.reach(t, False)
        n = net.n
        for marks, name in sorted(((a, "S"), (b, "T")), key=lambda x: (-min(sum(x[0]), n - sum(x[0])), x[1]))[:1]:
            size = sum(marks)
            cuts.append(Cut(flow, min(size, n - size), n, bytes(marks), k, "band", name))
        if best_only:
            break
    return sorted(cuts, key=lambda c: c.cutter), units


def split_orders(orders: list[np.ndarray]) -> list[np.ndarray]:
    """Sweep orders of the split graph: in- and out-copy of a node stand together."""
    return [np.stack([2 * o, 2 * o + 1], 1).reshape(-1) for o in orders]


def separator_of(side: bytes, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """0 / 1 (blocks) or 2 (separator) by node, from a cut of the split graph of edges u-v.

    A node whose bridge arc is cut is in the separator; of an external cut arc, its end on the larger side.
    """
    own = np.frombuffer(side, np.uint8).astype(bool)
    inn, out = own[0::2], own[1::2]
    label = np.where(inn & out, 1, 0).astype(np.int8)
    label[inn != out] = 2
    larger = 1 if int(own.sum()) * 2 > len(own) else 0
    crossing = (label[u] != label[v]) & (label[u] != 2) & (label[v] != 2)
    label[np.where(label[u[crossing]] == larger, u[crossing], v[crossing])] = 2
    return label
