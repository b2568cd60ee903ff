"""The in-task kernels against enumeration, fixed traces and plain shortest paths."""

import numpy as np
import pytest

from cutline.functions import index, multilevel
from cutline.functions.cutter import Cut, Cutter, SweepParams, band_cuts, choose, directions, front, interleave, pair_cutters, separator_of, split_orders, sweep_cutters, sweep_order
from cutline.functions.flow import Net, level_flow, max_flow
from cutline.functions.order import Graph, Splitter, bicomponents, chains, component_labels, cuts_of, dissect, full_order, separate, stages, tree_order


def lattice(w, h=None):
    h = h or w
    i = np.arange(w * h)
    gx, gy = i % w, i // w
    u = np.concatenate([i[gx < w - 1], i[gy < h - 1]])
    v = np.concatenate([i[gx < w - 1] + 1, i[gy < h - 1] + w])
    return Graph(w * h, u, v, 1000 * gx + 37 * i % 100, 1000 * gy + 53 * i % 100)


G = lattice(4)
MASKS = np.arange(1 << 16)
SIZES = sum(((MASKS >> a) & 1) != ((MASKS >> b) & 1) for a, b in zip(G.u, G.v, strict=True)).astype(int)


def minimisers(s, t):
    own = [m for m in MASKS if all(m >> x & 1 for x in s) and not any(m >> x & 1 for x in t)]
    least = min(SIZES[m] for m in own)
    return least, [m for m in own if SIZES[m] == least]


@pytest.mark.parametrize("s,t", [([0], [15]), ([0, 1], [14, 15]), ([5], [10]), ([0, 4, 8], [3])])
def test_flow_and_reach_equal_enumeration(s, t):
    value, best = minimisers(s, t)
    for run in (max_flow, level_flow, lambda n, a, b: max_flow(n, a, b, breadth=True)):
        net = Net.undirected(16, G.u, G.v)
        assert run(net, s, t) == value
        sr, _, _ = net.reach(s, True)
        tr, _, _ = net.reach(t, False)
        assert sum(1 << i for i in range(16) if sr[i]) == np.bitwise_and.reduce(best)
        assert sum(1 << i for i in range(16) if not tr[i]) == np.bitwise_or.reduce(best)
        f = net.flow()
        assert (f == -f[np.array(net.twin)]).all() and (np.abs(f) <= 1).all()
        inner = np.bincount(net.tails, f, 16)
        assert not inner[[i for i in range(16) if i not in s + t]].any()


def test_pair_trace():
    cuts = [c for c in Cutter(Net.undirected(16, G.u, G.v), [0], [15], list(range(16))).steps() if c]
    assert [c.size for c in cuts] == [2, 2, 3, 3, 4, 4, 4, 5, 5, 6, 6]
    assert [c.rule for c in cuts] == ["free", "single", "free", "single", "free", "free", "single", "free", "single", "free", "balanced"]
    assert [c.pierced for c in cuts][:3] == [(1,), (11,), (2,)]


def test_sweep_trace():
    order = sweep_order(G.x, G.y, np.arange(16), directions(4)[0])
    assert order.tolist() == [0, 12, 4, 8, 9, 1, 13, 5, 14, 6, 10, 2, 11, 3, 15, 7]
    cuts = [c for c in sweep_cutters(Net.undirected(16, G.u, G.v), [order], list(range(16)), SweepParams(q=1))[0].steps() if c]
    assert [(c.size, c.grown, c.rule) for c in cuts] == [(2, "S", "bulk"), (3, "T", "free"), (3, "T", "bulk"), (4, "S", "free"), (4, "T", "free"), (4, "S", "balanced")]


def test_cuts_are_recounted_and_monotone():
    g = lattice(9, 7)
    for splitter in (Splitter(params=SweepParams(q=4)), Splitter("pairs", pairs=5), Splitter("bands", SweepParams(q=4, alpha=0.2))):
        found, _ = cuts_of(g, splitter, False, bound=False)
        for c in found:
            side = np.frombuffer(c.side, np.uint8)
            assert (side[g.u] != side[g.v]).sum() == c.size
            assert min(side.sum(), g.n - side.sum()) == c.small
    one = [c for c in Cutter(Net.undirected(g.n, g.u, g.v), [0], [g.n - 1], list(range(g.n))).steps() if c]
    assert all(a.size <= b.size for a, b in zip(one, one[1:], strict=False))
    for side in "ST":
        own = [set(np.flatnonzero(np.frombuffer(c.side, np.uint8))) for c in one if c.grown == side]
        assert all(a <= b for a, b in zip(own, own[1:], strict=False))


def test_optimum_of_small_lattice():
    found = front(interleave(sweep_cutters(Net.undirected(16, G.u, G.v), [sweep_order(G.x, G.y, np.arange(16), d) for d in directions(8)], list(range(16)), SweepParams())))
    assert min(c.size for c in found if c.small == 8) == 4


def test_front_and_choice():
    cuts = [Cut(s, m, 100, b"", 0) for s, m in [(9, 10), (7, 12), (7, 20), (12, 30), (11, 30), (20, 45), (3, 4)]]
    assert [(c.size, c.small) for c in front(cuts)] == [(3, 4), (7, 20), (11, 30), (20, 45)]
    assert (choose(cuts).size, choose(cuts).small) == (7, 20)


def test_separators_separate():
    g = lattice(8)
    for style in (Splitter(params=SweepParams(q=4)), Splitter("bands", SweepParams(q=4, alpha=0.2), style="edgecut"), Splitter("pairs", pairs=3)):
        label = separate(g, style)
        assert not (((label[g.u] == 0) & (label[g.v] == 1)) | ((label[g.u] == 1) & (label[g.v] == 0))).any()
        assert (label == 0).any() and (label == 1).any()
    found, _ = cuts_of(g, Splitter(params=SweepParams(q=4)), True)
    assert all((separator_of(c.side, g.u, g.v) == 2).sum() <= c.size for c in found)


SHAPES = {
    "empty": (0, []), "one": (1, []), "two": (2, [(0, 1)]), "no edges": (4, []), "clique": (5, [(a, b) for a in range(5) for b in range(a)]),
    "star": (6, [(0, i) for i in range(1, 6)]), "path": (7, [(i, i + 1) for i in range(6)]), "cycle": (9, [(i, (i + 1) % 9) for i in range(9)]),
    "dumbbell": (8, [(a, b) for o in (0, 4) for a in range(o, o + 4) for b in range(o, a)] + [(3, 4)]), "two parts": (6, [(0, 1), (1, 2), (0, 2), (3, 4)]),
}


@pytest.mark.parametrize("name", SHAPES)
def test_orders_of_shapes(name):
    n, e = SHAPES[name]
    u, v = (np.array([min(x) for x in e], int), np.array([max(x) for x in e], int)) if e else (np.zeros(0, int), np.zeros(0, int))
    g = Graph(n, u, v, np.zeros(n, int), np.zeros(n, int))  # all nodes at one point
    for prep in (True, False):
        assert sorted(full_order(g, Splitter(params=SweepParams(q=4)), prep)) == list(range(n))
    assert sorted(dissect(g, Splitter("pairs", pairs=2))) == list(range(n))


def test_tree_depths():
    for n in range(1, 40):
        p = Graph(n, np.arange(n - 1), np.arange(1, n), np.zeros(n, int), np.zeros(n, int))
        order, depth = tree_order(p)
        assert depth == n.bit_length() and sorted(order) == list(range(n))


def test_bicomponents_and_chains():
    n, e = SHAPES["dumbbell"]
    g = Graph(n, np.array([min(x) for x in e]), np.array([max(x) for x in e]), np.zeros(n, int), np.zeros(n, int))
    assert sorted(np.bincount(bicomponents(g)).tolist()) == [1, 6, 6]
    # two nodes of degree 3 joined by three paths
    e = [(0, 2), (2, 1), (0, 3), (3, 1), (0, 4), (4, 5), (5, 1)]
    g = Graph(6, np.array([min(x) for x in e]), np.array([max(x) for x in e]), np.zeros(6, int), np.zeros(6, int))
    low, a, b = chains(g)
    assert low.tolist() == [False, False, True, True, True, True] and list(zip(a, b, strict=True)) == [(0, 1)]


def test_index_equals_shortest_paths():
    g = lattice(7)
    rank = np.empty(g.n, int)
    rank[full_order(g, Splitter(params=SweepParams(q=4)))] = np.arange(g.n)
    a, b = rank[g.u], rank[g.v]
    up = index.build(g.n, np.minimum(a, b), np.maximum(a, b))
    for x in up:  # upward neighbours are pairwise adjacent
        assert all(h in up[lo] for i, lo in enumerate(x) for h in x[i + 1 :])
    forth, back = (g.u * 7 + g.v) % 17 + 1, (g.u + 5 * g.v) % 13 + 1
    arcs = ([*a, *b], [*b, *a], [*forth.tolist(), *back.tolist()])
    w, lower = (index.Weights(up).attach(*arcs).customize(c) for c in ("upper", "lower"))
    assert w.w_up == lower.w_up and w.w_down == lower.w_down
    near = [[] for _ in range(g.n)]
    for t, h, x in zip(*arcs, strict=True):
        near[t].append((h, x))
    parent = index.parents(up)
    for s in range(g.n):
        dist = index.dijkstra(g.n, near, s)
        for t in range(g.n):
            assert w.tree_query(parent, s, t) == w.heap_query(s, t) == w.tree_query(parent, s, t, True) == dist[t]


def test_witnesses_keep_distances():
    g = lattice(6)
    rank = np.empty(g.n, int)
    rank[full_order(g, Splitter(params=SweepParams(q=4)))] = np.arange(g.n)
    a, b = rank[g.u], rank[g.v]
    up = index.build(g.n, np.minimum(a, b), np.maximum(a, b))
    forth, back = (g.u * 7 + g.v) % 17 + 1, (g.u + 5 * g.v) % 13 + 1
    arcs = ([*a, *b], [*b, *a], [*forth.tolist(), *back.tolist()])
    w = index.Weights(up).attach(*arcs).customize()
    before = [[*x] for x in w.w_up]
    gone = w.perfect()
    near = [[] for _ in range(g.n)]
    for t, h, x in zip(*arcs, strict=True):
        near[t].append((h, x))
    assert gone > 0
    for s in range(g.n):
        dist = index.dijkstra(g.n, near, s)
        for t in range(g.n):
            assert w.heap_query(s, t) == dist[t]
        for i, h in enumerate(up[s]):  # a weight stays iff it is the distance
            assert w.w_up[s][i] == (before[s][i] if before[s][i] <= dist[h] else index.FAR) and w.far_up[s][i] == dist[h]


def test_a_paused_cutter_goes_on():
    """Stopped at any flow, written down, read again: the same cuts."""
    g = lattice(9, 7)
    for net in (Net.undirected(g.n, g.u, g.v), Net.split(g.n, g.u, g.v)):
        orders = [sweep_order(g.x, g.y, np.arange(g.n), d) for d in directions(3)]
        wide = split_orders(orders) if net.n > g.n else orders
        for k in range(3):
            make = lambda: sweep_cutters(net, [wide[k]], list(range(net.n)), SweepParams(q=3), [k])[0]  # noqa: B023, E731
            whole = [(c.size, c.side, c.rule) for c in make().steps() if c]
            own, parts = make(), []
            for limit in [*range(1, 30), None]:
                parts += [(c.size, c.side, c.rule) for c in own.steps(limit) if c]
                own = Cutter.load(own.dump())
            assert own.done and parts == whole


def test_incremental_reaches_are_those_of_the_flow():
    """After every cut the cutter's marks are what a search from all its terminals finds."""
    g = lattice(8, 6)
    for net, pairs in ((Net.undirected(g.n, g.u, g.v), ([0, 1], [47])), (Net.split(g.n, g.u, g.v), ([0, 1], [94, 95]))):
        c = Cutter(net.copy(), *pairs, list(range(net.n)))
        for cut in c.steps():
            if cut:
                for side in (1, 2):
                    # the other side's terminals don't end the search, as nothing reaches them
                    assert c.net.reach([x for x in range(net.n) if c.term[x] == side], side == 1)[0] == c.reached[side]


def test_interleaved_bands_end_with_the_smallest():
    g = lattice(9, 7)
    orders = [sweep_order(g.x, g.y, np.arange(g.n), d) for d in directions(4)]
    net = Net.undirected(g.n, g.u, g.v)
    every, units = band_cuts(net, orders, 0.2)
    (first,), fewer = band_cuts(net, orders, 0.2, best_only=True)
    assert first.size == min(c.size for c in every) and fewer < units and sum(c.size for c in every) == units


@pytest.mark.parametrize("preset", multilevel.VERSIONS)
def test_partitioners_recount(preset):
    g = lattice(14, 11)
    side, info = multilevel.bisect(g.n, g.u.tolist(), g.v.tolist(), 0.1, preset)
    own = np.array(side)
    assert (own[g.u] != own[g.v]).sum() == info["cut"] and max(own.sum(), g.n - own.sum()) == info["large"] and (info["missed"] or info["large"] <= 85)
    label = multilevel.node_separator(g.n, g.u, g.v, side)
    assert not (((label[g.u] == 0) & (label[g.v] == 1)) | ((label[g.u] == 1) & (label[g.v] == 0))).any() and 0 < (label == 2).sum() <= info["cut"]


def test_flow_between_blocks_finds_the_bottleneck():
    # two lattices of five columns joined by one edge; the bisection cuts a column inside the first
    a = lattice(5)
    u, v = np.concatenate([a.u, a.u + 25, [24]]), np.concatenate([a.v, a.v + 25, [25]])
    near = multilevel._adjacency(50, u.tolist(), v.tolist(), [1] * len(u))
    side = [int(i % 5 > 2 or i >= 25) for i in range(50)]
    better = multilevel.flow_between(near, [1] * 50, side, 35)
    assert multilevel.cut_size(near, side) == 5 and multilevel.cut_size(near, better) == 1
    parts = multilevel.natural_fragments(50, u.tolist(), v.tolist(), 20)
    assert not set(parts[:25]) & set(parts[25:])


def test_stages_stand_apart():
    """A core with a chain and a tail: the tail is loose, the chain is one edge of the rest."""
    e = [(0, 1), (0, 2), (1, 2), (0, 3), (1, 3), (2, 3), (2, 4), (4, 5), (5, 3), (0, 6), (6, 7)]
    g = Graph(8, np.array([x[0] for x in e]), np.array([x[1] for x in e]), np.zeros(8, int), np.zeros(8, int))
    label, a, b = stages(g)
    assert label.tolist() == [2, 2, 2, 2, 1, 1, 0, 0] and list(zip(a, b, strict=True)) == [(2, 3)]
    made = full_order(g, Splitter(params=SweepParams(q=2)))
    assert sorted(made[:2]) == [6, 7] and sorted(made[2:4]) == [4, 5]


def test_multilevel_balance():
    g = lattice(12)
    for eps in (0.0, 0.05, 0.3):
        side, info = multilevel.bisect(g.n, g.u.tolist(), g.v.tolist(), eps)
        assert info["large"] <= -(-int((1 + eps) * g.n * 1000) // 2000) and sum(side[a] != side[b] for a, b in zip(g.u, g.v, strict=True)) == info["cut"]
    assert multilevel.bisect(g.n, g.u.tolist(), g.v.tolist(), 0.0, "QM")[0] is None


def test_band_cut_is_minimum():
    orders = [sweep_order(G.x, G.y, np.arange(16), d) for d in directions(4)]
    found, _ = band_cuts(Net.undirected(16, G.u, G.v), orders, 0.2)
    for c, o in zip(found, orders, strict=True):
        assert c.size == minimisers(o[:3].tolist(), o[-3:].tolist())[0]


def test_components():
    assert component_labels(6, np.array([0, 4]), np.array([3, 5])).tolist() == [0, 1, 2, 0, 4, 4]
    assert pair_cutters(Net.undirected(16, G.u, G.v), [([0], [15])], list(range(16)))[0].flow == 0


def test_units_of_many_seeds_are_found_by_two_searches():
    """A cutter finds its first flow, of many units, by one quick and one whole search; its flow and reach are those of one path at a time."""
    import numpy as np

    from cutline.functions import cutter, flow

    n, wide = 400, 20
    u = np.array([i for i in range(n) if i % wide < wide - 1] + list(range(n - wide)))
    v = np.array([i + 1 for i in range(n) if i % wide < wide - 1] + list(range(wide, n)))
    stay = (u * 7 + v * 5) % 10 >= 2
    net = flow.Net.undirected(n, u[stay], v[stay])
    s, t = list(range(wide)), list(range(n - wide, n))
    own = cutter.Cutter(net.copy(), s, t, list(range(n)))
    first = next(c for c in own.steps() if c is not None)
    plain = net.copy()
    units = flow.max_flow(plain, s, t)
    reach = plain.reach(s, True)[0], plain.reach(t, False)[0]
    side = "ST".index(first.grown)
    assert units > 2 and first.size == units and first.side == bytes(reach[side]) and own.searches == 2


def test_compiled_kernel_equals_python(spark):
    """Cuts, fronts, separators and orders of the compiled kernel are those of the Python kernels: sweeps, pairs, bands and repeated edge cuts, with and without a bound."""
    from cutline.functions import cutter
    from cutline.functions.order import Graph, Splitter, cuts_of, dissect, separate
    from cutline.operators import compiled, cutters
    from pyspark.sql import functions as F

    rng, requests, wanted = np.random.default_rng(3), [], []
    for w, h in ((2, 2), (5, 3), (9, 8), (16, 14)):
        at = np.arange(w * h)
        right, up = at[at % w < w - 1], at[at < w * (h - 1)]
        u, v = np.concatenate([right, up]), np.concatenate([right + 1, up + w])
        stay = (rng.random(len(u)) < 0.9) | (u % w == 0) | (v == u + 1) & (u < w)
        mixed = rng.permutation(w * h)
        a, b = mixed[u[stay]], mixed[v[stay]]
        u, v, place = np.minimum(a, b), np.maximum(a, b), np.argsort(mixed)
        label = component_labels(w * h, u, v)
        whole = Graph(w * h, u, v, 1000 * (place % w) + place % 7, 1000 * (place // w) + place % 5)
        g = whole.part(np.flatnonzero(label == label[mixed[0]]))
        for s in (cutters.config("SP4"), cutters.config("PP3"), cutters.config("BF"), Splitter("pairs", pairs=3, style="edgecut", patience=4)):
            for bound in (False, True):
                cuts = cuts_of(g, s, False, bound)[0]
                requests.append(compiled.packed(compiled.CUTS, g, s, bound=bound, logs=True))
                wanted.append(("cuts", g.n, [(c.cutter, c.size, c.small, c.side.hex()) for c in cutter.front(cuts)]))
            requests.append(compiled.packed(compiled.SEPARATE, g, s))
            wanted.append(("label", g.n, separate(g, s).tolist()))
            requests.append(compiled.packed(compiled.DISSECT, whole, s))
            wanted.append(("order", whole.n, dissect(whole, s)))
    table = spark.createDataFrame([(i, bytearray(r)) for i, r in enumerate(requests)], "i int, request binary")
    rows = {r.i: bytes(r.answer) for r in table.select("i", F.expr(f"{compiled.registered(spark)}(request)").alias("answer")).collect()}
    for i, (what, n, want) in enumerate(wanted):
        if what == "cuts":
            got = [(c.cutter, c.size, c.small, c.side.hex()) for c in compiled.read_cuts(rows[i], n)[0]]
        else:
            got = np.frombuffer(rows[i], np.int8 if what == "label" else "<i4").tolist()
        assert got == want, (i, what)
