"""The sweep-pierce cutter over tables: one cell that no task can hold, cut along one direction.

Terminals, what each side reaches and residual arcs are tables; a search is a few rounds over blocks of the graph. The steps and
their rules are those of the kernel (functions.cutter), and so are the cuts: for fixed terminals all maximum flows have the same two reaches. As there,
what a side reaches is closed, so paths only start at newly pierced nodes. The driver holds sizes, rules and at most a bulk step's limits.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.cutter import SweepParams, count_of
from ..model import Graph, kept
from .flow import BlockNet
from .geometry import sweep
from .graph import TASK_EDGES, hop_dist, to_arcs


@dataclass
class TableCut:
    size: int
    small: int
    n: int
    grown: str
    rule: str
    block: DataFrame  # node_id of the grown block


def undirected(g: Graph) -> DataFrame:
    """src, dst, cap of a graph with unit edges."""
    return to_arcs(g.edges).withColumn("cap", F.lit(1))


def cuts(g: Graph, k: int, params: SweepParams, capacity: DataFrame | None = None, block_edges: int = TASK_EDGES, most: int | None = None) -> Iterator[TableCut]:
    """The cuts of a connected graph along direction k of params.q, as they are found. capacity: src, dst, cap of both directions of each edge (all 1 if not given)."""
    capacity = undirected(g) if capacity is None else capacity
    n = g.nodes.count()
    half, seeds = -(-n // 2), max(1, min(count_of(params.alpha, n), n // 2))
    pos = kept(sweep(g.nodes.withColumn("cell_id", F.lit(0).cast("long")), params.q).filter(F.col("k") == k).select("node_id", "pos"), "table-sweep")
    net = BlockNet.of(g, capacity, block_edges)
    out = kept(net.arcs.filter("cap > 0").select("src", "dst").distinct(), "table-arcs")
    ends = {1: pos.filter(F.col("pos") < seeds).select("node_id"), 2: pos.filter(F.col("pos") >= n - seeds).select("node_id")}
    whole = Graph(g.nodes, out.select(F.least("src", "dst").alias("u"), F.greatest("src", "dst").alias("v")).distinct())
    far = {s: kept(hop_dist(whole, ends[s], block_edges).withColumnRenamed("dist", f"d{s}"), "table-hops") for s in (1, 2)}
    hops = kept(g.nodes.select("node_id").join(far[1], "node_id", "left").join(far[2], "node_id", "left").fillna(n, ["d1", "d2"]), "table-hops")
    term = {s: kept(ends[s], "table-terms") for s in (1, 2)}
    reached = {2: kept(net.reach(ends[2], False)[0].select("node_id"), "table-reach")}
    flow, tree = net.augment(ends[1], term[2], True)
    reached[1] = kept(tree.select("node_id"), "table-reach")
    if flow:
        reached[2] = kept(net.reach(term[2], False)[0].select("node_id"), "table-reach")
    absorbed, at = {}, {1: 0, 2: 0}
    while True:
        sizes = {s: reached[s].count() for s in (1, 2)}
        side = 1 if sizes[1] <= sizes[2] else 2
        size, other = sizes[side], 3 - side
        term[side] = reached[side]
        # outer neighbours of what the side holds, which are no terminals of the other side
        a, b = ("src", "dst") if side == 1 else ("dst", "src")
        around = out.join(reached[side].withColumnRenamed("node_id", a), a, "left_semi").select(F.col(b).alias("node_id")).distinct()
        found = kept(around.join(reached[side], "node_id", "left_anti").join(term[other], "node_id", "left_anti").join(hops, "node_id").join(reached[other].withColumn("held", F.lit(True)), "node_id", "left"), "table-candidates")
        score = (F.col("d2") - F.col("d1")) * (1 if side == 1 else -1)
        first = lambda df: df.select("node_id", score.alias("score")).orderBy("score", "node_id").limit(1).select("node_id")
        free = found.filter("held is null")
        pierced, rule = None, "end"
        if max(size, n - size) <= half:
            rule = "balanced"
        elif not free.isEmpty():
            pierced, rule = first(free), "free"
        else:
            raw = params.delta * ((1 - params.delta) * n / 2 - size)
            limit = count_of(params.gamma_o, n)
            if size <= params.gamma_a * n and raw > 0 and at[side] < limit:
                place = F.col("pos") if side == 1 else F.lit(n - 1) - F.col("pos")
                open_ = pos.join(term[1], "node_id", "left_anti").join(term[2], "node_id", "left_anti").select("node_id", place.alias("place")).filter((F.col("place") >= at[side]) & (F.col("place") < limit))
                step = kept(open_.orderBy("place").limit(max(1, int(raw))), "table-bulk")
                taken = step.agg(F.count("*").alias("n"), F.max("place").alias("last")).first()
                at[side] = taken["last"] + 1 if taken["n"] == max(1, int(raw)) else limit
                if taken["n"]:
                    pierced, rule = step.select("node_id"), "bulk"
            if pierced is None and not found.isEmpty():
                pierced, rule = first(found), "single"
        absorbed[side] = reached[side]
        yield TableCut(flow, min(size, n - size), n, "ST"[side - 1], rule, reached[side])
        if pierced is None or (most is not None and flow > most):
            return
        pierced = kept(pierced, "table-pierced")
        term[side] = kept(term[side].unionByName(pierced), "table-terms")
        new = pierced.join(reached[side], "node_id", "left_anti")
        if rule == "free":
            grown = net.reach(new, side == 1, reached[side])[0]
        else:
            units, grown = net.augment(new, term[other], side == 1, reached[side])
            flow += units
            if units:
                # the other side's absorbed nodes stay closed, so its reach goes out from its later terminals
                rest = term[other] if other not in absorbed else term[other].join(absorbed[other], "node_id", "left_anti")
                again = net.reach(rest, other == 1, absorbed.get(other))[0].select("node_id")
                reached[other] = kept(again if other not in absorbed else again.unionByName(absorbed[other]).distinct(), "table-reach")
        reached[side] = kept(reached[side].unionByName(grown.select("node_id")).distinct(), "table-reach")
