"""Distributed unit-capacity flow, for cells that no single task can hold.

`BlockNet` deals the arcs to blocks that tasks can hold, and its rounds are block crossings. `max_flow` needs DataFrame functions only: its flow is a table of arcs with residual capacities. A phase is a breadth-first search over residual arcs, one join a level, then all
reached targets send tokens back along the search tree; where tokens meet, the smaller one goes on. The arcs of the
tokens that arrive are flipped. At least one token arrives, so phases end after at most the flow's value. State is kept
in the shared folder between phases; the driver sees counts only.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import Graph, kept
from .graph import blocked, cut_edges


def network(edges: DataFrame) -> DataFrame:
    """src, dst, res: residual arcs of an undirected unit graph without flow."""
    return edges.select(F.col("u").alias("src"), F.col("v").alias("dst"), F.lit(1).alias("res")).unionByName(edges.select(F.col("v").alias("src"), F.col("u").alias("dst"), F.lit(1).alias("res")))


def reach(state: DataFrame, seeds: DataFrame, forward: bool = True, stop: DataFrame | None = None) -> tuple[DataFrame, bool]:
    """node_id, level, via of all nodes that residual arcs reach from seeds (or that reach them); ends with the level that meets stop."""
    a, b = ("src", "dst") if forward else ("dst", "src")
    arcs = state.filter("res > 0").select(F.col(a).alias("node_id"), F.col(b).alias("next"))
    seen = kept(seeds.select("node_id", F.lit(0).alias("level"), F.lit(None).cast("long").alias("via")).distinct(), "reach")
    front, level = seen, 0
    while True:
        level += 1
        met = front.select("node_id").join(arcs, "node_id").groupBy("next").agg(F.min("node_id").alias("via"))
        front = kept(met.select(F.col("next").alias("node_id"), F.lit(level).alias("level"), "via").join(seen, "node_id", "left_anti"), "reach")
        if front.isEmpty():
            return seen, False
        seen = seen.unionByName(front)
        if stop is not None and not front.join(stop, "node_id", "left_semi").isEmpty():
            return seen, True


def max_flow(state: DataFrame, sources: DataFrame, targets: DataFrame) -> tuple[DataFrame, int]:
    """The residual arcs of a maximum flow that extends the given one, and the units added."""
    state, units = kept(state, "flow"), 0
    while True:
        tree, found = reach(state, sources, stop=targets)
        if not found:
            return state, units
        tokens = tree.join(targets, "node_id", "left_semi").select(F.col("node_id").alias("token"), "node_id")
        passed = None
        while True:
            at = tokens.groupBy("node_id").agg(F.min("token").alias("token")).join(tree, "node_id")
            moving = kept(at.filter("via is not null").select("token", F.col("via").alias("src"), F.col("node_id").alias("dst")), "tokens")
            if moving.isEmpty():
                arrived = at.select("token")
                break
            passed = moving if passed is None else passed.unionByName(moving)
            tokens = moving.select("token", F.col("src").alias("node_id"))
        # arcs out of sources meet at their source, so that each source lets all its tokens pass
        first = passed.join(sources.withColumnRenamed("node_id", "src"), "src", "left_semi").select("token").distinct()
        arrived = first
        used = kept(passed.join(arrived, "token", "left_semi"), "paths")
        flips = used.select("src", "dst", F.lit(-1).alias("d")).unionByName(used.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit(1).alias("d")))
        change = flips.groupBy("src", "dst").agg(F.sum("d").alias("d"))
        state = kept(state.join(change, ["src", "dst"], "left").select("src", "dst", (F.col("res") + F.coalesce("d", F.lit(0))).cast("int").alias("res")), "flow")
        units += arrived.count()


def side_cut(g: Graph, own: DataFrame) -> DataFrame:
    """u, v of the edges that leave own(node_id): the source-side or target-side cut, from what the sources or targets reach."""
    return cut_edges(g.edges, g.nodes.select("node_id").join(own.select("node_id", F.lit(1).alias("side")).distinct(), "node_id", "left").fillna(0, ["side"]))


def trim_terminals(arcs: DataFrame, terms: DataFrame) -> DataFrame:
    """Terminals (node_id, term) with a neighbour of another kind; the others take part in no path."""
    other = terms.select(F.col("node_id").alias("dst"), F.col("term").alias("other"))
    around = arcs.join(terms.withColumnRenamed("node_id", "src"), "src").join(other, "dst", "left")
    inner = around.groupBy("src").agg(F.bool_and(F.coalesce(F.col("other") == F.col("term"), F.lit(False))).alias("inner"))
    return terms.join(inner.filter("inner").select(F.col("src").alias("node_id")), "node_id", "left_anti")


def flow_violations(state: DataFrame, capacity: DataFrame, sources: DataFrame, targets: DataFrame) -> DataFrame:
    """check_name, violations, checked: capacity, skew symmetry and conservation of a residual state."""
    flow = state.join(capacity, ["src", "dst"]).select("src", "dst", "cap", (F.col("cap") - F.col("res")).alias("f"))
    back = flow.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("f").alias("g"))
    ends = sources.union(targets).select(F.col("node_id").alias("src"))
    row = lambda name, df, bad: df.agg(F.lit(name).alias("check_name"), F.count(F.when(bad, 1)).alias("violations"), F.count("*").alias("checked"))
    net = flow.groupBy("src").agg(F.sum("f").alias("net")).join(ends, "src", "left_anti")
    return row("capacity", flow, (F.col("f") > F.col("cap")) | (F.abs("f") > 1)).unionByName(row("skew", flow.join(back, ["src", "dst"]), F.col("f") + F.col("g") != 0)).unionByName(row("conservation", net, F.col("net") != 0))


class BlockNet:
    """Residual arcs dealt to blocks, each of which a task can hold: the tier whose rounds are block crossings and not levels.

    arcs: block, src, dst, res, cap; an arc between blocks is in both. places: block, node_id. Searches run inside
    blocks in one task each and pass on what leaves them; the driver sees counts only."""

    TREE = "node_id long, depth long, via long, root long, block long"

    def __init__(self, arcs: DataFrame, places: DataFrame):
        self.arcs, self.places = arcs, places

    @classmethod
    def of(cls, g: Graph, capacity: DataFrame, block_edges: int) -> BlockNet:
        """capacity: src, dst, cap for both directions of g's edges."""
        edges, places = blocked(g, block_edges)
        both = edges.select("block", F.col("u").alias("src"), F.col("v").alias("dst")).unionByName(edges.select("block", F.col("v").alias("src"), F.col("u").alias("dst")))
        arcs = both.join(capacity, ["src", "dst"]).select("block", "src", "dst", F.col("cap").alias("res"), "cap")
        return cls(kept(arcs, "block-arcs"), places)

    def reach(self, seeds: DataFrame, forward: bool = True, closed: DataFrame | None = None, stop: DataFrame | None = None) -> tuple[DataFrame, bool]:
        """node_id, depth, via, root, block of what residual arcs reach from seeds (or what reaches them) without entering `closed`. Roots whose trees meet `stop` grow no further.

        A node that two blocks reach in one round keeps the smaller depth, so parents are less deep than their children."""
        start = seeds.select("node_id", F.lit(0).cast("long").alias("depth"), F.lit(None).cast("long").alias("via"), F.col("node_id").alias("root"), F.lit(-1).cast("long").alias("block"))
        seen = news = kept(start.distinct(), "tree")
        barred, met, rounds = None if closed is None else closed.select("node_id"), None, 0
        while True:
            asked = news.join(self.places.withColumnRenamed("block", "at"), "node_id").select("at", "node_id", "depth", "root", F.lit(True).alias("new"))
            hit = asked.select("at").distinct()
            # what a block must not enter again
            old = (seen if barred is None else seen.select("node_id").unionByName(barred)).join(self.places.withColumnRenamed("block", "at"), "node_id").join(hit, "at", "left_semi")
            marks = asked.unionByName(old.select("at", "node_id", F.lit(0).cast("long").alias("depth"), F.lit(0).cast("long").alias("root"), F.lit(False).alias("new")))
            arcs = self.arcs.filter("res > 0").select(F.col("block").alias("at"), "src", "dst").join(hit, "at", "left_semi")
            found = arcs.groupBy("at").cogroup(marks.groupBy("at")).applyInPandas(lambda key, a, b: _search(int(key[0]), a, b, forward), self.TREE)
            best = found.groupBy("node_id").agg(F.min(F.struct("depth", "via", "root", "block")).alias("t")).select("node_id", "t.*")
            news = kept(best.join(seen.select("node_id"), "node_id", "left_anti"), "tree")
            if news.isEmpty():
                return seen, met is not None
            rounds += 1
            seen = seen.unionByName(news)
            if rounds % 8 == 0:  # else plans grow with the rounds
                seen = kept(seen, "tree")
            if stop is not None:
                hits = news.join(stop, "node_id", "left_semi").select("root").distinct()
                hits = kept(hits if met is None else hits.unionByName(met), "met")
                if met is not None or not hits.isEmpty():
                    met, news = hits, news.join(hits, "root", "left_anti").select(news.columns)
                    if news.isEmpty():
                        return seen, True

    def lifts(self, tree: DataFrame) -> list[DataFrame]:
        """node_id, up: the ancestors 1, 2, 4 ... steps above, a root's being itself, so the last table has the roots. The tree's own roots may differ: a node's parent
        can be found by another block in the same round, with a smaller depth and another root."""
        up = kept(tree.select("node_id", F.coalesce("via", "node_id").alias("up"), "depth"), "lifts")
        out, steps = [up.select("node_id", "up")], up.agg(F.max("depth").alias("d")).first().d or 0
        for _ in range(max(0, steps - 1).bit_length()):
            out.append(kept(out[-1].join(out[-1].select(F.col("node_id").alias("up"), F.col("up").alias("next")), "up").select("node_id", F.col("next").alias("up")), "lifts"))
        return out

    def paths(self, lifts: list[DataFrame], ends: DataFrame) -> DataFrame:
        """src, dst of the tree arcs that lead to ends. A round doubles the steps that are known above each end."""
        at = ends.select("node_id")
        for up in lifts:
            at = kept(at.unionByName(at.join(up, "node_id").select(F.col("up").alias("node_id"))).distinct(), "walk")
        return at.join(lifts[0], "node_id").filter("up <> node_id").select(F.col("up").alias("src"), F.col("node_id").alias("dst"))

    def push(self, paths: DataFrame, forward: bool = True) -> None:
        """One unit along arcs src -> dst, or against them where the tree was found backward."""
        a, b = ("src", "dst") if forward else ("dst", "src")
        used = paths.select(F.col(a).alias("src"), F.col(b).alias("dst"))
        change = used.select("src", "dst", F.lit(-1).alias("d")).unionByName(used.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit(1).alias("d"))).groupBy("src", "dst").agg(F.sum("d").alias("d"))
        self.arcs = kept(self.arcs.join(change, ["src", "dst"], "left").select("block", "src", "dst", (F.col("res") + F.coalesce("d", F.lit(0))).cast("int").alias("res"), "cap"), "block-arcs")

    def augment(self, sources: DataFrame, targets: DataFrame, forward: bool = True, closed: DataFrame | None = None) -> tuple[int, DataFrame]:
        """Units of a maximum flow that extends the present one, and the last search's tree. Each phase pushes one unit for each root that
        meets a target: trees of different roots share no node."""
        units = 0
        while True:
            tree, found = self.reach(sources, forward, closed, targets)
            if not found:
                return units, tree
            lifts = self.lifts(tree)
            top = lifts[-1].withColumnRenamed("up", "root")
            ends = kept(tree.drop("root").join(targets, "node_id", "left_semi").join(top, "node_id").groupBy("root").agg(F.min(F.struct("depth", "node_id")).alias("e")).select("e.node_id"), "ends")
            self.push(self.paths(lifts, ends), forward)
            units += ends.count()

    def state(self) -> DataFrame:
        """src, dst, res: each arc once."""
        return self.arcs.select("src", "dst", "res").distinct()


def _search(block: int, arcs: pd.DataFrame, marks: pd.DataFrame, forward: bool) -> pd.DataFrame:
    """One block's breadth-first search from its new nodes, by depth; nodes that are marked already are not entered."""
    names = ["node_id", "depth", "via", "root", "block"]
    if not len(arcs) or not len(marks):
        return pd.DataFrame(columns=names)
    a, b = ("src", "dst") if forward else ("dst", "src")
    ids, place = np.unique(np.concatenate([arcs[a].to_numpy(np.int64), arcs[b].to_numpy(np.int64)]), return_inverse=True)
    tail, head = place[: len(arcs)], place[len(arcs) :]
    order = np.lexsort((head, tail))
    start, head = np.searchsorted(tail[order], np.arange(len(ids) + 1)).tolist(), head[order].tolist()
    known = {x: i for i, x in enumerate(ids.tolist())}
    depth, via, root = [-1] * len(ids), [-1] * len(ids), [0] * len(ids)
    waiting: dict[int, list[int]] = {}
    for x, d, r, new in sorted(zip(marks.node_id.tolist(), marks.depth.tolist(), marks.root.tolist(), marks.new.tolist(), strict=True), key=lambda m: not m[3]):
        i = known.get(x)
        if i is not None and depth[i] < 0:
            depth[i], root[i] = d, r
            if new:
                waiting.setdefault(d, []).append(i)
    out = []
    while waiting:
        d = min(waiting)
        for x in waiting.pop(d):
            for y in head[start[x] : start[x + 1]]:
                if depth[y] < 0:
                    depth[y], via[y], root[y] = d + 1, x, root[x]
                    out.append(y)
                    waiting.setdefault(d + 1, []).append(y)
    own = np.array(out, np.int64)
    return pd.DataFrame({"node_id": ids[own], "depth": np.array(depth, np.int64)[own], "via": ids[np.array(via, np.int64)[own]], "root": np.array(root, np.int64)[own], "block": block}) if out else pd.DataFrame(columns=names)
