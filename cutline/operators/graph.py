"""Graph preliminaries as DataFrame operations: normal form, arcs, degrees, subgraphs, cuts, components, distances."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import order as kernel
from ..model import Graph, kept, small, there

import numpy as np
import pandas as pd


def normalize_edges(pairs: DataFrame, a: str = "u", b: str = "v") -> DataFrame:
    """u < v, each edge once, no loops. Null ends are refused by the schema check, not dropped."""
    return pairs.filter(F.col(a) != F.col(b)).select(F.least(a, b).alias("u"), F.greatest(a, b).alias("v")).distinct()


def to_arcs(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("u").alias("src"), F.col("v").alias("dst")).unionByName(edges.select(F.col("v").alias("src"), F.col("u").alias("dst")))


def degrees(g: Graph) -> DataFrame:
    """node_id, degree; isolated nodes have 0."""
    counted = to_arcs(g.edges).groupBy(F.col("src").alias("node_id")).agg(F.count("*").alias("degree"))
    return g.nodes.select("node_id").join(counted, "node_id", "left").fillna(0, ["degree"])


def induced(g: Graph, keep: DataFrame) -> Graph:
    """The subgraph of the nodes in keep(node_id)."""
    ids = keep.select("node_id").distinct()
    edges = g.edges.join(ids.withColumnRenamed("node_id", "u"), "u", "left_semi").join(ids.withColumnRenamed("node_id", "v"), "v", "left_semi")
    return Graph(g.nodes.join(ids, "node_id", "left_semi"), edges.select("u", "v"))


def asymmetric_arcs(arcs: DataFrame) -> DataFrame:
    """Arcs without their reverse."""
    back = arcs.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    return arcs.join(back, ["src", "dst"], "left_anti")


def with_sides(edges: DataFrame, sides: DataFrame) -> DataFrame:
    """u, v, su, sv. sides: node_id, side."""
    return edges.join(sides.select(F.col("node_id").alias("u"), F.col("side").alias("su")), "u").join(sides.select(F.col("node_id").alias("v"), F.col("side").alias("sv")), "v")


def cut_edges(edges: DataFrame, sides: DataFrame) -> DataFrame:
    return with_sides(edges, sides).filter("su <> sv").select("u", "v")


def separator_violations(edges: DataFrame, sides: DataFrame) -> DataFrame:
    """Edges between the blocks 0 and 1 of a separator (2)."""
    return with_sides(edges, sides).filter("(su = 0 and sv = 1) or (su = 1 and sv = 0)").select("u", "v")


def is_balanced(large: Column, n: Column, eps_permille: Column) -> Column:
    """large <= ceil((1 + eps) * n / 2), in whole numbers with eps in thousandths."""
    return large * 2000 < (eps_permille + 1000) * n + 2000


#: Edges that a task holds at once while it looks for their forest or searches a block.
TASK_EDGES = 2_000_000


def forest(edges: DataFrame) -> DataFrame:
    """u, v with the same components as edges: each partition's edges, some at a time, give way to u -> smallest node of u's component among them."""

    def run(batches):
        held, size = [], 0

        def found(held):
            e = np.concatenate(held)
            ids, place = np.unique(e, return_inverse=True)
            place = place.reshape(-1, 2)
            label = kernel.component_labels(len(ids), place[:, 0], place[:, 1])
            own = label != np.arange(len(ids))
            return np.stack([ids[own], ids[label[own]]], 1)

        for batch in batches:
            held.append(batch[["u", "v"]].to_numpy(np.int64))
            size += len(batch)
            if size > TASK_EDGES:
                held = [found(held)]
                if len(held[0]) > size // 2:  # little to gain from this partition
                    yield pd.DataFrame(held[0], columns=["u", "v"])
                    held = []
                size = sum(map(len, held))
        if size:
            yield pd.DataFrame(found(held), columns=["u", "v"])

    return edges.select("u", "v").hint("rebalance").mapInPandas(run, "u long, v long")


def _is_star(arcs: DataFrame) -> bool:
    """Whether each u has one v, and no v is a u."""
    ends = arcs.select(F.col("u").alias("x"), F.lit(1).alias("out"), F.lit(0).alias("inn")).unionByName(arcs.select(F.col("v").alias("x"), F.lit(0).alias("out"), F.lit(1).alias("inn")))
    return ends.groupBy("x").agg(F.sum("out").alias("out"), F.max("inn").alias("inn")).filter("out > 1 or (out = 1 and inn = 1)").isEmpty()


def components(g: Graph) -> DataFrame:
    """node_id, component_id: the smallest node of each component.

    Partitions (of the size that the session advises) first replace their edges by forests; large-star and small-star rounds join the forests.
    Small graphs are one partition, whose forest is the answer; the plan is the same for all sizes."""
    arcs = kept(forest(g.edges), "cc")
    while not _is_star(arcs):
        arcs = kept(forest(_star_round(arcs)), "cc")
    label = arcs.select(F.col("u").alias("node_id"), F.col("v").alias("component_id"))
    return g.nodes.select("node_id").join(label, "node_id", "left").select("node_id", F.coalesce("component_id", "node_id").alias("component_id"))


def _star_round(arcs: DataFrame) -> DataFrame:
    both = arcs.select("u", "v").union(arcs.select("v", "u"))
    low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    # large star: higher neighbours hang on the least neighbour; small star: lower neighbours and the node itself do
    large = both.join(low, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    lower = large.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    least = lower.groupBy("u").agg(F.min("v").alias("m"))
    return lower.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", "m")).filter("u <> v").distinct()


def component_rounds(g: Graph) -> DataFrame:
    """As `components`, by star rounds alone: no Python, one shuffled join per round."""
    arcs = kept(g.edges.select("u", "v"), "cc")
    while True:
        new = kept(_star_round(arcs), "cc")
        if _is_star(new):
            break
        arcs = new
    label = new.select(F.col("u").alias("node_id"), F.col("v").alias("component_id"))
    return g.nodes.select("node_id").join(label, "node_id", "left").select("node_id", F.coalesce("component_id", "node_id").alias("component_id"))


def blocked(g: Graph, block_edges: int = TASK_EDGES) -> tuple[DataFrame, DataFrame]:
    """Edges by block and the blocks of each node: tiles of the plane of about block_edges edges, an edge across tiles in all of its ends'. About as many columns as rows of tiles, so that
    searches cross few of them. Nodes at one point are dealt by their id."""
    blocks = max(1, -(-g.edges.count() // block_edges))
    columns = math.isqrt(blocks - 1) + 1
    bounds = sorted(set(g.nodes.approxQuantile("x", [i / columns for i in range(1, columns)], 0.1 / columns))) if blocks > 1 else []
    rows = -(-blocks // (len(bounds) + 1))
    placed = g.nodes.select("node_id", "y", sum([(F.col("x") > b).cast("long") for b in bounds], F.lit(0).cast("long")).alias("column"))
    if rows > 1:
        split = placed.groupBy("column").agg(F.array_distinct(F.percentile_approx("y", [i / rows for i in range(1, rows)], max(10_000, 10 * rows))).alias("bounds"))
        split = kept(split, "tiles")
        tiles = split.agg(F.sum(F.size("bounds") + 1).alias("tiles")).first().tiles or 0
        placed = placed.join(small(split), "column").withColumn("row", F.size(F.filter("bounds", lambda b: b < F.col("y"))))
        tile = F.pmod(F.xxhash64("node_id"), F.lit(blocks)) if tiles < blocks // 2 else F.col("column") * rows + F.col("row")
    else:
        tile = F.col("column")
    place = placed.select("node_id", tile.cast("long").alias("block"))
    of = lambda c: place.select(F.col("node_id").alias(c), F.col("block").alias(f"b{c}"))
    both = g.edges.join(of("u"), "u").join(of("v"), "v")
    edges = kept(both.select(F.explode(F.array_distinct(F.array("bu", "bv"))).alias("block"), "u", "v"), "block-edges")
    return edges, kept(edges.select("block", F.col("u").alias("node_id")).union(edges.select("block", "v")).distinct(), "block-nodes")


def hop_dist(g: Graph, seeds: DataFrame, block_edges: int = TASK_EDGES) -> DataFrame:
    """node_id, dist from the nearest seed, of the nodes that are reached. Each block is searched in one task from the distances that reached it; rounds
    pass improved distances on to other blocks, until there are none."""
    edges, places = blocked(g, block_edges)

    def search(e: pd.DataFrame, s: pd.DataFrame) -> pd.DataFrame:
        if not len(s) or not len(e):
            return pd.DataFrame({"node_id": pd.Series(dtype="int64"), "dist": pd.Series(dtype="int64")})
        ids, place = np.unique(e[["u", "v"]].to_numpy(np.int64), return_inverse=True)
        place = place.reshape(-1, 2)
        n = len(ids)
        tail, head = np.concatenate([place[:, 0], place[:, 1]]), np.concatenate([place[:, 1], place[:, 0]])
        order = np.argsort(tail, kind="stable")
        start, head = np.searchsorted(tail[order], np.arange(n + 1)).tolist(), head[order].tolist()
        far = [1 << 60] * n
        waiting: dict[int, list[int]] = {}
        for x, d in zip(np.searchsorted(ids, s.node_id.to_numpy(np.int64)).tolist(), s.dist.tolist(), strict=True):
            if d < far[x]:
                far[x] = d
                waiting.setdefault(d, []).append(x)
        given = list(far)
        while waiting:
            d = min(waiting)
            for x in waiting.pop(d):
                if far[x] == d:
                    for y in head[start[x] : start[x + 1]]:
                        if far[y] > d + 1:
                            far[y] = d + 1
                            waiting.setdefault(d + 1, []).append(y)
        found = np.array(far, np.int64)
        better = found < np.array(given, np.int64)
        return pd.DataFrame({"node_id": ids[better], "dist": found[better]})

    dist = kept(seeds.select("node_id", F.lit(0).cast("long").alias("dist")).distinct(), "hops")
    news = dist
    while True:
        asked = news.join(places, "node_id")
        hit = asked.select("block").distinct()
        found = edges.join(hit, "block", "left_semi").groupBy("block").cogroup(asked.groupBy("block")).applyInPandas(lambda e, s: search(e, s), "node_id long, dist long")
        best = found.groupBy("node_id").agg(F.min("dist").alias("dist"))
        known = dist.withColumnRenamed("dist", "was")
        news = kept(best.join(known, "node_id", "left").filter("was is null or dist < was").select("node_id", "dist"), "hops-new")
        if news.isEmpty():
            return dist
        dist = kept(dist.unionByName(news).groupBy("node_id").agg(F.min("dist").alias("dist")), "hops")


def hop_rounds(g: Graph, seeds: DataFrame) -> DataFrame:
    """As `hop_dist`, without Python: a level is one join of the frontier."""
    arcs = to_arcs(g.edges)
    seen = kept(seeds.select("node_id", F.lit(0).cast("long").alias("dist")).distinct(), "bfs")
    front, d = seen, 0
    while not front.isEmpty():
        d += 1
        met = front.join(arcs, front.node_id == arcs.src).select(F.col("dst").alias("node_id")).distinct()
        front = kept(met.join(seen, "node_id", "left_anti").select("node_id", F.lit(d).cast("long").alias("dist")), "bfs")
        seen = seen.unionByName(front)
    return seen


def celled(g: Graph) -> tuple[DataFrame, DataFrame]:
    """Nodes and edges with cell_id, the component that they are in. A graph computes them once."""
    if g.cells is None or not there(g.cells[0]):
        label = kept(components(g), "cells")
        nodes = g.nodes.join(label, "node_id").withColumnRenamed("component_id", "cell_id")
        edges = g.edges.join(label.select(F.col("node_id").alias("u"), F.col("component_id").alias("cell_id")), "u")
        g.cells = kept(nodes, "cell-nodes"), kept(edges.select("cell_id", "u", "v"), "cell-edges")
    return g.cells


def cell_graph(nodes: pd.DataFrame, edges: pd.DataFrame) -> tuple[kernel.Graph, np.ndarray]:
    """A cell's kernel graph and its node ids, in id order."""
    nodes = nodes.sort_values("node_id")
    ids = nodes.node_id.to_numpy(np.int64)
    u, v = (np.searchsorted(ids, edges[c].to_numpy(np.int64)) for c in ("u", "v"))
    order = np.lexsort((v, u))
    return kernel.Graph(len(ids), u[order], v[order], nodes.x.to_numpy(np.int64), nodes.y.to_numpy(np.int64)), ids


def cogrouped(a: DataFrame, b: DataFrame, *by: str):
    """Both tables grouped by their keys. The number of partitions is set, as adaptive execution joins groups of few bytes into one task, however long each takes."""
    tasks = 4 * a.sparkSession.sparkContext.defaultParallelism
    return a.repartition(tasks, *by).groupBy(*by).cogroup(b.repartition(tasks, *by).groupBy(*by))


def per_cell(nodes: DataFrame, edges: DataFrame, work, schema: str | T.StructType, by: list[str] | None = None) -> DataFrame:
    """work(cell_id, kernel graph, ids) -> pandas rows, one task per cell."""
    by = by or ["cell_id"]

    def run(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        g, ids = cell_graph(a, b)
        return work(*(int(k) for k in key), g, ids)

    return nodes.groupBy(*by).cogroup(edges.groupBy(*by)).applyInPandas(run, schema)


def bicomponents(g: Graph) -> DataFrame:
    """cell_id, u, v, bicomp: a number for each edge's biconnected component within its cell."""
    nodes, edges = celled(g)

    def work(cell, k, ids):
        return pd.DataFrame({"cell_id": cell, "u": ids[k.u], "v": ids[k.v], "bicomp": kernel.bicomponents(k) if len(k.u) else np.zeros(0, np.int64)})

    return per_cell(nodes, edges, work, "cell_id long, u long, v long, bicomp long")


def preorder(g: Graph) -> DataFrame:
    """cell_id, node_id, pos: depth-first visit order from the cell's root, the smallest md5 of an id; shuffles ids as a common start."""
    nodes, edges = celled(g)

    def work(cell, k, ids):
        import hashlib

        near = k.lists()
        root = min(range(k.n), key=lambda i: hashlib.md5(str(ids[i]).encode()).hexdigest())
        seen, out, stack = [False] * k.n, [], [root]
        while stack:
            x = stack.pop()
            if not seen[x]:
                seen[x] = True
                out.append(x)
                stack.extend(y for y in reversed(sorted(near[x])) if not seen[y])
        return pd.DataFrame({"cell_id": cell, "node_id": ids[out], "pos": np.arange(len(out))})

    return per_cell(nodes, edges, work, "cell_id long, node_id long, pos long")


def midline_ranks(cells: DataFrame) -> DataFrame:
    """node_id, rank from node_id, gx, gy: nested grid lines, the one of more trailing zero bits ranked higher; ties by id."""
    from .geometry import global_rank

    zeros = lambda c: F.bit_count(F.expr(f"({c} + 1) & (-({c} + 1))") - 1)
    height = F.greatest(zeros("gx") * 2 + 1, zeros("gy") * 2)
    return global_rank(cells.select("node_id", height.alias("height")), ["height", "node_id"], "rank").select("node_id", "rank")
