"""Cutters over the cells of a graph: fronts, chosen cuts and separators."""

from __future__ import annotations

import time

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import cutter as kernel
from ..functions import multilevel, order
from ..functions.cutter import SweepParams
from ..functions.order import Splitter
from ..model import Graph, kept, small
from . import compiled
from .graph import cell_graph, celled, is_balanced, per_cell

CUT_SCHEMA = "cell_id long, config string, cutter int, step int, size long, small long, n long, grown string, rule string, connected boolean, units long"


def config(name: str, **more) -> Splitter:
    """SP4, SP8 ... (sweep), PP3, PP20 ... (pairs), BF (bands)."""
    if name.startswith("SP"):
        return Splitter("sweep", SweepParams(q=int(name[2:]), **more))
    if name.startswith("PP"):
        return Splitter("pairs", pairs=int(name[2:]), **more)
    if name == "BF":
        return Splitter("bands", SweepParams(q=4, **({"alpha": 0.2} | more)), style="edgecut")
    raise ValueError(name)


def connected_sides(g: order.Graph, side: np.ndarray) -> bool:
    label = order.component_labels(g.n, *(x[side[g.u] == side[g.v]] for x in (g.u, g.v)))
    return len(np.unique(label)) == len(np.unique(side))


def _rows(cell: int, name: str, cuts: list[kernel.Cut], units: int, connected: list[bool | None]) -> pd.DataFrame:
    out = [(cell, name, c.cutter, i, c.size, c.small, c.n, c.grown, c.rule, connected[i], units) for i, c in enumerate(cuts)]
    return pd.DataFrame(out, columns=[x.split()[0] for x in CUT_SCHEMA.split(", ")])


#: Cells of at least so many nodes have their cutters dealt to lanes, one task each.
LANE_NODES = 2000


def _laned(g: Graph, splitter: Splitter, lanes: int) -> tuple[DataFrame, DataFrame]:
    """Cells' nodes and edges with lanes and lane: large cells once for each lane."""
    nodes, edges = celled(g)
    large = kept(nodes.groupBy("cell_id").agg(F.count("*").alias("n")).filter(F.col("n") >= LANE_NODES).select("cell_id", F.lit(max(1, min(lanes, splitter.cutters))).alias("lanes")), "large-cells")
    table = small(large)

    def dealt(df):
        with_lanes = df.join(table, "cell_id", "left").withColumn("lanes", F.coalesce("lanes", F.lit(1)))
        return with_lanes.withColumn("lane", F.explode(F.sequence(F.lit(0), F.col("lanes") - 1)))

    return dealt(nodes), dealt(edges)


def cuts(g: Graph, name: str, splitter: Splitter | None = None, only_front: bool = True, bound: bool = False, least_nodes: int = 3, connected: bool = False, lanes: int = 8) -> DataFrame:
    """The cuts of each cell by a named configuration. Without `bound` no cutter depends on another, so a large cell's cutters are
    dealt to lanes; with it one task runs all cutters of a cell, interleaved exactly."""
    splitter = splitter or config(name)

    def ask(key, k, _):
        if k.n < least_nodes or not len(k.u):
            return None
        return compiled.packed(compiled.CUTS, k, splitter, range(key[2], splitter.cutters, key[1]), bound, only_front, connected=connected)

    def read(key, k, ids, _, answer):
        made, whether, units = compiled.read_cuts(answer, k.n)
        return _rows(key[0], name, made, units, whether).assign(lane=key[2])

    found = kept(compiled.asked(*_laned(g, splitter, 1 if bound else lanes), ["cell_id", "lanes", "lane"], ask, read, CUT_SCHEMA + ", lane int"), "cuts")
    spent = found.groupBy("cell_id", "lane").agg(F.max("units").alias("units")).groupBy("cell_id").agg(F.sum("units").alias("spent"))
    best = pareto(found) if only_front else found
    place = Window.partitionBy("cell_id").orderBy(*(["small"] if only_front else ["lane", "step"]))
    names = [x.split()[0] for x in CUT_SCHEMA.split(", ")]
    return best.join(spent, "cell_id").withColumn("step", F.row_number().over(place) - 1).withColumn("units", F.col("spent")).select(*names)


def growth(g: Graph, splitter: Splitter, lanes: int = 8) -> tuple[DataFrame, DataFrame]:
    """Fronts with the blocks of their cuts, without a row for each cut and node: (cell_id, cutter, grown, node_id, pos), where a side's nodes stand in the
    order in which it absorbed them (n for nodes that it never did) of the sides that have cuts of the front, and (cell_id, cutter, step, grown, size, small, n, upto): a cut's block are the nodes with pos < upto."""

    def ask(key, k, _):
        return compiled.packed(compiled.CUTS, k, splitter, range(key[2], splitter.cutters, key[1]), logs=True, brief=True) if len(k.u) else None

    def read(key, k, ids, _, answer):
        names = ["cell_id", "cutter", "grown", "node_id", "pos", "step", "size", "small", "n", "upto"]
        cuts, logs, cell = [], {}, key[0]
        for i, c in enumerate(compiled.read_cuts(answer, k.n)[0]):
            log, upto = c.held
            logs[c.cutter, c.grown] = log
            cuts.append((cell, c.cutter, c.grown, None, None, i, c.size, c.small, c.n, upto))
        parts = [pd.DataFrame(cuts, columns=names)]
        for (number, grown), log in logs.items():
            pos = np.full(k.n, k.n, np.int64)
            pos[log] = np.arange(len(log))
            parts.append(pd.DataFrame({"cell_id": cell, "cutter": number, "grown": grown, "node_id": ids, "pos": pos}).reindex(columns=names))
        return parts

    schema = "cell_id long, cutter int, grown string, node_id long, pos long, step int, size long, small long, n long, upto long"
    both = kept(compiled.asked(*_laned(g, splitter, lanes), ["cell_id", "lanes", "lane"], ask, read, schema), "growth")
    best = kept(pareto(both.filter("step is not null").drop("node_id", "pos")), "front")
    place = Window.partitionBy("cell_id").orderBy("small")
    sides = kept(best.select("cell_id", "cutter", "grown").distinct(), "front-sides")
    places = both.filter("step is null").select("cell_id", "cutter", "grown", "node_id", "pos").join(small(sides), ["cell_id", "cutter", "grown"], "left_semi")
    return places, best.withColumn("step", F.row_number().over(place) - 1)


def wide_cuts(g: Graph, params: SweepParams, budget: int = 8) -> DataFrame:
    """As `cuts` with `bound`, for few large cells: one task per cell and cutter. Rounds have a flow budget that doubles; between rounds a cutter
    is a row with its residual arcs and marks, and one whose flow can't improve its cell's best expansion so far doesn't go on."""
    splitter = Splitter("sweep", params)
    name = f"SP{params.q}"
    schema = f"{CUT_SCHEMA}, state binary"

    def rows(cell, own, kg_n, found, done):
        out = pd.DataFrame([(cell, name, c.cutter, i, c.size, c.small, c.n, c.grown, c.rule, None, own.units, None) for i, c in enumerate(found)], columns=[x.split()[0] for x in schema.split(", ")])
        if not done:
            out.loc[len(out)] = (cell, name, own.number, -1, own.flow, 0, kg_n, "", "open", None, own.units, own.dump())
        return out

    def begin(cell, of, lane, kg, ids, limit=budget):
        if kg.n < 3 or not len(kg.u):
            return pd.DataFrame(columns=[x.split()[0] for x in schema.split(", ")])
        net = kernel.Net.undirected(kg.n, kg.u, kg.v)
        sweep = kernel.sweep_order(kg.x, kg.y, np.arange(kg.n), kernel.directions(params.q)[lane])
        (own,) = kernel.sweep_cutters(net, [sweep], list(range(kg.n)), params, [lane])
        found = kernel.thinned(own.steps(limit))
        return rows(cell, own, kg.n, found, own.done)

    nodes, edges = celled(g)
    each = lambda df: df.withColumn("lanes", F.lit(params.q)).withColumn("lane", F.explode(F.sequence(F.lit(0), F.lit(params.q - 1))))
    done = kept(per_cell(each(nodes), each(edges), begin, schema, ["cell_id", "lanes", "lane"]), "wide-cuts")
    results = done.filter("step >= 0").drop("state")
    best = None
    while True:
        good = done.filter("step >= 0").filter(F.col("small") * 5 >= F.col("n")).select("cell_id", "size", "small")
        best = kept(choose_rows(good if best is None else good.unionByName(best)), "wide-best")
        waiting = done.filter("step < 0").join(best.select("cell_id", F.col("size").alias("b_size"), F.col("small").alias("b_small")), "cell_id", "left")
        waiting = waiting.filter(F.col("b_size").isNull() | (F.col("size") * F.col("b_small") < F.col("b_size") * F.floor(F.col("n") / 2))).drop("b_size", "b_small")
        if waiting.isEmpty():
            break
        budget *= 2

        def go_on(batches, limit=budget):
            for batch in batches:
                for cell, n, state in zip(batch.cell_id, batch.n, batch.state, strict=True):
                    own = kernel.Cutter.load(state)
                    yield rows(cell, own, n, kernel.thinned(own.steps(limit)), own.done)

        done = kept(waiting.repartition("cell_id", "cutter").mapInPandas(go_on, schema), "wide-cuts")
        results = results.unionByName(done.filter("step >= 0").drop("state"))
    return pareto(results)


def choose_rows(found: DataFrame) -> DataFrame:
    """cell_id, size, small of least expansion."""
    key = F.struct((F.col("size").cast("decimal(38,18)") / F.col("small").cast("decimal(20,0)")).alias("e"), (-F.col("small")).alias("s"))
    return found.groupBy("cell_id").agg(F.min_by(F.struct("size", "small"), key).alias("c")).select("cell_id", "c.size", "c.small")


def cut_report(found: DataFrame, config: str = "config") -> DataFrame:
    """config, eps_permille, achieved, size as a table prints them: the reached imbalance in per cent with one place, "<0.1" for a smaller one, "0.0" for none; a cut that
    misses its demand has its size in brackets, and a refused or missing one a dash. found: config, eps_permille, size, small, n and, if known, missed, refused."""
    missed = F.coalesce(F.col("missed"), F.lit(False)) if "missed" in found.columns else F.lit(False)
    large = F.col("n") - F.col("small")
    # the imbalance in thousandths over perfect halves, as a whole number
    excess = large * 2 - F.col("n") - F.col("n") % 2
    percent = F.when(excess <= 0, "0.0").when(excess * 1000 < F.col("n"), "<0.1").otherwise(F.format_string("%.1f", F.lit(100.0) * excess / F.col("n")))
    size = F.when(missed, F.concat(F.lit("("), F.col("size").cast("string"), F.lit(")"))).otherwise(F.col("size").cast("string"))
    return found.select(F.col(config).alias("config"), "eps_permille", F.when(F.col("size").isNull(), "-").otherwise(percent).alias("achieved"), F.coalesce(size, F.lit("-")).alias("size"))


def pareto(found: DataFrame, by: tuple[str, ...] = ("cell_id",)) -> DataFrame:
    """Cuts that no other beats in size and balance: a running minimum of the size by falling balance."""
    w = Window.partitionBy(*by).orderBy(F.desc("small"), "size", "cutter", "step")
    least = F.min("size").over(w.rowsBetween(Window.unboundedPreceding, -1))
    return found.filter("small > 0").withColumn("least", least).filter("least is null or size < least").drop("least")


def choose(found: DataFrame, by: tuple[str, ...] = ("cell_id",)) -> DataFrame:
    """Per cell the cut of least expansion with at least a fifth on the smaller side, compared as whole numbers; ties to the better balance."""
    good = found.filter(F.col("small") * 5 >= F.col("n"))
    # sizes and blocks fit 31 bits each, so the quotient of 18 places tells any two expansions apart
    key = F.struct((F.col("size").cast("decimal(38,18)") / F.col("small").cast("decimal(20,0)")).alias("e"), (-F.col("small")).alias("s"), F.col("size"))
    return good.groupBy(*by).agg(F.min_by(F.struct("size", "small", "n"), key).alias("c")).select(*by, "c.size", "c.small", "c.n")


def best_within(found: DataFrame, eps_permille: list[int], by: tuple[str, ...] = ("cell_id",)) -> DataFrame:
    """eps_permille, size, small, n: the smallest cut within each demanded imbalance; among equals the most balanced."""
    spark = found.sparkSession
    demanded = F.broadcast(spark.createDataFrame([(e,) for e in eps_permille], "eps_permille long"))
    large = F.col("n") - F.col("small")
    fits = found.join(demanded, is_balanced(large, F.col("n"), F.col("eps_permille")))
    return fits.groupBy(*by, "eps_permille").agg(F.min(F.struct("size", (-F.col("small")).alias("s"), "n")).alias("c")).select(*by, "eps_permille", "c.size", (-F.col("c.s")).alias("small"), "c.n")


def multilevel_cuts(g: Graph, eps_permille: list[int], presets: list[str], seed: int = 0, enforce: bool = True, tries: int = 4, start: DataFrame | None = None) -> DataFrame:
    """cell_id, config, eps_permille, size, small, n, missed, refused, connected, seconds by the multilevel and natural-cut partitioners: one task for each cell, configuration
    and demanded imbalance. start: node_id, pos of an order that numbers a cell's nodes before the partitioners see them (all get the same)."""
    names = ["cell_id", "config", "eps_permille", "size", "small", "n", "missed", "refused", "connected", "seconds"]
    nodes, edges = celled(g)
    nodes = nodes.join(start.select("node_id", "pos"), "node_id") if start is not None else nodes.withColumn("pos", F.col("node_id"))
    asked = F.explode(F.array(*[F.struct(F.lit(p).alias("config"), F.lit(e).cast("long").alias("eps_permille")) for p in presets for e in eps_permille])).alias("asked")
    each = lambda df: df.select("*", asked).select(*df.columns, "asked.config", "asked.eps_permille")
    by = ["cell_id", "config", "eps_permille"]

    def run(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        k, _ = cell_graph(a, b)
        if k.n < 3 or not len(k.u):
            return pd.DataFrame(columns=names)
        began = time.perf_counter()
        place = np.argsort(np.argsort(a.sort_values("node_id").pos.to_numpy(), kind="stable"), kind="stable")
        side, info = multilevel.bisect(k.n, place[k.u].tolist(), place[k.v].tolist(), int(key[2]) / 1000, str(key[1]), seed, tries, enforce)
        took = time.perf_counter() - began
        if side is None:
            return pd.DataFrame([(int(key[0]), key[1], int(key[2]), None, None, k.n, False, True, None, took)], columns=names)
        own = np.array(side)[place]
        return pd.DataFrame([(int(key[0]), key[1], int(key[2]), info["cut"], k.n - info["large"], k.n, info["missed"], False, connected_sides(k, own), took)], columns=names)

    return each(nodes).groupBy(*by).cogroup(each(edges).groupBy(*by)).applyInPandas(run, "cell_id long, config string, eps_permille long, size long, small long, n long, missed boolean, refused boolean, connected boolean, seconds double")


def pair_cuts(g: Graph, pairs: DataFrame, only_front: bool = True) -> DataFrame:
    """Cuts from handpicked terminal sets, which travel with their nodes. pairs: cutter, node_id, term (1 source, 2 target)."""
    nodes, edges = celled(g)
    own = pairs.groupBy("node_id").agg(F.collect_list(F.struct("cutter", "term")).alias("terms"))  # a node's terms, one for each cutter
    marked = nodes.join(own, "node_id", "left")

    def ask(key, k, a):
        sets: dict[int, tuple[list[int], list[int]]] = {}
        for at, terms in enumerate(a.terms):
            for t in terms if terms is not None else ():
                sets.setdefault(t["cutter"], ([], []))[t["term"] - 1].append(at)
        good = {i: s for i, s in sorted(sets.items()) if s[0] and s[1]}
        return compiled.packed(compiled.CUTS, k, Splitter("pairs"), list(good), only_front=only_front, connected=True, sets=list(good.values())) if good else None

    def read(key, k, ids, _, answer):
        made, whether, units = compiled.read_cuts(answer, k.n)
        return _rows(key[0], "PP", made, units, whether)

    return compiled.asked(marked, edges, ["cell_id"], ask, read, CUT_SCHEMA)


def chosen_sides(g: Graph, splitter: Splitter) -> DataFrame:
    """cell_id, node_id, side (0, 1, 2 = separator) of each cell's chosen separator."""

    schema = "cell_id long, node_id long, side int"

    def rows(cell, ids, label):
        return pd.DataFrame({"cell_id": cell, "node_id": ids, "side": label.astype(np.int32)})

    def work(cell, k, ids):
        return rows(cell, ids, order.separate(k, splitter) if k.n >= 3 and len(k.u) else np.zeros(k.n, np.int8))

    nodes, edges = celled(g)
    if not compiled.knows(splitter):
        return per_cell(nodes, edges, work, schema)
    ask = lambda key, k, _: compiled.packed(compiled.SEPARATE, k, splitter) if k.n >= 3 and len(k.u) else None
    return compiled.asked(nodes, edges, ["cell_id"], ask, lambda key, k, ids, _, answer: rows(key[0], ids, np.zeros(k.n, np.int8) if answer is None else np.frombuffer(answer, np.int8)), schema)


def landmarks(g: Graph) -> Graph:
    """A graph without coordinates gets hop distances to two far landmarks as coordinates."""

    def work(cell, k, ids):
        near = kernel.Net.undirected(k.n, k.u, k.v)
        first = near.hops([0])
        a = max(range(k.n), key=lambda i: (first[i], -i))
        da = near.hops([a])
        b = max(range(k.n), key=lambda i: (da[i], -i))
        db = near.hops([b])
        return pd.DataFrame({"node_id": ids, "x": [1000 * (p - q) for p, q in zip(da, db, strict=True)], "y": [1000 * (p + q) for p, q in zip(da, db, strict=True)]})

    nodes, edges = celled(g)
    return Graph(per_cell(nodes, edges, work, "node_id long, x long, y long"), g.edges)
