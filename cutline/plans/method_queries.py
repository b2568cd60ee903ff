"""Queries of the cutters, fronts, separators and orders."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import cutter as kernel
from ..functions import multilevel, order
from ..functions.cutter import SweepParams
from ..model import Graph, kept, wide
from ..operators import cutters, dissect
from ..operators import graph as ops
from ..sources import graphs
from .catalog import query, zeros
from .graph_queries import ARCS, CUST_N, EMB_N, NAT, PART, PART_N, SUPP


def front_query(graph: str, name: str):
    def run(spark, sf_dir):
        return cutters.cuts(graphs.graph(spark, sf_dir, graph), name)

    return run


def front_checks(g: Graph, splitter):
    """check_name, violations, checked: fronts cover all nodes, sizes are recounted from edges, blocks too, and fronts strictly improve.

    A cutter's cuts are few numbers, the places where their blocks end. A node is in the blocks that end after its place and an edge is cut by those that end
    between its two; so counts by number of ends before a place, and their running sums over the cuts, recount all cuts at once."""
    places, found = cutters.growth(g, splitter)
    found = kept(found, "fronts")
    keys = ["cell_id", "cutter", "grown"]
    n = g.nodes.agg(F.count("*").alias("checked"))
    ends = found.groupBy(*keys).agg(F.array_sort(F.collect_set("upto")).alias("ends"))
    side = F.struct("cutter", "grown", F.size(F.filter("ends", lambda x: x <= F.col("pos"))).alias("i"))
    # a row for each node: all nodes of a cell have places on the same sides, so the lists of an edge's ends stand side by side
    lists = kept(places.join(ends, keys).groupBy("cell_id", "node_id").agg(F.array_sort(F.collect_list(side)).alias("sides")), "places")
    placed = lists.select("cell_id", F.explode("sides").alias("s")).select("cell_id", "s.*")
    a, b = (lists.select("cell_id", F.col("node_id").alias(c), F.col("sides").alias(f"s{c}")) for c in ("u", "v"))
    pairs = F.explode(F.filter(F.arrays_zip("su", "sv"), lambda x: ~x["su"].eqNullSafe(x["sv"]))).alias("x")
    apart = g.edges.join(wide(a), "u").join(wide(b), ["cell_id", "v"]).select("cell_id", pairs).select("cell_id", "x.su.cutter", "x.su.grown", F.col("x.su.i").alias("iu"), F.col("x.sv.i").alias("iv"))
    event = lambda df, i, d, kind: df.select(*keys, i.alias("i"), F.lit(d).alias("d"), F.lit(kind).alias("kind"))
    counted = event(apart, F.least("iu", "iv"), 1, "edges").unionByName(event(apart, F.greatest("iu", "iv"), -1, "edges")).unionByName(event(placed, F.col("i"), 1, "nodes"))
    cut = found.select(*keys, "step", F.col("upto")).join(ends, keys).select(*keys, "step", (F.array_position("ends", F.col("upto")) - 1).cast("int").alias("j"))
    sums = cut.join(counted.groupBy(*keys, "kind", "i").agg(F.sum("d").alias("d")), keys).filter("i <= j").groupBy("cell_id", "step").agg(F.sum(F.when(F.col("kind") == "edges", F.col("d")).otherwise(0)).alias("recount"), F.sum(F.when(F.col("kind") == "nodes", F.col("d")).otherwise(0)).alias("ones"))
    each = found.join(sums, ["cell_id", "step"], "left")
    w = Window.partitionBy("cell_id").orderBy("step")
    marked = kept(each.withColumn("before", F.lag("size").over(w)).withColumn("less", F.lag("small").over(w)), "recount")
    bad = {
        "cut_recount": F.coalesce("recount", F.lit(-1)) != F.col("size"),
        "block_recount": F.coalesce(F.least("ones", F.col("n") - F.col("ones")), F.lit(-1)) != F.col("small"),
        "front_strict": F.coalesce((F.col("before") >= F.col("size")) | (F.col("less") >= F.col("small")), F.lit(False)),
    }
    cover = lists.select("node_id").distinct().agg(F.count("*").alias("covered"))
    rows = [marked.agg(F.lit(k).alias("check_name"), F.count(F.when(v, 1)).alias("violations")).crossJoin(n) for k, v in bad.items()]
    rows.append(cover.crossJoin(n).select(F.lit("cover").alias("check_name"), (F.col("checked") - F.col("covered")).alias("violations"), "checked"))
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out.select("check_name", "violations", "checked")


_CHECKS = ["cut_recount", "block_recount", "front_strict", "cover"]


def _checked(graph, name, splitter=None):
    return lambda spark, sf_dir: front_checks(graphs.graph(spark, sf_dir, graph), splitter or cutters.config(name))


for _name in ("SP4", "SP8", "SP12", "SP16", "PP3", "PP20"):
    query(f"{_name.lower()}_front", zeros(_CHECKS, f"select count(*) from ({CUST_N}) n"))(_checked("cust", _name))
query("pp100_front", zeros(_CHECKS, f"select count(*) from ({CUST_N}) n"))(_checked("cust", "PP100"))
query("bandflow_front", zeros(_CHECKS, f"select count(*) from ({CUST_N}) n"))(_checked("cust", "BF"))
query("sp8_front_emb", zeros(_CHECKS, f"select count(*) from ({EMB_N}) n"))(_checked("emb", "SP8"))
query("cut_schedule_front", zeros(_CHECKS, f"select count(*) from ({CUST_N}) n"))(_checked("cust", "SP4", order.Splitter("sweep", SweepParams(q=4), schedule="cut")))


@query("landmark_front_users", zeros(_CHECKS, f"with e as ({graphs.duck('users', 'edges')}) select count(*) from (select u from e union select v from e) n"))
def landmark_front_users(spark, sf_dir):
    """A graph without coordinates: hop distances to two landmarks stand in for them."""
    g = graphs.graph(spark, sf_dir, "users")
    return front_checks(cutters.landmarks(Graph(kept(g.nodes), kept(g.edges))), cutters.config("SP4"))


_OPTIMA = f"with e as ({NAT}), m as (select cast(range as bigint) as mask from range(1, 65535)), c as (select mask, sum(case when ((mask >> u) & 1) <> ((mask >> v) & 1) then 1 else 0 end) as size from m, e group by mask)"


@query("bandflow_cuts", f"""{_OPTIMA}, b as (select k, bit_or(case when pos < 3 then cast(1 as bigint) << node_id else 0 end) as s, bit_or(case when pos >= 13 then cast(1 as bigint) << node_id else 0 end) as t from (
    select d.k, n.node_id, row_number() over (partition by d.k order by x * c + y * s, node_id) - 1 as pos from ({graphs.duck('nat', 'nodes')}) n, ({' union all '.join(f'select {k} as k, {c} as c, {s} as s' for k, (c, s) in enumerate(kernel.directions(4)))}) d) q group by k)
    select k as cutter, cast(min(size) as bigint) as size from b, c where (mask & s) = s and (mask & t) = 0 group by k""")
def bandflow_cuts(spark, sf_dir):
    """The four band flows on the 4 x 4 lattice have the sizes of minimum cuts between their bands."""
    found = cutters.cuts(graphs.graph(spark, sf_dir, "nat"), "BF", only_front=False)
    return found.select("cutter", "size")


_TRACE = [(2, 0x1), (2, 0x8000), (3, 0x3), (3, 0x8800), (4, 0x7), (4, 0x8880), (4, 0xF), (5, 0x3F), (5, 0xCCC0), (6, 0xECC0), (6, 0x33F)]


@query("pierce_trace_nat", " union all ".join(f"select {i} as step, cast({s} as bigint) as size, cast({m} as bigint) as mask" for i, (s, m) in enumerate(_TRACE)))
def pierce_trace_nat(spark, sf_dir):
    """Each cut of a pair-pierce run from corner to corner, as found by enumerating all bipartitions under the tie rules."""

    def work(cell, k, ids):
        own = kernel.pair_cutters(kernel.Net.undirected(k.n, k.u, k.v), [([0], [15])], list(range(k.n)))
        found = kernel.interleave(own, trace=True)
        return pd.DataFrame([(i, c.size, int(sum(1 << int(ids[x]) for x, b in enumerate(c.side) if b))) for i, c in enumerate(found)], columns=["step", "size", "mask"])

    nodes, edges = ops.celled(graphs.graph(spark, sf_dir, "nat"))
    return ops.per_cell(nodes, edges, work, "step int, size long, mask long")


def _grown(k, own: list[int], other: bool):
    """A kernel cutter from 0 to 15 whose source side holds the nodes `own`; other: whether the target side reaches all nodes."""
    cutter = kernel.Cutter(kernel.Net.undirected(k.n, k.u, k.v), [0], [15], list(range(k.n)))
    cutter.net.cap_list = cutter.net.cap.tolist()
    for x in own:
        cutter.reached[1][x] = 1
    cutter.waiting[1] = list(own)
    cutter._absorb(1)
    cutter.reached[2] = bytearray([int(other)] * k.n)
    return cutter


@query("candidates_nat", f"with e as ({NAT}), a as ({ARCS}) select distinct dst as node_id from a where src in (0, 1, 4) and dst not in (0, 1, 4) and dst <> 15")
def candidates_nat(spark, sf_dir):
    """The kernel's piercing candidates where the source side holds 0, 1 and 4: outer ends of cut edges that aren't targets."""

    def work(cell, k, ids):
        cutter = _grown(k, [0, 1, 4], True)
        return pd.DataFrame({"node_id": [int(ids[y]) for y in cutter.edge[1] if cutter.term[y] != 2]})

    return ops.per_cell(*ops.celled(graphs.graph(spark, sf_dir, "nat")), work, "node_id long")


@query("pierce_choice", f"""with recursive e as ({NAT}), a as ({ARCS}), s(node_id, d) using key (node_id) as (select cast(0 as bigint), 0 union select a.dst, min(s.d + 1) from s join a on a.src = s.node_id left join recurring.s r on r.node_id = a.dst where r.d is null group by a.dst),
    t(node_id, d) using key (node_id) as (select cast(15 as bigint), 0 union select a.dst, min(t.d + 1) from t join a on a.src = t.node_id left join recurring.t r on r.node_id = a.dst where r.d is null group by a.dst)
    select c.node_id, cast(t.d - s.d as bigint) as score from (select unnest([2, 5, 8]) as node_id) c join s on s.node_id = c.node_id join t on t.node_id = c.node_id order by 2, 1 limit 1""")
def pierce_choice(spark, sf_dir):
    """The kernel's choice among the candidates 2, 5, 8, all of which the target side reaches: least dist(p, t) - dist(s, p), then the smallest id."""

    def work(cell, k, ids):
        cutter = _grown(k, [0, 1, 4], True)
        _, (x,), _ = cutter._pierce(1, 3, cutter.reached[2])
        return pd.DataFrame({"node_id": [int(ids[x])], "score": [cutter.from_t[x] - cutter.from_s[x]]})

    return ops.per_cell(*ops.celled(graphs.graph(spark, sf_dir, "nat")), work, "node_id long, score long")


@query("avoid_augmenting", "select 'free' as rule, cast(2 as bigint) as node_id")
def avoid_augmenting(spark, sf_dir):
    """Where the target side reaches 5 and 8 only, the candidate 2 leaves the flow maximal and is taken whatever its distances."""

    def work(cell, k, ids):
        cutter = _grown(k, [0, 1, 4], False)
        cutter.reached[2][5] = cutter.reached[2][8] = 1
        rule, (x,), _ = cutter._pierce(1, 3, cutter.reached[2])
        return pd.DataFrame({"rule": [rule], "node_id": [int(ids[x])]})

    return ops.per_cell(*ops.celled(graphs.graph(spark, sf_dir, "nat")), work, "rule string, node_id long")


def _line(n: int) -> kernel.Cutter:
    """A kernel cutter on n nodes in sweep order, without edges; the first and last twentieth are its seeds."""
    return kernel.sweep_cutters(kernel.Net.undirected(n, np.zeros(0, np.int64), np.zeros(0, np.int64)), [np.arange(n)], list(range(n)), SweepParams())[0]


_NATIONS = "n as (select c_nationkey as nation, count(*) as n from customer group by 1), m as (select nation, n, n // 4 as most, least(greatest(n // 20, 1), n // 2) as seeds from n)"


@query("bulk_steps", f"""with {_NATIONS}, r as (select *, i * n // 50 as have from m, (select cast(range as bigint) as i from range(25)) i), s as (select *, cast(0.05 as double) * (cast(0.95 as double) * n / 2 - have) as raw from r)
    select nation, have, case when have > cast(0.4 as double) * n or raw <= 0 then 0 else least(greatest(1, cast(floor(raw) as bigint)), greatest(most - seeds, 0)) end as step from s""")
def bulk_steps(spark, sf_dir):
    """The kernel's bulk steps with the default parameters in cells of as many nodes as nations have customers, by what a side holds: fiftieths of the cell."""

    def run(batches):
        for batch in batches:
            out = []
            for nation, n in zip(batch.nation, batch.n.tolist(), strict=True):
                cutter = _line(n)
                for i in range(25):
                    cutter.next[1] = 0
                    out.append((nation, i * n // 50, len(cutter._bulk(1, i * n // 50))))
            yield pd.DataFrame(out, columns=["nation", "have", "step"])

    return _nations(spark, sf_dir).mapInPandas(run, "nation int, have long, step long")


@query("bulk_limits", f"""with {_NATIONS}, t as (select *, greatest(most - seeds, 0) as taken from m) select nation, 'S' as side, taken, case when taken > 0 then most - 1 else -1 end as last from t
    union all select nation, 'T', taken, case when taken > 0 then n - most else -1 end from t""")
def bulk_limits(spark, sf_dir):
    """Bulk steps in cells of as many nodes as nations have customers: those of either side end with the first quarter of its sweep order, a fifth of which its seeds took; the target side's go the other way."""

    def run(batches):
        for batch in batches:
            out = []
            for nation, n in zip(batch.nation, batch.n, strict=True):
                for side in (1, 2):
                    cutter, taken = _line(int(n)), []
                    while step := cutter._bulk(side, 0):
                        taken += step
                    out.append((nation, "ST"[side - 1], len(taken), taken[-1] if taken else -1))
            yield pd.DataFrame(out, columns=["nation", "side", "taken", "last"])

    return _nations(spark, sf_dir).mapInPandas(run, "nation int, side string, taken long, last long")


def _nations(spark, sf_dir):
    """nation, n: how many customers it has."""
    return graphs.read(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count("*").alias("n"))


_MADE = "select o_custkey as cell_id, cast(round(o_totalprice * 100) as bigint) % 50 + 1 as size, o_orderkey % 51 as small from orders"


def _made(spark, sf_dir):
    """Orders as cuts of cells of 100 nodes, a cell for each customer: many sizes, balances and ties."""
    o = graphs.read(spark, sf_dir, "orders")
    size, small = F.round(F.col("o_totalprice") * 100).cast("long") % 50 + 1, F.col("o_orderkey") % 51
    return o.select(F.col("o_custkey").alias("cell_id"), (F.col("o_orderkey") % 8).cast("int").alias("cutter"), F.col("o_orderkey").alias("step"), size.alias("size"), small.alias("small"), F.lit(100).cast("long").alias("n"))


@query("pareto_fixture", f"""with c as (select cell_id, small, min(size) as size from ({_MADE}) q where small > 0 group by 1, 2), b as (select *, min(size) over (partition by cell_id order by small desc rows between unbounded preceding and 1 preceding) as least from c)
    select cell_id, size, small from b where least is null or size < least""")
def pareto_fixture(spark, sf_dir):
    return cutters.pareto(_made(spark, sf_dir)).select("cell_id", "size", "small")


@query("choose_cut", f"""with c as ({_MADE}), k as (select *, row_number() over (partition by cell_id order by cast(size as double) / small, small desc) as k from c where small >= 20) select cell_id, size, small from k where k = 1""")
def choose_cut(spark, sf_dir):
    return cutters.choose(_made(spark, sf_dir)).select("cell_id", "size", "small")


@query("best_eps_nat", f"""{_OPTIMA}, l as (select size, greatest(bit_count(mask), 16 - bit_count(mask)) as large from c), e2 as (select unnest([0, 100, 300, 500]) as eps)
    select cast(eps as bigint) as eps_permille, cast(min(size) as bigint) as size from e2, l where large <= ((eps + 1000) * 16 + 1999) // 2000 group by eps""")
def best_eps_nat(spark, sf_dir):
    """Best cuts within demanded imbalances on the 4 x 4 lattice are the true optima."""
    g = graphs.graph(spark, sf_dir, "nat")
    both = cutters.cuts(g, "SP8").unionByName(cutters.cuts(g, "PP20"))
    return cutters.best_within(both, [0, 100, 300, 500]).select("eps_permille", "size")


@query("wide_equals_local", "select cast(0 as bigint) as differences")
def wide_equals_local(spark, sf_dir):
    """One task per cutter, in rounds of doubling budgets, finds the expansion that one task for all cutters finds."""
    g = graphs.graph(spark, sf_dir, "cust")
    a = cutters.choose(cutters.cuts(g, "SP4")).select("cell_id", "size", "small")
    b = cutters.choose(cutters.wide_cuts(g, SweepParams(q=4))).select("cell_id", "size", "small")
    return a.exceptAll(b).unionByName(b.exceptAll(a)).agg(F.count("*").alias("differences"))


@query("bound_equals_free", "select cast(0 as bigint) as differences")
def bound_equals_free(spark, sf_dir):
    """Cutters that stop when they can't improve the best expansion find the same least expansion as cutters that run to their ends."""
    g = graphs.graph(spark, sf_dir, "cust")
    a, b = (cutters.choose(cutters.cuts(g, "SP8", bound=x)).select("cell_id", F.col("size").alias(f"size{x}"), F.col("small").alias(f"small{x}")) for x in (False, True))
    # as whole numbers: rows that hold one quotient as a decimal were not always found equal
    same = F.col("sizeFalse") * F.col("smallTrue") == F.col("sizeTrue") * F.col("smallFalse")
    return a.join(b, "cell_id", "full").agg(F.count(F.when(~F.coalesce(same, F.lit(False)), 1)).alias("differences"))


@query("bandflow_first_nat", f"{_OPTIMA}, b as (select k, bit_or(case when pos < 3 then cast(1 as bigint) << node_id else 0 end) as s, bit_or(case when pos >= 13 then cast(1 as bigint) << node_id else 0 end) as t from (" + f"""
    select d.k, n.node_id, row_number() over (partition by d.k order by x * c + y * s, node_id) - 1 as pos from ({graphs.duck('nat', 'nodes')}) n, ({' union all '.join(f'select {k} as k, {c} as c, {s} as s' for k, (c, s) in enumerate(kernel.directions(4)))}) d) q group by k)
    select cast(min(size) as bigint) as size from b, c where (mask & s) = s and (mask & t) = 0""")
def bandflow_first_nat(spark, sf_dir):
    """Interleaved band flows: the first direction whose flow is maximal has the smallest cut of all."""

    def work(cell, k, ids):
        found, _ = order.cuts_of(k, cutters.config("BF"), False, best_only=True)
        return pd.DataFrame({"size": [c.size for c in found]})

    return ops.per_cell(*ops.celled(graphs.graph(spark, sf_dir, "nat")), work, "size long")


@query("cut_report", """with o as (select *, 1000 + o_custkey as n, (o_orderkey % 13) * (o_orderkey % 13) as off from orders), c as (select *, 2 * off as excess, cast(round(o_totalprice * 100) as bigint) % 90 + 1 as size from o),
    t as (select *, (2000 * excess + n) // (2 * n) as tenths from c) select o_orderpriority as config, (o_orderkey % 10) * 100 as eps_permille,
    case when o_orderstatus = 'F' then '-' when excess = 0 then '0.0' when excess * 1000 < n then '<0.1' else (tenths // 10) || '.' || (tenths % 10) end as achieved,
    case o_orderstatus when 'F' then '-' when 'P' then '(' || size || ')' else cast(size as varchar) end as size from t""")
def cut_report(spark, sf_dir):
    """How cuts stand in a table: less than a tenth of a per cent, missed demands, refusals. Orders stand for cuts, pending ones for missed demands and finished ones for refusals."""
    o = graphs.read(spark, sf_dir, "orders").withColumn("n", F.lit(1000) + F.col("o_custkey")).withColumn("refused", F.col("o_orderstatus") == "F")
    answered = lambda c: F.when(~F.col("refused"), c)
    size = F.round(F.col("o_totalprice") * 100).cast("long") % 90 + 1
    small = F.expr("n div 2 - (o_orderkey % 13) * (o_orderkey % 13)")
    made = o.select(F.col("o_orderpriority").alias("config"), (F.col("o_orderkey") % 10 * 100).alias("eps_permille"), answered(size).alias("size"), answered(small).alias("small"), "n", (F.col("o_orderstatus") == "P").alias("missed"), "refused")
    return cutters.cut_report(made)


@query("handpicked_cut", zeros(["found", "terminals_apart"], f"select count(*) from ({CUST_N}) n"))
def handpicked_cut(spark, sf_dir):
    """Three corner countries against the central one."""
    g = graphs.graph(spark, sf_dir, "cust")
    c = graphs.read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("node_id"), F.col("c_nationkey").alias("nk"))
    terms = c.filter("nk in (0, 4, 20, 12)").select(F.lit(0).alias("cutter"), "node_id", F.when(F.col("nk") == 12, 2).otherwise(1).alias("term"))
    found = cutters.pair_cuts(g, terms)
    n = g.nodes.agg(F.count("*").alias("checked"))
    count = found.agg(F.count("*").alias("cuts"), F.coalesce(F.sum(F.when(F.col("small") < 1, 1)), F.lit(0)).alias("empty"))
    row = count.crossJoin(n)
    return row.select(F.lit("found").alias("check_name"), F.when(F.col("cuts") > 0, 0).otherwise(1).cast("long").alias("violations"), "checked").unionByName(row.select(F.lit("terminals_apart").alias("check_name"), F.col("empty").cast("long").alias("violations"), "checked"))


# --- separators and orders --------------------------------------------------------------------------


@query("split_graph", f"with e as ({SUPP}) select 2 * s_suppkey as src, 2 * s_suppkey + 1 as dst, 'bridge' as kind from supplier union all select 2 * u + 1, 2 * v, 'external' from e union all select 2 * v + 1, 2 * u, 'external' from e")
def split_graph(spark, sf_dir):
    return dissect.split_graph(graphs.graph(spark, sf_dir, "supp"))


@query("node_sep", zeros(["blocks_apart", "blocks_not_empty", "fifth_on_smaller"], f"select count(*) from ({CUST_N}) n"))
def node_sep(spark, sf_dir):
    """The chosen separator of the customer graph: no edge between its blocks, and a fifth of the rest on the smaller one."""
    g = graphs.graph(spark, sf_dir, "cust")
    s = kept(cutters.chosen_sides(g, cutters.config("SP4")), "separator")
    n = s.agg(F.count("*").alias("checked"))
    apart = ops.separator_violations(g.edges, s).agg(F.count("*").alias("violations"))
    size = s.groupBy("cell_id").agg(*[F.count(F.when(F.col("side") == i, 1)).alias(f"n{i}") for i in (0, 1)])
    empty = size.agg(F.count(F.when((F.col("n0") == 0) | (F.col("n1") == 0), 1)).alias("violations"))
    fifth = size.agg(F.count(F.when(F.least("n0", "n1") * 5 < F.col("n0") + F.col("n1"), 1)).alias("violations"))
    rows = [r.crossJoin(n).select(F.lit(k).alias("check_name"), "violations", "checked") for k, r in (("blocks_apart", apart), ("blocks_not_empty", empty), ("fifth_on_smaller", fifth))]
    return rows[0].unionByName(rows[1]).unionByName(rows[2])


def order_checks(g: Graph, ranks):
    """The order is a permutation 0 .. n - 1 of the nodes."""
    both = g.nodes.join(ranks, "node_id", "full")
    return both.agg(F.count(F.when(F.col("rank").isNull() | F.col("x").isNull(), 1)).alias("missing"), (F.count("rank") - F.countDistinct("rank")).alias("repeated"), F.min("rank").alias("least"), (F.max("rank") + 1).alias("nodes"))


def _permutation(nodes: str) -> str:
    return f"select cast(0 as bigint) as missing, cast(0 as bigint) as repeated, cast(0 as bigint) as least, count(*) as nodes from ({nodes}) n"


def _order(graph, name, **more):
    return lambda spark, sf_dir: (lambda g: order_checks(g, dissect.dissection_order(g, cutters.config(name), **more)))(graphs.graph(spark, sf_dir, graph))


query("nd_perm_part", _permutation(PART_N))(_order("part", "SP4"))
query("nd_perm_cust", _permutation(CUST_N))(_order("cust", "SP8"))
query("nd_levels_cust", _permutation(CUST_N))(_order("cust", "SP4", leaf_nodes=400))
query("nd_plain_part", _permutation(PART_N))(_order("part", "SP4", preprocess=False))
query("nd_edgecut_part", _permutation(PART_N))(_order("part", "BF"))
query("nd_pairs_part", _permutation(PART_N))(_order("part", "PP3"))


@query("nd_retry_supp", _permutation(graphs.duck("supp", "nodes")))
def nd_retry_supp(spark, sf_dir):
    """The older style: edge cuts are repeated until none is better ten times in a row."""
    g = graphs.graph(spark, sf_dir, "supp")
    return order_checks(g, dissect.dissection_order(g, order.Splitter("pairs", pairs=3, style="edgecut", patience=10), False))


_KINDS = "case when m = n - 1 then 'tree' when m = n * (n - 1) // 2 then 'clique' else 'split' end"
_SIZES = f"with recursive e as ({{edges}}), a as ({ARCS}), v as (select distinct src as id from a), r(id, low) as (select id, id from v union select a.dst, r.low from r join a on a.src = r.id where r.low < a.dst), c as (select id, min(low) as cell_id from r group by 1), k as (select cell_id, count(*) as n from c group by 1), m as (select cell_id, count(*) as m from e join c on c.id = e.u group by 1)"


@query("tree_cells", _SIZES.replace("{edges}", graphs.duck("talk", "edges")) + f" select k.cell_id, n, m, {_KINDS} as kind from k join m on m.cell_id = k.cell_id")
def tree_cells(spark, sf_dir):
    return dissect.classify(graphs.graph(spark, sf_dir, "talk"))


@query("path_tree_depth", _SIZES.replace("{edges}", graphs.duck("talk", "edges")) + " select cell_id, n, cast(floor(log2(n)) as bigint) + 1 as depth from k")
def path_tree_depth(spark, sf_dir):
    """A path of n nodes needs floor(log2 n) + 1 levels."""
    return dissect.tree_depths(graphs.graph(spark, sf_dir, "talk"))


@query("clique_cells_region", "select min(n_nationkey) as cell_id, count(*) as n, count(*) * (count(*) - 1) // 2 as m, case when count(*) = 2 then 'tree' when count(*) = 1 then 'tree' else 'clique' end as kind from nation group by n_regionkey")
def clique_cells_region(spark, sf_dir):
    """The nations of a region, all joined with each other, are cells that the recursion recognises as cliques."""
    t = graphs.read(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("node_id"), "n_regionkey", F.lit(0).cast("long").alias("x"), F.lit(0).cast("long").alias("y"))
    pairs = t.select(F.col("node_id").alias("u"), "n_regionkey").join(t.select(F.col("node_id").alias("v"), "n_regionkey"), "n_regionkey").filter("u < v")
    return dissect.classify(Graph(t.drop("n_regionkey"), pairs.select("u", "v")))


@query("core_split", zeros(["core_once", "core_in_cell"], f"select count(*) from ({PART_N}) n"))
def core_split(spark, sf_dir):
    """Each node is in or out of its component's core once, and no component that has edges lacks a core."""
    g = graphs.graph(spark, sf_dir, "part")
    c = kept(dissect.core_split(g), "core")
    once = c.groupBy("node_id").count().agg(F.lit("core_once").alias("check_name"), F.count(F.when(F.col("count") != 1, 1)).alias("violations"), F.sum("count").alias("checked"))
    cell = c.groupBy("cell_id").agg(F.count("*").alias("n"), F.sum("core").alias("core")).agg(F.lit("core_in_cell").alias("check_name"), F.count(F.when((F.col("n") > 1) & (F.col("core") < 2), 1)).alias("violations"), F.sum("n").alias("checked"))
    return once.unionByName(cell)


_LOW = f"with recursive e as ({PART}), a as ({ARCS}), low as (select n.node_id as id from ({PART_N}) n left join a on a.src = n.node_id group by 1 having count(a.src) <= 2), b as (select a.src, a.dst from a join low x on x.id = a.src join low y on y.id = a.dst), r(id, low) as (select id, id from low union select b.dst, r.low from r join b on b.src = r.id where r.low < b.dst)"


@query("chains_part", f"{_LOW} select id as node_id, min(low) as chain from r group by 1")
def chains_part(spark, sf_dir):
    return dissect.low_degree_components(graphs.graph(spark, sf_dir, "part"))


@query("chain_edges_part", f"{_LOW}, c as (select id, min(low) as chain from r group by 1), o as (select distinct c.chain, a.dst from c join a on a.src = c.id where a.dst not in (select id from low)), p as (select chain, count(*) as k, min(dst) as u, max(dst) as v, (select count(*) from c x join a on a.src = x.id where x.chain = o.chain and a.dst not in (select id from low)) as ends from o group by chain) select distinct u, v from p where k = 2 and ends = 2")
def chain_edges_part(spark, sf_dir):
    """The edges that stand for chains: between the two outer neighbours of each component of nodes of degree 2 or less."""
    return dissect.chain_edges(graphs.graph(spark, sf_dir, "part"))


@query("nd_apart_cust", f"select cast(0 as bigint) as joined, cast(0 as bigint) as below, count(*) as edges from ({graphs.duck('cust', 'edges')}) e")
def nd_apart_cust(spark, sf_dir):
    """Separators separate and rank above: no edge joins two parts of one cell, but through a node that was closed there and ranks higher."""
    g = graphs.graph(spark, sf_dir, "cust")
    placed = kept(dissect.cell_positions(g, cutters.config("SP4"), leaf_nodes=100), "positions")
    ranks = dissect.global_rank(placed, ["path", "pos"], "rank")
    steps = dissect.path_steps(F.col("path"))
    of = lambda c: ranks.select(F.col("node_id").alias(c), steps.alias(f"p{c}"), F.col("rank").alias(f"r{c}"))
    both = g.edges.join(wide(of("u")), "u").join(wide(of("v")), "v")
    at = F.array_position(F.zip_with("pu", "pv", lambda a, b: ~a.eqNullSafe(b)), True)
    step = lambda c: F.get(F.col(c), F.col("at") - 1)
    # the first two steps are the component and the stage of the preprocessing, which edges may cross
    apart = both.withColumn("at", at).filter("at > 2")
    closed = lambda c: F.coalesce(step(c) == "~", F.lit(False))
    below = (closed("pu") & (F.col("ru") < F.col("rv"))) | (closed("pv") & (F.col("rv") < F.col("ru")))
    n = g.edges.agg(F.count("*").alias("edges"))
    return apart.agg(F.count(F.when(~closed("pu") & ~closed("pv"), 1)).alias("joined"), F.count(F.when((closed("pu") != closed("pv")) & below, 1)).alias("below")).crossJoin(n)


@query("ml_cuts", " union all ".join(f"select '{p}' as config, cast({e} as bigint) as eps_permille, true as answered, true as balanced from (select 1) q" for p in ("ML-a", "ML-b", "ML-c", "QM", "NC", "ENC") for e in (30, 200)))
def ml_cuts(spark, sf_dir):
    """The multilevel and natural-cut partitioners find a cut and keep the demanded balance, or say that they missed it, which only natural cuts do, as fragments are not split."""
    found = cutters.multilevel_cuts(graphs.graph(spark, sf_dir, "cust"), [30, 200], ["ML-a", "ML-b", "ML-c", "QM", "NC", "ENC"])
    held = ops.is_balanced(F.col("n") - F.col("small"), F.col("n"), F.col("eps_permille"))
    may = F.col("config").isin("NC", "ENC") & F.col("missed")
    return found.groupBy("config", "eps_permille").agg(F.bool_and(F.col("size") > 0).alias("answered"), F.bool_and(held | may).alias("balanced"))


@query("ml_recount", "select config, cast(0 as bigint) as wrong from (select unnest(['ML-a', 'ML-b', 'ML-c', 'QM', 'NC', 'ENC', 'ML-s']) as config) c")
def ml_recount(spark, sf_dir):
    """Bisections and node separators of these partitioners are recounted edge by edge: the reported cut, and no edge between the blocks of a separator."""
    nodes, edges = ops.celled(graphs.graph(spark, sf_dir, "supp"))
    names = ["ML-a", "ML-b", "ML-c", "QM", "NC", "ENC", "ML-s"]
    each = lambda df: df.withColumn("config", F.explode(F.array(*[F.lit(c) for c in names])))

    def run(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        k, _ = ops.cell_graph(a, b)
        name = str(key[1])
        side, info = multilevel.bisect(k.n, k.u.tolist(), k.v.tolist(), 0.1, "ML-c" if name == "ML-s" else name)
        own = np.array(side)
        wrong = int((own[k.u] != own[k.v]).sum() != info["cut"])
        if name == "ML-s":
            label = multilevel.node_separator(k.n, k.u, k.v, side)
            wrong += int(((label[k.u] == 0) & (label[k.v] == 1) | (label[k.u] == 1) & (label[k.v] == 0)).sum()) + int((label == 2).sum() > info["cut"])
        return pd.DataFrame({"config": [name], "wrong": [wrong]})

    found = each(nodes).groupBy("cell_id", "config").cogroup(each(edges).groupBy("cell_id", "config")).applyInPandas(run, "config string, wrong long")
    return found.groupBy("config").agg(F.sum("wrong").alias("wrong"))


@query("qm_cut", zeros(["balanced", "cut_found"], f"select count(*) from ({CUST_N}) n"))
def qm_cut(spark, sf_dir):
    """The quick partitioner keeps 10 % imbalance and finds a cut."""
    found = kept(cutters.multilevel_cuts(graphs.graph(spark, sf_dir, "cust"), [100], ["QM"]), "ml")
    bad = {"balanced": F.count(F.when(~ops.is_balanced(F.col("n") - F.col("small"), F.col("n"), F.lit(100)), 1)), "cut_found": F.count(F.when(F.col("size") < 1, 1))}
    rows = [found.agg(F.lit(k).alias("check_name"), v.alias("violations"), F.sum("n").alias("checked")) for k, v in bad.items()]
    return rows[0].unionByName(rows[1])


@query("ml_miss_flag", f"with n as (select count(*) as n from ({CUST_N}) c) select n, true as sound from n")
def ml_miss_flag(spark, sf_dir):
    """Perfect balance is demanded but not enforced: a cut is marked as missed iff its larger block has more than half of the nodes, rounded up."""
    found = cutters.multilevel_cuts(graphs.graph(spark, sf_dir, "cust"), [0], ["ML-c"], enforce=False)
    return found.select("n", (F.col("missed") == (F.col("n") - F.col("small") > F.expr("(n + 1) div 2"))).alias("sound"))
