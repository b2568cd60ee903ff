"""Queries of the graph preliminaries, geometry and flow."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import cutter as kernel
from ..functions.cutter import directions
from ..model import Graph, kept
from ..operators import cutters, flow, geometry, table_cutter
from ..operators import graph as ops
from ..sources import graphs
from .catalog import query, zeros

PART, PART_N = graphs.duck("part", "edges"), graphs.duck("part", "nodes")
CUST, CUST_N = graphs.duck("cust", "edges"), graphs.duck("cust", "nodes")
EMB, EMB_N = graphs.duck("emb", "edges"), graphs.duck("emb", "nodes")
SUPP, NAT = graphs.duck("supp", "edges"), graphs.duck("nat", "edges")
ARCS = "select u as src, v as dst from e union all select v, u from e"


@query("edges_part", PART)
def edges_part(spark, sf_dir):
    return ops.normalize_edges(graphs.edges(spark, sf_dir, "part"))


@query("edges_cust", CUST)
def edges_cust(spark, sf_dir):
    return ops.normalize_edges(graphs.edges(spark, sf_dir, "cust"))


@query("edges_emb", EMB)
def edges_emb(spark, sf_dir):
    return graphs.edges(spark, sf_dir, "emb")


@query("arcs_part", f"with e as ({PART}) {ARCS}")
def arcs_part(spark, sf_dir):
    return ops.to_arcs(graphs.edges(spark, sf_dir, "part"))


@query("degree_hist", f"with e as ({PART}), a as ({ARCS}), d as (select n.node_id, count(a.src) as degree from ({PART_N}) n left join a on a.src = n.node_id group by 1) select degree, count(*) as nodes from d group by 1")
def degree_hist(spark, sf_dir):
    return ops.degrees(graphs.graph(spark, sf_dir, "part")).groupBy("degree").agg(F.count("*").alias("nodes"))


@query("induced_sub", f"with e as ({PART}) select u, v from e where u % 3 <> 0 and v % 3 <> 0")
def induced_sub(spark, sf_dir):
    g = graphs.graph(spark, sf_dir, "part")
    return ops.induced(g, g.nodes.filter("node_id % 3 <> 0")).edges


@query("sym_violations", f"with e as ({PART}), a as ({ARCS} where u % 5 <> 0) select count(*) as missing from a where not exists (select 1 from a b where b.src = a.dst and b.dst = a.src)")
def sym_violations(spark, sf_dir):
    e = graphs.edges(spark, sf_dir, "part")
    one_way = e.select(F.col("u").alias("src"), F.col("v").alias("dst")).unionByName(e.filter("u % 5 <> 0").select(F.col("v").alias("src"), F.col("u").alias("dst")))
    return ops.asymmetric_arcs(one_way).agg(F.count("*").alias("missing"))


@query("cut_size_half", f"with e as ({CUST}) select count(*) as cut_size from e where (u % 2 = 0) <> (v % 2 = 0)")
def cut_size_half(spark, sf_dir):
    g = graphs.graph(spark, sf_dir, "cust")
    sides = g.nodes.select("node_id", (F.col("node_id") % 2).alias("side"))
    return ops.cut_edges(g.edges, sides).agg(F.count("*").alias("cut_size"))


_EPS = [0, 10, 30, 50, 100, 200, 300, 500, 700, 900]


@query("balance_table", f"""with n as (select count(*) as n from part), l as (select cast(i as bigint) as i from range(5) t(i)), e as (select unnest({_EPS}) as eps)
    select cast(eps as bigint) as eps_permille, n, n - n // (2 + i) as large, (n - n // (2 + i)) <= ((eps + 1000) * n + 1999) // 2000 as balanced, round(2.0 * (n - n // (2 + i)) / n - 1, 6) as imbalance from n, l, e""")
def balance_table(spark, sf_dir):
    n = graphs.nodes(spark, sf_dir, "part").agg(F.count("*").alias("n"))
    rows = n.withColumn("i", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(4).cast("long")))).withColumn("eps_permille", F.explode(F.array(*[F.lit(e).cast("long") for e in _EPS])))
    large = rows.withColumn("large", F.expr("n - n div (2 + i)"))
    return large.select("eps_permille", "n", "large", ops.is_balanced(F.col("large"), F.col("n"), F.col("eps_permille")).alias("balanced"), F.round(F.lit(2.0) * F.col("large") / F.col("n") - 1, 6).alias("imbalance"))


@query("sep_violations", f"with e as ({SUPP}) select count(*) as violations from e where u % 3 <> v % 3 and u % 3 < 2 and v % 3 < 2")
def sep_violations(spark, sf_dir):
    g = graphs.graph(spark, sf_dir, "supp")
    return ops.separator_violations(g.edges, g.nodes.select("node_id", (F.col("node_id") % 3).alias("side"))).agg(F.count("*").alias("violations"))


_REACH = f"with recursive e as ({PART}), a as ({ARCS}), r(node_id, low) as (select node_id, node_id from ({PART_N}) n union select a.dst, r.low from r join a on a.src = r.node_id where r.low < a.dst)"


@query("components_part", f"{_REACH} select node_id, min(low) as component_id from r group by 1")
def components_part(spark, sf_dir):
    return ops.components(graphs.graph(spark, sf_dir, "part"))


_TALK = graphs.duck("talk", "edges")


@query("component_rounds_talk", f"with e as ({_TALK}), n as (select u as node_id from e union select v from e) select node_id, min(node_id) over (partition by node_id // 1000, node_id % 1000 - k) as component_id from (select node_id, row_number() over (partition by node_id // 1000 order by node_id) as k from n) q")
def component_rounds_talk(spark, sf_dir):
    """Components by star rounds alone: conversations are runs of turns."""
    return ops.component_rounds(graphs.graph(spark, sf_dir, "talk"))


@query("bfs_part", f"""with recursive e as ({PART}), a as ({ARCS}), d(node_id, dist) using key (node_id) as (select node_id, cast(0 as bigint) from ({PART_N}) n where node_id = (select min(u) from e)
    union select a.dst, min(d.dist + 1) from d join a on a.src = d.node_id left join recurring.d r on r.node_id = a.dst where r.dist is null group by a.dst) select node_id, dist from d""")
def bfs_part(spark, sf_dir):
    g = graphs.graph(spark, sf_dir, "part")
    return ops.hop_dist(g, g.edges.agg(F.min("u").alias("node_id")))


@query("bfs_rounds_supp", f"""with recursive e as ({SUPP}), a as ({ARCS}), d(node_id, dist) using key (node_id) as (select cast(0 as bigint), cast(0 as bigint)
    union select a.dst, min(d.dist + 1) from d join a on a.src = d.node_id left join recurring.d r on r.node_id = a.dst where r.dist is null group by a.dst) select node_id, dist from d""")
def bfs_rounds_supp(spark, sf_dir):
    """The distributed search, one join a level."""
    g = graphs.graph(spark, sf_dir, "supp")
    return ops.hop_rounds(g, g.nodes.filter("node_id = 0"))


@query("bicomp_sizes", zeros(["edges_once", "numbers_gapless"], f"select count(*) from ({SUPP}) e"))
def bicomp_sizes(spark, sf_dir):
    """Each edge has one biconnected component, and components are numbered without gaps."""
    g = graphs.graph(spark, sf_dir, "supp")
    b = kept(ops.bicomponents(g))
    once = b.groupBy("u", "v").count().agg(F.lit("edges_once").alias("check_name"), F.count(F.when(F.col("count") != 1, 1)).alias("violations"), F.sum("count").alias("checked"))
    gaps = b.groupBy("cell_id").agg((F.max("bicomp") + 1 - F.countDistinct("bicomp")).alias("gap"), F.count("*").alias("m")).agg(F.lit("numbers_gapless").alias("check_name"), F.sum("gap").alias("violations"), F.sum("m").alias("checked"))
    return once.unionByName(gaps)


@query("bridges", f"with e as ({_TALK}), f as ({SUPP}) select 'talk' as graph, count(*) as bridges, count(*) as edges from e union all select 'supp', 0, count(*) from f")
def bridges(spark, sf_dir):
    """Every edge of a conversation's path is a bridge, i.e. a biconnected component of one edge; no edge of the full lattice of suppliers is."""
    out = None
    for name in ("talk", "supp"):
        b = ops.bicomponents(graphs.graph(spark, sf_dir, name)).groupBy("cell_id", "bicomp").count()
        row = b.agg(F.lit(name).alias("graph"), F.coalesce(F.sum(F.when(F.col("count") == 1, 1)), F.lit(0)).alias("bridges"), F.sum("count").alias("edges"))
        out = row if out is None else out.unionByName(row)
    return out


@query("preorder_perm", f"select count(*) as nodes, cast(0 as bigint) as repeated from ({CUST_N}) n")
def preorder_perm(spark, sf_dir):
    p = ops.preorder(graphs.graph(spark, sf_dir, "cust"))
    return p.agg(F.count("*").alias("nodes"), (F.count("*") - F.countDistinct("cell_id", "pos")).alias("repeated"))


@query("midline_rank", """with n as (select s_suppkey as id, s_suppkey % w as gx, s_suppkey // w as gy from supplier, (select cast(ceil(sqrt(count(*))) as bigint) as w from supplier) q)
    select id as node_id, row_number() over (order by greatest(2 * bit_count(((gx + 1) & (-(gx + 1))) - 1) + 1, 2 * bit_count(((gy + 1) & (-(gy + 1))) - 1)), id) - 1 as rank from n""")
def midline_rank(spark, sf_dir):
    return ops.midline_ranks(grid(spark, sf_dir, "supplier", "s_suppkey"))


def grid(spark, sf_dir, table, key):
    """node_id, gx, gy of a lattice."""
    import math

    t = graphs.read(spark, sf_dir, table)
    w = math.isqrt(max(0, t.count() - 1)) + 1
    return t.select(F.col(key).alias("node_id"), (F.col(key) % w).alias("gx"), F.expr(f"{key} div {w}").alias("gy"))


@query("directions_8", f"select k, c as cx, s as cy, min(x * c + y * s) as first, max(x * c + y * s) as last from ({PART_N}) n, ({' union all '.join(f'select {k} as k, cast({c} as bigint) as c, cast({s} as bigint) as s' for k, (c, s) in enumerate(directions(8)))}) d group by 1, 2, 3")
def directions_8(spark, sf_dir):
    """The eight directions, and how far the part graph's nodes reach along each."""
    spread = geometry.project(graphs.nodes(spark, sf_dir, "part"), 8).groupBy("k").agg(F.min("key").alias("first"), F.max("key").alias("last"))
    return spread.join(F.broadcast(spark.createDataFrame(geometry.direction_rows(8), "k int, cx long, cy long")), "k").select("k", "cx", "cy", "first", "last")


def _directed(q: int) -> str:
    return " union all ".join(f"select {k} as k, {c} as c, {s} as s" for k, (c, s) in enumerate(directions(q)))


@query("projection_emb", f"select node_id, k, x * c + y * s as key from ({EMB_N}) n, ({_directed(4)}) d")
def projection_emb(spark, sf_dir):
    return geometry.project(graphs.nodes(spark, sf_dir, "emb"), 4).select("node_id", "k", "key")


_SWEPT = f"select k, node_id, row_number() over (partition by k order by x * c + y * s, node_id) - 1 as pos, count(*) over (partition by k) as n from ({EMB_N}) n, ({_directed(8)}) d"


@query("sweep_emb", f"select k, node_id, pos from ({_SWEPT}) s")
def sweep_emb(spark, sf_dir):
    return geometry.sweep(graphs.nodes(spark, sf_dir, "emb").withColumn("cell_id", F.lit(0)), 8).select("k", "node_id", "pos")


@query("bands_emb", f"select k, node_id, case when pos < n // 20 then 1 else 2 end as term from ({_SWEPT}) s where pos < n // 20 or pos >= n - n // 20")
def bands_emb(spark, sf_dir):
    return geometry.bands(graphs.nodes(spark, sf_dir, "emb").withColumn("cell_id", F.lit(0)), 8, 0.05).select("k", "node_id", "term")


@query("edgecut_sep", f"with e as ({CUST}) select distinct case when u % 2 = 0 then u else v end as node_id from e where u % 2 <> v % 2")
def edgecut_sep(spark, sf_dir):
    """A separator from an edge cut: the cut's ends on one side."""
    g = graphs.graph(spark, sf_dir, "cust")
    cut = ops.cut_edges(g.edges, g.nodes.select("node_id", (F.col("node_id") % 2).alias("side")))
    return cut.select(F.when(F.col("u") % 2 == 0, F.col("u")).otherwise(F.col("v")).alias("node_id")).distinct()


# --- flow on the 4 x 4 lattice, against all 2 ** 16 bipartitions ------------------------------------

_CUTS = f"with e as ({NAT}), m as (select cast(range as bigint) as mask from range(65536)), c as (select mask, sum(case when ((mask >> u) & 1) <> ((mask >> v) & 1) then 1 else 0 end) as size from m, e where (mask & 1) = 1 and ((mask >> 15) & 1) = 0 group by mask), b as (select * from c where size = (select min(size) from c))"


def _ends(spark, s, t):
    one = lambda ids: spark.createDataFrame([(i,) for i in ids], "node_id long")
    return one(s), one(t)


def _flowed(spark, sf_dir):
    e = graphs.edges(spark, sf_dir, "nat")
    s, t = _ends(spark, [0], [15])
    state, units = flow.max_flow(flow.network(e), s, t)
    return e, s, t, state, units


@query("stcut_value", f"{_CUTS} select cast(min(size) as bigint) as value from b")
def stcut_value(spark, sf_dir):
    units = _flowed(spark, sf_dir)[-1]
    return spark.createDataFrame([(units,)], "value long")


@query("reach_source", f"{_CUTS}, s as (select bit_and(mask) as x from b) select cast(i as bigint) as node_id from s, range(16) r(i) where ((x >> i) & 1) = 1")
def reach_source(spark, sf_dir):
    _, s, _, state, _ = _flowed(spark, sf_dir)
    return flow.reach(state, s)[0].select("node_id")


@query("reach_target", f"{_CUTS}, s as (select bit_or(mask) as x from b) select cast(i as bigint) as node_id from s, range(16) r(i) where ((x >> i) & 1) = 0")
def reach_target(spark, sf_dir):
    _, _, t, state, _ = _flowed(spark, sf_dir)
    return flow.reach(state, t, forward=False)[0].select("node_id")


@query("stcut_sides", f"{_CUTS}, s as (select bit_and(mask) as x from b) select u, v from e, s where ((x >> u) & 1) <> ((x >> v) & 1)")
def stcut_sides(spark, sf_dir):
    """The source-side cut."""
    e, s, _, state, _ = _flowed(spark, sf_dir)
    return flow.side_cut(graphs.graph(spark, sf_dir, "nat"), flow.reach(state, s)[0])


@query("flow_violations", f"""with e as ({NAT}) select 'capacity' as check_name, cast(0 as bigint) as violations, 2 * count(*) as checked from e
    union all select 'skew', 0, 2 * count(*) from e union all select 'conservation', 0, 14 from (select 1) q""")
def flow_violations(spark, sf_dir):
    e, s, t, state, _ = _flowed(spark, sf_dir)
    return flow.flow_violations(state, flow.network(e).withColumnRenamed("res", "cap"), s, t)


@query("trim_terminals", f"""with e as ({SUPP}), a as ({ARCS}), t as (select s_suppkey as id, case when s_suppkey < (select count(*) // 4 from supplier) then 1 else 2 end as term from supplier where s_suppkey < (select count(*) // 4 from supplier) or s_suppkey >= (select count(*) - count(*) // 4 from supplier))
    select t.id as node_id, t.term from t where exists (select 1 from a left join t o on o.id = a.dst where a.src = t.id and (o.term is null or o.term <> t.term))""")
def trim_terminals(spark, sf_dir):
    g = graphs.graph(spark, sf_dir, "supp")
    n = g.nodes.count()
    terms = g.nodes.select("node_id", F.when(F.col("node_id") < n // 4, 1).when(F.col("node_id") >= n - n // 4, 2).alias("term")).filter("term is not null")
    return flow.trim_terminals(ops.to_arcs(g.edges), terms)


def _banded(spark, sf_dir, k):
    """The supplier graph between its bands along direction k of two, a fifth of the nodes each, and the flow over blocks of about 50 edges."""
    g = graphs.graph(spark, sf_dir, "supp")
    terms = kept(geometry.bands(g.nodes.withColumn("cell_id", F.lit(0)), 2, 0.2).filter(F.col("k") == k).select("node_id", "term"), "terms")
    s, t = (terms.filter(F.col("term") == i).select("node_id") for i in (1, 2))
    net = flow.BlockNet.of(g, table_cutter.undirected(g), 50)
    units, tree = net.augment(s, t)
    return g, s, t, net, units, tree


@query("flow_bands_supp", f"""with e as ({SUPP}), n as (select count(*) as n from supplier) select 'capacity' as check_name, cast(0 as bigint) as violations, 2 * count(*) as checked from e union all select 'skew', 0, 2 * count(*) from e
    union all select 'conservation', 0, n - 2 * greatest(1, n // 5) from n union all select 'source_cut', 0, n from n union all select 'target_cut', 0, n from n union all select 'one_task', 0, n from n""")
def flow_bands_supp(spark, sf_dir):
    """A maximum flow of many units over a whole graph: it is a flow, the source-side and the target-side cut have its value, and the flow of one task has, too."""
    import pandas as pd

    from ..functions.flow import Net
    from ..functions.flow import max_flow as task_flow

    g, s, t, net, units, tree = _banded(spark, sf_dir, 0)
    state = kept(net.state(), "flow")
    n = g.nodes.agg(F.count("*").alias("checked"))
    first, last = tree.select("node_id"), net.reach(t, False)[0].select("node_id")
    rows = [flow.flow_violations(state, table_cutter.undirected(g), s, t)]
    for name, own in (("source_cut", first), ("target_cut", last)):
        size = flow.side_cut(g, own).agg(F.count("*").alias("size"))
        rows.append(size.crossJoin(n).select(F.lit(name).alias("check_name"), F.abs(F.col("size") - units).alias("violations"), "checked"))
    marked = g.nodes.join(s.withColumn("term", F.lit(1)).unionByName(t.withColumn("term", F.lit(2))), "node_id", "left").fillna(0, ["term"]).withColumn("cell_id", F.lit(0).cast("long"))

    def run(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        k, _ = ops.cell_graph(a, b)
        term = a.sort_values("node_id").term.to_numpy()
        value = task_flow(Net.undirected(k.n, k.u, k.v), *[[i for i, x in enumerate(term) if x == side] for side in (1, 2)])
        return pd.DataFrame({"check_name": ["one_task"], "violations": [abs(value - units)], "checked": [k.n]})

    whole = g.edges.withColumn("cell_id", F.lit(0).cast("long"))
    rows.append(marked.groupBy("cell_id").cogroup(whole.groupBy("cell_id")).applyInPandas(lambda a, b: run(a, b), "check_name string, violations long, checked long"))
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


@query("flow_levels_nat", f"{_CUTS} select cast(min(size) as bigint) as stack, cast(min(size) as bigint) as queue, cast(min(size) as bigint) as levels from b")
def flow_levels_nat(spark, sf_dir):
    """The three ways to augment have the value of a minimum cut: stack search, queue search, and all paths of a level graph at once."""
    import pandas as pd

    from ..functions.flow import Net, level_flow
    from ..functions.flow import max_flow as task_flow

    def work(cell, k, ids):
        net = lambda: Net.undirected(k.n, k.u, k.v)
        return pd.DataFrame({"stack": [task_flow(net(), [0], [15])], "queue": [task_flow(net(), [0], [15], breadth=True)], "levels": [level_flow(net(), [0], [15])]})

    nodes, edges = ops.celled(graphs.graph(spark, sf_dir, "nat"))
    return ops.per_cell(nodes, edges, work, "stack long, queue long, levels long")


@query("table_cutter_nat", "select cast(0 as bigint) as differences, true as found")
def table_cutter_nat(spark, sf_dir):
    """The cutter over tables, with blocks of about eight edges, finds cut by cut what the cutter of one task finds: sizes, rules and blocks."""
    import numpy as np
    import pandas as pd

    g, params = graphs.graph(spark, sf_dir, "nat"), kernel.SweepParams(q=2)
    rows = []
    for i, c in enumerate(table_cutter.cuts(g, 0, params, block_edges=8)):
        rows.append(c.block.select(F.lit(i).alias("step"), F.lit(c.size).alias("size"), F.lit(c.grown).alias("grown"), F.lit(c.rule).alias("rule"), "node_id"))
    tables = rows[0]
    for r in rows[1:]:
        tables = tables.unionByName(r)

    def work(cell, k, ids):
        sweep = kernel.sweep_order(k.x, k.y, np.arange(k.n), kernel.directions(2)[0])
        (own,) = kernel.sweep_cutters(kernel.Net.undirected(k.n, k.u, k.v), [sweep], list(range(k.n)), params)
        cuts = [c for c in own.steps() if c]
        return pd.DataFrame([(i, c.size, c.grown, c.rule, int(ids[x])) for i, c in enumerate(cuts) for x in np.flatnonzero(np.frombuffer(c.side, np.uint8))], columns=["step", "size", "grown", "rule", "node_id"])

    task = kept(ops.per_cell(*ops.celled(g), work, "step int, size int, grown string, rule string, node_id long"), "task-cuts")
    return tables.exceptAll(task).unionByName(task.exceptAll(tables)).agg(F.count("*").alias("differences")).crossJoin(task.agg((F.count("*") > 0).alias("found")))


@query("cut_eq_flow", f"{_CUTS} select cast(min(size) as bigint) as flow, cast(min(size) as bigint) as cut_size from b")
def cut_eq_flow(spark, sf_dir):
    """The certificate: the cut's size is the flow's value."""
    _, s, _, state, units = _flowed(spark, sf_dir)
    return flow.side_cut(graphs.graph(spark, sf_dir, "nat"), flow.reach(state, s)[0]).agg(F.lit(units).cast("long").alias("flow"), F.count("*").alias("cut_size"))


@query("flow_tiers_agree", "select cast(2 as bigint) as tasks, cast(2 as bigint) as tables")
def flow_tiers_agree(spark, sf_dir):
    """The flow of one task and the flow of tables have one value."""
    g = graphs.graph(spark, sf_dir, "nat")
    pairs = spark.createDataFrame([(0, 0, 1), (0, 15, 2)], "cutter int, node_id long, term int")
    first = cutters.pair_cuts(g, pairs, only_front=False).agg(F.min("size").alias("tasks"))
    return first.select("tasks", F.lit(_flowed(spark, sf_dir)[-1]).cast("long").alias("tables"))


@query("sides_connected", "select true as halves, false as stripes")
def sides_connected(spark, sf_dir):
    """Whether both blocks are connected: lower half against every other column of the 4 x 4 lattice."""
    g = graphs.graph(spark, sf_dir, "nat")
    out = []
    for rule in ("node_id < 8", "node_id % 2 = 0"):
        sides = g.nodes.select("node_id", F.expr(f"cast({rule} as int)").alias("side"))
        inner = ops.with_sides(g.edges, sides).filter("su = sv").select("u", "v")
        out.append(ops.components(Graph(g.nodes, inner)).select("component_id").distinct().count() == 2)
    return spark.createDataFrame([tuple(out)], "halves boolean, stripes boolean")


