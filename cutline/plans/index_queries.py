"""Queries of the contraction index, on the supplier lattice with its midline order, against recursive SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..model import kept
from ..operators import graph as ops
from ..operators import index
from ..sources import graphs
from .catalog import ORACLES, query
from .graph_queries import grid

RANKED = ORACLES["midline_rank"].replace("with n as", "n as", 1)
_BASE = f"""r as (select node_id as id, rank as rk from (with {RANKED}) q), e as ({graphs.duck('supp', 'edges')}), w as ({graphs.duck('supp', 'time')}),
 a as (select x.rk as p, y.rk as q from e join r x on x.id = e.u join r y on y.id = e.v union all select y.rk, x.rk from e join r x on x.id = e.u join r y on y.id = e.v),
 z(o, cur) as (select rk, rk from r union select z.o, a.q from z join a on a.p = z.cur where z.cur <= z.o),
 i as (select o as lo, cur as hi from z where cur > o)"""
_TREE = f"{_BASE}, t as (select r.rk as rank, min(i.hi) as parent, count(i.hi) as up_degree from r left join i on i.lo = r.rk group by 1)"
_ANC = f"{_TREE}, n(rank, anc) as (select rank, rank from t union select n.rank, t.parent from n join t on t.rank = n.anc where t.parent is not null)"


def _ranks(spark, sf_dir):
    return ops.midline_ranks(grid(spark, sf_dir, "supplier", "s_suppkey"))


def _built(spark, sf_dir):
    g, ranks = graphs.graph(spark, sf_dir, "supp"), kept(_ranks(spark, sf_dir), "ranks")
    return g, ranks, kept(index.build_index(g, ranks), "index")


@query("index_arcs_supp", f"with recursive {_BASE} select lo, hi, not exists (select 1 from a where a.p = i.lo and a.q = i.hi) as is_shortcut from i")
def index_arcs_supp(spark, sf_dir):
    return _built(spark, sf_dir)[2]


@query("index_rounds_supp", f"with recursive {_BASE} select lo, hi from i")
def index_rounds_supp(spark, sf_dir):
    """The same index by DataFrame rounds."""
    g, ranks = graphs.graph(spark, sf_dir, "supp"), _ranks(spark, sf_dir)
    return index.build_index_rounds(index.oriented(g.edges, ranks))


@query("etree_supp", f"with recursive {_TREE} select rank, parent, up_degree from t")
def etree_supp(spark, sf_dir):
    _, ranks, i = _built(spark, sf_dir)
    return index.etree(i, ranks)


@query("ancestors_supp", f"with recursive {_ANC} select rank, anc from n")
def ancestors_supp(spark, sf_dir):
    _, ranks, i = _built(spark, sf_dir)
    return index.ancestors(index.etree(i, ranks))


@query("search_space_supp", f"with recursive {_ANC}, s as (select n.rank, count(*) as nodes, sum(t.up_degree) as arcs from n join t on t.rank = n.anc group by 1) select cast(sum(nodes) as bigint) as nodes_sum, max(nodes) as nodes_max, cast(sum(arcs) as bigint) as arcs_sum, cast(max(arcs) as bigint) as arcs_max from s")
def search_space_supp(spark, sf_dir):
    _, ranks, i = _built(spark, sf_dir)
    return index.search_space(index.etree(i, ranks))


_SIZES = f"with recursive {_BASE}, d as (select lo, count(*) as d from i group by 1)"


@query("index_size", f"{_SIZES} select cast(sum(d) as bigint) as index_arcs from d")
def index_size(spark, sf_dir):
    return index.sizes(_built(spark, sf_dir)[2]).select("index_arcs")


@query("triangles", f"{_SIZES} select cast(sum(d * (d - 1) // 2) as bigint) as triangles from d")
def triangles(spark, sf_dir):
    return index.sizes(_built(spark, sf_dir)[2]).select("triangles")


@query("tw_bound", f"{_SIZES} select max(d) as tw_bound from d")
def tw_bound(spark, sf_dir):
    return index.sizes(_built(spark, sf_dir)[2]).select("tw_bound")


@query("search_ratio", f"with recursive {_ANC}, s as (select n.rank, count(*) as nodes from n group by 1) select round(max(nodes) * count(*) * 1.0 / sum(nodes), 6) as max_over_avg from s")
def search_ratio(spark, sf_dir):
    _, ranks, i = _built(spark, sf_dir)
    s = index.search_space(index.etree(i, ranks)).crossJoin(ranks.agg(F.count("*").alias("n")))
    return s.select(F.round(F.col("nodes_max") * F.col("n") * F.lit(1.0) / F.col("nodes_sum"), 6).alias("max_over_avg"))


def _arcs(metric: str) -> str:
    return f"b as (select x.rk as p, y.rk as q, {metric} as w from w join r x on x.id = w.u join r y on y.id = w.v union all select y.rk, x.rk, {metric} from w join r x on x.id = w.u join r y on y.id = w.v)"


def _lower(metric: str) -> str:
    """Shortest paths from each rank whose inner ranks are lower than it: the customized weight of each index arc."""
    return f"""{_arcs(metric)}, c(o, v, d) using key (o, v) as (select rk, rk, cast(0 as bigint) from r
      union select c.o, b.q, min(c.d + b.w) from c join b on b.p = c.v left join recurring.c k on k.o = c.o and k.v = b.q where (c.v = c.o or c.v < c.o) and (k.d is null or c.d + b.w < k.d) group by c.o, b.q)"""


@query("custom_w_supp", f"with recursive {_BASE}, {_lower('w.weight')} select i.lo, i.hi, c.d as up, c.d as down from i join c on c.o = i.lo and c.v = i.hi")
def custom_w_supp(spark, sf_dir):
    g, ranks, i = _built(spark, sf_dir)
    return index.customize(i, g, ranks, graphs.metric(spark, sf_dir, "supp"))


@query("custom_lower_supp", ORACLES["custom_w_supp"])
def custom_lower_supp(spark, sf_dir):
    """The same weights by lower triangles."""
    g, ranks, i = _built(spark, sf_dir)
    return index.customize(i, g, ranks, graphs.metric(spark, sf_dir, "supp"), "lower")


@query("two_metrics", f"with recursive {_BASE}, {_lower('10 + w.weight * w.weight')} select i.lo, i.hi, c.d as up, c.d as down from i join c on c.o = i.lo and c.v = i.hi")
def two_metrics(spark, sf_dir):
    """Another metric on the same topology."""
    g, ranks, i = _built(spark, sf_dir)
    index.customize(i, g, ranks, graphs.metric(spark, sf_dir, "supp"))
    return index.customize(i, g, ranks, graphs.metric(spark, sf_dir, "supp").withColumn("weight", F.col("weight") * F.col("weight") + 10))


_PAIRS = "p as (select cast(range as bigint) as pair_id, (range * 7919 + 13) % (select count(*) from supplier) as s, (range * 104729 + 71) % (select count(*) from supplier) as t from range(1000))"
_DIST = f"""with recursive e as ({graphs.duck('supp', 'edges')}), w as ({graphs.duck('supp', 'time')}), {_PAIRS}, a as (select u as src, v as dst, weight as w from w union all select v, u, weight from w),
 d(o, v, d) using key (o, v) as (select distinct s, s, cast(0 as bigint) from p union select d.o, a.dst, min(d.d + a.w) from d join a on a.src = d.v left join recurring.d k on k.o = d.o and k.v = a.dst where k.d is null or d.d + a.w < k.d group by d.o, a.dst)
 select pair_id, s, t, d.d as dist from p left join d on d.o = p.s and d.v = p.t"""


def pairs(spark, sf_dir, n=1000):
    count = graphs.nodes(spark, sf_dir, "supp").count()
    return spark.range(n).select(F.col("id").alias("pair_id"), ((F.col("id") * 7919 + 13) % count).alias("s"), ((F.col("id") * 104729 + 71) % count).alias("t"))


def _asked(method):
    def run(spark, sf_dir):
        g, ranks, i = _built(spark, sf_dir)
        w = kept(index.customize(i, g, ranks, graphs.metric(spark, sf_dir, "supp")), "weights")
        asked = pairs(spark, sf_dir)
        return index.query_labels(w, g, ranks, asked) if method == "labels" else index.query(w, g, ranks, asked, method.removesuffix("_pruned"), method.endswith("_pruned"))

    return run


for _name, _method in (("dist_supp", "heap"), ("dist_etree_supp", "etree"), ("dist_pruned_supp", "etree_pruned"), ("dist_labels_supp", "labels")):
    query(_name, _DIST)(_asked(_method))


@query("path_weights_supp", f"with recursive {_BASE} select cast(0 as bigint) as wrong, 2 * count(*) as checked from i")
def path_weights_supp(spark, sf_dir):
    """All index arcs, both ways, unpack to paths of original arcs whose weights add up to the arc's."""
    g, ranks, i = _built(spark, sf_dir)
    return index.unpack_checks(i, g, ranks, graphs.metric(spark, sf_dir, "supp")).agg(F.sum("wrong").alias("wrong"), F.sum("checked").alias("checked"))


@query("custom_rounds_supp", ORACLES["custom_w_supp"])
def custom_rounds_supp(spark, sf_dir):
    """Customization by rounds over blocks of ranks."""
    g, ranks, i = _built(spark, sf_dir)
    return index.customize_rounds(i, ranks, graphs.metric(spark, sf_dir, "supp"))


@query("lower_triangles_supp", f"with recursive {_BASE} select a.lo as low, a.hi as u, b.hi as v from i a join i b on a.lo = b.lo and a.hi < b.hi join i c on c.lo = a.hi and c.hi = b.hi")
def lower_triangles_supp(spark, sf_dir):
    """Two upward neighbours of a rank are always joined by an arc, so pairs are triangles."""
    return index.lower_triangles(_built(spark, sf_dir)[2])


@query("dist_rounds_supp", _DIST)
def dist_rounds_supp(spark, sf_dir):
    """Distances by joins alone: labels that grow along index arcs."""
    g, ranks, i = _built(spark, sf_dir)
    w = kept(index.customize(i, g, ranks, graphs.metric(spark, sf_dir, "supp")), "weights")
    return index.query_rounds(w, ranks, pairs(spark, sf_dir))


@query("dist_witness_supp", _DIST)
def dist_witness_supp(spark, sf_dir):
    """Distances on an index without the arcs that other paths make needless; upward searches with heaps need no elimination tree, which such arcs may carry."""
    g, ranks, i = _built(spark, sf_dir)
    w = kept(index.customize(i, g, ranks, graphs.metric(spark, sf_dir, "supp"), witness=True), "weights")
    return index.query(w, g, ranks, pairs(spark, sf_dir), "heap")


@query("witness_arcs_supp", f"""with recursive {_BASE}, {_lower('w.weight')}, f(o, v, d) using key (o, v) as (select rk, rk, cast(0 as bigint) from r
      union select f.o, b.q, min(f.d + b.w) from f join b on b.p = f.v left join recurring.f k on k.o = f.o and k.v = b.q where k.d is null or f.d + b.w < k.d group by f.o, b.q)
    select i.lo, i.hi from i join c on c.o = i.lo and c.v = i.hi join f on f.o = i.lo and f.v = i.hi where c.d <= f.d""")
def witness_arcs_supp(spark, sf_dir):
    """The arcs that stay are those whose weight is the distance between their ends."""
    g, ranks, i = _built(spark, sf_dir)
    return index.customize(i, g, ranks, graphs.metric(spark, sf_dir, "supp"), witness=True).select("lo", "hi")


def _one_way(spark, sf_dir):
    """A metric whose directions differ: src, dst, weight."""
    e = graphs.graph(spark, sf_dir, "supp").edges
    both = e.select(F.col("u").alias("src"), F.col("v").alias("dst")).unionByName(e.select(F.col("v").alias("src"), F.col("u").alias("dst")))
    return both.withColumn("weight", 1 + (F.col("src") * 11 + F.col("dst") * 3) % 23)


_B = "b as (select x.rk as p, y.rk as q, 1 + (x.id * 11 + y.id * 3) % 23 as w from e join r x on x.id = e.u join r y on y.id = e.v union all select y.rk, x.rk, 1 + (y.id * 11 + x.id * 3) % 23 from e join r x on x.id = e.u join r y on y.id = e.v)"
_SPREAD = "{n}(o, v, d) using key (o, v) as (select rk, rk, cast(0 as bigint) from r union select {n}.o, {to}, min({n}.d + b.w) from {n} join b on {at} = {n}.v left join recurring.{n} k on k.o = {n}.o and k.v = {to} where ({n}.v = {n}.o or {n}.v < {n}.o) and (k.d is null or {n}.d + b.w < k.d) group by {n}.o, {to})"


@query("custom_directed_supp", f"with recursive {_BASE}, {_B}, {_SPREAD.format(n='c', at='b.p', to='b.q')}, {_SPREAD.format(n='h', at='b.q', to='b.p')} select i.lo, i.hi, c.d as up, h.d as down from i join c on c.o = i.lo and c.v = i.hi join h on h.o = i.lo and h.v = i.hi")
def custom_directed_supp(spark, sf_dir):
    """A metric with different weights each way."""
    g, ranks, i = _built(spark, sf_dir)
    return index.customize(i, g, ranks, _one_way(spark, sf_dir))


_DIST_ONE_WAY = _DIST.replace("a as (select u as src, v as dst, weight as w from w union all select v, u, weight from w)", "a as (select u as src, v as dst, 1 + (u * 11 + v * 3) % 23 as w from e union all select v, u, 1 + (v * 11 + u * 3) % 23 from e)")


@query("dist_directed_supp", _DIST_ONE_WAY)
def dist_directed_supp(spark, sf_dir):
    g, ranks, i = _built(spark, sf_dir)
    w = kept(index.customize(i, g, ranks, _one_way(spark, sf_dir)), "weights")
    return index.query_labels(w, g, ranks, pairs(spark, sf_dir))
