"""Queries of the surrounding relational operators on the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..sources.graphs import read
from .catalog import query


@query("scan_parquet", "select l_orderkey, l_linenumber, cast(round(l_extendedprice * 100) as bigint) as cents from lineitem where l_quantity >= 45 and l_returnflag = 'R'")
def scan_parquet(spark, sf_dir):
    t = read(spark, sf_dir, "lineitem").filter((F.col("l_quantity") >= 45) & (F.col("l_returnflag") == "R"))
    return t.select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * 100).cast("long").alias("cents"))


@query("coords_part", "select p_partkey as node_id, p_partkey % 100 * 1000 + p_size as x, case when p_size > 25 then 1 else 0 end as big from part")
def coords_part(spark, sf_dir):
    return read(spark, sf_dir, "part").select(F.col("p_partkey").alias("node_id"), (F.col("p_partkey") % 100 * 1000 + F.col("p_size")).alias("x"), F.when(F.col("p_size") > 25, 1).otherwise(0).alias("big"))


@query("filter_mix", "select c_custkey from customer where c_mktsegment in ('BUILDING', 'MACHINERY') and c_acctbal between 0 and 5000 and c_name like '%1%' and c_nationkey is not distinct from c_nationkey")
def filter_mix(spark, sf_dir):
    t = read(spark, sf_dir, "customer")
    return t.filter(F.col("c_mktsegment").isin("BUILDING", "MACHINERY") & F.col("c_acctbal").between(0, 5000) & F.col("c_name").like("%1%") & F.col("c_nationkey").eqNullSafe(F.col("c_nationkey"))).select("c_custkey")


@query("join_trade", "select s_nationkey, count(distinct l_partkey) as parts, count(*) as lines from lineitem join supplier on s_suppkey = l_suppkey group by 1")
def join_trade(spark, sf_dir):
    s = read(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    t = read(spark, sf_dir, "lineitem").select("l_suppkey", "l_partkey").join(s.hint("shuffle_hash"), F.col("s_suppkey") == F.col("l_suppkey"))
    return t.groupBy("s_nationkey").agg(F.countDistinct("l_partkey").alias("parts"), F.count("*").alias("lines"))


@query("join_merge", "select o_orderpriority, count(*) as lines from orders join lineitem on o_orderkey = l_orderkey group by 1")
def join_merge(spark, sf_dir):
    o = read(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority")
    t = read(spark, sf_dir, "lineitem").select("l_orderkey").join(o.hint("merge"), F.col("o_orderkey") == F.col("l_orderkey"))
    return t.groupBy("o_orderpriority").agg(F.count("*").alias("lines"))


@query("semi_docs", "select doc_id from documents d where exists (select 1 from labels l where l.doc_id = d.doc_id and quality = 1)")
def semi_docs(spark, sf_dir):
    return read(spark, sf_dir, "documents").select("doc_id").join(read(spark, sf_dir, "labels").filter("quality = 1"), "doc_id", "left_semi")


@query("anti_docs", "select doc_id from documents d where not exists (select 1 from labels l where l.doc_id = d.doc_id and toxic = 1)")
def anti_docs(spark, sf_dir):
    return read(spark, sf_dir, "documents").select("doc_id").join(read(spark, sf_dir, "labels").filter("toxic = 1"), "doc_id", "left_anti")


@query("outer_degree", "select c_custkey, count(o_orderkey) as orders from customer left join orders on o_custkey = c_custkey group by 1")
def outer_degree(spark, sf_dir):
    o = read(spark, sf_dir, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count("o_orderkey").alias("orders"))
    return read(spark, sf_dir, "customer").select("c_custkey").join(o, "c_custkey", "left").fillna(0, ["orders"])


@query("range_grid", "select a.vec_id as a, b.vec_id as b from embeddings a join embeddings b on a.vec_id < b.vec_id and abs(round(a.embedding[1] * 10000) - round(b.embedding[1] * 10000)) <= 20 and abs(round(a.embedding[2] * 10000) - round(b.embedding[2] * 10000)) <= 60")
def range_grid(spark, sf_dir):
    """A band join by grid cells: each row meets the cells around its own only."""
    t = read(spark, sf_dir, "embeddings").select("vec_id", *[F.round(F.col("embedding")[i].cast("double") * 10000).cast("long").alias(n) for i, n in ((0, "x"), (1, "y"))])
    cell = t.withColumn("gx", F.floor(F.col("x") / 20)).withColumn("gy", F.floor(F.col("y") / 60))
    around = cell.withColumn("gx", F.explode(F.sequence(F.col("gx") - 1, F.col("gx") + 1))).withColumn("gy", F.explode(F.sequence(F.col("gy") - 1, F.col("gy") + 1)))
    a, b = (d.select(F.col("vec_id").alias(k), F.col("x").alias(f"x{k}"), F.col("y").alias(f"y{k}"), "gx", "gy") for d, k in ((cell, "a"), (around, "b")))
    return a.join(b, ["gx", "gy"]).filter((F.col("a") < F.col("b")) & (F.abs(F.col("xa") - F.col("xb")) <= 20) & (F.abs(F.col("ya") - F.col("yb")) <= 60)).select("a", "b")


@query("asof_weight", "with f as (select event_id % 50 as arc, ts, event_id, cast(round(value * 100) as bigint) as w from events where event_id % 3 <> 0), q as (select event_id as query_id, event_id % 50 as arc, ts from events where event_id % 3 = 0) select query_id, (select arg_max(w, (ts, event_id)) from f where f.arc = q.arc and f.ts <= q.ts) as weight from q")
def asof_weight(spark, sf_dir):
    """The latest observed weight of an arc at a query's time: one union and one window, no range join."""
    e = read(spark, sf_dir, "events").select("event_id", "ts", (F.col("event_id") % 50).alias("arc"), F.round(F.col("value") * 100).cast("long").alias("w"))
    asks = F.col("event_id") % 3 == 0
    w = Window.partitionBy("arc").orderBy("ts", asks.cast("int"), "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return e.withColumn("weight", F.last(F.when(~asks, F.col("w")), ignorenulls=True).over(w)).filter(asks).select(F.col("event_id").alias("query_id"), "weight")


@query("agg_nation", "select c_nationkey, count(*) as n, min(c_custkey) as least, arg_max(c_custkey, (c_acctbal, c_custkey)) as richest, count(*) filter (where c_mktsegment = 'BUILDING') as building, bit_and(c_custkey) as bits_and, bit_or(c_custkey) as bits_or from customer group by 1")
def agg_nation(spark, sf_dir):
    return read(spark, sf_dir, "customer").groupBy("c_nationkey").agg(
        F.count("*").alias("n"), F.min("c_custkey").alias("least"), F.max_by("c_custkey", F.struct("c_acctbal", "c_custkey")).alias("richest"),
        F.count(F.when(F.col("c_mktsegment") == "BUILDING", 1)).alias("building"), F.bit_and("c_custkey").alias("bits_and"), F.bit_or("c_custkey").alias("bits_or"),
    )


@query("distinct_users", "select event_type, count(distinct user_id) as users from events group by 1")
def distinct_users(spark, sf_dir):
    return read(spark, sf_dir, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@query("approx_users", "select event_type, count(distinct user_id) as users, true as close from events group by 1")
def approx_users(spark, sf_dir):
    """The sketch's count of distinct users is within three of its standard errors (1 %) of the exact one."""
    both = read(spark, sf_dir, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.approx_count_distinct("user_id", 0.01).alias("about"))
    return both.select("event_type", "users", (F.abs(F.col("about") - F.col("users")) <= 0.03 * F.col("users") + 1).alias("close"))


@query("percentiles", "select p_brand, cast(quantile_disc(p_size, 0.5) as bigint) as median from part group by 1")
def percentiles(spark, sf_dir):
    return read(spark, sf_dir, "part").groupBy("p_brand").agg(F.expr("percentile_disc(0.5) within group (order by p_size)").cast("long").alias("median"))


@query("cube_segments", "select c_mktsegment, c_nationkey, count(*) as n from customer group by cube (c_mktsegment, c_nationkey)")
def cube_segments(spark, sf_dir):
    return read(spark, sf_dir, "customer").cube("c_mktsegment", "c_nationkey").agg(F.count("*").alias("n"))


@query("rollup_dates", "select year(o_orderdate) as y, month(o_orderdate) as m, count(*) as n from orders group by rollup (y, m)")
def rollup_dates(spark, sf_dir):
    o = read(spark, sf_dir, "orders").select(F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m"))
    return o.rollup("y", "m").agg(F.count("*").alias("n"))


@query("gsets_flags", "select l_returnflag, l_linestatus, count(*) as n from lineitem group by grouping sets ((l_returnflag), (l_linestatus), ())")
def gsets_flags(spark, sf_dir):
    read(spark, sf_dir, "lineitem").select("l_returnflag", "l_linestatus").createOrReplaceTempView("cutline_flags")
    return spark.sql("select l_returnflag, l_linestatus, count(*) as n from cutline_flags group by grouping sets ((l_returnflag), (l_linestatus), ())")


@query("win_rank", "select p_partkey, rank() over (partition by p_brand order by p_size desc) as r, dense_rank() over (partition by p_brand order by p_size desc) as d, ntile(4) over (partition by p_brand order by p_size, p_partkey) as q from part")
def win_rank(spark, sf_dir):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_size"))
    q = Window.partitionBy("p_brand").orderBy("p_size", "p_partkey")
    return read(spark, sf_dir, "part").select("p_partkey", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("d"), F.ntile(4).over(q).cast("long").alias("q"))


@query("win_running", "select o_orderkey, min(cents) over (partition by o_custkey order by o_orderkey rows unbounded preceding) as low, sum(cents) over (partition by o_custkey order by o_orderkey range between 100 preceding and current row)::bigint as near from (select o_orderkey, o_custkey, cast(round(o_totalprice * 100) as bigint) as cents from orders) o")
def win_running(spark, sf_dir):
    o = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", F.round(F.col("o_totalprice") * 100).cast("long").alias("cents"))
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    return o.select("o_orderkey", F.min("cents").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("low"), F.sum("cents").over(w.rangeBetween(-100, 0)).alias("near"))


@query("transitions", "select a, b, count(*) as n from (select user_id as a, lead(user_id) over (partition by event_type order by ts, event_id) as b from events) s where a <> b group by 1, 2")
def transitions(spark, sf_dir):
    e = read(spark, sf_dir, "events").select(F.col("user_id").alias("a"), F.lead("user_id").over(Window.partitionBy("event_type").orderBy("ts", "event_id")).alias("b"))
    return e.filter("a <> b").groupBy("a", "b").agg(F.count("*").alias("n"))


@query("topk_parts", "select p_partkey, p_size from part order by p_size desc, p_partkey limit 25")
def topk_parts(spark, sf_dir):
    return read(spark, sf_dir, "part").select("p_partkey", "p_size").orderBy(F.desc("p_size"), "p_partkey").limit(25)


@query("topk_per_nation", "select c_nationkey, c_custkey from (select c_nationkey, c_custkey, row_number() over (partition by c_nationkey order by c_acctbal desc, c_custkey) as r from customer) q where r <= 3")
def topk_per_nation(spark, sf_dir):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return read(spark, sf_dir, "customer").withColumn("r", F.row_number().over(w)).filter("r <= 3").select("c_nationkey", "c_custkey")


@query("setops", "select 'intersect' as op, count(*) as n from (select c_nationkey from customer intersect select s_nationkey from supplier) q union all select 'except', count(*) from (select l_partkey from lineitem except select p_partkey from part where p_size > 10) q union all select 'union', count(*) from (select c_nationkey from customer union select s_nationkey from supplier) q union all select 'except_all', count(*) from (select c_nationkey from customer except all select s_nationkey from supplier) q")
def setops(spark, sf_dir):
    c = read(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k"))
    s = read(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k"))
    lines, parts = read(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("k")), read(spark, sf_dir, "part").filter("p_size > 10").select(F.col("p_partkey").alias("k"))
    named = {"intersect": c.intersect(s), "except": lines.subtract(parts), "union": c.union(s).distinct(), "except_all": c.exceptAll(s)}
    rows = [d.agg(F.lit(n).alias("op"), F.count("*").alias("n")) for n, d in named.items()]
    return rows[0].unionByName(rows[1]).unionByName(rows[2]).unionByName(rows[3])


@query("hosts", "select page_id, regexp_extract(url, '//([^/]*)', 1) as host, len(string_split(url, '/')) as parts from pages")
def hosts(spark, sf_dir):
    return read(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "//([^/]*)", 1).alias("host"), F.size(F.split("url", "/")).cast("long").alias("parts"))


@query("dates", "select o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as month, dayofyear(o_orderdate) as day from orders")
def dates(spark, sf_dir):
    return read(spark, sf_dir, "orders").select("o_orderkey", F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("month"), F.dayofyear("o_orderdate").cast("long").alias("day"))


@query("bits", "select p_partkey, cast(bit_count(p_partkey) as bigint) as ones, p_partkey << 3 as up, ((p_partkey - 1000) % 7 + 7) % 7 as rest from part")
def bits(spark, sf_dir):
    return read(spark, sf_dir, "part").select("p_partkey", F.bit_count("p_partkey").cast("long").alias("ones"), F.shiftleft("p_partkey", 3).alias("up"), F.pmod(F.col("p_partkey") - 1000, F.lit(7)).alias("rest"))


@query("vec_dot", "select vec_id, cast(list_sum(list_transform(embedding, lambda x: cast(round(x * 1000) as bigint) * cast(round(x * 1000) as bigint))) as bigint) as norm from embeddings")
def vec_dot(spark, sf_dir):
    # the product has a component's own precision, nulls are left out, and a vector without values has no norm, as in SQL
    whole = F.transform(F.filter("embedding", lambda x: x.isNotNull()), lambda x: F.round((x * 1000).cast("float")).cast("long"))
    norm = F.aggregate(whole, F.lit(0).cast("long"), lambda a, b: a + b * b)
    return read(spark, sf_dir, "embeddings").select("vec_id", F.when(F.size(whole) > 0, norm).alias("norm"))


@query("props_json", "select event_id, len(json_keys(props)) as keys from events")
def props_json(spark, sf_dir):
    return read(spark, sf_dir, "events").select("event_id", F.size(F.map_keys(F.from_json("props", "map<string,string>"))).cast("long").alias("keys"))


@query("href_edges", "select distinct page_id, unnest(regexp_extract_all(html, 'href=\"(/[^\"]*)\"', 1)) as path from pages")
def href_edges(spark, sf_dir):
    return read(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="(/[^"]*)"'), 1)).alias("path")).distinct()


_REACHED = "with recursive r(n) as (select c_custkey from {c} where c_custkey between 1 and 2 union all select k.c_custkey from r join {c} k on k.c_custkey = r.n * 3) select n from r"


@query("reach_rcte", _REACHED.replace("{c}", "customer"))
def reach_rcte(spark, sf_dir):
    """The customers whose keys tripling reaches from the first two."""
    return spark.sql(_REACHED, c=read(spark, sf_dir, "customer").select("c_custkey"))


@query("udtf_steps", "with recursive s(step, have) as (select cast(0 as bigint), cast(50 as bigint) union all select step + 1, have + greatest(1, cast(floor(0.05 * (0.95 * 1000 / 2 - have)) as bigint)) from s where have <= 400) select step, have from s where have <= 400")
def udtf_steps(spark, sf_dir):
    """A table function of the bulk steps of a side that starts with 50 of 1000 nodes."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="step bigint, have bigint")
    class SweepSteps:
        def eval(self, n: int, have: int, twentieth: int, most: int):
            step = 0
            while have <= most:
                yield step, have
                # delta ((1 - delta) n / 2 - have) with delta = twentieth / 20, in whole numbers
                raw = twentieth * ((20 - twentieth) * n - 40 * have)
                step, have = step + 1, have + max(1, raw // 800)

    return SweepSteps(F.lit(1000), F.lit(50), F.lit(1), F.lit(400))


@query("udf_project", "select vec_id as node_id, cast(round(cast(embedding[1] as double) * 10000) as bigint) * 923880 + cast(round(cast(embedding[2] as double) * 10000) as bigint) * 382683 as key from embeddings")
def udf_project(spark, sf_dir):
    """The projection as a pandas UDF, to compare with the native one."""
    from ..functions.udfs import projector
    from ..sources import graphs

    return graphs.nodes(spark, sf_dir, "emb").select("node_id", projector(923880, 382683)("x", "y").alias("key"))


@query("udaf_expansion", "select c_nationkey, round(min(cast(c_custkey as double) / (1 + c_nationkey)), 6) as least from customer group by 1")
def udaf_expansion(spark, sf_dir):
    """A grouped-aggregate pandas UDF for the least expansion of size and block."""
    from ..functions.udfs import least_expansion

    return read(spark, sf_dir, "customer").groupBy("c_nationkey").agg(least_expansion(F.col("c_custkey").cast("double"), (F.col("c_nationkey") + 1).cast("double")).alias("least"))
