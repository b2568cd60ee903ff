"""Directions, projections, sweep positions and terminal bands, all in integer arithmetic."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.cutter import directions
from ..model import kept, small


def direction_rows(q: int) -> list[tuple[int, int, int]]:
    return [(k, c, s) for k, (c, s) in enumerate(directions(q))]


def project(nodes: DataFrame, q: int) -> DataFrame:
    """nodes with k and key, the node's place along direction k. The q directions are literals of the plan."""
    rows = F.array(*[F.struct(F.lit(k).alias("k"), F.lit(c).cast("long").alias("c"), F.lit(s).cast("long").alias("s")) for k, c, s in direction_rows(q)])
    each = nodes.withColumn("d", F.explode(rows))
    return each.select(*nodes.columns, F.col("d.k").alias("k"), (F.col("x") * F.col("d.c") + F.col("y") * F.col("d.s")).alias("key"))


def global_rank(df: DataFrame, order: list[str], name: str) -> DataFrame:
    """Numbers all rows from 0 by order, without a window over one partition: range partitions, their counts, and local numbers."""
    ranged = kept(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__row", F.monotonically_increasing_id()), "ranked")
    part, local = F.shiftright("__row", 33), F.col("__row").bitwiseAND(F.lit((1 << 33) - 1))
    before, first = 0, {}
    for r in sorted(ranged.groupBy(part.alias("p")).count().collect(), key=lambda r: r["p"]):
        first[r["p"]] = before
        before += r["count"]
    if not first:
        return df.withColumn(name, F.lit(0).cast("long"))
    offset = F.element_at(F.create_map(*[F.lit(x) for kv in first.items() for x in kv]), part)
    return ranged.withColumn(name, (offset + local).cast("long")).drop("__row")


def sweep(nodes: DataFrame, q: int) -> DataFrame:
    """cell_id, k, node_id, pos: each cell's nodes along each direction, ties by id. Rows are numbered by range partitions, so a cell is not one task."""
    ranked = kept(global_rank(project(nodes, q).select("cell_id", "k", "key", "node_id"), ["cell_id", "k", "key", "node_id"], "place"), "swept")
    first = kept(ranked.groupBy("cell_id", "k").agg(F.min("place").alias("first")), "sweep-starts")
    return ranked.join(small(first), ["cell_id", "k"]).select("cell_id", "k", "node_id", (F.col("place") - F.col("first")).alias("pos"))


#: Values that a group's bracket may hold before its distinct values are counted one by one; buckets that a larger bracket is cut into.
WHOLE, BUCKETS = 20_000, 1024


def nth(values: DataFrame, by: list[str], take: DataFrame) -> DataFrame:
    """by, value, before: each group's take-th smallest value, and how many values are smaller. values: by, value (long); take: by, take.

    Selection: a bracket around the wanted rank is cut into buckets, whose counts (one aggregate for all groups) give the next bracket, until it holds
    at most WHOLE values or one value many times. No group is sorted or collected."""
    bounds = values.groupBy(*by).agg(F.min("value").alias("low"), F.max("value").alias("high"), F.count("*").alias("inside"))
    state = kept(take.join(bounds, by).select(*by, "low", "high", "inside", F.col("take").alias("need"), F.lit(0).cast("long").alias("before")), "brackets")
    wide = (F.col("inside") > WHOLE) & (F.col("high") > F.col("low"))
    while not state.filter(wide).isEmpty():
        open_ = state.filter(wide).withColumn("step", F.expr(f"(high - low) div {BUCKETS} + 1"))
        counted = values.join(small(open_), by).filter(F.col("value").between(F.col("low"), F.col("high"))).groupBy(*by, F.expr("(value - low) div step").alias("bucket")).agg(F.count("*").alias("rows"))
        running = F.coalesce(F.sum("rows").over(Window.partitionBy(*by).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        hit = counted.withColumn("less", running).join(open_, by).filter("less < need and less + rows >= need")
        low = F.col("low") + F.col("bucket") * F.col("step")
        narrowed = hit.select(*by, low.alias("low"), F.least("high", low + F.col("step") - 1).alias("high"), F.col("rows").alias("inside"), (F.col("need") - F.col("less")).alias("need"), (F.col("before") + F.col("less")).alias("before"))
        state = kept(state.filter(~wide).unionByName(narrowed), "brackets")
    counted = values.join(small(state), by).filter(F.col("value").between(F.col("low"), F.col("high"))).groupBy(*by, "need", "before", "value").agg(F.count("*").alias("rows"))
    running = F.coalesce(F.sum("rows").over(Window.partitionBy(*by).orderBy("value").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return counted.withColumn("less", running).filter("less < need and less + rows >= need").select(*by, "value", (F.col("before") + F.col("less")).alias("before"))


def bands(nodes: DataFrame, q: int, alpha: float) -> DataFrame:
    """cell_id, k, node_id, term (1 source, 2 target): the first and last floor(alpha * n) nodes of each sweep, at least one; of equal keys
    sources have the smallest ids and targets the largest. Thresholds are found by selection, first of keys, then of ids at the threshold key."""
    keyed = project(nodes, q).select("cell_id", "k", "node_id", F.col("key").alias("low"), (-F.col("key")).alias("high"))
    sign = F.when(F.col("term") == 1, 1).otherwise(-1)
    ends = F.explode(F.array(F.struct(F.lit(1).alias("term"), F.col("low").alias("value")), F.struct(F.lit(2).alias("term"), F.col("high").alias("value")))).alias("end")
    each = kept(keyed.select("cell_id", "k", "node_id", ends).select("cell_id", "k", "end.term", "end.value", "node_id"), "band-keys")
    by = ["cell_id", "k", "term"]
    count = F.greatest(F.lit(1), F.least(F.floor(F.lit(alpha) * F.col("n") + F.lit(1e-9)), F.floor(F.col("n") / 2))).cast("long")
    take = kept(each.groupBy(*by).agg(F.count("*").alias("n")).select(*by, count.alias("take")), "band-sizes")
    keys = kept(nth(each, by, take).withColumnRenamed("value", "key"), "band-keys")
    tied = each.join(small(keys), by).filter(F.col("value") == F.col("key")).select(*by, (F.col("node_id") * sign).alias("value"))
    ids = kept(nth(tied, by, keys.join(take, by).select(*by, (F.col("take") - F.col("before")).alias("take"))).select(*by, F.col("value").alias("last")).join(keys, by), "band-ids")
    marked = each.join(small(ids), by).filter((F.col("value") < F.col("key")) | ((F.col("value") == F.col("key")) & (F.col("node_id") * sign <= F.col("last"))))
    return marked.groupBy("cell_id", "k", "node_id").agg(F.min("term").cast("int").alias("term"))
