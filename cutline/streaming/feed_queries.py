"""Queries of the metric feed: each runs the stream over the events table to its end and returns what the sink got."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..model import shared_folder
from ..operators import index
from ..plans import index_queries
from ..plans.catalog import query
from ..sources import graphs
from . import feed


def _source(spark, sf_dir):
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    whole = f"{sf_dir}/events.parquet"
    one_file = events.inputFiles()
    # a file source reads folders: the table's own, or the folder of the single file
    path = whole if len(one_file) > 1 or one_file[0].rstrip("/").rpartition("/")[2] != "events.parquet" else sf_dir
    stream = spark.readStream.schema(events.schema).option("pathGlobFilter", "events.parquet" if path == sf_dir else "*.parquet").parquet(path)
    return feed.observations(stream)


def drained(df, mode="append"):
    spark = df.sparkSession
    out, state = (f"{shared_folder(spark)}/{k}-{uuid.uuid4().hex}" for k in ("feed", "feed-state"))
    if mode == "complete":
        # each batch brings the whole result; it goes to a folder of its own, not through the driver
        batches = []

        def write(batch, number):
            batch.write.mode("overwrite").parquet(f"{out}/batch={number}")
            batches.append(number)

        df.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{out}/batch={batches[-1]}") if batches else spark.createDataFrame([], df.schema)
    df.writeStream.format("parquet").option("path", out).option("checkpointLocation", state).trigger(availableNow=True).outputMode(mode).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(out)


_OBS = "o as (select event_id, event_id % 50 as arc, ts, user_id, cast(round(value * 100) as bigint) as weight from events)"
_US = lambda c: F.unix_micros(c)


@query("feed_tumbling", f"with {_OBS} select epoch_us(time_bucket(interval '1 hour', ts)) as start, arc, count(*) as n, cast(sum(weight) as bigint) as weight from o group by 1, 2")
def feed_tumbling(spark, sf_dir):
    return drained(feed.windowed(_source(spark, sf_dir)), "complete").select(_US(F.col("start")).alias("start"), "arc", "n", "weight")


@query("feed_sliding", f"with {_OBS}, s as (select *, unnest([0, 1, 2, 3]) as k from o) select epoch_us(time_bucket(interval '15 minutes', ts) - k * interval '15 minutes') as start, arc, count(*) as n, cast(sum(weight) as bigint) as weight from s group by 1, 2")
def feed_sliding(spark, sf_dir):
    return drained(feed.windowed(_source(spark, sf_dir), "1 hour", "15 minutes"), "complete").select(_US(F.col("start")).alias("start"), "arc", "n", "weight")


@query("feed_session", f"with {_OBS}, g as (select *, case when ts - lag(ts) over (partition by user_id order by ts) <= interval '30 minutes' then 0 else 1 end as new from o), s as (select *, sum(new) over (partition by user_id order by ts, event_id) as k from g) select user_id, epoch_us(min(ts)) as start, count(*) as n from s group by user_id, k")
def feed_session(spark, sf_dir):
    return drained(feed.sessions(_source(spark, sf_dir)), "complete").select("user_id", _US(F.col("start")).alias("start"), "n")


@query("feed_dedup", f"with {_OBS} select count(distinct event_id) as events from o")
def feed_dedup(spark, sf_dir):
    """The feed twice over: each event arrives once."""
    s = _source(spark, sf_dir)
    return drained(feed.deduplicated(s.unionByName(_source(spark, sf_dir)))).agg(F.count("*").alias("events"))


@query("feed_last", f"with {_OBS} select arc, arg_max(weight, (ts, event_id)) as weight from o group by 1")
def feed_last(spark, sf_dir):
    """The latest weight of each arc through foreachBatch snapshots."""
    path, state = (f"{shared_folder(spark)}/{k}-{uuid.uuid4().hex}" for k in ("snapshot", "snapshot-state"))
    _source(spark, sf_dir).writeStream.foreachBatch(feed.snapshot_writer(path)).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    last = spark.read.parquet(path).agg(F.max("batch")).first()[0]
    return spark.read.parquet(f"{path}/batch={last}").select("arc", "weight")


def _drained_updates(df):
    """What a memory sink got of a stream in update mode."""
    name, state = f"feed_{uuid.uuid4().hex}", f"{shared_folder(df.sparkSession)}/feed-state-{uuid.uuid4().hex}"
    df.writeStream.format("memory").queryName(name).outputMode("update").option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    return df.sparkSession.table(name)


@query("feed_ttl", f"""with {_OBS}, l as (select arc, arg_max(weight, (epoch_us(ts) // 1000, event_id)) as weight, max(epoch_us(ts) // 1000) as ms from o group by 1), m as (select max(ms) as top from l)
    select arc, weight, ms, false as expired from l union all select arc, weight, ms, true from l, m where ms + 60000 < top""")
def feed_ttl(spark, sf_dir):
    """Last weights with a time to live of a minute after the watermark: each arc's latest, and the end of those that went stale."""
    got = _drained_updates(feed.last_with_ttl(_source(spark, sf_dir), 60_000, "0 seconds"))
    return got.select("arc", "weight", F.unix_millis("ts").alias("ms"), "expired")


@query("feed_join", f"with {_OBS} select a.event_id as a, b.event_id as b from o a join o b on a.user_id = b.user_id and a.event_id % 2 = 0 and b.event_id % 2 = 1 and b.ts >= a.ts and b.ts <= a.ts + interval '10 minutes'")
def feed_join(spark, sf_dir):
    """Two streams joined by user and time."""
    return drained(feed.followed(_source(spark, sf_dir).filter("event_id % 2 = 0"), _source(spark, sf_dir).filter("event_id % 2 = 1")))


@query("feed_late_rows", f"with {_OBS}, m as (select max(epoch_us(ts) // 1000) - 3600000 as edge from o where event_id % 2 = 0) select case when epoch_us(ts) // 1000 < edge then 'late' else 'in time' end as kind, count(*) as n from o, m where event_id % 2 = 1 group by 1")
def feed_late_rows(spark, sf_dir):
    """Rows of a batch by whether a watermark of an hour over the rows before would drop them: both go to sinks of their own."""
    events = feed.observations(spark.read.parquet(f"{sf_dir}/events.parquet"))
    in_time, late = feed.split_late(events.filter("event_id % 2 = 1"), events.filter("event_id % 2 = 0"), 3_600_000)
    return in_time.select(F.lit("in time").alias("kind")).unionByName(late.select(F.lit("late").alias("kind"))).groupBy("kind").agg(F.count("*").alias("n"))


_LIVE = index_queries._BASE.replace(f"w as ({graphs.duck('supp', 'time')})", f"{_OBS}, last as (select arc, arg_max(weight, (ts, event_id)) as weight from o group by 1), w as (select e.u, e.v, 1 + abs(coalesce(l.weight, 0)) % 1000 as weight from e left join last l on l.arc = (e.u * 7 + e.v * 3) % 50)")


@query("feed_customized", f"with recursive {_LIVE}, {index_queries._lower('w.weight')} select i.lo, i.hi, c.d as up, c.d as down from i join c on c.o = i.lo and c.v = i.hi")
def feed_customized(spark, sf_dir):
    """The stream of weights re-customizes the index: each batch merges its weights into the snapshot and writes the index' weights for it."""
    g, ranks, arcs = index_queries._built(spark, sf_dir)
    path, state = (f"{shared_folder(spark)}/{k}-{uuid.uuid4().hex}" for k in ("live", "live-state"))

    def customize(last, number):
        live = last.select("arc", F.col("weight").alias("seen"))
        metric = g.edges.withColumn("arc", (F.col("u") * 7 + F.col("v") * 3) % 50).join(live, "arc", "left").select("u", "v", (1 + F.abs(F.coalesce("seen", F.lit(0))) % 1000).alias("weight"))
        index.customize(arcs, g, ranks, metric).write.mode("overwrite").parquet(f"{path}-weights/batch={number}")

    _source(spark, sf_dir).writeStream.foreachBatch(feed.snapshot_writer(path, customize)).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    whole = spark.read.parquet(f"{path}-weights")
    return whole.join(whole.agg(F.max("batch").alias("batch")), "batch").select("lo", "hi", "up", "down")
