"""The live metric feed: observed arc weights from events, windows, late rows, last weights, and re-customization."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def observations(events: DataFrame, arcs: int = 50) -> DataFrame:
    """event_id, arc, ts, user_id, weight. ts becomes a TIMESTAMP, which watermarks need."""
    return events.select("event_id", (F.col("event_id") % arcs).alias("arc"), F.col("ts").cast("timestamp").alias("ts"), "user_id", F.round(F.col("value") * 100).cast("long").alias("weight"))


def windowed(obs: DataFrame, length: str = "1 hour", slide: str | None = None, late: str = "2 hours") -> DataFrame:
    """start, arc, n, weight: counts and the sum of weights by event-time window; works on streams and on tables."""
    marked = obs.withWatermark("ts", late) if obs.isStreaming else obs
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return marked.groupBy(w.alias("w"), "arc").agg(F.count("*").alias("n"), F.sum("weight").alias("weight")).select(F.col("w.start").alias("start"), "arc", "n", "weight")


def sessions(obs: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    """user_id, start, n: runs of a user's events without a longer gap."""
    marked = obs.withWatermark("ts", late) if obs.isStreaming else obs
    return marked.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def deduplicated(obs: DataFrame, late: str = "2 hours") -> DataFrame:
    """Each event once, although files may repeat it."""
    return obs.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"]) if obs.isStreaming else obs.dropDuplicates(["event_id"])


def last_weights(obs: DataFrame) -> DataFrame:
    """arc, weight of the latest event: the metric that a snapshot holds."""
    return obs.groupBy("arc").agg(F.max_by("weight", F.struct("ts", "event_id")).alias("weight"))


def snapshot_writer(path: str, customize=None):
    """A foreachBatch function that merges a batch into the snapshot of batch id - 1 and, if given, customizes with it.

    A batch writes its own folder, so a batch that runs again after a failure overwrites just its own result.
    """

    def write(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        new = batch.select("arc", "ts", "event_id", "weight")
        if number:
            new = new.unionByName(spark.read.parquet(f"{path}/batch={number - 1}").select("arc", "ts", "event_id", "weight"))
        last = new.groupBy("arc").agg(F.max_by(F.struct("ts", "event_id", "weight"), F.struct("ts", "event_id")).alias("l")).select("arc", "l.ts", "l.event_id", "l.weight")
        last.write.mode("overwrite").parquet(f"{path}/batch={number}")
        if customize is not None:
            customize(spark.read.parquet(f"{path}/batch={number}"), number)

    return write


def last_with_ttl(obs: DataFrame, ttl_ms: int, late: str = "2 hours") -> DataFrame:
    """arc, ts, weight, expired: the latest weight of each arc as batches bring it, and once more with expired = true when the watermark has passed
    its time by more than ttl_ms; the arc's state is dropped then. Rows that come later than that start anew."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def keep(key, rows, state: GroupState):
        if state.hasTimedOut:
            ms, _, weight = state.get
            state.remove()
            yield pd.DataFrame({"arc": [key[0]], "ms": [ms], "weight": [weight], "expired": [True]})
            return
        best = state.get if state.exists else None
        for part in rows:
            for now in zip(part.ms.tolist(), part.event_id.tolist(), part.weight.tolist(), strict=True):
                if best is None or now[:2] > best[:2]:
                    best = now
        state.update(best)
        state.setTimeoutTimestamp(max(best[0] + ttl_ms, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"arc": [key[0]], "ms": [best[0]], "weight": [best[2]], "expired": [False]})

    timed = obs.withWatermark("ts", late).select("arc", "ts", F.unix_millis("ts").alias("ms"), "event_id", "weight")
    kept = timed.groupBy("arc").applyInPandasWithState(keep, "arc long, ms long, weight long, expired boolean", "ms long, event_id long, weight long", "update", GroupStateTimeout.EventTimeTimeout)
    return kept.select("arc", F.timestamp_millis("ms").alias("ts"), "weight", "expired")


def followed(first: DataFrame, second: DataFrame, within: str = "10 minutes", late: str = "2 hours") -> DataFrame:
    """a, b: pairs of a user's observations, one of each stream, of which the second comes within a time after the first. Both sides' state ends with the watermarks."""
    mark = lambda df, id_, ts: (df.withWatermark("ts", late) if df.isStreaming else df).select(F.col("event_id").alias(id_), F.col("user_id").alias(f"u{id_}"), F.col("ts").alias(ts))
    a, b = mark(first, "a", "ta"), mark(second, "b", "tb")
    return a.join(b, (F.col("ua") == F.col("ub")) & (F.col("tb") >= F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr(f"interval {within}"))).select("a", "b")


def split_late(obs: DataFrame, seen: DataFrame, late_ms: int) -> tuple[DataFrame, DataFrame]:
    """A batch's rows that are in time and those that a watermark over the rows seen so far (ts) would drop, so that the latter can go to a sink of their own."""
    newest = seen.agg(F.max(F.unix_millis("ts")).alias("newest"))
    marked = obs.crossJoin(F.broadcast(newest)).withColumn("is_late", F.coalesce(F.unix_millis("ts") < F.col("newest") - late_ms, F.lit(False)))
    return marked.filter("not is_late").drop("newest", "is_late"), marked.filter("is_late").drop("newest", "is_late")
