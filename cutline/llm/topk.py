"""Exact top-k inner products with MaxScore over sharded postings.

A vector component is a term, and the rows with a value in it are its posting list. What a list can add to a score is bounded by the
query's component times the list's largest value of the same sign (values of the other sign only lower a score). A query's terms
sorted by bound split into non-essential ones, whose bounds together stay below the k-th best score so far, and essential ones: a
row that is in no essential list can't be among the best. Essential lists are traversed; rows whose partial score plus the remaining
bounds still reaches the threshold are probed in the other terms, largest bounds first, and drop out as soon as they are beaten. Ties
stay competitive, so the result is exact.

Rows are dealt into shards of about `shard_rows` rows and queries into blocks of about `block_rows`; each block meets each shard in
one task that returns at most k rows a query, and the shards' lists are merged by a window. A shard's lists are cut into runs of
`RUN` rows, longest vectors first, each with its own bounds: after every run the threshold rises to the k-th best score so far,
terms move to the non-essential side, and a run whose bounds together stay below it is passed over. A first shard is searched alone, and its
k-th best scores are where all other shards begin. Memory of a task is one shard and one block, whatever the table.

Lists of dense embeddings hold nearly every row, so a run keeps a list as an array by row number, and products of many lists are taken at once;
sums are whole numbers below 2**53 in doubles, or longs where a run's bounds don't prove that.

Defined results: vectors that are null or hold a null or non-finite component take no part, neither as query nor as
row; shorter vectors have zeros at their end; scores that don't fit a long wrap around; rows that share the query's id
are the query's own and left out; repeated rows are ranked one after another; empty tables give an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import in_arrow, stored, table

SHARD_ROWS = 8192
BLOCK_ROWS = 512
RUN = 1024
PROBE = 8
#: Sums of whole numbers below this are exact in doubles.
EXACT = float(1 << 53)


def scaled(df: DataFrame, key: str, vector: str, scale: int) -> DataFrame:
    """id and v: floor(scale * x) of each component as long; without null, broken and non-finite vectors."""
    x = F.col(vector)
    sound = x.isNotNull() & ~F.exists(x, lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf")))
    return df.filter(sound).select(F.col(key).alias("id"), F.transform(x, lambda c: F.floor(c.cast("double") * scale).cast("long")).alias("v"))


class Run:
    """The posting lists of some rows: one array by row number for each term, and how far its values reach to both sides."""

    def __init__(self, ids: np.ndarray, rows: np.ndarray):
        self.ids, self.rows, self.lists = ids, rows, np.ascontiguousarray(rows.T)
        self.up, self.down = (np.maximum(0, x.max(1).astype(float)) for x in (self.lists, -self.lists.astype(float)))
        self.doubles = self.lists.astype(np.float64)

    def bounds(self, q: np.ndarray) -> np.ndarray:
        return np.where(q > 0, q * self.up, -q * self.down)

    def partial(self, terms: np.ndarray, q: np.ndarray, exact: bool, among: np.ndarray | None = None) -> np.ndarray:
        """Sums over these terms for all rows, or for the rows `among`."""
        lists = (self.doubles if exact else self.lists)[terms]
        if among is not None:
            lists = lists[:, among]
        return (q[terms].astype(lists.dtype) @ lists).astype(np.int64)


class Shard:
    """Runs of rows, longest vectors first. `work` counts rows, rows that stayed after the essential lists, and values looked up."""

    def __init__(self, ids: np.ndarray, rows: np.ndarray, run: int = RUN):
        order = np.lexsort((ids, -(rows.astype(float) ** 2).sum(1)))
        ids, rows = ids[order], rows[order]
        self.runs = [Run(ids[at : at + run], rows[at : at + run]) for at in range(0, len(ids), run)]
        self.work = np.zeros(3, np.int64)

    def search(self, q: np.ndarray, own: int, k: int, least: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Ids and scores of the k best rows without id `own`, ties to smaller ids; rows below `least` may be missing."""
        ids, scores = np.zeros(0, np.int64), np.zeros(0, np.int64)
        for run in self.runs:
            bound = run.bounds(q)
            order = np.argsort(bound, kind="stable")
            below = np.cumsum(bound[order])
            exact = float((np.abs(q) * np.maximum(run.up, run.down)).sum()) < EXACT
            self.work += (len(run.ids), 0, 0)
            light, rest, among = 0, 0.0, None
            if least is not None and exact:
                if below[-1] < least:
                    continue
                light = int(np.searchsorted(below, least, "left"))  # so many terms together stay below the threshold
                rest = below[light - 1] if light else 0.0
            partial = run.partial(order[light:], q, exact)
            self.work += (0, 0, len(run.ids) * (len(order) - light))
            if light:
                among = np.flatnonzero(partial + rest >= least)
                partial = partial[among]
                self.work += (0, len(among), 0)
            while light and len(among):
                step = order[max(0, light - PROBE) : light]
                light = max(0, light - PROBE)
                rest = below[light - 1] if light else 0.0
                partial = partial + run.partial(step, q, exact, among)
                self.work += (0, 0, len(among) * len(step))
                alive = partial + rest >= least
                among, partial = among[alive], partial[alive]
            found = run.ids if among is None else run.ids[among]
            keep = found != own
            ids, scores = np.concatenate([ids, found[keep]]), np.concatenate([scores, partial[keep]])
            if len(ids) > k:
                cut = np.partition(scores, len(scores) - k)[len(scores) - k]
                some = scores >= cut
                ids, scores = ids[some], scores[some]
                best = np.lexsort((ids, -scores))[:k]
                ids, scores = ids[best], scores[best]
            if len(ids) == k:
                least = max(int(scores.min()), least) if least is not None else int(scores.min())
        best = np.lexsort((ids, -scores))
        return ids[best], scores[best]


def narrow(rows: np.ndarray) -> tuple[str, bytes]:
    """The smallest whole-number type that holds rows, and their bytes in it."""
    kind = next(t for t in ("<i2", "<i4", "<i8") if not rows.size or (rows.min() >= np.iinfo(t).min and rows.max() <= np.iinfo(t).max))
    return kind, rows.astype(kind).tobytes()


def _packed(df: DataFrame, group: str, prefix: str) -> DataFrame:
    """One row per group: its ids, rows and thresholds as bytes. Groups have a bounded number of rows by the caller's choice of their number."""

    def pack(t: pa.Table) -> pa.Table:
        vectors = t.column("v").to_pylist()
        rows = np.zeros((t.num_rows, max([1, *map(len, vectors)])), np.int64)
        for i, v in enumerate(vectors):
            rows[i, : len(v)] = v
        kind, raw = narrow(rows)
        blobs = {"ids": t.column("id").to_numpy().astype(np.int64).tobytes(), "rows": raw, "least": np.array(t.column("least").to_pylist(), np.float64).tobytes()}
        return pa.table({group: t.column(group).slice(0, 1), f"{prefix}_kind": pa.array([kind]), **{f"{prefix}_{c}": pa.array([b], pa.binary()) for c, b in blobs.items()}})

    return df.groupBy(group).applyInArrow(pack, f"{group} long, {prefix}_kind string, {prefix}_ids binary, {prefix}_rows binary, {prefix}_least binary")


def _met(pairs: DataFrame, k: int) -> DataFrame:
    """query_id, vec_id, score: the k best rows of each shard for each query of each block that it meets."""
    names = [f"{p}_{c}" for p in "rq" for c in ("kind", "ids", "rows", "least")]

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                r_kind, r_ids, r_rows, _, q_kind, q_ids, q_rows, q_least = (batch.column(c)[i].as_py() for c in names)
                ids, asked, least = np.frombuffer(r_ids, np.int64), np.frombuffer(q_ids, np.int64), np.frombuffer(q_least, np.float64)
                data, queries = np.frombuffer(r_rows, r_kind).reshape(len(ids), -1), np.frombuffer(q_rows, q_kind).reshape(len(asked), -1)
                width = max(data.shape[1], queries.shape[1])
                data, queries = (np.pad(x, ((0, 0), (0, width - x.shape[1]))).astype(np.int64) for x in (data, queries))
                shard, out = Shard(ids, data), [[], [], []]
                for own, q, t in zip(asked.tolist(), queries, least.tolist(), strict=True):
                    found, score = shard.search(q, own, k, None if np.isnan(t) else int(t))
                    for column, x in zip(out, (np.full(len(found), own, np.int64), found, score), strict=True):
                        column.append(x)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in out], ["query_id", "vec_id", "score"])

    return in_arrow(pairs.select(*names), run, "query_id long, vec_id long, score long")


def search(rows: DataFrame, queries: DataFrame, k: int, shard_rows: int = SHARD_ROWS, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """query_id, rank, vec_id, score. rows and queries: id long, v array<long> (as of `scaled`)."""
    shards = max(1, -(-rows.count() // shard_rows))
    blocks = max(1, -(-queries.count() // block_rows))
    dealt = lambda df, name, n: df.filter("id is not null").withColumn(name, F.pmod(F.xxhash64("id"), F.lit(n)))
    each = lambda a, n: F.explode(F.sequence(F.lit(a).cast("long"), F.lit(n - 1).cast("long")))
    left = stored(_packed(dealt(rows, "shard", shards).withColumn("least", F.lit(None).cast("double")), "shard", "r"), "topk-shards")
    asked = dealt(queries, "block", blocks)
    first = stored(_packed(asked.withColumn("least", F.lit(None).cast("double")), "block", "q"), "topk-blocks").withColumn("shard", F.lit(0).cast("long"))
    found = stored(_met(left.filter("shard = 0").withColumn("block", each(0, blocks)).join(first, ["shard", "block"]), k), "topk-first")
    if shards > 1:
        # a threshold is a score that k rows of the first shard reach; doubles hold it exactly below 2**53, and none is taken from there on
        reached = found.groupBy("query_id").agg(F.count("*").alias("n"), F.min("score").alias("s")).filter((F.col("n") >= k) & (F.abs("s") < EXACT)).select(F.col("query_id").alias("id"), F.col("s").cast("double").alias("least"))
        later = _packed(asked.join(reached, "id", "left"), "block", "q").withColumn("shard", each(1, shards))
        found = found.unionByName(_met(left.filter("shard > 0").withColumn("block", each(0, blocks)).join(later, ["shard", "block"]), k))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op1_maxscore(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ten best rows of every hundredth vector by integer inner product."""
    rows = scaled(table(spark, sf_dir, "embeddings"), "vec_id", "embedding", 1024)
    return search(rows, rows.filter(F.pmod("id", F.lit(100)) == 0), 10)


OP1_SQL = """
with e as (select vec_id, list_transform(embedding, lambda x: cast(floor(1024 * cast(x as double)) as bigint)) as v from embeddings
           where embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0),
s as (select q.vec_id as query_id, r.vec_id, cast(list_dot_product(q.v::double[], r.v::double[]) as bigint) as score
      from e q join e r on q.vec_id % 100 = 0 and q.vec_id <> r.vec_id),
t as (select *, row_number() over (partition by query_id order by score desc, vec_id) as rank from s)
select query_id, cast(rank as integer) as rank, vec_id, score from t where rank <= 10
"""
