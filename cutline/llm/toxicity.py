"""Toxicity: a linear classifier over character n-grams, features scaled by naive Bayes log-count ratios.

Features are hashed character n-grams of a whole text, counted once per text. Training takes at most about `sample` labelled rows, those
with the smallest key hashes, and counts in how many toxic and clean texts each n-gram occurs, and takes r = ln of the ratio of the smoothed shares. The n-grams
with the largest r * sqrt(support) in absolute value become the features, with value r where present. A logistic regression
over these is fitted by Newton's method.

Scoring looks each position's n-gram up in a table of weights; n-grams that are no feature weigh 0, so that only
the few others are made distinct per text.

Defined results: null and empty texts get the score of a text without any feature; without labels, or with one
class only, every score is the smoothed share of toxic labels; repeated labels of a row count repeatedly.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import in_arrow, stored, table
from .language import remainder
from .ngrams import chunks, rolling, spans

ORDERS = (3, 4, 5, 6)
SLOTS = 1 << 20
PART = 1 << 14
#: Labelled rows that counts and regression are fitted on at about the most, those with the smallest key hashes; the only
#: sample of this operator. All texts are scored.
SAMPLE = 40_000
#: Tasks that count the sample.
COUNTERS = 16
FEATURES = 4096


def _slots(h: np.ndarray) -> np.ndarray:
    return (h & np.uint64(SLOTS - 1)).astype(np.int64)


def features_of(column: pa.Array, wanted: np.ndarray | None = None):
    """(row, slot) of each distinct n-gram of each text; only slots where `wanted` holds, if given. Yields blocks."""
    at = 0
    for buffer, starts, ends in chunks(column, 1_000_000):
        rows, slots = [], []
        for n in ORDERS:
            slot = _slots(rolling(buffer, n))
            first, last = spans(starts, ends, n, len(slot))
            where = np.flatnonzero(wanted[slot]) if wanted is not None else np.arange(len(slot))
            row = np.searchsorted(first, where, "right") - 1
            inside = (row >= 0) & (where < last[np.maximum(row, 0)])
            rows.append(row[inside])
            slots.append(slot[where[inside]])
        pair = np.unique(np.concatenate(rows) * SLOTS + np.concatenate(slots))
        yield at, len(starts), pair // SLOTS, pair % SLOTS
        at += len(starts)


def count_features(labelled: DataFrame) -> tuple[np.ndarray, np.ndarray, int, int]:
    """Clean and toxic texts that hold each slot, and numbers of clean and toxic texts. labelled: text, label (0 or 1), a bounded sample."""

    def count(batches):
        held, n = np.zeros((2, SLOTS), np.int32), np.zeros(2, np.int64)
        for batch in batches:
            labels = batch.column("label").to_numpy(zero_copy_only=False).astype(np.int64)
            n += np.bincount(labels, minlength=2)
            for at, _, row, slot in features_of(batch.column("text")):
                for label in (0, 1):
                    held[label] += np.bincount(slot[labels[at + row] == label], minlength=SLOTS).astype(np.int32)
        # a task's counts leave in parts, so that they are added up in parallel
        for label in (0, 1):
            blobs = [held[label, part : part + PART].tobytes() for part in range(0, SLOTS, PART)]
            yield pa.RecordBatch.from_arrays([pa.array([label] * len(blobs), pa.int32()), pa.array(range(len(blobs)), pa.int32()), pa.array(blobs, pa.binary()), pa.array([int(n[label])] * len(blobs), pa.int64())], ["label", "part", "counts", "n"])

    def add(t: pa.Table) -> pa.Table:
        total = sum(np.frombuffer(b, np.int32).astype(np.int64) for b in t.column("counts").to_pylist())
        return pa.table({"label": t.column("label").slice(0, 1), "part": t.column("part").slice(0, 1), "counts": pa.array([total.astype(np.int32).tobytes()], pa.binary()), "n": pa.array([sum(t.column("n").to_pylist())], pa.int64())})

    schema = "label int, part int, counts binary, n long"
    counts, n = np.zeros((2, SLOTS), np.int64), [0, 0]
    for r in in_arrow(labelled.select("text", "label").repartition(COUNTERS), count, schema).groupBy("label", "part").applyInArrow(add, schema).collect():
        counts[r.label, r.part * PART : (r.part + 1) * PART] = np.frombuffer(r.counts, np.int32)
        n[r.label] = r.n
    return counts[0], counts[1], *n


class Model:
    def __init__(self, weights: np.ndarray, bias: float):
        self.weights, self.bias, self.wanted = weights.astype(np.float32), float(bias), weights != 0

    def score(self, column: pa.Array) -> np.ndarray:
        out = np.full(len(column), self.bias)
        for at, n, row, slot in features_of(column, self.wanted):
            out[at : at + n] += np.bincount(row, self.weights[slot], n)
        return 1 / (1 + np.exp(-np.clip(out, -500, 500)))


def fit(x_rows: np.ndarray, x_cols: np.ndarray, values: np.ndarray, y: np.ndarray, n_features: int, penalty: float, rounds: int = 25) -> tuple[np.ndarray, float]:
    """L2-penalised logistic regression by Newton steps, each solved by conjugate gradients; sparse rows (row, column) with values[column]."""
    v = values[x_cols]
    forward = lambda w: np.bincount(x_rows, v * w[x_cols], len(y))
    back = lambda e: np.bincount(x_cols, v * e[x_rows], n_features)
    rate = (y.sum() + 0.5) / (len(y) + 1)
    w, b = np.zeros(n_features), float(np.log(rate / (1 - rate)))

    def loss(w, b):
        z = forward(w) + b
        return float((np.logaddexp(0, z) - y * z).sum() + penalty / 2 * w @ w)

    now = loss(w, b)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(forward(w) + b, -500, 500)))
        h = np.maximum(p * (1 - p), 1e-9)
        g, gb = back(p - y) + penalty * w, float((p - y).sum())
        if np.sqrt(g @ g + gb * gb) < 1e-4 * len(y) ** 0.5:
            break
        apply = lambda d, db: ((t := h * (forward(d) + db)), (back(t) + penalty * d, float(t.sum()) + 1e-9 * db))[1]
        d, db, r, rb = np.zeros(n_features), 0.0, -g, -gb
        q, qb, rr = r.copy(), rb, r @ r + rb * rb
        for _ in range(60):
            a, ab = apply(q, qb)
            step = rr / max(q @ a + qb * ab, 1e-30)
            d, db, r, rb = d + step * q, db + step * qb, r - step * a, rb - step * ab
            new = r @ r + rb * rb
            if new < 1e-6 * (g @ g + gb * gb):
                break
            q, qb, rr = r + new / rr * q, rb + new / rr * qb, new
        scale = 1.0
        while scale > 1e-6 and (then := loss(w + scale * d, b + scale * db)) > now:
            scale /= 2
        if scale <= 1e-6:
            break
        w, b, gain, now = w + scale * d, b + scale * db, now - then, then
        if gain < 1e-6 * max(1.0, now):
            break
    return w, b


def train(labelled: DataFrame, rows: int, features: int = FEATURES, sample: int = SAMPLE, penalty: float = 1.0, alpha: float = 1.0) -> Model:
    """labelled: key, text, label (0 or 1), about `rows` of them."""
    place = F.pmod(F.xxhash64(F.col("key").cast("string")), F.lit(1 << 20)) / float(1 << 20)
    labelled = stored(labelled.filter(place < min(1.0, sample / max(1, rows))).select("text", "label"), "labelled")
    clean, toxic, n0, n1 = count_features(labelled)
    weights = np.zeros(SLOTS)
    if not n0 or not n1:
        share = (n1 + 0.5) / (n0 + n1 + 1)
        return Model(weights, float(np.log(share / (1 - share))))
    ratio = np.log(((toxic + alpha) / (n1 + 2 * alpha)) / ((clean + alpha) / (n0 + 2 * alpha)))
    worth = np.abs(ratio) * np.sqrt(np.minimum(toxic / n1, 1) * n1 + np.minimum(clean / n0, 1) * n1)
    worth[(toxic + clean) < 3] = 0
    chosen = np.sort(np.argsort(-worth, kind="stable")[:features])
    chosen = chosen[worth[chosen] > 0]
    column_of = np.full(SLOTS, -1, np.int64)
    column_of[chosen] = np.arange(len(chosen))
    wanted = column_of >= 0
    held = labelled.sparkSession.sparkContext.broadcast(wanted)

    def sparse(batches):
        for batch in batches:
            labels = batch.column("label").to_numpy(zero_copy_only=False)
            for at, n, row, slot in features_of(batch.column("text"), held.value):
                ends = np.searchsorted(row, np.arange(n + 1))
                yield pa.RecordBatch.from_arrays([pa.array(labels[at : at + n].astype(np.int32)), pa.array([slot[ends[i] : ends[i + 1]].astype(np.int32).tobytes() for i in range(n)], pa.binary())], ["y", "slots"])

    rows = in_arrow(labelled, sparse, "y int, slots binary").toPandas()
    lengths = rows.slots.map(len).to_numpy() // 4
    cols = column_of[np.frombuffer(b"".join(rows.slots), np.int32)]
    # values are the log-count ratios, so the fitted weight is multiplied by them
    w, b = fit(np.repeat(np.arange(len(rows)), lengths), cols, ratio[chosen], rows.y.to_numpy(float), len(chosen), penalty)
    weights[chosen] = w * ratio[chosen]
    return Model(weights, b)


def predict(docs: DataFrame, model: Model, text: str = "text") -> DataFrame:
    """docs with score (0 to 1) and predicted (1 from 0.5 on); columns of these names are replaced."""
    docs = docs.drop("score", "predicted")
    held, names = docs.sparkSession.sparkContext.broadcast(model), docs.columns
    schema = T.StructType([*docs.schema.fields, T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())])

    def run(batches):
        for batch in batches:
            score = held.value.score(batch.column(text))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(score), pa.array((score >= 0.5).astype(np.int32))], [*names, "score", "predicted"])

    return in_arrow(docs, run, schema)


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A toxicity score for every document; a fifth is held out of training."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    held_out = F.coalesce(remainder(F.col("doc_id"), 5) == 0, F.lit(False))
    labels = table(spark, sf_dir, "labels").filter(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out)
    labelled = docs.filter(~held_out).join(labels.select("doc_id", "toxic"), "doc_id").select(F.col("doc_id").alias("key"), F.coalesce("text", F.lit("")).alias("text"), F.col("toxic").alias("label"))
    return predict(docs, train(labelled, labels.count())).select("doc_id", held_out.alias("held_out"), "score", "predicted")
