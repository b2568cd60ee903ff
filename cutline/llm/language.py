"""Language identification with bit-sliced Bloom filters of character n-grams.

Training counts the n-grams of a bounded sample of documents per language. An n-gram belongs to a language if its
share of that language's n-grams is at least `ratio` of its largest share in any language. One filter serves 64 languages, and there are as many
filters as the languages need: a slot holds a bitmask of languages, an n-gram sets its languages' bits in `probes` slots, and the AND of these slots
returns all languages of the filter that contain it (and, rarely, others: false positives).

A text is decided by its n-grams: for each language the number of masks with its bit (its popcount) minus the number that
the filter's fill makes likely by chance, weighted by the n-gram's order. The largest count wins, ties go to the language of more training text.

Defined results: null, empty texts and texts without a letter are `und` with score 0; training rows with a null language or text
are left out; without any training row every text is `und`. N-grams that stand once in the sample are left out, except those of a language that has no others.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .common import in_arrow, small, stored, table
from .ngrams import chunks, rolling, spans, sums

ORDERS = (2, 3, 4, 5)
#: Documents of one language that training reads at about the most; whole texts. The only sample of this operator.
SAMPLE_PER_LANGUAGE = 2000
#: Languages of one filter: the bits of its widest mask word.
WORD_LANGUAGES = 64
#: Bits of an n-gram's hash between the starts of two probes.
PROBE_SHIFT = 22
#: Slots of a filter that one row holds while filters are put together.
PART_SLOTS = 1 << 16
#: Counts that a training task holds before it passes them on.
HELD_GRAMS = 1_000_000


def gram_counts(rows: DataFrame) -> DataFrame:
    """lang, n, h, c: hashed n-grams of each language's texts. rows: lang, text."""

    def count(batches):
        held: dict[tuple[str, int], list] = {}
        size = 0

        def merged(parts):
            h = np.concatenate([p[0] for p in parts])
            c = np.concatenate([p[1] for p in parts])
            u, where = np.unique(h, return_inverse=True)
            return u, np.bincount(where, c, len(u)).astype(np.int64)

        def out():
            for (lang, n), parts in held.items():
                u, c = merged(parts)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(u), pa.string()), pa.array(np.full(len(u), n, np.int32)), pa.array(u.view(np.int64)), pa.array(c)], ["lang", "n", "h", "c"])
            held.clear()

        for batch in batches:
            langs = np.array(batch.column("lang").to_pylist(), object)
            for lang in sorted(set(langs)):
                for buffer, starts, ends in chunks(batch.column("text").filter(pa.array(langs == lang))):
                    for n in ORDERS:
                        h = rolling(buffer, n)
                        first, last = spans(starts, ends, n, len(h))
                        inside = np.zeros(len(h) + 1, np.int32)
                        np.add.at(inside, first, 1)
                        np.add.at(inside, last, -1)
                        u, c = np.unique(h[np.cumsum(inside)[:-1] > 0], return_counts=True)
                        parts = held.setdefault((lang, n), [])
                        parts.append((u, c))
                        size += len(u)
                        if len(parts) > 8:
                            held[lang, n] = [merged(parts)]
                            size -= sum(len(x[0]) for x in parts) - len(held[lang, n][0][0])
                if size > HELD_GRAMS:
                    yield from out()
                    size = 0
        yield from out()

    return in_arrow(rows.select("lang", "text"), count, "lang string, n int, h long, c long").groupBy("lang", "n", "h").agg(F.sum("c").alias("c"))


class Filter:
    """The bit-sliced filter of up to 64 languages and the false positive rate of each of them."""

    def __init__(self, masks: np.ndarray, languages: int, probes: int):
        kind = next(t for t in (np.uint8, np.uint16, np.uint32, np.uint64) if np.dtype(t).itemsize * 8 >= max(1, languages))
        self.probes, self.slots, self.masks = probes, len(masks), masks.astype(kind)
        fill = np.array([(self.masks >> kind(i) & kind(1)).mean() for i in range(languages)])
        self.false = fill**probes

    def _places(self, h: np.ndarray) -> list[np.ndarray]:
        low = np.uint64(self.slots - 1)
        return [((h >> np.uint64(PROBE_SHIFT * i)) & low).astype(np.int64) for i in range(self.probes)]

    def languages_of(self, h: np.ndarray) -> np.ndarray:
        """The bitmask of languages for each hash."""
        places = self._places(h)
        mask = self.masks[places[0]]
        for at in places[1:]:
            mask &= self.masks[at]
        return mask


class Filters:
    """The filters of all languages, 64 languages in each. langs: the language of filter k's bit i is langs[64 * k + i]."""

    def __init__(self, langs: list[str], filters: list[Filter]):
        self.langs, self.filters = langs, filters

    def decide(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Predicted language and score (the winner's part of all languages' corrected counts) of each text."""
        letters = pc.match_substring_regex(column.cast(pa.large_string()).fill_null(""), r"\p{L}").to_numpy(zero_copy_only=False)
        lang, score = np.full(len(column), "und", object), np.zeros(len(column))
        if not self.langs:
            return lang, score
        at = 0
        for buffer, starts, ends in chunks(column):
            counts = np.zeros((len(starts), len(self.langs)))
            for n in ORDERS:
                h = rolling(buffer, n)
                first, last = spans(starts, ends, n, len(h))
                total = last - first
                for k, part in enumerate(self.filters):
                    mask = part.languages_of(h)
                    for i, false in enumerate(part.false):
                        hits = sums((mask >> mask.dtype.type(i)) & mask.dtype.type(1), first, last)
                        counts[:, k * WORD_LANGUAGES + i] += n * np.maximum(0, hits - total * false) / (1 - false)
            best = counts.argmax(1)
            own = slice(at, at + len(starts))
            lang[own] = np.array(self.langs, object)[best]
            score[own] = counts.max(1) / np.maximum(counts.sum(1), 1e-12)
            at += len(starts)
        lang[~letters], score[~letters] = "und", 0.0
        return lang, np.clip(score, 0.0, 1.0)


def owned(counts: DataFrame, ratio: float) -> DataFrame:
    """lang, h of the n-grams that belong to a language. counts: lang, n, h, c."""
    most = stored(counts.groupBy("lang").agg(F.max("c").alias("most")), "language-most")
    whole = stored(counts.groupBy("lang", "n").agg(F.sum("c").alias("total")), "language-totals")
    repeated = counts.join(small(most), "lang").filter("c >= 2 or most = 1").join(small(whole), ["lang", "n"])
    shared = repeated.withColumn("share", F.col("c") / F.col("total"))
    best = F.max("share").over(Window.partitionBy("n", "h"))  # a row per language
    return shared.withColumn("best", best).filter(F.col("share") >= F.lit(ratio) * F.col("best")).select("lang", "h")


def build(counts: DataFrame, ratio: float, probes: int, bits_per_gram: int) -> Filters:
    """Filters of counted n-grams. Executors set the bits; the driver only gets the finished masks, one blob for each PART_SLOTS slots."""
    spark = counts.sparkSession
    totals = {r[0]: r[1] for r in counts.groupBy("lang").agg(F.sum("c")).collect()}
    langs = sorted(totals, key=lambda x: (-totals[x], x))
    bits = spark.createDataFrame([(lang, i // WORD_LANGUAGES, (1 << i % WORD_LANGUAGES) - (1 << 64 if i % WORD_LANGUAGES == 63 else 0)) for i, lang in enumerate(langs)], "lang string, k int, bit long")
    grams = stored(owned(counts, ratio).join(F.broadcast(bits), "lang").groupBy("k", "h").agg(F.bit_or("bit").alias("mask")), "language-grams")
    size = {r[0]: 1 << max(10, int(np.ceil(np.log2(r[1] * bits_per_gram / 8)))) for r in grams.groupBy("k").count().collect()}
    slots = spark.createDataFrame([(k, n - 1) for k, n in size.items()], "k int, low long")
    places = F.array(*[F.shiftrightunsigned("h", PROBE_SHIFT * i).bitwiseAND(F.col("low")) for i in range(probes)])
    each = grams.join(F.broadcast(slots), "k").select("k", "mask", F.explode(places).alias("slot"))
    filled = each.groupBy("k", "slot").agg(F.bit_or("mask").alias("mask")).withColumn("part", F.floor(F.col("slot") / PART_SLOTS))

    def blob(t: pa.Table) -> pa.Table:
        masks = np.zeros(PART_SLOTS, np.int64)
        masks[t.column("slot").to_numpy() % PART_SLOTS] = t.column("mask").to_numpy()
        return pa.table({"k": t.column("k").slice(0, 1), "part": t.column("part").slice(0, 1), "masks": pa.array([masks.tobytes()], pa.binary())})

    whole = {k: np.zeros(max(n, PART_SLOTS), np.uint64) for k, n in size.items()}
    for r in filled.groupBy("k", "part").applyInArrow(blob, "k int, part long, masks binary").toLocalIterator():
        whole[r.k][r.part * PART_SLOTS : (r.part + 1) * PART_SLOTS] = np.frombuffer(r.masks, np.uint64)
    parts = range(0, len(langs), WORD_LANGUAGES)
    return Filters(langs, [Filter(whole[k][: size[k]] if k in size else np.zeros(1 << 10, np.uint64), len(langs[at : at + WORD_LANGUAGES]), probes) for k, at in enumerate(parts)])


def train(rows: DataFrame, ratio: float = 0.35, sample: int = SAMPLE_PER_LANGUAGE, key: str = "doc_id", lang: str = "lang", text: str = "text", probes: int = 2, bits_per_gram: int = 16) -> Filters:
    """Filters from rows' languages: about `sample` whole documents of each, those with the smallest key hashes."""
    known = rows.filter(F.col(lang).isNotNull() & F.col(text).isNotNull())
    sizes = stored(known.groupBy(F.col(lang).cast("string").alias("lang")).agg(F.count("*").alias("rows")), "language-sizes")
    place = F.pmod(F.xxhash64(F.col(key).cast("string")), F.lit(1 << 20)) / float(1 << 20)
    keyed = known.select(F.col(lang).cast("string").alias("lang"), F.col(text).alias("text"), place.alias("place"))
    chosen = keyed.join(small(sizes), "lang").filter(F.col("place") * F.col("rows") < sample).select("lang", "text")
    return build(stored(gram_counts(chosen), "language-counts"), ratio, probes, bits_per_gram)


def predict(docs: DataFrame, filters: Filters, text: str = "text") -> DataFrame:
    """docs with lang_pred and score; columns of these names are replaced."""
    docs = docs.drop("lang_pred", "score")
    held = docs.sparkSession.sparkContext.broadcast(filters)
    names = docs.columns
    schema = T.StructType([*docs.schema.fields, T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])

    def run(batches):
        for batch in batches:
            lang, score = held.value.decide(batch.column(text))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(lang, pa.string()), pa.array(score)], [*names, "lang_pred", "score"])

    return in_arrow(docs, run, schema)


def remainder(key, n: int):
    """crc32 of the key as text, modulo n."""
    return F.pmod(F.crc32(F.encode(key.cast("string"), "UTF-8")), F.lit(n))


def op10_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The language of every document; a third is held out of training."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    held_out = F.coalesce(remainder(F.col("doc_id"), 3) == 1, F.lit(False))
    filters = train(docs.filter(~held_out))
    done = predict(docs.select("doc_id", "text"), filters)
    return done.select("doc_id", held_out.alias("held_out"), "lang_pred", "score")
