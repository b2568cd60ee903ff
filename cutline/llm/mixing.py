"""Entropy balancing of sources to target word counts, in DataFrame operations only.

Every document gets a rate r: how often the mix takes it. Among all rates between 0 and `cap` whose words
meet each source's target, entropy balancing takes those of least relative entropy to the base rate 1,
each document weighing 1. The dual of that problem is convex, with one multiplier per source, and its solution
tilts the base rates exponentially: r = cap * e^z / (cap - 1 + e^z), z = multiplier * size / (mean size of its source),
which is e^z where the cap is far off. Newton iterations with a bracket (bisection where a step
leaves it) solve it; each iteration is one distributed aggregate over the (source, size) histogram, whose
sums are exact decimals, so that partitioning can't change them. Multipliers and brackets are a table with one row per source; no source reaches the driver.

Rates become copies per (source, size) cell: copies are handed out so that running totals in order of falling
size stay within half a document of the running expected number, and what is then missing of a source's words
is made up with its shortest documents. Within a cell the documents with the smallest hashes get the odd copies.

Defined results: null or empty texts have size 0 and are taken once at rate 1 (0 words); a null source
is a source of its own, sorted last; a source without words has target 0; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import WORD, numbered, small, stored, table

#: The multiplier of a source whose rate is the cap or 0 to the last bit.
BOUND = 60.0


def source_targets(cells: DataFrame, weights: list[float], share: float, cap: float) -> DataFrame:
    """source, source_size, target: weights repeat over the sources in code point order, null last; the targets
    share `share` times all words by weight, none above cap times its source, the excess reshared by weight.

    Water-filling in closed form: a source is full iff the level at which it fills (cap * size / weight) is
    at most the common level, and the common level follows from the prefix of sources sorted by fill level.
    """
    sums = cells.groupBy("source").agg(F.sum(F.col("size") * F.col("n")).cast("long").alias("source_size"))
    place = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    ranked = sums.withColumn("weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(place, F.lit(len(weights))) + 1).cast("int")))
    full = ranked.withColumn("fills", F.lit(cap) * F.col("source_size") / F.col("weight"))
    before = Window.orderBy("fills", F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    onward = Window.orderBy("fills", F.col("source").asc_nulls_last()).rowsBetween(0, Window.unboundedFollowing)
    total = F.sum("source_size").over(Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    level = (F.lit(share) * total - F.coalesce(F.sum(F.lit(cap) * F.col("source_size")).over(before), F.lit(0.0))) / F.sum("weight").over(onward)
    levels = full.withColumn("level", level)
    # the first source that is not filled at its level gives the level of all after it
    whole = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    common = F.min(F.when(F.col("fills") > F.col("level"), F.struct("fills", F.col("source").isNull().alias("last"), "source", "level"))).over(whole)["level"]
    target = F.when(common.isNull(), F.lit(cap) * F.col("source_size")).otherwise(F.least(F.lit(cap) * F.col("source_size"), F.col("weight") * common))
    return levels.select("source", "source_size", target.cast("double").alias("target"))


def _rate(z, cap: float):
    tilt = F.exp(F.least(z, F.lit(60.0)))
    return F.lit(cap) * tilt / (F.lit(cap - 1) + tilt)


def balance(cells: DataFrame, targets: DataFrame, cap: float, tolerance: float = 1e-6, rounds: int = 60) -> DataFrame:
    """source, multiplier, mean: where the words at the tilted rates meet the targets within tolerance * target.

    cells: source, size, n. targets: source, source_size, target. A target of cap times its source has the
    multiplier BOUND, a target of 0 has -BOUND. The state is a table with one row per source; every round writes it anew.
    """
    counted = cells.groupBy(F.col("source").alias("s")).agg(F.sum("n").alias("docs"))
    known = targets.join(counted, F.col("source").eqNullSafe(F.col("s")))
    fixed = F.when(F.col("target") >= F.col("source_size") * F.lit(cap * (1 - 1e-12)), BOUND).when(F.col("target") <= 0, -BOUND)
    mean = F.when(F.col("source_size") > 0, F.col("source_size").cast("double") / F.col("docs")).otherwise(1.0)
    state = stored(
        known.select("source", "target", mean.alias("mean"), F.coalesce(fixed, F.lit(0.0)).alias("multiplier"), F.lit(-BOUND).alias("low"), F.lit(BOUND).alias("high"), fixed.isNotNull().alias("done")),
        "mix-state",
    )
    scaled = F.col("size") / F.col("mean")
    rate = _rate(F.col("multiplier") * scaled, cap)
    words = F.col("n") * F.col("size") * rate
    slope = words * (1 - rate / cap) * scaled
    exact = lambda c: F.sum(c.cast("decimal(38,9)")).cast("double")
    for _ in range(rounds):
        open_ = state.filter("not done")
        if open_.isEmpty():
            break
        at = small(open_.select(F.col("source").alias("s"), "multiplier", "mean"))
        got = cells.join(at, F.col("source").eqNullSafe(F.col("s"))).groupBy("s").agg(exact(words).alias("words"), exact(slope).alias("slope"))
        gap, x = F.col("words") - F.col("target"), F.col("multiplier")
        met = F.abs(gap) <= tolerance * F.col("target")
        low, high = F.when(gap > 0, F.col("low")).otherwise(x), F.when(gap > 0, x).otherwise(F.col("high"))
        bracketed = open_.join(got, F.col("source").eqNullSafe(F.col("s"))).select("source", "target", "mean", "multiplier", low.alias("low"), high.alias("high"), met.alias("done"), (x - F.when(F.col("slope") > 0, gap / F.col("slope"))).alias("step"))
        inside = F.when((F.col("step") > F.col("low")) & (F.col("step") < F.col("high")), F.col("step")).otherwise((F.col("low") + F.col("high")) / 2)
        stepped = bracketed.withColumn("multiplier", F.when(F.col("done"), x).otherwise(inside)).select(*state.columns)
        state = stored(state.filter("done").unionByName(stepped), "mix-state")
    return state.select("source", "multiplier", "mean")


def copies_per_cell(cells: DataFrame, targets: DataFrame, multipliers: DataFrame, cap: int) -> DataFrame:
    """source, size, n, copies: whole copies of each cell's documents, near the tilted rates and the source's target."""
    by_source = lambda x: x.withColumnRenamed("source", "s")
    same = F.col("source").eqNullSafe(F.col("s"))
    rated = cells.join(small(by_source(multipliers)), same).drop("s").withColumn("rate", _rate(F.col("multiplier") * F.col("size") / F.col("mean"), float(cap)))
    falling = Window.partitionBy("source").orderBy(F.col("size").desc()).rowsBetween(Window.unboundedPreceding, 0)
    expected = F.sum((F.col("n") * F.col("rate")).cast("decimal(38,9)")).over(falling)
    due = F.floor(expected + F.lit(0.5)).cast("long")
    rounded = rated.withColumn("due", due)
    last = F.coalesce(F.lag("due").over(Window.partitionBy("source").orderBy(F.col("size").desc())), F.lit(0))
    first = rounded.withColumn("copies", F.greatest(F.lit(0), F.least(F.col("n") * cap, F.col("due") - last)))
    whole = Window.partitionBy("source")
    missing = F.round(F.col("target")).cast("long") - F.sum(F.col("copies") * F.col("size")).over(whole)
    lacking = first.join(small(by_source(targets.select("source", "target"))), same).drop("s").withColumn("missing", missing)
    room = F.when(F.col("missing") > 0, F.col("n") * cap - F.col("copies")).otherwise(F.col("copies"))
    rising = Window.partitionBy("source").orderBy("size").rowsBetween(Window.unboundedPreceding, -1)
    roomy = lacking.withColumn("room", F.when(F.col("size") > 0, room).otherwise(0)).withColumn("before", F.coalesce(F.sum(F.col("room") * F.col("size")).over(rising), F.lit(0)))
    left = F.greatest(F.lit(0), F.abs("missing") - F.col("before"))
    more = F.when(F.col("size") > 0, F.least(F.col("room"), F.round(left / F.col("size")).cast("long"))).otherwise(0)
    return roomy.select("source", "size", "n", (F.col("copies") + F.signum(F.col("missing").cast("double")).cast("long") * more).alias("copies"))


def word_count(text):
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def mix(docs: DataFrame, key: str = "doc_id", source: str = "source", text: str = "text", weights=(5.0, 2.0, 1.0), share: float = 1.5, cap: int = 2) -> DataFrame:
    """key, source, size, source_size, target, copies: how often the mix takes each row of docs."""
    sized = stored(docs.select(F.col(key).alias("key"), F.col(source).cast("string").alias("source"), word_count(F.col(text)).alias("size")), "mix-sizes")
    cells = stored(sized.groupBy("source", "size").agg(F.count("*").alias("n")), "mix-cells")
    targets = stored(source_targets(cells, list(weights), share, float(cap)), "mix-targets")
    copies = stored(copies_per_cell(cells, targets, balance(cells, targets, float(cap)), cap), "mix-copies")
    cell = copies.select(F.col("source").alias("s"), F.col("size").alias("z"), F.floor(F.col("copies") / F.col("n")).alias("each"), F.pmod("copies", "n").alias("odd"))
    ranked = numbered(sized, ["source", "size"], ["key"], "place")
    # source and size of a cell are the hot keys of this join, so a table of cells that is small enough goes to the documents
    taken = ranked.join(small(cell), F.col("source").eqNullSafe(F.col("s")) & (F.col("size") == F.col("z")))
    taken = taken.withColumn("copies", (F.col("each") + (F.col("place") < F.col("odd")).cast("int")).cast("long"))
    out = taken.drop("s", "z").join(small(targets.withColumnRenamed("source", "s")), F.col("source").eqNullSafe(F.col("s")))
    return out.select(F.col("key").alias(key), F.col("source").alias(source), "size", "source_size", "target", "copies")


def op3_entropy_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents mixed to 150 % of their words; how many words of each the mix takes."""
    mixed = mix(table(spark, sf_dir, "documents").select("doc_id", "source", "text"))
    return mixed.select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).cast("long").alias("taken"))
