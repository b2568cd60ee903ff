"""N-gram Jaccard join with adaptive multi-match prefixes, and the components of its links.

Sets of word shingles are ordered by one global order: shingles that are frequent in the corpus last, by their counts, the
others by hash. Two sets of sizes n and m with the wanted Jaccard similarity share at least
req = ceil(t / (1 + t) * (n + m)) shingles, so they share one among the first n - req + 1 of the one and m - req + 1 of the
other, and at least L among the first n - req + L and m - req + L. Each document chooses its L: the one of least estimated cost, that
is the total length of its prefix's lists plus the candidates that can match L times in them. The length of a frequent shingle's list is
known; that of the others is estimated for each document by the mean over those of its shingles that fall into a hash sample of
all shingles, whose lists are counted over all documents. A pair needs the smaller L of its two documents, within the prefixes
that its own two sizes give.

1. One pass gives each text's set size and signature; equal sets are one *set* from here on. It also counts the corpus' frequent and sampled shingles.
2. Each set's prefix is dealt by shingle. Short lists give all their pairs at once, with their matches. As the prefixes are long enough
   for the most unequal sizes, a pair of similar sizes can be held to the larger L that both whole prefixes allow: its matches in
   short lists, and as many more as the two have shingles in long lists, must reach it. In long lists only one hub, the set with the
   smallest part of rare shingles, is paired with the others, in one streaming pass. The lists of frequent shingles are dealt into piles of
   about PILE sets, each with its hub, and the hubs of a shingle's piles are paired with the first of them, so that no list is one task.
3. Pairs are checked exactly on whole texts, and links are contracted to components.
4. In long lists, sets outside the list's largest component are paired with the sets of other components, by size class, where one
   of their first shingles meets (L = 1: longer prefixes would meet everywhere in such lists), and are checked as well. Every set has a bitmap of
   its shingles' hashes, and a bit that only one of two sets has stands for a shingle that they don't share; pairs that share too few for
   that reason are left out of the join itself. Sets of one component need no further check, so
   a group of copies never gives all its pairs; no link between different components is lost.

`near_duplicates` finds components and needs no more links than join them; `similar_pairs` finds every link between different
sets, and `link_counts` every document's number of links, at the cost of all these pairs.

Defined results: null and empty texts have empty sets and link with nothing; exact copies, repeated rows and texts with equal sets share a component;
the component's id is its smallest doc_id; an empty table gives an empty result. Sets are told apart by 64-bit signatures.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import discard, in_arrow, small, stored, table
from .shingles import mixed, sets, signature

#: Similarity as a fraction: 75 / 100.
NUMERATOR, DENOMINATOR = 75, 100
#: Shingles in at least so many documents count as frequent; at most so many are known to all tasks (12 MB).
#: The order only decides how many candidates there are, never which links are found.
FREQUENT, MAX_FREQUENT = 16, 500_000
#: Lists of more sets than this are long.
LONG = 16
#: Sets of a pile of a frequent shingle's list, about.
PILE = 256
#: Piles that the rows of one set or component are dealt to when they get its id.
SALTS = 16
#: Shingles whose hash ends in so many zero bits are counted in all documents, for cost estimates; more bits where more than MAX_SAMPLED of them stand in two documents or more.
SAMPLE_BITS, MAX_SAMPLED = 5, 100_000
#: Longs of a set's bitmap.
BITMAP = 8
#: Shingles that a task holds before it counts them.
HELD_SHINGLES = 2_000_000
MOST_MATCHES = 4
CHECK_COST = 20.0
#: Sets of candidate pairs whose ids a broadcast may hold (about 40 bytes each); beyond it their texts are found by a shuffled join.
BROADCAST_SETS = 1_000_000
#: Size classes of the join within long lists: ratio of successive bounds.
CLASS_RATIO = 1.34

MARKS = [f"m{i}" for i in range(BITMAP)]

_N, _POS, _L = 26, 24, 3  # bits of a posting's size, position and matches; its rarity is above them


def required(n, m):
    """Shingles that sets of sizes n and m must share: ceil(t / (1 + t) * (n + m))."""
    return -(-(NUMERATOR * (n + m)) // (NUMERATOR + DENOMINATOR))


class Lists:
    """What every task knows of the lists' lengths: those of frequent shingles, those of sampled ones, and the mean of the latter."""

    def __init__(self, frequent: np.ndarray, counts: np.ndarray, sampled: np.ndarray, lengths: np.ndarray, mask: int, mean: float):
        self.frequent, self.counts, self.sampled, self.lengths, self.mask, self.mean = frequent, counts, sampled, lengths, np.uint64(mask), mean

    def others(self, s: np.ndarray) -> float:
        """The estimated mean number of other sets in the lists of a set's infrequent shingles."""
        own = s[(s & self.mask) == 0]
        if not len(own):
            return self.mean
        if not len(self.sampled):
            return 0.0
        at = np.minimum(np.searchsorted(self.sampled, own), len(self.sampled) - 1)
        return float(np.where(self.sampled[at] == own, self.lengths[at] - 1, 0).mean())


def bitmap(s: np.ndarray) -> bytes:
    """A bit for each shingle, by the high bits of its hash."""
    marks = np.zeros(64 * BITMAP, np.uint8)
    marks[(s >> np.uint64(40)) % np.uint64(64 * BITMAP)] = 1
    return np.packbits(marks).tobytes()


def describe_docs(docs: DataFrame, key: str, text: str) -> tuple[DataFrame, Lists]:
    """(key, n, rid, m0 ...: the bitmap) of each row, and the lengths of lists."""
    low = np.uint64((1 << SAMPLE_BITS) - 1)

    def run(batches):
        held, size = [], 0

        def flush():
            u, c = np.unique(np.concatenate([np.zeros(0, np.uint64), *held]), return_counts=True)
            own, part = c > 1, (u & low) == 0
            n = int(own.sum()), int(part.sum())
            kinds = np.repeat(np.array([1, 2], np.int32), n)
            none = [pa.nulls(sum(n), pa.int64())] * BITMAP
            return pa.RecordBatch.from_arrays([pa.nulls(sum(n), kind), pa.array(np.concatenate([c[own], c[part]]).astype(np.int64)), pa.array(np.concatenate([u[own], u[part]]).view(np.int64)), pa.array(kinds), *none], names)

        names, kind = ["key", "n", "h", "kind", *MARKS], None
        for batch in batches:
            kind, n, rid, marks = batch.schema.field(0).type, [], [], []
            for s in sets(batch.column(1)):
                n.append(len(s))
                rid.append(signature(s) if len(s) else None)
                marks.append(bitmap(s))
                held.append(s)
                size += len(s)
                if size > HELD_SHINGLES:
                    yield flush()
                    held, size = [], 0
            bits = np.frombuffer(b"".join(marks), np.int64).reshape(-1, BITMAP)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(rid, pa.int64()), pa.array(np.zeros(len(n), np.int32)), *[pa.array(bits[:, i].copy()) for i in range(BITMAP)]], names)
        if kind is not None:
            yield flush()

    type_ = docs.schema[key].dataType.simpleString()
    both = stored(in_arrow(docs.select(F.col(key).alias("key"), F.col(text).cast("string")), run, f"key {type_}, n long, h long, kind int, " + ", ".join(f"{m} long" for m in MARKS)), "sets")
    frequent = both.filter("kind = 1").groupBy("h").agg(F.sum("n").alias("n")).filter(F.col("n") >= FREQUENT).orderBy(F.desc("n"), "h").limit(MAX_FREQUENT).toPandas()
    of = lambda t, c: t[c].to_numpy(np.int64)
    order = np.argsort(of(frequent, "h").view(np.uint64))
    # of the sampled shingles only infrequent ones tell about lists whose lengths are not known
    counted = stored(both.filter("kind = 2").groupBy("h").agg(F.sum("n").alias("n")).filter(F.col("n") < FREQUENT), "sampled")
    whole = counted.agg(F.sum("n").alias("n"), F.sum(F.col("n") * (F.col("n") - 1)).alias("others")).first()
    levels = {b: counted.filter(F.col("n") > 1).filter(F.col("h").bitwiseAND(F.lit((1 << b) - 1)) == 0) for b in range(SAMPLE_BITS, 40, 4)}
    bits = next(b for b, t in levels.items() if b == max(levels) or t.count() <= MAX_SAMPLED)
    sampled = levels[bits].toPandas()
    by = np.argsort(of(sampled, "h").view(np.uint64))
    short = lambda x: np.minimum(x, 1 << 30).astype(np.int32)
    known = Lists(of(frequent, "h").view(np.uint64)[order], short(of(frequent, "n")[order]), of(sampled, "h").view(np.uint64)[by], short(of(sampled, "n")[by]), (1 << bits) - 1, float(whole.others or 0) / max(1, whole.n or 0))
    return both.filter("kind = 0").select("key", "n", F.col("h").alias("rid"), *MARKS), known


def prefix(s: np.ndarray, known: Lists) -> tuple[np.ndarray, np.ndarray, int, int]:
    """A set's prefix in the global order, its frequent shingles' counts (0 for others), its number of matches L, and its rarity (0 to 255)."""
    n, count = len(s), np.zeros(len(s), np.int64)
    if len(known.frequent):
        at = np.minimum(np.searchsorted(known.frequent, s), len(known.frequent) - 1)
        count = np.where(known.frequent[at] == s, known.counts[at], 0)
    order = np.argsort(count, kind="stable")
    least = n - -(-NUMERATOR * n // DENOMINATOR) + 1
    first = count[order[: least + MOST_MATCHES - 1]]
    lists = np.cumsum(np.where(first > 0, first - 1, known.others(s[count == 0])))
    most = min(MOST_MATCHES, -(-NUMERATOR * n // DENOMINATOR))
    cost = [float(lists[min(least + k - 1, len(lists) - 1)]) * (1 + CHECK_COST / (k + 1)) for k in range(most)]
    k = int(np.argmin(cost))
    return s[order[: least + k]], count[order[: least + k]], k + 1, int(255 * (count == 0).sum() // n)


def postings(docs: DataFrame, text: str, known: Lists) -> DataFrame:
    """token, pile, meta, rid of all prefixes; meta sorts by rarity and holds size, position and matches. pile: 0, or from 1 on for frequent shingles of more than PILE sets."""
    held = docs.sparkSession.sparkContext.broadcast(known)

    def run(batches):
        names = ["token", "pile", "meta", "rid"]
        parts, size = [[] for _ in names], 0

        def flush():
            columns = [np.concatenate([np.zeros(0, np.int64), *x]) for x in parts]
            for x in parts:
                x.clear()
            return pa.RecordBatch.from_arrays([pa.array(x) for x in columns], names)

        for batch in batches:
            seen = set()  # copies of a set stand in each list once
            for s in sets(batch.column(0)):
                if not len(s) or (rid := signature(s)) in seen:
                    continue
                seen.add(rid)
                own, count, matches, rarity = prefix(s, held.value)
                head = (rarity << (_N + _POS + _L)) | (len(s) << (_POS + _L)) | matches
                # piles of all shingles are nested, so that sets with many shingles in common meet the same few hubs
                piles = np.left_shift(1, np.ceil(np.log2(np.maximum(count, PILE) / PILE)).astype(np.int64))
                place = int(mixed(np.array([rid], np.int64).view(np.uint64))[0] >> np.uint64(1))
                for x, v in zip(parts, (own.view(np.int64), np.where(piles > 1, 1 + (place & (piles - 1)), 0), head + (np.arange(len(own), dtype=np.int64) << _L), np.full(len(own), rid, np.int64)), strict=True):
                    x.append(v)
                size += len(own)
                if size > 200_000:
                    yield flush()
                    size = 0
        yield flush()

    return in_arrow(docs.select(F.col(text).cast("string")), run, "token long, pile long, meta long, rid long")


def _parts(meta):
    """Size, position and matches of metas, in numpy."""
    return (meta >> (_POS + _L)) & ((1 << _N) - 1), (meta >> _L) & ((1 << _POS) - 1), meta & ((1 << _L) - 1)


def competing(meta_a, meta_b) -> np.ndarray:
    """Whether matches at these positions count for pairs of these sizes."""
    (na, pa_, la), (nb, pb, lb) = _parts(meta_a), _parts(meta_b)
    req, spare = required(na, nb), np.minimum(la, lb) - 1
    return (DENOMINATOR * np.minimum(na, nb) >= NUMERATOR * np.maximum(na, nb)) & (pa_ <= na - req + spare) & (pb <= nb - req + spare)


def most_matches(meta_a, meta_b) -> np.ndarray:
    """The largest L that both whole prefixes allow for pairs of these sizes."""
    (na, _, la), (nb, _, lb) = _parts(meta_a), _parts(meta_b)
    req = required(na, nb)
    least = lambda n: -(-(NUMERATOR * n) // DENOMINATOR)
    return np.minimum(la + req - least(na), lb + req - least(nb))


def within(meta_a, meta_b) -> np.ndarray:
    """Whether matches at these positions count towards `most_matches`."""
    (na, pa_, _), (nb, pb, _) = _parts(meta_a), _parts(meta_b)
    req, spare = required(na, nb), most_matches(meta_a, meta_b) - 1
    return (DENOMINATOR * np.minimum(na, nb) >= NUMERATOR * np.maximum(na, nb)) & (pa_ <= na - req + spare) & (pb <= nb - req + spare)


def candidates(posts: DataFrame, long: int = LONG) -> DataFrame:
    """Rows (pair): a, b, meta_a, meta_b, c and every matches of short lists' pairs (within the chosen L, within the largest); rows (not pair): token, set a and hub b of long lists."""

    def run(batches):
        names = ["pair", "token", "a", "meta_a", "b", "meta_b", "c", "every"]
        rest = None  # the rows of the last token so far, if its list is short so far
        hub = None  # token, pile, rid, meta of the long list at hand

        def listed(token, rid, meta, lead_rid, lead_meta):
            n = len(rid)
            return pa.RecordBatch.from_arrays([pa.array(np.zeros(n, bool)), pa.array(token), pa.array(rid), pa.array(meta), pa.array(lead_rid), pa.array(lead_meta), pa.array(np.zeros(n, np.int64)), pa.array(np.zeros(n, np.int64))], names)

        def paired(rid, meta, starts, lengths):
            found = []
            for k in np.unique(lengths).tolist():
                if k < 2:
                    continue
                base = starts[lengths == k]
                i, j = np.triu_indices(k, 1)
                for part in range(0, len(base), max(1, 400_000 // len(i))):
                    own = base[part : part + max(1, 400_000 // len(i))]
                    x, y = (own[:, None] + i).ravel(), (own[:, None] + j).ravel()
                    good = within(meta[x], meta[y])
                    x, y = x[good], y[good]
                    swap = rid[x] > rid[y]
                    found.append(np.where(swap, y, x) * np.int64(len(rid)) + np.where(swap, x, y))
            pairs = np.concatenate([np.zeros(0, np.int64), *found])
            x, y = pairs // max(1, len(rid)), pairs % max(1, len(rid))
            key = np.empty(len(x), [("a", np.int64), ("b", np.int64)])
            key["a"], key["b"] = rid[x], rid[y]
            u, first, at = np.unique(key, return_index=True, return_inverse=True)
            every = np.bincount(at.ravel(), minlength=len(u)).astype(np.int64)
            c = np.bincount(at.ravel(), competing(meta[x], meta[y]), len(u)).astype(np.int64)
            return pa.RecordBatch.from_arrays([pa.array(np.ones(len(u), bool)), pa.array(np.zeros(len(u), np.int64)), pa.array(u["a"].copy()), pa.array(meta[x[first]]), pa.array(u["b"].copy()), pa.array(meta[y[first]]), pa.array(c), pa.array(every)], names)

        def process(token, pile, meta, rid, final):
            nonlocal rest, hub
            other = (token[1:] != token[:-1]) | (pile[1:] != pile[:-1])
            new = np.concatenate([[True], other | (rid[1:] != rid[:-1])])
            starts = np.concatenate([[True], other])[new]
            token, pile, meta, rid = token[new], pile[new], meta[new], rid[new]  # equal sets once in each list
            starts = np.flatnonzero(starts)
            ends = np.append(starts[1:], len(token))
            if hub is not None and (token[0], pile[0]) == hub[:2]:
                e = int(ends[0])
                # the hub's last row may stand again at the start
                yield listed(token[:e], rid[:e], meta[:e], np.full(e, hub[2]), np.full(e, hub[3]))
                starts, ends = starts[1:], ends[1:]
                if not len(starts):
                    rest = None
                    return
            hub = None
            if not final:
                a, e = int(starts[-1]), int(ends[-1])
                if e - a > long or pile[a]:
                    hub = (token[a], pile[a], rid[a], meta[a])
                    rest = None
                else:
                    rest = (token[a:e], pile[a:e], meta[a:e], rid[a:e])
                    starts, ends = starts[:-1], ends[:-1]
            lengths = ends - starts
            small = (lengths <= long) & (pile[starts] == 0)
            big = np.flatnonzero(~small)
            for i in big.tolist():
                a, e = int(starts[i]), int(ends[i])
                yield listed(token[a:e], rid[a:e], meta[a:e], np.full(e - a, rid[a]), np.full(e - a, meta[a]))
            yield paired(rid, meta, starts[small], lengths[small])

        for batch in batches:
            own = [batch.column(c).to_numpy(zero_copy_only=False) for c in ("token", "pile", "meta", "rid")]
            if not len(own[0]):
                continue
            if rest is not None:
                own = [np.concatenate(x) for x in zip(rest, own, strict=True)]
                rest = None
            yield from process(*own, False)
        if rest is not None:
            last, rest = rest, None
            yield from process(*last, True)

    # by rarity and size, then set: positions would give lists of the same sets different hubs
    dealt = posts.repartition("token", "pile").sortWithinPartitions("token", "pile", F.shiftright("meta", _POS + _L), "rid")
    return in_arrow(dealt, run, "pair boolean, token long, a long, meta_a long, b long, meta_b long, c long, every long")


def _field(meta: Column, shift: int, bits: int) -> Column:
    return F.shiftright(meta, shift).bitwiseAND(F.lit((1 << bits) - 1))


def _size(meta: Column) -> Column:
    return _field(meta, _POS + _L, _N)


def _competing(a: Column, b: Column) -> Column:
    """Whether matches at these positions are within the prefixes for one match (L = 1)."""
    na, nb = _size(a), _size(b)
    req = F.ceil((na + nb) * NUMERATOR / (NUMERATOR + DENOMINATOR))
    return (F.least(na, nb) * DENOMINATOR >= F.greatest(na, nb) * NUMERATOR) & (_field(a, _L, _POS) <= na - req) & (_field(b, _L, _POS) <= nb - req)


def verified(pairs: DataFrame, docs: DataFrame, described: DataFrame, key: str, text: str) -> DataFrame:
    """The pairs (a, b) whose whole sets have the wanted similarity."""
    needed = pairs.select(F.col("a").alias("rid")).union(pairs.select("b")).distinct()
    first = described.select("rid", "key").filter("rid is not null").groupBy("rid").agg(F.min("key").alias("r"))  # before the join, as a set may have many copies
    reps = stored(first.join(needed, "rid"), "pair-docs")

    def shingled(batches):
        for batch in batches:
            rids, blobs = [], []
            for rid, s in zip(batch.column(1).to_pylist(), sets(batch.column(0)), strict=True):
                if len(s) and signature(s) == rid:  # rows may share a doc_id
                    rids.append(rid)
                    blobs.append(s.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(rids, pa.int64()), pa.array(blobs, pa.binary())], ["rid", "s"])

    texts = docs.select(F.col(key).alias("rep"), F.col(text).cast("string").alias("t")).join(F.broadcast(reps) if reps.count() <= BROADCAST_SETS else reps, F.col("rep").eqNullSafe(F.col("r")))
    whole = stored(in_arrow(texts.select("t", "rid"), shingled, "rid long, s binary"), "pair-sets")

    def check(batches):
        for batch in batches:
            a, b = [], []
            for x, y, s, t in zip(*(batch.column(c).to_pylist() for c in ("a", "b", "sa", "sb")), strict=True):
                s, t = np.frombuffer(s, np.uint64), np.frombuffer(t, np.uint64)
                at = np.searchsorted(t, s)
                both = int((t[np.minimum(at, len(t) - 1)] == s).sum())
                if DENOMINATOR * both >= NUMERATOR * (len(s) + len(t) - both):
                    a.append(x)
                    b.append(y)
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    side = lambda c: whole.select(F.col("rid").alias(c), F.col("s").alias(f"s{c}"))
    links = stored(in_arrow(pairs.select("a", "b").join(side("a"), "a").join(side("b"), "b"), check, "a long, b long"), "links")
    discard(whole)
    return links


def components(links: DataFrame) -> DataFrame:
    """rid, comp: the smallest id in the component of each end of a link. Labels fall to the smallest neighbour's and then to their label's label."""
    both = stored(links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "arcs")
    labels = stored(both.groupBy(F.col("a").alias("rid")).agg(F.min("b").alias("m")).select("rid", F.least("rid", "m").alias("comp")), "labels")
    while True:
        near = both.join(labels.select(F.col("rid").alias("b"), "comp"), "b").groupBy(F.col("a").alias("rid")).agg(F.min("comp").alias("near"))
        fell = labels.join(near, "rid").select("rid", F.least("comp", "near").alias("comp"), F.col("comp").alias("was"))
        jump = labels.select(F.col("rid").alias("comp"), F.col("comp").alias("up"))
        new = stored(fell.join(jump, "comp", "left").select("rid", F.least("comp", F.coalesce("up", "comp")).alias("comp"), "was"), "labels")
        if new.filter("comp <> was").isEmpty():
            return labels
        labels = new.select("rid", "comp")


def _alike(one: str, other: str) -> Column:
    """Whether the bitmaps of two sets (struct columns bits_<name> and metas m<name>) let them share what their sizes ask for."""
    na, nb = _size(F.col(f"m{one}")), _size(F.col(f"m{other}"))
    req = F.ceil((na + nb) * NUMERATOR / (NUMERATOR + DENOMINATOR))
    alone = lambda p, q: sum((F.bit_count(F.col(f"bits_{p}.{m}").bitwiseAND(F.bitwise_not(F.col(f"bits_{q}.{m}")))) for m in MARKS), F.lit(0))
    return (na - alone(one, other) >= req) & (nb - alone(other, one) >= req)


def _cross(listed: DataFrame, labels: DataFrame, described: DataFrame) -> DataFrame:
    """a, b, meta_a, meta_b: pairs of sets of different components that share one of their first shingles in a long list, and whose bitmaps don't keep them apart."""
    inside = listed.select(F.col("a").alias("rid")).distinct()
    bits = described.filter("rid is not null").groupBy("rid").agg(*[F.first(m).alias(m) for m in MARKS]).join(inside, "rid").select("rid", F.struct(*MARKS).alias("bits"))
    known = listed.select("token", F.col("a").alias("rid"), F.col("meta_a").alias("meta")).join(labels, "rid", "left").join(bits, "rid").withColumn("comp", F.coalesce("comp", "rid"))
    known = stored(known.withColumn("class", F.floor(F.log(_size(F.col("meta")).cast("double")) / float(np.log(CLASS_RATIO))).cast("int")), "long-lists")
    most = known.groupBy("token", "comp").agg(F.count("*").alias("n")).groupBy("token").agg(F.max(F.struct("n", "comp"))["comp"].alias("most"), F.count("*").alias("comps")).filter("comps > 1")
    minor = known.join(small(stored(most, "long-heads")), "token").filter("comp <> most")
    reach = int(np.ceil(np.log(DENOMINATOR / NUMERATOR) / np.log(CLASS_RATIO)))
    probe = minor.select("token", F.col("rid").alias("x"), F.col("meta").alias("mx"), F.col("comp").alias("cx"), F.col("bits").alias("bits_x"), "most", F.explode(F.sequence(F.col("class") - reach, F.col("class") + reach)).alias("class"))
    other = known.select("token", "class", F.col("rid").alias("y"), F.col("meta").alias("my"), F.col("comp").alias("cy"), F.col("bits").alias("bits_y"))
    # of two minor sets each finds the other; the smaller id speaks
    met = probe.join(other, ["token", "class"]).filter((F.col("cx") != F.col("cy")) & ((F.col("cy") == F.col("most")) | (F.col("x") < F.col("y"))) & _competing(F.col("mx"), F.col("my")) & _alike("x", "y"))
    first = F.col("x") < F.col("y")
    pick = lambda a, b: F.when(first, F.col(a)).otherwise(F.col(b))
    both = met.select(pick("x", "y").alias("a"), pick("y", "x").alias("b"), pick("mx", "my").alias("meta_a"), pick("my", "mx").alias("meta_b"))
    return both.groupBy("a", "b").agg(*[F.first(c).alias(c) for c in ("meta_a", "meta_b")])


def _reachable(pairs: DataFrame, in_long: DataFrame) -> DataFrame:
    """Pairs whose matches can still reach what their chosen L and the largest L ask for: those counted in short lists, and no more
    in long lists than either set has shingles there. c and every null: no match in short lists.

    pairs: a, b, meta_a, meta_b, c, every. in_long: rid, n."""
    of = lambda c: in_long.select(F.col("rid").alias(c), F.col("n").alias(f"in_{c}"))
    more = F.least(F.coalesce("in_a", F.lit(0)), F.coalesce("in_b", F.lit(0)))
    metas = [F.col("meta_a"), F.col("meta_b")]
    chosen = F.least(*[_field(m, 0, _L) for m in metas])
    req = F.ceil((_size(metas[0]) + _size(metas[1])) * NUMERATOR / (NUMERATOR + DENOMINATOR))
    most = F.least(*[_field(m, 0, _L) - F.ceil(_size(m) * NUMERATOR / DENOMINATOR) for m in metas]) + req
    known = lambda c: F.coalesce(c, F.lit(0))
    return pairs.join(of("a"), "a", "left").join(of("b"), "b", "left").filter((known("c") + more >= chosen) & (known("every") + more >= most)).select("a", "b")


def near_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text", long: int = LONG) -> DataFrame:
    """key, n_shingles, component_id of each row of docs."""
    described, known = describe_docs(docs, key, text)
    found = stored(candidates(postings(docs, text, known), long), "candidates")
    listed = found.filter("not pair")
    in_long = stored(listed.groupBy(F.col("a").alias("rid")).agg(F.count("*").alias("n")), "in-long")
    swap = F.col("a") > F.col("b")
    # the hubs of a shingle's piles meet the first of them
    piles = listed.groupBy("token", "b").agg(F.first("meta_b").alias("meta_b"))
    top = piles.groupBy("token").agg(F.min(F.struct(F.shiftright("meta_b", _POS + _L).alias("head"), "b", "meta_b")).alias("top"), F.count("*").alias("piles")).filter("piles > 1")
    between = piles.join(top, "token").select("token", F.col("b").alias("a"), F.col("meta_b").alias("meta_a"), F.col("top.b").alias("b"), F.col("top.meta_b").alias("meta_b"))
    hubs = listed.select(between.columns).unionByName(between).filter((F.col("a") != F.col("b")) & _competing(F.col("meta_a"), F.col("meta_b"))).select(
        F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), *[F.when(swap, F.col(y)).otherwise(F.col(x)).alias(x) for x, y in (("meta_a", "meta_b"), ("meta_b", "meta_a"))],
        F.lit(0).cast("long").alias("c"), F.lit(0).cast("long").alias("every"), F.lit(True).alias("hub"),
    )
    both = found.filter("pair").select("a", "b", "meta_a", "meta_b", "c", "every", F.lit(False).alias("hub")).unionByName(hubs)
    counted = stored(both.groupBy("a", "b").agg(*[F.first(c).alias(c) for c in ("meta_a", "meta_b")], *[F.sum(c).alias(c) for c in ("c", "every")], F.max("hub").alias("hub")), "pair-counts")
    first = stored(_reachable(counted.filter("hub or c >= 1"), in_long), "pairs")
    links = verified(first, docs, described, key, text)
    labels = components(links)
    if not listed.isEmpty():
        crossing = _cross(listed, labels, described).join(counted.select("a", "b", "c", "every"), ["a", "b"], "left")
        second = _reachable(crossing, in_long).join(first, ["a", "b"], "left_anti")
        # what the first links have joined needs no check
        of = lambda c: labels.select(F.col("rid").alias(c), F.col("comp").alias(f"comp_{c}"))
        second = second.join(of("a"), "a", "left").join(of("b"), "b", "left").filter(F.coalesce("comp_a", "a") != F.coalesce("comp_b", "b"))
        second = stored(second.select("a", "b"), "more-pairs")
        if not second.isEmpty():
            labels = components(links.unionByName(verified(second, docs, described, key, text)))
    # copies of one set and members of one component are dealt over salts
    salt = F.pmod(F.xxhash64("key"), F.lit(SALTS))
    salted = lambda x: x.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    classed = described.drop(*MARKS).withColumn("salt", salt).join(salted(labels), ["rid", "salt"], "left").withColumn("comp", F.coalesce("comp", "rid"))
    least = classed.filter("comp is not null").groupBy("comp").agg(F.min("key").alias("component_id"), F.count("*").alias("rows")).filter("rows > 1").drop("rows")
    out = classed.join(salted(least), ["comp", "salt"], "left")
    return out.select(F.col("key").alias(key), F.col("n").alias("n_shingles"), F.coalesce("component_id", "key").alias("component_id"))


def similar_pairs(docs: DataFrame, key: str = "doc_id", text: str = "text") -> tuple[DataFrame, DataFrame]:
    """Every link between different sets as (a, b), and the membership (key, rid) of each row in its set; rows of one set are linked with each other."""
    described, known = describe_docs(docs, key, text)
    posts = stored(postings(docs, text, known).select("token", "meta", "rid").distinct(), "postings")
    of = lambda c: posts.select("token", F.col("rid").alias(c), F.col("meta").alias(f"meta_{c}"))
    met = of("a").join(of("b"), "token").filter((F.col("a") < F.col("b")) & _competing(F.col("meta_a"), F.col("meta_b")))
    pairs = stored(met.select("a", "b").distinct(), "all-pairs")
    return verified(pairs, docs, described, key, text), described.select(F.col("key").alias(key), "rid")


def link_counts(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, n_links: to how many other rows each row of docs is linked."""
    links, members = similar_pairs(docs, key, text)
    size = stored(members.filter("rid is not null").groupBy("rid").agg(F.count("*").alias("n")), "set-sizes")
    both = links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    others = both.join(size.withColumnRenamed("rid", "b"), "b").groupBy(F.col("a").alias("rid")).agg(F.sum("n").alias("others"))
    whole = size.join(others, "rid", "left").select("rid", (F.col("n") - 1 + F.coalesce("others", F.lit(0))).alias("n_links"))
    return members.join(whole, "rid", "left").select(key, F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"))


def op9_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The near-duplicate component of every document."""
    return near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"))


OP9_SQL = r"""
with recursive w as (select doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') as ws from documents),
g as (select distinct doc_id, unnest(case when len(ws) = 0 then []::varchar[] when len(ws) < 5 then [array_to_string(ws, ' ')]
      else list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i+4], ' ')) end) as s from w),
n as (select doc_id, count(*) as n from g group by doc_id),
p as (select a.doc_id as x, b.doc_id as y, count(*) as common from g a join g b on a.s = b.s and a.doc_id <> b.doc_id group by 1, 2),
l as (select x, y from p join n nx on nx.doc_id = x join n ny on ny.doc_id = y where 100 * common >= 75 * (nx.n + ny.n - common)),
r as (select x, y from l union select r.x, l.y from r join l on l.x = r.y)
select w.doc_id, coalesce(n.n, 0) as n_shingles, least(w.doc_id, coalesce(m.least, w.doc_id)) as component_id
from w left join n on n.doc_id = w.doc_id left join (select x, min(y) as least from r group by x) m on m.x = w.doc_id
"""
