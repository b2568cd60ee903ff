"""Reversible line dedup: exact reference counts of line keys, with sharded cuckoo filters in front of them.

State. Two tables. *Counts*: key hash (128 bits as two longs) and the number of documents that hold the line. Inserting a
batch of documents adds its counts, deleting documents subtracts theirs; both are one aggregate of signed counts, so any
history of insertions and deletions ends at the table that the remaining documents alone would give. *Filters*: a line is
*frequent* when its count reaches `min_docs`; frequent keys are dealt by their hash over shards, and each shard is one row with a
cuckoo filter of 16-bit fingerprints in buckets of four. A key that becomes frequent is inserted in its shard's filter and one that falls
below the threshold is deleted from it; shards without such keys keep their row. Executors build and change filters, one shard to a task.

Scan. Lines are asked at their shard's filter first: most are not in it and stay without further work. A hit is checked
against the exact keys, so false positives of the filters never drop a line. While the frequent keys fit `BROADCAST_KEYS`, all filters and
exact keys go to every task and one pass over the texts decides. Beyond that, the hashes of lines are dealt by shard and salt, each
pile behind its shard's filter and exact keys, and decided in one streaming pass; a line that all documents share is spread over the salts.

A frequent line goes from every document, or, with keep="first", from all but the one with the smallest row hash, so that of
exact copies one stays whole.

Defined results: null or empty text is one empty line, which is never dropped; repeated rows count as documents
of their own (and with keep="first" all keep what one of them keeps); a text whose lines are all dropped becomes the empty text; an empty
table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import in_arrow, stored, table

#: Key hashes that a broadcast may hold (24 bytes each, and about 3 of filter): 54 MB.
BROADCAST_KEYS = 2_000_000
#: Frequent keys of one shard, about.
SHARD_KEYS = 1 << 15
#: Piles that a shard's lines are dealt to where filters are not broadcast.
SALTS = 64
#: Distinct line keys and their bytes that a counting task holds before it passes them on.
HELD_KEYS, HELD_BYTES = 200_000, 16_000_000
STRIP = b" \t\n\x0b\x0c\r"
MASK = (1 << 64) - 1


def key_of(line: bytes) -> bytes:
    """A line's key: ASCII white space stripped at both ends, A-Z lower-cased."""
    return line.strip(STRIP).lower()


def hashes(key: bytes) -> tuple[int, int]:
    first = xxhash.xxh64_intdigest(key, 42)
    return first, xxhash.xxh64_intdigest(key, first)


class CuckooFilter:
    """A cuckoo filter over 64-bit hashes: 16-bit fingerprints, four to a bucket, two buckets to a key."""

    SLOTS = 4

    def __init__(self, capacity: int):
        self.buckets = 1 << max(1, int(np.ceil(np.log2(max(1, capacity) / (self.SLOTS * 0.85)))))
        self.table = np.zeros((self.buckets, self.SLOTS), np.uint16)
        self.stash: dict[tuple[int, int], int] = {}

    def _places(self, h):
        """Fingerprint (never 0) and both buckets of hashes; the second is the first xor a hash of the fingerprint."""
        h = np.asarray(h, np.uint64)
        mark = ((h >> np.uint64(48)) | np.uint64(1)).astype(np.uint16)
        one = (h & np.uint64(self.buckets - 1)).astype(np.int64)
        return mark, one, self._other(mark, one)

    def _other(self, mark, bucket):
        jump = (np.asarray(mark, np.uint64) * np.uint64(0x5BD1E995)) >> np.uint64(3)
        return np.asarray(bucket ^ (jump & np.uint64(self.buckets - 1)).astype(np.int64))

    def insert(self, h: int) -> None:
        mark, one, two = (int(x[0]) for x in self._places([h]))
        at = one
        for turn in range(500):
            for b in (at, int(self._other([mark], np.array([at]))[0])):
                free = np.flatnonzero(self.table[b] == 0)
                if len(free):
                    self.table[b, free[0]] = mark
                    return
            slot = turn % self.SLOTS
            at = int(self._other([mark], np.array([at]))[0])
            mark, self.table[at, slot] = int(self.table[at, slot]), mark
        # a full filter keeps what is left beside the table, so nothing is ever lost
        pair = (mark, min(at, int(self._other([mark], np.array([at]))[0])))
        self.stash[pair] = self.stash.get(pair, 0) + 1

    def delete(self, h: int) -> bool:
        """Removes one earlier insertion of h; False if there is none."""
        mark, one, two = (int(x[0]) for x in self._places([h]))
        for b in (one, two):
            held = np.flatnonzero(self.table[b] == mark)
            if len(held):
                self.table[b, held[0]] = 0
                return True
        pair = (mark, min(one, two))
        if self.stash.get(pair):
            self.stash[pair] -= 1
            return True
        return False

    def contains(self, h) -> np.ndarray:
        mark, one, two = self._places(h)
        found = (self.table[one] == mark[:, None]).any(1) | (self.table[two] == mark[:, None]).any(1)
        if self.stash:
            found |= np.fromiter((bool(self.stash.get((int(m), int(min(a, b))))) for m, a, b in zip(mark, one, two, strict=True)), bool, len(mark))
        return found


    def to_bytes(self) -> bytes:
        left = [(m, at, n) for (m, at), n in self.stash.items() if n]
        return np.array([len(left), *(x for row in left for x in row)], np.int64).tobytes() + self.table.tobytes()

    @classmethod
    def from_bytes(cls, raw: bytes) -> CuckooFilter:
        made = cls.__new__(cls)
        n = int(np.frombuffer(raw, np.int64, 1)[0])
        left = np.frombuffer(raw, np.int64, 3 * n, 8).reshape(n, 3).tolist()
        made.stash = {(m, at): k for m, at, k in left}
        made.table = np.frombuffer(raw, np.uint16, offset=8 + 24 * n).reshape(-1, cls.SLOTS).copy()
        made.buckets = len(made.table)
        return made


def shard_bits(keys: int) -> int:
    """Shards are numbered by so many bits of the hash; growth adds shards, not larger filters."""
    return max(0, -(-keys // SHARD_KEYS) - 1).bit_length()


def _shard(bits: int):
    return F.shiftrightunsigned("h1", 16).bitwiseAND(F.lit((1 << bits) - 1)).alias("shard")


def build_filters(frequent: DataFrame, bits: int) -> DataFrame:
    """shard, filter: one row for each shard that has keys. frequent: h1, h2."""

    def build(t: pa.Table) -> pa.Table:
        made = CuckooFilter(max(t.num_rows, SHARD_KEYS // 8))
        for h in t.column("h1").to_numpy().view(np.uint64).tolist():
            made.insert(h)
        return pa.table({"shard": t.column("shard").slice(0, 1), "filter": pa.array([made.to_bytes()], pa.binary())})

    return frequent.select("h1", _shard(bits)).groupBy("shard").applyInArrow(build, "shard long, filter binary")


def change_filters(filters: DataFrame, bits: int, before: DataFrame, after: DataFrame, min_docs: int) -> DataFrame:
    """The filters after counts went from `before` to `after`: keys that reached the threshold are inserted, keys that fell below it deleted. Other shards keep their rows."""
    was, now = ((x.filter(F.col("n") >= min_docs).select("h1", "h2", F.lit(v).alias("v"))) for x, v in ((before, -1), (after, 1)))
    changed = was.unionByName(now).groupBy("h1", "h2").agg(F.sum("v").alias("v")).filter("v <> 0").select("h1", "v", _shard(bits))

    def change(key: tuple, old: pa.Table, new: pa.Table) -> pa.Table:
        if not new.num_rows:
            return old.select(["shard", "filter"])
        made = CuckooFilter.from_bytes(old.column("filter")[0].as_py()) if old.num_rows else CuckooFilter(max(new.num_rows, SHARD_KEYS // 8))
        for h, v in sorted(zip(new.column("h1").to_numpy().view(np.uint64).tolist(), new.column("v").to_pylist(), strict=True), key=lambda x: x[1]):
            if v > 0:
                made.insert(h)
            else:
                made.delete(h)
        return pa.table({"shard": pa.array([key[0].as_py()], pa.int64()), "filter": pa.array([made.to_bytes()], pa.binary())})

    return filters.groupBy("shard").cogroup(changed.groupBy("shard")).applyInArrow(change, "shard long, filter binary")


class Known:
    """Filters by shard and the exact frequent keys behind them; `first` is the row hash that keeps a line (with keep="first")."""

    def __init__(self, bits: int, filters: dict[int, CuckooFilter], h1: np.ndarray, h2: np.ndarray, first: np.ndarray):
        order = np.lexsort((h2, h1))
        self.bits, self.filters, self.h1, self.h2, self.first = bits, filters, h1[order], h2[order], first[order]

    def may_hold(self, h: np.ndarray) -> np.ndarray:
        of, out = (h >> np.uint64(16)) & np.uint64((1 << self.bits) - 1), np.zeros(len(h), bool)
        for s in np.unique(of).tolist():
            if s in self.filters:
                out[of == s] = self.filters[s].contains(h[of == s])
        return out

    def keeper(self, h1: int, h2: int) -> int | None:
        """The row hash that keeps a frequent line's key; None if the key is not frequent."""
        at = int(np.searchsorted(self.h1, np.uint64(h1)))
        while at < len(self.h1) and self.h1[at] == h1:
            if self.h2[at] == h2:
                return int(self.first[at])
            at += 1
        return None


def _lines(batch: pa.RecordBatch, col: str) -> Iterator[list[bytes]]:
    for raw in batch.column(col).cast(pa.binary() if not pa.types.is_large_string(batch.column(col).type) else pa.large_binary()).to_pylist():
        yield (raw or b"").split(b"\n")


def line_counts(docs: DataFrame, text: str = "text", sign: int = 1, owner=None) -> DataFrame:
    """h1, h2, n: in how many rows each non-empty line key occurs, times sign. With a column `owner` also first: the smallest of its values among these rows."""

    def count(batches):
        seen: dict[bytes, list[int]] = {}
        held = 0

        def out():
            pairs = [hashes(k) for k in seen]
            columns = [pa.array(np.array([p[i] for p in pairs], np.uint64).view(np.int64)) for i in (0, 1)]
            columns += [pa.array([sign * v[0] for v in seen.values()], pa.int64()), pa.array([v[1] for v in seen.values()], pa.int64())]
            seen.clear()
            return pa.RecordBatch.from_arrays(columns, ["h1", "h2", "n", "first"])

        for batch in batches:
            for lines, own in zip(_lines(batch, "t"), batch.column("owner").to_pylist(), strict=True):
                for k in {key_of(x) for x in lines}:
                    if not k:
                        continue
                    if v := seen.get(k):
                        v[0] += 1
                        if own < v[1]:
                            v[1] = own
                    else:
                        seen[k] = [1, own]
                        held += len(k)
                if len(seen) > HELD_KEYS or held > HELD_BYTES:
                    yield out()
                    held = 0
        yield out()

    partial = in_arrow(docs.select(F.col(text).cast("string").alias("t"), (F.lit(0).cast("long") if owner is None else owner).alias("owner")), count, "h1 long, h2 long, n long, first long")
    return partial.groupBy("h1", "h2").agg(F.sum("n").alias("n"), *([] if owner is None else [F.min("first").alias("first")]))


def apply_changes(counts: DataFrame | None, inserted: DataFrame | None = None, deleted: DataFrame | None = None, text: str = "text") -> DataFrame:
    """The reference-count table after inserting and deleting documents; keys at count 0 leave it."""
    parts = [] if counts is None else [counts.select("h1", "h2", "n")]
    parts += [line_counts(rows, text, sign) for rows, sign in ((inserted, 1), (deleted, -1)) if rows is not None]
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.unionByName(p)
    return whole.groupBy("h1", "h2").agg(F.sum("n").alias("n")).filter("n > 0")


def drop_frequent(docs: DataFrame, counts: DataFrame, min_docs: int, text: str = "text", broadcast_keys: int = BROADCAST_KEYS, filters: DataFrame | None = None, bits: int = 0, owner=None) -> DataFrame:
    """docs with n_lines, n_dropped and kept (columns of these names are replaced): the text without lines whose key has a count of min_docs or more.

    filters, bits: the filters of these counts, if they are kept from before; else they are built. counts may have `first`, the value of `owner` that keeps a line."""
    first = F.col("first") if "first" in counts.columns else F.lit(None).cast("long")
    frequent = stored(counts.filter(F.col("n") >= min_docs).select("h1", "h2", first.alias("first")), "line-keys")
    n = frequent.count()
    if filters is None:
        bits = shard_bits(n)
        filters = stored(build_filters(frequent, bits), "line-filters")
    inner = docs.select(F.struct(*[c for c in docs.columns if c not in ("n_lines", "n_dropped", "kept")]).alias("row"), F.col(text).cast("string").alias("t"), (F.lit(0).cast("long") if owner is None else owner).alias("owner"))
    decided = _by_broadcast(inner, frequent, filters, bits) if n <= broadcast_keys else _by_shuffle(inner, frequent, filters, bits)
    return decided.select("row.*", *[F.col(c) for c in ("n_lines", "n_dropped", "kept")])


def _emit(batch: pa.RecordBatch, rows: list[list[bytes]], dropped: list[set[int]]) -> pa.RecordBatch:
    kept = [b"\n".join(x for i, x in enumerate(lines) if i not in gone) if gone else b"\n".join(lines) for lines, gone in zip(rows, dropped, strict=True)]
    return pa.RecordBatch.from_arrays(
        [batch.column("row"), pa.array([len(x) for x in rows], pa.int64()), pa.array([len(x) for x in dropped], pa.int64()), pa.array(kept, pa.binary()).cast(pa.string())],
        ["row", "n_lines", "n_dropped", "kept"],
    )


def _by_broadcast(inner: DataFrame, frequent: DataFrame, filters: DataFrame, bits: int) -> DataFrame:
    keys = frequent.toPandas()
    of = lambda c: keys[c].to_numpy(np.int64).view(np.uint64)
    first = keys["first"].astype("float64").isna().to_numpy() if len(keys) else np.zeros(0, bool)
    none = bool(first.all())
    held = inner.sparkSession.sparkContext.broadcast(Known(bits, {r.shard: CuckooFilter.from_bytes(r.filter) for r in filters.toLocalIterator()}, of("h1"), of("h2"), np.zeros(len(keys), np.int64) if none else keys["first"].to_numpy(np.int64)))

    def scan(batches):
        known = held.value
        for batch in batches:
            rows, owners = list(_lines(batch, "t")), batch.column("owner").to_pylist()
            own = [key_of(x) for lines in rows for x in lines]
            h1 = np.fromiter((xxhash.xxh64_intdigest(k, 42) for k in own), np.uint64, len(own))
            dropped: list[set[int]] = [set() for _ in rows]
            starts = np.cumsum([0, *(len(x) for x in rows)])
            for hit in np.flatnonzero(known.may_hold(h1)).tolist():
                h = int(h1[hit])
                if own[hit] and (keeper := known.keeper(h, xxhash.xxh64_intdigest(own[hit], h))) is not None:
                    doc = int(np.searchsorted(starts, hit, "right")) - 1
                    if none or owners[doc] != keeper:
                        dropped[doc].add(hit - int(starts[doc]))
            yield _emit(batch, rows, dropped)

    return in_arrow(inner, scan, _schema(inner), 1_000_000)


def _schema(inner: DataFrame):
    return T.StructType([inner.schema["row"], T.StructField("n_lines", T.LongType()), T.StructField("n_dropped", T.LongType()), T.StructField("kept", T.StringType())])


def _by_shuffle(inner: DataFrame, frequent: DataFrame, filters: DataFrame, bits: int) -> DataFrame:
    """For more frequent keys than a broadcast may hold: lines' hashes meet their shard's filter and keys in one of SALTS piles; only texts that lose lines are matched again."""
    rows = stored(inner.withColumn("id", F.monotonically_increasing_id()), "line-rows")

    def explode(batches):
        for batch in batches:
            ids, owners, h1, h2 = [], [], [], []
            for i, own, lines in zip(batch.column("id").to_pylist(), batch.column("owner").to_pylist(), _lines(batch, "t"), strict=True):
                for k in {key_of(x) for x in lines}:
                    if k:
                        a, b = hashes(k)
                        ids.append(i)
                        owners.append(own)
                        h1.append(a)
                        h2.append(b)
            longs = [pa.array(np.array(x, np.uint64).view(np.int64)) for x in (h1, h2)]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(owners, pa.int64()), *longs], ["id", "owner", "h1", "h2"])

    lines = in_arrow(rows.select("id", "owner", "t"), explode, "id long, owner long, h1 long, h2 long")
    each = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))).alias("salt")
    nothing = lambda *names: [F.lit(None).cast("binary" if c == "filter" else "long").alias(c) for c in names]
    piles = (
        filters.select("shard", each, F.lit(0).alias("kind"), *nothing("id", "owner", "h1", "h2"), "filter")
        .unionByName(frequent.select(_shard(bits), each, F.lit(1).alias("kind"), *nothing("id"), F.col("first").alias("owner"), "h1", "h2", *nothing("filter")))
        .unionByName(lines.select(_shard(bits), F.pmod(F.xxhash64("id"), F.lit(SALTS)).alias("salt"), F.lit(2).alias("kind"), "id", "owner", "h1", "h2", *nothing("filter")))
    )

    def probe(batches):
        at, known, exact = None, None, []
        for batch in batches:
            pile = np.stack([batch.column(c).to_numpy(zero_copy_only=False) for c in ("shard", "salt")])
            kinds = batch.column("kind").to_numpy(zero_copy_only=False)
            cuts = np.flatnonzero(np.concatenate([[True], (pile[:, 1:] != pile[:, :-1]).any(0) | (kinds[1:] != kinds[:-1])]))
            for a, b in zip(cuts.tolist(), [*cuts[1:].tolist(), batch.num_rows], strict=True):
                part, kind, here = batch.slice(a, b - a), int(kinds[a]), tuple(pile[:, a].tolist())
                if here != at:
                    at, known, exact = here, None, []
                if kind == 0:
                    known = CuckooFilter.from_bytes(part.column("filter")[0].as_py())
                elif known is None:
                    continue  # no key of this shard is frequent
                elif kind == 1:
                    exact.append(part)
                else:
                    if isinstance(known, CuckooFilter):
                        whole = pa.Table.from_batches(exact)
                        first = whole.column("owner")
                        none = first.null_count == whole.num_rows
                        known = Known(bits, {here[0]: known}, *(whole.column(c).to_numpy().view(np.uint64) for c in ("h1", "h2")), np.zeros(whole.num_rows, np.int64) if none else first.to_numpy())
                        exact = []
                    h1, h2, own = (part.column(c).to_numpy(zero_copy_only=False) for c in ("h1", "h2", "owner"))
                    gone = np.zeros(len(h1), bool)
                    for i in np.flatnonzero(known.may_hold(h1.view(np.uint64))).tolist():
                        keeper = known.keeper(int(h1[i]) & MASK, int(h2[i]) & MASK)
                        gone[i] = keeper is not None and (none or keeper != own[i])
                    yield part.select(["id", "h1", "h2"]).filter(pa.array(gone))

    dealt = piles.repartition("shard", "salt").sortWithinPartitions("shard", "salt", "kind")
    gone = in_arrow(dealt, probe, "id long, h1 long, h2 long").groupBy("id").agg(F.collect_list(F.struct("h1", "h2")).alias("gone"))
    joined = rows.join(gone, "id", "left").drop("id", "owner")

    def scan(batches):
        for batch in batches:
            lines, dropped = list(_lines(batch, "t")), []
            for own, gone in zip(lines, batch.column("gone").to_pylist(), strict=True):
                marks = {(x["h1"] & MASK, x["h2"] & MASK) for x in gone or ()}
                dropped.append({i for i, x in enumerate(own) if marks and (k := key_of(x)) and hashes(k) in marks})
            yield _emit(batch, lines, dropped)

    return in_arrow(joined, scan, _schema(inner), 1_000_000)


def dedup_lines(docs: DataFrame, min_docs: int = 10, text: str = "text", broadcast_keys: int = BROADCAST_KEYS, keep: str = "none") -> DataFrame:
    """docs with n_lines, n_dropped and kept, counted over docs themselves. keep: "none" or "first" of the documents that hold a frequent line."""
    if keep not in ("none", "first"):
        raise ValueError(f"keep={keep!r}")
    owner = F.xxhash64(*docs.columns) if keep == "first" else None
    return drop_frequent(docs, line_counts(docs, text, owner=owner), min_docs, text, broadcast_keys, owner=owner)


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents without the lines that ten or more documents share."""
    done = dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return done.select("doc_id", "n_lines", "n_dropped", F.sha2(F.encode("kept", "UTF-8"), 256).alias("kept_sha256"))


OP4_SQL = r"""
with d as (select doc_id, row_number() over () as r, string_split(coalesce(text, ''), chr(10)) as lines from documents),
l as (select r, doc_id, unnest(lines) as line, unnest(range(len(lines))) as pos from d),
k as (select *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as key from l),
f as (select key from k where key <> '' group by key having count(distinct r) >= 10),
m as (select k.*, f.key is not null as gone from k left join f on f.key = k.key)
select doc_id, count(*) as n_lines, cast(sum(case when gone then 1 else 0 end) as bigint) as n_dropped,
       sha256(coalesce(string_agg(line, chr(10) order by pos) filter (where not gone), '')) as kept_sha256
from m group by r, doc_id
"""
