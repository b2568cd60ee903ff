"""Best-fit decreasing packing of tokenised documents into windows of a fixed capacity.

Documents are tokenised whole, an end id is added, and documents longer than the window are cut into full windows
and a rest. All pieces then have one of `capacity` lengths, so the packing needs only the number of pieces of each
length: equal pieces are interchangeable. The plan is made on the driver from that histogram (at most `capacity`
rows, whatever the corpus), lengths in falling order. A segment tree over remaining capacities finds the tightest
open windows that a length fits; windows with the same remaining capacity are kept as spans and filled together, which gives the
very windows that placing piece by piece would. The outcome is a short list of rules (length, ranks -> windows, offset).

Pieces are then numbered within their length without one task for a length, and the rules place them.

Defined results: a null or empty text is the end id alone; repeated rows are packed as documents of their own;
an empty table gives an empty result.
"""

from __future__ import annotations

import functools
import json
import os
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import in_arrow, numbered, stored, table

#: The split pattern of the byte-level vocabulary family, as its tokenizers library states it. Fixed value.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def _byte_of_char() -> dict[str, int]:
    """The byte-level alphabet: printable bytes stand for themselves, the others for characters from U+0100 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


@functools.lru_cache(maxsize=2)
def encoder(path: str):
    """text -> ids as numpy, equal to the tokenizers library's encode(text, add_special_tokens=False) with the file at path.

    A merge table in a byte-level vocabulary is the order of its ids, so the much faster tiktoken can run the same file. That is
    checked against the tokenizers library on probes; if they differ, or tiktoken is missing or gives up on a text, the tokenizers library
    encodes. It is loaded only for the probes and such texts, as either holds the whole vocabulary in memory.
    """
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    slow = functools.lru_cache(maxsize=1)(lambda: Tokenizer.from_file(path))
    plain = lambda text: np.array(slow().encode(text, add_special_tokens=False).ids, np.uint32)
    try:
        import tiktoken

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        special = {x["content"]: x["id"] for x in spec.get("added_tokens", [])}
        of = _byte_of_char()
        ranks = {bytes(of[c] for c in token): i for token, i in spec["model"]["vocab"].items() if token not in special}
        fast = tiktoken.Encoding("vocabulary", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens=special)
        quick = lambda text: fast.encode_to_numpy(text, allowed_special="all")
        probes = ["", " a  b\n\n c", "It's 12 äöü€ ", "漢字 x\t\r\n", *special, *(f"a{s} b" for s in special)]
        if any(not np.array_equal(quick(p), plain(p)) for p in probes):
            return plain
        slow.cache_clear()
    except (ImportError, KeyError, ValueError):
        return plain

    def encode(text: str) -> np.ndarray:
        try:
            return quick(text)
        except Exception:  # a text that the pattern engine gives up on
            return plain(text)

    return encode


class CapacityTree:
    """A segment tree over remaining capacities 0..n: which have open windows, and the tightest that fits a length."""

    def __init__(self, n: int):
        self.leaves = 1 << n.bit_length()
        self.any = [False] * (2 * self.leaves)

    def set(self, capacity: int, value: bool) -> None:
        at = capacity + self.leaves
        self.any[at] = value
        while at > 1:
            at //= 2
            self.any[at] = self.any[2 * at] or self.any[2 * at + 1]

    def tightest(self, length: int) -> int | None:
        """The smallest capacity of at least length with an open window."""
        at = length + self.leaves
        if self.any[at]:
            return length
        while at > 1:
            if at % 2 == 0 and self.any[at + 1]:
                at += 1
                break
            at //= 2
        else:
            return None
        while at < self.leaves:
            at = 2 * at if self.any[2 * at] else 2 * at + 1
        return at - self.leaves


def plan(counts: dict[int, int], capacity: int) -> list[tuple[int, int, int, int, int]]:
    """Rules (length, first rank, first window, pieces per window, offset) by length and rank, of the best-fit decreasing packing."""
    spans: dict[int, list[tuple[int, int]]] = {}
    tree, rules, windows = CapacityTree(capacity), [], 0

    def put(c: int, first: int, n: int) -> None:
        if n:
            spans.setdefault(c, []).append((first, n))
            tree.set(c, True)

    for length in sorted(counts, reverse=True):
        left, rank = counts[length], 0
        while left:
            c = tree.tightest(length)
            if c is None:
                n = -(-left // (capacity // length))
                put(capacity, windows, n)
                windows += n
                c = capacity
            first, n = spans[c].pop()
            tree.set(c, bool(spans[c]))
            each = c // length
            use = min(n, left // each)
            if not use:
                each, use = left, 1
            rules.append((length, rank, first, each, capacity - c))
            put(c - each * length, first, use)
            put(c, first + use, n - use)
            rank += use * each
            left -= use * each
    return rules


def tokenise(docs: DataFrame, path: str, capacity: int, end_id: int, key: str = "doc_id", text: str = "text", keep_ids: bool = False) -> DataFrame:
    """key, start, length, ids_crc32, doc_tokens (and ids): the pieces of each document."""

    def cut(batches):
        encode = encoder(path)
        for batch in batches:
            out: list[list] = [[], [], [], [], [], []]
            for k, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                ids = np.append(encode(t or ""), np.uint32(end_id)).astype("<u4")
                for at in range(0, len(ids), capacity):
                    piece = ids[at : at + capacity]
                    row = (k, at, len(piece), zlib.crc32(piece.tobytes()), len(ids), piece.astype(np.int32) if keep_ids else None)
                    for column, v in zip(out, row, strict=True):
                        column.append(v)
            kinds = [batch.schema.field(0).type, *[pa.int64()] * 4, pa.list_(pa.int32())]
            columns = [pa.array(x, t) for x, t in zip(out, kinds, strict=True)][: 6 if keep_ids else 5]
            yield pa.RecordBatch.from_arrays(columns, ["key", "start", "length", "ids_crc32", "doc_tokens", "ids"][: 6 if keep_ids else 5])

    kind = docs.schema[key].dataType.simpleString()
    schema = f"key {kind}, start long, length long, ids_crc32 long, doc_tokens long" + (", ids array<int>" if keep_ids else "")
    return in_arrow(docs.select(F.col(key).alias("key"), F.col(text).cast("string").alias("text")), cut, schema).withColumnRenamed("key", key)


def place(pieces: DataFrame, capacity: int, key: str = "doc_id") -> DataFrame:
    """pieces with sequence_id and offset, by best-fit decreasing over all of them."""
    counts = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}
    rules = sorted(plan(counts, capacity))
    lengths, ranks, firsts, eaches, offsets = (np.array(x, np.int64) for x in (zip(*rules, strict=True) if rules else [[]] * 5))
    start_of = {int(v): int(i) for v, i in zip(*np.unique(lengths, return_index=True), strict=True)}
    held = pieces.sparkSession.sparkContext.broadcast((lengths, ranks, firsts, eaches, offsets))
    ranked = numbered(pieces, ["length"], [key, "start"], "rank")

    def assign(batches):
        lengths, ranks, firsts, eaches, offsets = held.value
        for batch in batches:
            length, rank = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("length", "rank"))
            rule = np.zeros(len(length), np.int64)
            for v in np.unique(length).tolist():
                low = start_of[v]
                high = int(np.searchsorted(lengths, v, "right"))
                own = length == v
                rule[own] = low + np.searchsorted(ranks[low:high], rank[own], "right") - 1
            nth = rank - ranks[rule]
            added = [pa.array(firsts[rule] + nth // eaches[rule]), pa.array(offsets[rule] + nth % eaches[rule] * length)]
            yield pa.RecordBatch.from_arrays([batch.column(c) for c in names] + added, [*names, "sequence_id", "offset"])

    names = pieces.columns
    from pyspark.sql import types as T

    schema = T.StructType([*pieces.schema.fields, T.StructField("sequence_id", T.LongType()), T.StructField("offset", T.LongType())])
    return in_arrow(ranked, assign, schema)


def pack(docs: DataFrame, path: str, capacity: int = 2048, end_id: int = 1, key: str = "doc_id", text: str = "text", keep_ids: bool = False) -> DataFrame:
    """One row per piece of each document: where in its document, and where in which sequence."""
    return place(stored(tokenise(docs, path, capacity, end_id, key, text, keep_ids), "pieces"), capacity, key)


def padded_length(tokens, capacity: int = 2048):
    """What a sequence of so many tokens takes: the capacity, or its own length where that is a power of two."""
    return F.when(F.bit_count(tokens) == 1, tokens).otherwise(F.lit(capacity))


def sequences(packed: DataFrame, capacity: int = 2048, pad_id: int = 0) -> DataFrame:
    """sequence_id, ids, tokens: whole padded sequences of pieces that were packed with keep_ids. A sequence has at most `capacity` ids."""
    parts = F.array_sort(F.collect_list(F.struct("offset", "ids")))
    whole = packed.groupBy("sequence_id").agg(F.flatten(F.transform(parts, lambda p: p["ids"])).alias("ids"), F.sum("length").alias("tokens"))
    pad = F.array_repeat(F.lit(pad_id), (padded_length(F.col("tokens"), capacity) - F.col("tokens")).cast("int"))
    return whole.withColumn("ids", F.concat("ids", pad))


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op5_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents packed into sequences of 2048 tokens."""
    packed = pack(table(spark, sf_dir, "documents").select("doc_id", "text"), default_vocabulary())
    return packed.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")
