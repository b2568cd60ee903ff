"""The corpus pipeline: language ID, line dedup, near-duplicate removal, mixing to target weights, packing.

Each stage takes all documents that its predecessor kept and returns documents again; only the last returns the pieces of packed sequences.
Between stages the documents are a Parquet table in the shared folder, so a lost executor costs one stage at the most.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutline.llm import language, line_dedup, mixing, near_dup, packing
from cutline.llm.common import shared_folder, stored, table, written

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a recognised language. Those without text or without a letter go; a missing lang is filled in."""
    found = language.predict(docs.select(*COLUMNS), language.train(docs))
    return found.filter(F.col("lang_pred") != "und").withColumn("lang", F.coalesce("lang", "lang_pred")).select(*COLUMNS)


def keyed(docs: DataFrame) -> DataFrame:
    """docs with `row`: doc_id and a hash of all columns. Rows with the same key are equal, so which of them stays makes no difference."""
    return docs.select(*COLUMNS, F.struct("doc_id", F.xxhash64(*COLUMNS).alias("hash")).alias("row"))


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the lines that ten or more of them share, but for the one that keeps them: of exact copies one stays whole. A document that loses all its lines stays as an empty text."""
    done = line_dedup.dedup_lines(docs.select(*COLUMNS), keep="first")
    return done.withColumn("text", F.col("kept")).withColumn("n_chars", F.length("kept").cast("long")).select(*COLUMNS)


def keep_one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each near-duplicate component: the one with the smallest doc_id (and hash, where rows share a doc_id). Equal rows count once; a text without words is a group of its own."""
    docs = keyed(docs)
    classes = stored(near_dup.near_duplicates(docs.select("row", "text"), key="row"), "classes")
    others = classes.filter(F.col("row") != F.col("component_id")).select("row").distinct()
    kept = docs.join(others, "row", "left_anti")
    repeated = stored(classes.groupBy("row").count().filter("count > 1").select("row"), "repeated")
    if repeated.isEmpty():
        return kept.select(*COLUMNS)
    once = kept.join(repeated, "row", "left_semi").dropDuplicates(["row"])
    return kept.join(repeated, "row", "left_anti").unionByName(once).select(*COLUMNS)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them: no time, once or twice."""
    docs = keyed(docs)
    copies = stored(mixing.mix(docs, key="row").groupBy("row").agg(F.sum("copies").alias("copies"), F.count("*").alias("rows")), "row-copies")
    once = docs.join(copies.filter("copies > 0"), "row")
    if not copies.filter("rows > 1").isEmpty():  # of equal rows one stands for all
        once = once.filter("rows = 1").unionByName(once.filter("rows > 1").dropDuplicates(["row"]))
    return once.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))).select(*COLUMNS)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents in sequences of 2048 tokens."""
    return packing.pack(docs.select("doc_id", "text"), packing.default_vocabulary())


STAGES = [
    ("language_id", identify_language),
    ("line_dedup", drop_repeated_lines),
    ("near_duplicates", keep_one_of_each_group),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]

#: Tokenising is beyond SQL; tests/llm checks each stage against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str, folder: str | None = None) -> DataFrame:
    """The packed pieces of all documents. Each stage's documents are a table in `folder`, a new one of the shared folder if none is given; a run that is started again with the
    folder of an earlier one goes on after that one's last finished stage. What a stage stores on its way is removed when its documents are written."""
    folder = folder or f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    docs = table(spark, sf_dir, "documents")
    for number, (name, stage) in enumerate(STAGES[:-1]):
        docs = written(lambda stage=stage, docs=docs: stage(spark, docs, sf_dir), spark, f"{folder}/{number}-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
