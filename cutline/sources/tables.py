"""Graph tables in Spark's own formats, and result folders that a run can write again without harm."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..schema import require

FORMATS = ("parquet", "orc", "json", "csv")


def read_table(spark: SparkSession, path: str, schema: T.StructType, kind: str = "parquet") -> DataFrame:
    """A table of one of the engine's schemas; text formats are read by it, the others are checked against it. Broken text rows are an error."""
    if kind not in FORMATS:
        raise ValueError(f"format {kind!r}, not one of {FORMATS}")
    reader = spark.read.format(kind)
    if kind in ("csv", "json"):
        reader = reader.schema(schema).option("mode", "FAILFAST")
    return require(reader.option("header", True).load(path) if kind == "csv" else reader.load(path), schema)


def write_run(df: DataFrame, path: str, run: str, kind: str = "parquet", by: str | None = None) -> str:
    """Writes df as the folder run=<run> of path; a run that is repeated replaces its own folder only. by: a column of few values to partition by."""
    target = f"{path}/run={run}"
    writer = df.write.mode("overwrite").format(kind)
    if kind == "csv":
        writer = writer.option("header", True)
    (writer.partitionBy(by) if by else writer).save(target)
    return target


def write_index(index: DataFrame, path: str, run: str, buckets: int = 64) -> str:
    """An index (lo, hi, ...) in folders of neighbouring ranks, so that a customization or query of some ranks reads some folders."""
    top = index.agg(F.max("hi").alias("top")).first().top or 0
    width = top // buckets + 1
    return write_run(index.withColumn("bucket", F.expr(f"lo div {width}")).repartition("bucket").sortWithinPartitions("lo", "hi"), path, run, by="bucket")
