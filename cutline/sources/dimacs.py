"""Reader and writer of the DIMACS shortest-path challenge text format: `.gr` arcs (a tail head weight), `.co` positions (v id x y).

`read_arcs` and `read_positions` split plain text files by Spark's own byte ranges; `DimacsSource` offers the same records
as a Python data source (format "dimacs", option kind: arcs or positions), with byte ranges of its own for local files.
"""

from __future__ import annotations

import os

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

ARCS = "src bigint, dst bigint, weight bigint"
POSITIONS = "node_id bigint, x bigint, y bigint"


def _records(spark: SparkSession, path: str, mark: str, names: list[str]) -> DataFrame:
    part = F.split(F.trim("value"), r"\s+")
    lines = spark.read.text(path).filter(F.col("value").startswith(mark + " "))
    return lines.select(*[part[i + 1].cast("long").alias(n) for i, n in enumerate(names)])


def read_arcs(spark: SparkSession, path: str) -> DataFrame:
    return _records(spark, path, "a", ["src", "dst", "weight"])


def read_positions(spark: SparkSession, path: str) -> DataFrame:
    return _records(spark, path, "v", ["node_id", "x", "y"])


def write_arcs(arcs: DataFrame, path: str) -> None:
    """Folder of text files with arc records, and a problem line with the largest node number and the number of arcs in one of them."""
    size = arcs.agg(F.coalesce(F.max(F.greatest("src", "dst")), F.lit(0)).alias("n"), F.count("*").alias("m"))
    problem = size.select(F.concat_ws(" ", F.lit("p sp"), "n", "m").alias("value"))
    problem.unionByName(arcs.select(F.concat_ws(" ", F.lit("a"), "src", "dst", "weight").alias("value"))).write.mode("overwrite").text(path)


def check_problem(spark: SparkSession, path: str) -> tuple[int, int]:
    """Nodes and arcs that the problem line tells; an error if it is missing, stands twice, or the arc records differ from it."""
    part = F.split(F.trim("value"), r"\s+")
    told = spark.read.text(path).filter(F.col("value").startswith("p ")).select(part[2].cast("long").alias("n"), part[3].cast("long").alias("m")).limit(2).collect()
    if len(told) != 1:
        raise ValueError(f"{len(told) or 'no'} problem line{'s' if told else ''}")
    found = read_arcs(spark, path).agg(F.max(F.greatest("src", "dst")).alias("n"), F.count("*").alias("m")).first()
    if found.m != told[0].m or (found.n or 0) > told[0].n:
        raise ValueError(f"the problem line tells {told[0].n} nodes and {told[0].m} arcs; there are {found.m} arcs with nodes up to {found.n}")
    return told[0].n, told[0].m


class _Range(InputPartition):
    def __init__(self, path: str, start: int, end: int):
        super().__init__(None)
        self.path, self.start, self.end = path, start, end


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.mark = options["path"], "a" if options.get("kind", "arcs") == "arcs" else "v"
        self.size = int(options.get("range", 64 << 20))

    def partitions(self):
        files = [os.path.join(self.path, f) for f in sorted(os.listdir(self.path)) if not f.startswith(("_", "."))] if os.path.isdir(self.path) else [self.path]
        return [_Range(f, a, min(a + self.size, n)) for f in files for n in [os.path.getsize(f)] for a in range(0, max(n, 1), self.size)]

    def read(self, partition):
        with open(partition.path, "rb") as f:
            f.seek(max(0, partition.start - 1))
            if partition.start:
                f.readline()  # a line belongs to the range that it begins in
            while f.tell() < partition.end and (line := f.readline()):
                part = line.split()
                if part and part[0].decode() == self.mark:
                    yield tuple(int(x) for x in part[1:4])


class DimacsSource(DataSource):
    @classmethod
    def name(cls):
        return "dimacs"

    def schema(self):
        return ARCS if self.options.get("kind", "arcs") == "arcs" else POSITIONS

    def reader(self, schema):
        return _Reader(self.options)
