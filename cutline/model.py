"""A graph: nodes with fixed-point positions, and undirected edges u < v."""

from __future__ import annotations

import tempfile
import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_own: list[str] = []
#: Rows of a small table (a row per cell, direction or hub) that a broadcast may hold.
BROADCAST_ROWS = 200_000


@dataclass
class Graph:
    nodes: DataFrame
    edges: DataFrame
    #: Nodes and edges with cell_id, once they have been computed.
    cells: tuple[DataFrame, DataFrame] | None = None


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir, which all machines share. Where it is unset, local mode has a folder of this process; a cluster is an error."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
    if not _own:
        _own.append(f"file://{tempfile.mkdtemp(prefix='cutline-')}")
    return _own[0]


def kept(df: DataFrame, label: str = "state") -> DataFrame:
    """df as a table in the shared folder, read again: where loops cut their lineage."""
    path = f"{shared_folder(df.sparkSession)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """A stored table for a join: with a broadcast hint while it has at most `rows` rows, else as it is, so that the join is shuffled."""
    return F.broadcast(df) if df.count() <= rows else df


def wide(df: DataFrame) -> DataFrame:
    """A table for a join that is shuffled at any size. The files of rows with lists or paths are a small part of what the rows take in memory, so by their size Spark would send tables to the driver and broadcast them."""
    return df.hint("merge")


def there(df: DataFrame) -> bool:
    """Whether the files of a kept table are still there."""
    jvm, session = df.sparkSession._jvm, df.sparkSession._jsparkSession
    files = df.inputFiles()
    path = lambda f: jvm.org.apache.hadoop.fs.Path(f)
    return bool(files) and path(files[0]).getFileSystem(session.sessionState().newHadoopConf()).exists(path(files[0]))
