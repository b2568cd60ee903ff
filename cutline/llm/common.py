"""What several corpus operators share: inputs, intermediate tables and distributed numbering."""

from __future__ import annotations

import contextlib
import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Fixed values of the text contracts: the ASCII white space that separates words and is stripped from lines.
SPACE = " \t\n\x0b\x0c\r"
WORD = "[^\\x20\\x09-\\x0D]+"

#: Rows of a small table (a row per language, source or cell) that a broadcast may hold.
BROADCAST_ROWS = 200_000
#: Rows that one window of `numbered` ranks at most, about.
PART_ROWS = 100_000
#: Bytes of an Arrow batch that a Python worker takes up at once; a single longer row is a batch of its own.
BATCH_BYTES = 4_000_000
BATCH_SETTING, BATCH_DEFAULT = "spark.sql.execution.arrow.maxBytesPerBatch", "67108864b"

_own_folder: list[str] = []
_made: list[str] = []  # folders of stored tables, as far as they are known to be there


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that all machines share (spark.checkpoint.dir). Where it is unset, local mode, as in tests, has a folder of this process's own; a cluster is an error."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
    if not _own_folder:
        _own_folder.append(f"file://{tempfile.mkdtemp(prefix='cutline-')}")
    return _own_folder[0]


def stored(df: DataFrame, label: str) -> DataFrame:
    """df written as a Parquet table in the shared folder and read again: lineage ends here, and lost executors cost no recomputation."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _made.append(path)
    return spark.read.schema(df.schema).parquet(path)


def _path(spark: SparkSession, path: str):
    file = spark._jvm.org.apache.hadoop.fs.Path(path)
    return file, file.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf())


@contextlib.contextmanager
def scratch(spark: SparkSession):
    """Removes the tables that were stored inside when it ends: for steps whose result has been written elsewhere by then."""
    mark = len(_made)
    try:
        yield
    finally:
        for path in _made[mark:]:
            file, system = _path(spark, path)
            system.delete(file, True)
        del _made[mark:]


def written(df: Callable[[], DataFrame], spark: SparkSession, path: str) -> DataFrame:
    """The table at path; if a run has not finished writing it, df() is written there first. What df() stores on its way is removed."""
    file, system = _path(spark, f"{path}/_SUCCESS")
    if not system.exists(file):
        with scratch(spark):
            df().write.mode("overwrite").parquet(path)
    return spark.read.parquet(path)


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """A stored table for a join: with a broadcast hint while it has at most `rows` rows, else as it is, so that the join is shuffled."""
    return F.broadcast(df) if df.count() <= rows else df


def discard(df: DataFrame) -> None:
    """Removes the files of a stored table that nothing reads any more."""
    for folder in {f.rpartition("/")[0] for f in df.inputFiles()}:
        file, system = _path(df.sparkSession, folder)
        system.delete(file, True)


def pieces_of(batch: pa.RecordBatch, most: int = BATCH_BYTES) -> Iterator[pa.RecordBatch]:
    """The batch's rows in order, in slices of at most `most` bytes, or of one row."""
    todo = [batch]
    while todo:
        part = todo.pop()
        if part.nbytes <= most or part.num_rows <= 1:
            yield part
        else:
            half = part.num_rows // 2
            todo += [part.slice(half), part.slice(0, half)]


def in_arrow(df: DataFrame, run: Callable, schema, most: int = BATCH_BYTES) -> DataFrame:
    """df.mapInArrow(run, schema) with bounded memory: run sees batches of at most `most` bytes, and as Spark keeps its Python
    workers from stage to stage, a task gives back what it has freed when it ends. Where the session has Spark's default for the bytes
    of a batch that it sends to Python, it gets BATCH_BYTES, as either side holds a whole batch."""
    conf = df.sparkSession.conf
    if conf.get(BATCH_SETTING, None) == BATCH_DEFAULT:
        conf.set(BATCH_SETTING, f"{BATCH_BYTES}b")

    def bounded(batches):
        try:
            yield from run(part for batch in batches for part in pieces_of(batch, most))
        finally:
            pa.default_memory_pool().release_unused()
            with contextlib.suppress(OSError, AttributeError):  # other C libraries have no malloc_trim
                ctypes.CDLL(None).malloc_trim(0)

    return df.mapInArrow(bounded, schema)


def text_key(col: Column) -> Column:
    """A key as text; null and the empty text have keys of their own."""
    return F.coalesce(F.concat(F.lit("k"), col.cast("string")), F.lit("n"))


def numbered(df: DataFrame, group: list[str], order: list[str], name: str, part_rows: int = PART_ROWS) -> DataFrame:
    """Adds gapless numbers from 0 within each group, without one task for a whole group.

    A group is cut into a power of 16 of parts by the md5 of its order columns, so many that a group of all rows would have parts of at most
    about part_rows rows. The parts are counted
    (a map-side combined aggregate), running totals of the counts give each part its first number, and
    rows are numbered inside their part only. The order is (part, order columns); rows equal in all of
    these are interchangeable. Nulls in the group columns form a group.
    """
    digits = 1
    rows = df.count()
    while rows > part_rows * 16**digits:
        digits += 1
    cell = lambda c: F.col("row")[c]  # noqa: E731  the input's columns stay in a struct, so that names can't clash
    marks = [f"group{i}" for i in range(len(group))]
    keyed = df.select(
        F.struct(*[F.col(c) for c in df.columns if c != name]).alias("row"),
        F.substring(F.md5(F.concat_ws("\x01", *[text_key(F.col(c)) for c in order])), 1, digits).alias("part"),
        *[text_key(F.col(c)).alias(mark) for mark, c in zip(marks, group, strict=True)],
    )
    before = Window.partitionBy(*marks).orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    first = keyed.groupBy(*marks, "part").agg(F.count("*").alias("n")).withColumn("first", F.coalesce(F.sum("n").over(before), F.lit(0))).drop("n")
    within = Window.partitionBy(*marks, "part").orderBy(*[cell(c).asc_nulls_first() for c in order])
    ranked = keyed.withColumn("rank", F.row_number().over(within) - 1)
    return ranked.join(first, [*marks, "part"]).select("row.*", (F.col("first") + F.col("rank")).cast("long").alias(name))
