"""Shared storage: tables that cut lineage, and binary files that any Spark file system can hold.

Everything goes below ``spark.checkpoint.dir``, which all executors see; each call gets a fresh folder, so a
re-run never meets the files of an earlier one. Folders live as long as the application and are swept at exit.
"""

from __future__ import annotations

import atexit
import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_swept: set[str] = set()


def shared_dir(spark: SparkSession) -> str:
    """The folder in ``spark.checkpoint.dir``; only where none is set (tests on one machine) a temporary one."""
    folder = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir()
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = tempfile.mkdtemp(prefix="dyntri-")
        spark.sparkContext.setCheckpointDir(folder)
        folder = spark.sparkContext.getCheckpointDir()
    if folder not in _swept:
        _swept.add(folder)
        atexit.register(_sweep, spark, f"{folder}/dyntri-tables")
    return folder


def _sweep(spark: SparkSession, folder: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
    except Exception:  # noqa: BLE001  the session may be gone already
        pass


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/dyntri-tables/{uuid.uuid4().hex}/{name}"


def saved(df: DataFrame, name: str) -> DataFrame:
    """``df`` written as Parquet to the shared folder and read again: later steps don't recompute it."""
    path = fresh_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def give_back() -> None:
    """Memory that this process has freed goes back to the system, where its allocators can do that."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def frugal(kernel: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """``kernel`` for mapInArrow; its worker, which lives on between tasks, keeps none of the memory that is free before and after."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        give_back()
        try:
            yield from kernel(batches)
        finally:
            give_back()

    return run


def packed(df: DataFrame):
    """All columns of a row as one struct, whatever they are called; ``select("row.*")`` gives them back."""
    return F.struct(*[F.col("`" + c.replace("`", "``") + "`") for c in df.columns]).alias("row")


def tasks(df: DataFrame, bytes_each: int, least: int | None = None) -> int:
    """Partitions for a table: as its estimated size asks for, and at least the session's number for shuffles (or ``least``)."""
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    own = max(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
    # a plan without statistics of its own claims a size beyond all bounds
    return max(own if least is None else least, min(-(-size // bytes_each), 1_000_000)) if size < 1 << 60 else own


def write_blobs(df: DataFrame, column: str, path: str, per_file: int = 0) -> None:
    """One file per task: the bytes of ``column``, each value followed by one NUL byte; per_file: values in a file at most.

    Spark's text sink copies a string's bytes as they are, so binary formats go through its committer and any
    Hadoop file system without Python touching a file.
    """
    df.select(F.col(column).cast("string").alias("value")).write.option("lineSep", "\u0000").option("maxRecordsPerFile", per_file).text(path)


def read_blobs(spark: SparkSession, path: str) -> DataFrame:
    """(path string, content binary) of the files that :func:`write_blobs` wrote; empty ones are left out."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path)
    return files.where("length > 0").select("path", "content")
