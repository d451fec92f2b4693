"""Lineage cuts in the folder that all executors share, and tables that go again with the step that made them."""

from __future__ import annotations

import contextlib
import gc
import tempfile
import threading
import time
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession


def _shared(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one only where none is set (tests)."""
    context = spark.sparkContext
    own = context.getConf().get("spark.checkpoint.dir") or context.getCheckpointDir()
    if not own:
        if not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="dyntri-"))
        own = context.getCheckpointDir()
    return own


def fresh_folder(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder."""
    return f"{_shared(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


_scopes = threading.local()


@contextlib.contextmanager
def passing(spark: SparkSession) -> Iterator[None]:
    """What this thread cuts inside goes at the end, with the shuffles behind it; nothing lazy may leave the block."""
    outer, _scopes.folders = getattr(_scopes, "folders", None), []
    try:
        yield
    finally:
        own, _scopes.folders = _scopes.folders, outer
        jvm = spark.sparkContext._jvm
        for folder in own:
            path = jvm.org.apache.hadoop.fs.Path(folder)
            path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def settled(spark: SparkSession) -> None:
    """Lets go of the shuffles of steps that are over: Spark deletes them once the driver's garbage is collected."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()
    time.sleep(1)


def cut(df: DataFrame) -> DataFrame:
    """``df`` checkpointed to ``spark.checkpoint.dir``; inside :func:`passing` as Parquet, which takes a fraction of that."""
    _shared(df.sparkSession)
    if getattr(_scopes, "folders", None) is None:
        return df.checkpoint()
    _scopes.folders.append(folder := fresh_folder(df.sparkSession, "cut"))
    df.write.parquet(folder)
    return df.sparkSession.read.schema(df.schema).parquet(folder)


#: Bytes of a stored stream from which runs go one after the other.
LARGE = 16_000_000


def _size(df: DataFrame) -> int:
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def is_large(df: DataFrame) -> bool:
    """Whether a stored table is; plans without statistics of their own claim a size beyond all bounds and count as small."""
    return LARGE <= _size(df) < 1 << 60


def runs_at_once(df: DataFrame) -> int:
    """Runs over a large stored table that go together: those of 40 times LARGE, or one."""
    return max(1, 40 * LARGE // _size(df))
