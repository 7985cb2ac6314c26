"""Where plans that iterate put what they have so far, so that lineage stays short and lost executors lose nothing."""

from __future__ import annotations

import atexit
import ctypes
import gc
import shutil
import tempfile
import uuid

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

_own: list[str] = []
_written: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir; a folder of our own only where that is unset (tests, local mode)."""
    if found := spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir"):
        return found.rstrip("/")
    if not _own:
        _own.append(tempfile.mkdtemp(prefix="alignspark-plans-"))
        atexit.register(shutil.rmtree, _own[0], ignore_errors=True)
    return f"file://{_own[0]}"


def new_path(spark: SparkSession, name: str) -> str:
    _written.append(f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}")
    return _written[-1]


def cut(df: DataFrame, name: str = "cut") -> DataFrame:
    """Write df as Parquet into the shared folder and read it back: lineage ends there, and a lost executor loses nothing."""
    path = new_path(df.sparkSession, name)
    df.write.parquet(path)
    made = df.sparkSession.read.schema(df.schema).parquet(path)
    made._written_at = path
    return made


def release(spark: SparkSession, since: int, *keep: DataFrame) -> None:
    """Delete what was written after the first `since` paths, but for what keep, frames of cut(), read. Other frames that read it are done for."""
    kept = {k._written_at for k in keep}
    for path in [p for p in _written[since:] if p not in kept]:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
        _written.remove(path)


def written() -> int:
    """Number of paths written so far, a mark for release()."""
    return len(_written)


def tidy(run):
    """A generator over Arrow batches that hands its memory back when it ends: workers live on and serve other stages."""

    def tidied(batches):
        try:
            yield from run(batches)
        finally:
            gc.collect()
            pa.default_memory_pool().release_unused()
            if hasattr(libc := ctypes.CDLL(None), "malloc_trim"):
                libc.malloc_trim(0)

    return tidied
