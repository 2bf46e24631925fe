"""Helpers that the operators share: the shared folder, written tables, and file systems."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import os
import re
import tempfile
import uuid
from collections.abc import Callable, Iterable
from typing import TypeVar

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

T = TypeVar("T")

#: Words of the contracts: runs of anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"

#: Upper bound of one Arrow batch sent to Python, in rows; Spark also bounds its bytes.
ARROW_ROWS = 2000


_made: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or on a local session one of ours if unset."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir is not set: on a cluster it must name a folder that driver and executors share")
        base = "file://" + tempfile.mkdtemp(prefix="batchplan-")
        spark.conf.set("spark.checkpoint.dir", base)
    return base.rstrip("/")


def new_path(spark: SparkSession, label: str) -> str:
    """A path in the shared folder that nothing uses yet."""
    _made.append(f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}")
    return _made[-1]


def written(df: DataFrame, label: str) -> DataFrame:
    """df written as Parquet in the shared folder and read again.

    It cuts the lineage: a lost executor later costs no more than a reread.
    """
    path = new_path(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def written_mark() -> int:
    """A point in the order of written tables, for ``release_since``."""
    return len(_made)


def made_since(mark: int) -> list[str]:
    """The paths of the tables written since ``mark``."""
    return _made[mark:]


def release_since(spark: SparkSession, mark: int = 0, keep: Iterable[DataFrame] = ()) -> None:
    """Delete the tables written since ``mark``, but for those that ``keep`` read; nothing may read the others any more."""
    release_tables(spark, made_since(mark), keep)


def release_tables(spark: SparkSession, paths: Iterable[str], keep: Iterable[DataFrame] = ()) -> None:
    """Delete written tables, but for those that ``keep`` read."""
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    spared = [f for df in keep for f in df.inputFiles()]
    for made in paths:
        if made in _made and not any(made.rsplit("/", 1)[1] in f for f in spared):
            path = jvm.org.apache.hadoop.fs.Path(made)
            path.getFileSystem(conf).delete(path, True)
            _made.remove(made)
    forget_shuffles(spark)


def forget_shuffles(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of tables that nothing refers to; it does so when garbage is collected."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def trim_executors(spark: SparkSession) -> None:
    """Let the executors' JVMs give back the heap that ended stages have used: a task for each core collects garbage.

    A heap that has grown stays as large until then, and the Python workers of the next stage stand beside it.
    """
    cores = spark.sparkContext.defaultParallelism
    spark.range(0, cores, 1, cores).select(F.java_method(F.lit("java.lang.System"), F.lit("gc")).alias("done")).write.format("noop").mode("overwrite").save()


def release(spark: SparkSession) -> None:
    """Delete the tables that operators have written so far; call it when their results are stored elsewhere."""
    release_since(spark)


def publish(fs: pafs.FileSystem, made: str, final: str) -> None:
    """Rename a finished file, in place of one that an earlier attempt may have left."""
    if not isinstance(fs, pafs.LocalFileSystem) and fs.get_file_info(final).type != pafs.FileType.NotFound:
        fs.delete_file(final)
    fs.move(made, final)


_worker: dict = {}


def _trim() -> None:
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # a C library without it keeps the memory
        ctypes.CDLL(None).malloc_trim(0)


def tidied(run: Callable, keeps: str = "") -> Callable:
    """run, which drops what other operators than ``keeps`` have cached, and gives memory back at its end.

    Python workers serve one stage after another, and idle ones stay beside the next stage's.
    """

    def tidy(batches):
        if any(key[0] != keeps for key in _worker):
            _worker.clear()
            _trim()
        yield from run(batches)
        _trim()

    return tidy


def worker_cache(key: tuple, make: Callable[[], T]) -> T:
    """What a Python worker keeps between its tasks: one operator's cache at a time, so they don't add up."""
    if key not in _worker:
        if _worker:
            _worker.clear()
            _trim()
        _worker[key] = make()
    return _worker[key]


def bound_arrow(spark: SparkSession) -> None:
    """Keep Arrow batches small, so that a worker holds a few MB of texts at a time."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(ARROW_ROWS))
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(16 << 20))


def filesystem(uri: str) -> tuple[pafs.FileSystem, str]:
    """The pyarrow file system of a URI (file, hdfs, s3, gs, ...) and the path in it."""
    if "://" not in uri and not uri.startswith("file:"):
        return pafs.LocalFileSystem(), os.path.abspath(uri)
    if uri.startswith("file:"):
        return pafs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    return pafs.FileSystem.from_uri(uri)


def text_or_empty(text: str | Column = "text") -> Column:
    """The text; the empty string for null."""
    return F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
