"""Session helpers: where shared files go, how lineage is cut, how workers find this package."""

from __future__ import annotations

import contextlib
import ctypes
import os
import tempfile
import uuid
from collections.abc import Callable, Iterator
from functools import partial

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

PACKAGE_ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def workers(spark: SparkSession) -> SparkSession:
    """Let Python workers import this package; changes no Spark setting."""
    env = spark.sparkContext.environment
    paths = [p for p in env.get("PYTHONPATH", "").split(":") if p]
    if PACKAGE_ROOT not in paths:
        env["PYTHONPATH"] = ":".join([PACKAGE_ROOT, *paths])
    return spark


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir``.

    Where it is unset, a temporary folder serves a local session; a cluster's executors couldn't see it, so there it is an error.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="attrgraph-")
        spark.sparkContext.setCheckpointDir(base)
    return base.rstrip("/")


def fresh_path(spark: SparkSession, label: str) -> str:
    """A new path in the shared folder, removed when the application ends."""
    path = f"{shared_folder(spark)}/attrgraph/{label}-{uuid.uuid4().hex}"
    jvm_path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    jvm_path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(jvm_path)
    return path


def materialise(df: DataFrame, label: str = "step") -> DataFrame:
    """Cut lineage: write ``df`` as Parquet to the shared folder and read it again."""
    spark = df.sparkSession
    path = fresh_path(spark, label)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._attrgraph_written = True
    return out


def written(df: DataFrame, label: str = "step") -> DataFrame:
    """``df`` itself if ``materialise`` made it, else a written copy."""
    return df if getattr(df, "_attrgraph_written", False) else materialise(df, label)


def discard(df: DataFrame) -> None:
    """Delete the files behind a ``materialise``d frame that nothing reads any more."""
    spark = df.sparkSession
    for name in {os.path.dirname(f) for f in df.inputFiles()}:
        if "/attrgraph/" in name:
            path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(name)
            path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


#: What a worker's process keeps between tasks, by operator.
_KEPT: dict[str, dict] = {}


def kept(operator: str) -> dict:
    """A place for what an operator's tasks in one process share; ``lean`` functions of other operators empty it."""
    return _KEPT.setdefault(operator, {})


def give_back() -> None:
    """Freed memory goes back to the system, as far as the allocators allow."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def _lean(batches: Iterator, run: Callable[[Iterator], Iterator], operator: str) -> Iterator:
    for other, held in _KEPT.items():
        if other != operator:
            held.clear()
    give_back()
    try:
        yield from run(batches)
    finally:
        give_back()


def lean(run: Callable[[Iterator], Iterator], operator: str) -> Callable[[Iterator], Iterator]:
    """A worker function over batches that first drops what other operators have kept in its process (Spark uses one for many stages),
    and gives freed memory back when its task ends."""
    return partial(_lean, run=run, operator=operator)
