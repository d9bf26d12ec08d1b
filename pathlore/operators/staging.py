"""Tables written to the shared folder to cut lineage; they survive the loss of executors."""

from __future__ import annotations

import contextlib
import threading
import uuid
from collections.abc import Callable, Iterator

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession

_SCRATCH = threading.local()
#: Bytes shuffled from which on the files of shuffles that nothing reads any more are given back; by application, what was shuffled when they last were.
SHUFFLED_BYTES = 128 << 20
_SHUFFLED: dict[str, int] = {}


@contextlib.contextmanager
def scratch() -> Iterator[None]:
    """Whatever this thread stages or keeps within is given back at the end: for work whose results are taken inside."""
    outer, mine = getattr(_SCRATCH, "held", None), []
    _SCRATCH.held = mine
    try:
        yield
    finally:
        _SCRATCH.held = outer
        for give_back in reversed(mine):
            with contextlib.suppress(Exception):  # what is gone already needs no deleting
                give_back()


def _held(give_back: Callable[[], object]) -> None:
    if getattr(_SCRATCH, "held", None) is not None:
        _SCRATCH.held.append(give_back)


def keep(df: DataFrame) -> DataFrame:
    """Cached, on disk where memory is short."""
    kept = df.persist(StorageLevel.MEMORY_AND_DISK)
    _held(kept.unpersist)
    return kept


def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``. Where it is unset, as in tests, a local session gets one of our own."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        folder = "file:///tmp/checkpoints/pathlore"
    return folder.rstrip("/")


def shared_path(spark: SparkSession, name: str) -> str:
    return f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"


def stage(df: DataFrame, name: str) -> DataFrame:
    """Write a table into the shared folder and read it back."""
    path = shared_path(df.sparkSession, name)
    _held(lambda: delete(df.sparkSession, path))
    df.write.parquet(path)
    free_shuffles(df.sparkSession)
    staged = df.sparkSession.read.schema(df.schema).parquet(path)
    staged._staged_path = path
    return staged


def delete(spark: SparkSession, path: str) -> None:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def free_shuffles(spark: SparkSession) -> bool:
    """Spark deletes a shuffle's files once the driver has collected its last reference: ask for that when much was shuffled since. Whether it was asked."""
    executors = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    now, app = sum(executors.apply(i).totalShuffleWrite() for i in range(executors.size())), spark.sparkContext.applicationId
    if now - _SHUFFLED.get(app, 0) < SHUFFLED_BYTES:
        return False
    _SHUFFLED[app] = now
    spark._jvm.System.gc()
    return True


def stage_pairs(df: DataFrame, key: str, least_bytes: int) -> DataFrame:
    """A table that many rounds join by ``key``: written once, bucketed and sorted by it, if Spark's estimate of its size says that it is not small."""
    spark = df.sparkSession
    if int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()) <= least_bytes:
        return df
    name = f"pairs_{uuid.uuid4().hex}"
    buckets = int(spark.conf.get("spark.sql.shuffle.partitions", "200"))
    _held(lambda: spark.sql(f"DROP TABLE IF EXISTS {name}"))
    df.write.format("parquet").option("compression", "zstd").bucketBy(buckets, key).sortBy(key).saveAsTable(name)
    laid = spark.table(name)
    laid._laid_table = name
    return laid


def release(df: DataFrame) -> None:
    """Delete a table that ``stage`` or ``stage_pairs`` wrote, once nothing reads it any more."""
    path, name = getattr(df, "_staged_path", None), getattr(df, "_laid_table", None)
    if path:
        delete(df.sparkSession, path)
    if name:
        df.sparkSession.sql(f"DROP TABLE IF EXISTS {name}")
