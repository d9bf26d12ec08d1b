"""Helpers shared by the operators: staged tables, skew-safe joins, connected components."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pathlore.operators import staging
from pathlore.operators.staging import release, shared_path, shared_root

__all__ = ["attach_groups", "connected_components", "map_batches", "partitions_for", "release", "shared_path", "shared_root", "stage", "stage_bucketed", "text_or_empty", "trim_driver", "unload", "with_row_tag"]

#: Groups larger than one ``HEAVY_PARTS``-th of all rows count as heavy; so there are fewer than that many.
HEAVY_PARTS = 2000
#: Lower bound on the size of a heavy group, so that small inputs have none.
HEAVY_LEAST = 64


def trim_driver(spark: SparkSession) -> str:
    """Let the driver's JVM return freed native memory to the system, and what it says of that; empty where it can't.

    Hundreds of threads (broadcasts, shuffles, map outputs) allocate and free beside the heap, and the allocator keeps what each arena once
    had: some hundred MB after many small jobs, which no limit on the heap holds. Takes some 20 ms.
    """
    jvm, new = spark._jvm, spark.sparkContext._gateway.new_array

    def filled(kind: object, *values: object) -> object:
        out = new(kind, len(values))
        for i, v in enumerate(values):
            out[i] = v
        return out

    try:
        named, objects = jvm.java.lang.Class.forName, jvm.java.lang.Object
        kinds = filled(jvm.java.lang.Class, *map(named, ("javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")))
        invoke = named("javax.management.MBeanServer").getMethod("invoke", kinds)
        command = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand")
        asked = filled(objects, command, "systemTrimNativeHeap", filled(objects), filled(jvm.java.lang.String))
        return invoke.invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), asked)
    except Exception:  # a JVM without this command: nothing is lost but memory
        return ""


def stage(df: DataFrame, name: str) -> DataFrame:
    """Write a table into the shared folder and read it back; the driver gives back what the job took beside its heap."""
    staged = staging.stage(df, name)
    trim_driver(df.sparkSession)
    return staged


def stage_bucketed(df: DataFrame, name: str, key: str, buckets: int) -> DataFrame:
    """Write a table into the warehouse, bucketed by ``key``: later groupings by the key need no shuffle of it."""
    table = f"{name}_{uuid.uuid4().hex}"
    df.write.format("parquet").option("compression", "zstd").bucketBy(buckets, key).saveAsTable(table)
    trim_driver(df.sparkSession)
    return df.sparkSession.table(table)


def partitions_for(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))


def with_row_tag(df: DataFrame) -> DataFrame:
    """A number for each row, unique and stable only once the result is staged."""
    return df.withColumn("row_tag", F.monotonically_increasing_id())


def give_back() -> None:
    """Return freed memory to the system: Python workers stay alive between tasks and stages."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def unload(shared: Broadcast) -> None:
    """Let a worker forget a broadcast's value: it would hold it while idle. The next task reads it from its file again."""
    shared.__dict__.pop("_value", None)


def map_batches(df: DataFrame, work: Callable[[pa.RecordBatch], Iterable[pa.RecordBatch] | None], schema: str, shared: Broadcast | None = None) -> DataFrame:
    """``mapInArrow`` with a function of one batch; ``shared``: a broadcast that the worker forgets after its task."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield from work(batch)
        if shared is not None:
            unload(shared)
        give_back()

    return df.mapInArrow(each, schema)


def attach_groups(rows: DataFrame, groups: DataFrame, key: str, size: str, total: int) -> DataFrame:
    """Left join of ``rows`` with one row a ``key`` of ``groups``, safe when one key holds a large share of the rows.

    ``size`` is the column of ``groups`` with the number of rows of the key. Keys with more than
    total/HEAVY_PARTS rows are fewer than HEAVY_PARTS, a bound that holds for any input, so their groups are
    broadcast; the others meet in a shuffled join in which no key is large.
    """
    least = max(HEAVY_LEAST, total // HEAVY_PARTS)
    extra = [c for c in groups.columns if c != key]
    heavy = groups.where(F.col(size) > least)
    light = groups.where(F.col(size) <= least)
    is_heavy = F.broadcast(heavy.select(F.col(key).alias("_heavy_key")))
    marked = rows.join(is_heavy, F.col(key).eqNullSafe(F.col("_heavy_key")), "left")
    of_heavy = marked.where(F.col("_heavy_key").isNotNull()).drop("_heavy_key").join(F.broadcast(heavy), key, "inner")
    of_light = marked.where(F.col("_heavy_key").isNull()).drop("_heavy_key").join(light, key, "left")
    return of_heavy.select(*rows.columns, *extra).unionByName(of_light.select(*rows.columns, *extra))


def connected_components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, root) for every node of ``edges`` (a, b: long); root is the smallest node that it can reach.

    Alternates the large-star and the small-star step until the edges stay the same. Every round is staged;
    only counts and checksums come to the driver.
    """
    pairs = stage(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    mark = F.coalesce(F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")), F.lit(0).cast("decimal(38,0)"))
    seen = pairs.agg(F.count("*"), mark).first()
    for _ in range(rounds):
        if not seen[0]:
            break
        both = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("n"), F.least("a", "m").alias("m"))
        large = both.join(least, both.a == least.n).where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        lower = large.groupBy("a").agg(F.min("b").alias("m")).withColumnRenamed("a", "n")
        small = large.join(lower, large.a == lower.n).select(F.explode(F.array(F.struct("a", "m"), F.struct(F.col("b").alias("a"), "m"))).alias("e"))
        small = small.select(F.col("e.a").alias("a"), F.col("e.m").alias("b")).where("a <> b").distinct()
        fresh = stage(small, "edges")
        now = fresh.agg(F.count("*"), mark).first()
        release(pairs)
        pairs = fresh
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    return pairs.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(pairs.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
