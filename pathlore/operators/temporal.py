"""Temporal joins around the event edges: as-of, interval, and chain stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, right_at: str, take: str) -> DataFrame:
    """For each left row the right row of the same key with the latest time not after it; one shuffle, no range join.

    ``take`` is the right column to bring; of right rows with equal times the one with the largest ``take`` counts.
    """
    a = left.select(*left.columns, F.col(at).alias("_t"), F.lit(1).alias("_side"), F.lit(None).cast(right.schema[take].dataType).alias("_v"))
    b = right.select(*(F.col(key) if c == key else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns), F.col(right_at).alias("_t"), F.lit(0).alias("_side"), F.col(take).alias("_v"))
    order = W.partitionBy(key).orderBy("_t", "_side", "_v").rowsBetween(W.unboundedPreceding, 0)
    return a.unionByName(b).withColumn("_last", F.last("_v", ignorenulls=True).over(order)).where("_side = 1").select(*left.columns, F.col("_last").alias(take))


def interval_pairs(rows: DataFrame, key: str, at: str, id_: str, seconds: int) -> DataFrame:
    """Pairs of a key's rows at most ``seconds`` apart, first before second: an equi-join on time buckets, not a theta join."""
    sec = F.unix_micros(F.col(at).cast("timestamp"))
    base = rows.select(F.col(key).alias("k"), F.col(id_).alias("id"), sec.alias("t"), F.floor(sec / (seconds * 1_000_000)).alias("cell"))
    late = base.select("k", F.col("id").alias("id2"), F.col("t").alias("t2"), F.explode(F.array(F.col("cell"), F.col("cell") - 1)).alias("cell"))
    return base.join(late, ["k", "cell"]).where((F.col("t2") > F.col("t")) & (F.col("t2") <= F.col("t") + seconds * 1_000_000)).select(F.col("k").alias(key), F.col("id").alias("first_id"), F.col("id2").alias("second_id"))


def chain_positions(rows: DataFrame, key: str, *order: str) -> DataFrame:
    """Positions along a chain role (each row leads to the next of its key): its star is a comparison of positions."""
    return rows.withColumn("position", F.row_number().over(W.partitionBy(key).orderBy(*order)))
