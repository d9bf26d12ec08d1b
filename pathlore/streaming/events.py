"""Events as a stream of edges: ontology concepts over windows, and rewritten star-free queries as stream-static joins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pathlore.plans.ontology import Name, Ontology

EVENT_LABELS = ("View", "Click", "Purchase", "Signup", "Error")


def read_event_stream(spark: SparkSession, folder: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def concepts_of(onto: Ontology, concepts: tuple[str, ...]) -> Column:
    """The named concepts that an event type falls under, from the saturated axioms: an expression, no join."""
    out = []
    for c in concepts:
        below = sorted({x.name for x in onto.concept_subs(Name(c)) if isinstance(x, Name)} & set(EVENT_LABELS))
        out.append(F.when(F.initcap("event_type").isin(*below), F.lit(c)))
    return F.filter(F.array(*out), lambda x: x.isNotNull())


def with_concepts(events: DataFrame, onto: Ontology, concepts: tuple[str, ...] = ("Interaction", "Activity")) -> DataFrame:
    return events.select("*", F.explode(concepts_of(onto, concepts)).alias("concept"))


def tumbling(events: DataFrame, onto: Ontology, size: str = "1 day") -> DataFrame:
    """Works on a batch and on a stream (give the stream a watermark first)."""
    return with_concepts(events, onto).groupBy(F.window("ts", size).alias("w"), "concept").agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("window_start"), "concept", "n", "total")


def sliding(events: DataFrame, onto: Ontology, size: str = "2 days", step: str = "1 day") -> DataFrame:
    return with_concepts(events, onto).groupBy(F.window("ts", size, step).alias("w"), "concept").agg(F.count("*").alias("n")).select(F.col("w.start").alias("window_start"), "concept", "n")


def sessions(events: DataFrame, onto: Ontology, gap: str = "1 hour") -> DataFrame:
    return with_concepts(events, onto, ("Activity",)).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("session_start"), "n")


def error_customers(events: DataFrame, wealthy: DataFrame) -> DataFrame:
    """The star-free rest of a rewritten query on new edges: a stream-static semi-join with a node set (node key in c_custkey)."""
    return events.where(F.col("event_type") == "error").join(wealthy, events.user_id == wealthy.c_custkey, "left_semi")


def without_repeats(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each event once, as long as its repeats come within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def followed_by(events: DataFrame, first: str, then: str, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Pairs of a user's events, the one of type ``then`` after that of type ``first`` and at most ``within`` later.

    Works on a batch and on a stream: there both sides have a watermark, so the state of each is dropped once no partner can
    come any more, and events later than ``late`` are left out.
    """
    side = lambda kind, *names: events.where(F.col("event_type") == kind).select(*(F.col(c).alias(n) for c, n in zip(("event_id", "user_id", "ts"), names, strict=True)))
    a, b = side(first, "event_id", "user_id", "ts"), side(then, "next_id", "next_user", "next_ts")
    if events.isStreaming:
        a, b = a.withWatermark("ts", late), b.withWatermark("next_ts", late)
    near = (F.col("user_id") == F.col("next_user")) & (F.col("next_ts") > F.col("ts")) & (F.col("next_ts") <= F.col("ts") + F.expr(f"INTERVAL {within}"))
    return a.join(b, near).select("user_id", "event_id", "next_id")
