"""Graphs and answers on disk."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathlore.sources.graph import NodeKind, PropertyGraph


def write_graph(graph: PropertyGraph, path: str) -> None:
    """Edges by role and nodes by kind, sorted by their join key within files; properties keep their typed columns."""
    for role, rows in graph.roles.items():
        rows.withColumn("role", F.lit(role)).sortWithinPartitions("src").write.mode("overwrite").parquet(f"{path}/edges/role={role}")
        rows.select("src", "dst").sortWithinPartitions("dst").write.mode("overwrite").parquet(f"{path}/edges_by_dst/role={role}")
    for kind, k in graph.kinds.items():
        labels = F.array(*(F.when(F.lit(True) if c is None else c, F.lit(n)) for n, c in k.labels.items())) if k.labels else F.array().cast("array<string>")
        k.rows.withColumn("labels", F.filter(labels, lambda x: x.isNotNull())).sortWithinPartitions("node_id").write.mode("overwrite").parquet(f"{path}/nodes/kind={kind}")


def read_graph(spark: SparkSession, path: str, roles: list[str], kinds: dict[str, list[str]]) -> PropertyGraph:
    """``kinds`` gives the labels that nodes of each kind may have."""
    g = PropertyGraph(spark)
    for r in roles:
        rows = spark.read.parquet(f"{path}/edges/role={r}")
        g.roles[r] = rows.drop("role")
    for kind, labels in kinds.items():
        rows = spark.read.parquet(f"{path}/nodes/kind={kind}")
        props = tuple(c for c in rows.columns if c not in ("node_id", "labels", "kind"))
        g.kinds[kind] = NodeKind(rows, {n: F.array_contains("labels", n) for n in labels}, props)
    return g


def write_bucketed_edges(graph: PropertyGraph, name: str, buckets: int) -> dict[str, str]:
    """Tables of edges bucketed and sorted by src: repeated joins along them need no shuffle of the edges."""
    out = {}
    for role, rows in graph.roles.items():
        out[role] = f"{name}_{role}".lower()
        rows.write.mode("overwrite").format("parquet").bucketBy(buckets, "src").sortBy("src").saveAsTable(out[role])
    return out


def import_properties(spark: SparkSession, path: str, kind: str = "csv", key: str = "node_id") -> DataFrame:
    """Open properties from CSV or JSON as (node_id, props map); a missing value is no property."""
    rows = spark.read.option("header", True).csv(path) if kind == "csv" else spark.read.json(path)
    keys = [c for c in rows.columns if c != key]
    pairs = reduce(lambda a, b: a + b, [[F.lit(c), F.col(c).cast("string")] for c in keys], [])
    return rows.select(F.col(key).cast("long").alias("node_id"), F.map_filter(F.create_map(*pairs), lambda k, v: v.isNotNull()).alias("props"))
