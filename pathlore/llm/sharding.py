"""Sharding by Karmarkar-Karp differencing of indivisible groups.

Rows with equal text form a group that stays in one shard. Groups are dealt into differencing tasks by hash; each
task repeatedly combines the two partial partitions with the largest spread, the one in falling and the other in
rising order, until one partition of its groups is left. These partitions, one a task, are combined by the same rule
on the driver, which sees MAX_TASKS x shards sums at most. The law is ``bytes``: shard sizes are near equal, as far
as the largest group allows.

A null text has no bytes; a row's size is its UTF-8 bytes plus 1. An empty table gives an empty result. Null and
repeated doc_ids are placed as any other row.
"""

from __future__ import annotations

import heapq
from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathlore.llm.common import attach_groups, partitions_for, stage, text_or_empty, with_row_tag

#: Groups that one differencing task takes, and the most tasks.
GROUPS_PER_TASK = 4096
MAX_TASKS = 16384


def difference(partials: Sequence[Sequence[int]], ways: int) -> list[list[int]]:
    """For each partial partition (``ways`` sums), the final way of each of its parts."""
    if not len(partials):
        return []
    heap, made = [], []
    for i, sums in enumerate(partials):
        order = sorted(range(ways), key=lambda j: -sums[j])
        falling = [sums[j] for j in order]
        made.append((order, None, None, falling))
        heap.append((falling[-1] - falling[0], i))
    heapq.heapify(heap)
    while len(heap) > 1:
        a = heapq.heappop(heap)[1]
        b = heap[0][1]
        one, two = made[a][3], made[b][3]
        sums = [one[j] + two[ways - 1 - j] for j in range(ways)]
        order = sorted(range(ways), key=lambda j: -sums[j])
        falling = [sums[j] for j in order]
        made.append((order, a, b, falling))
        heapq.heapreplace(heap, (falling[-1] - falling[0], len(made) - 1))
    ends: list[list[int] | None] = [None] * len(made)
    ends[-1] = list(range(ways))
    out: list[list[int]] = [[] for _ in partials]
    for i in range(len(made) - 1, -1, -1):
        order, a, b, _ = made[i]
        place = [0] * ways  # of each part before it was put in falling order
        for rank, j in enumerate(order):
            place[j] = ends[i][rank]
        if a is None:
            out[i] = place
        else:
            ends[a] = place
            ends[b] = place[::-1]
        ends[i] = None
    return out


def _difference_task(ways: int):
    def work(groups: pd.DataFrame) -> pd.DataFrame:
        groups = groups.sort_values("digest")
        sizes = groups["bytes"].to_numpy()
        places = difference([[int(s)] + [0] * (ways - 1) for s in sizes], ways)
        return pd.DataFrame({"digest": groups["digest"].to_numpy(), "task": groups["task"].to_numpy(), "part": np.array([p[0] for p in places], "int32"), "bytes": sizes, "rows": groups["rows"].to_numpy()})

    return work


def shard_by_bytes(docs: DataFrame, shards: int = 16) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard: one row a document."""
    spark = docs.sparkSession
    text = text_or_empty()
    size = (F.coalesce(F.octet_length("text"), F.lit(0)) + 1).cast("long")
    rows = stage(with_row_tag(docs.select("doc_id", size.alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.unhex(F.sha2(text.cast("binary"), 256)).alias("digest"))), "sizes")
    groups = rows.groupBy("digest").agg(F.sum("size").alias("bytes"), F.count("*").alias("rows"))
    total, count = rows.count(), rows.select(F.approx_count_distinct("digest")).first()[0]
    tasks = int(min(MAX_TASKS, max(1, -(-count // GROUPS_PER_TASK))))
    dealt = groups.withColumn("task", F.pmod(F.xxhash64("digest"), F.lit(tasks)).cast("int"))
    parts = stage(dealt.groupBy("task").applyInPandas(_difference_task(shards), "digest binary, task int, part int, bytes long, rows long"), "parts")
    sums: dict[int, list[int]] = {}
    for r in parts.groupBy("task", "part").agg(F.sum("bytes").alias("bytes")).collect():  # tasks x shards rows at most
        sums.setdefault(r.task, [0] * shards)[r.part] = r.bytes
    names = sorted(sums)
    places = difference([sums[t] for t in names], shards)
    lookup = spark.createDataFrame([(t, p, s) for t, place in zip(names, places, strict=True) for p, s in enumerate(place)], "task int, part int, shard int")
    placed = parts.join(F.broadcast(lookup), ["task", "part"]).select("digest", "shard", "rows")
    rows = attach_groups(rows, placed, "digest", "rows", total)
    return _with_slots(rows).select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def _with_slots(rows: DataFrame) -> DataFrame:
    """Gapless numbers within each shard, without a shard ever being in one task: ranks within (shard, cell) plus the rows of earlier cells."""
    from pyspark.sql import Window as W

    cells = partitions_for(rows.sparkSession)
    rows = rows.withColumn("cell", F.pmod(F.xxhash64("row_tag"), F.lit(cells)).cast("int"))
    counts = rows.groupBy("shard", "cell").agg(F.count("*").alias("n"))
    before = W.partitionBy("shard").orderBy("cell").rowsBetween(W.unboundedPreceding, -1)
    starts = counts.select("shard", "cell", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("first"))  # shards x cells rows
    rank = F.row_number().over(W.partitionBy("shard", "cell").orderBy("doc_id", "row_tag"))
    return rows.withColumn("rank", rank).join(F.broadcast(starts), ["shard", "cell"]).withColumn("slot", (F.col("first") + F.col("rank") - 1).cast("long"))
