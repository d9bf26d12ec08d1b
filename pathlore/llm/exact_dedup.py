"""Exact deduplication against a persistent digest index, with DataFrame operators only.

The index is a table bucketed and sorted by digest. New data are digested, reduced to one row a digest
(partial aggregation first, so a text with very many copies is no hot spot), anti-joined with the index by
sort-merge, and what is new is appended. A later batch sees what earlier batches hold.

Texts are equal when identical after lower-casing A-Z; a null text counts as empty. Of equal texts in a batch
the row with the largest doc_id stays; null ids lose to any other, and of rows that share that id the one whose
columns hash largest stays, which does not depend on how the batch is partitioned (of wholly equal rows, any one). A text that an
earlier batch brought drops all rows of the batch. ``group_size`` counts the rows of the batch. An empty table gives an
empty result; other columns are ignored.

A batch id stands for fixed rows. The batch may run again, whole or after a broken append, under any partitioning: digests that
are there stay, missing ones are added, and the result is the same. One writer at a time.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pathlore.llm.common import attach_groups, partitions_for, stage, stage_bucketed, text_or_empty, with_row_tag

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def digest(text: str = "text") -> Column:
    """SHA-256 of the text with A-Z lower-cased, as 32 bytes."""
    return F.unhex(F.sha2(F.translate(text_or_empty(text), UPPER, LOWER).cast("binary"), 256))


class DigestIndex:
    """A bucketed, sorted Parquet table (digest, keep_id, batch_id).

    With ``path`` the files outlive the session and ``DigestIndex`` opens them again; otherwise the table lies in
    the warehouse.
    """

    def __init__(self, spark: SparkSession, name: str, buckets: int = 0, path: str | None = None):
        self.spark, self.name = spark, name
        self.buckets = buckets or partitions_for(spark)
        at = f"LOCATION '{path}'" if path else ""
        spark.sql(
            f"CREATE TABLE IF NOT EXISTS {name} (digest BINARY, keep_id BIGINT, batch_id STRING) "
            f"USING parquet CLUSTERED BY (digest) SORTED BY (digest) INTO {self.buckets} BUCKETS {at}"
        )

    def table(self) -> DataFrame:
        return self.spark.table(self.name)

    def append(self, groups: DataFrame) -> None:
        """Add the groups whose digest is new: a sort-merge anti-join on the bucketed key, then an append."""
        known = self.table().select("digest").hint("merge")
        fresh = groups.join(known, "digest", "left_anti").select("digest", "keep_id", "batch_id")
        fresh.write.mode("append").format("parquet").bucketBy(self.buckets, "digest").sortBy("digest").saveAsTable(self.name)

    def deduplicate(self, docs: DataFrame, batch_id: str, whole_rows: bool = False) -> DataFrame:
        """One row a document: doc_id, keep_id, group_size, kept, digest, and the whole row as ``row`` if asked for."""
        carry = ["row"] if whole_rows else []
        rows = docs.select("doc_id", digest().alias("digest"), row_hash(docs).alias("row_hash"), *([F.struct(*docs.columns).alias("row")] if whole_rows else []))
        rows = stage(with_row_tag(rows), "digests")
        best = F.max(F.struct("doc_id", "row_hash", "row_tag")).alias("best")
        groups = rows.groupBy("digest").agg(best, F.count("*").alias("group_size"))
        groups = groups.select("digest", F.col("best.doc_id").alias("keep_id"), F.col("best.row_tag").alias("keep_tag"), "group_size", F.lit(batch_id).alias("batch_id"))
        groups = stage_bucketed(groups, "digest_groups", "digest", self.buckets)
        self.append(groups)
        # Only the batch's own groups meet the index, both bucketed by digest; so heavy groups are those of the batch.
        index = self.table().select("digest", F.col("keep_id").alias("index_id"), F.col("batch_id").alias("index_batch"))
        own = groups.join(index.hint("merge"), "digest")
        own = own.select("digest", F.col("index_id").alias("keep_id"), "group_size", F.when(F.col("index_batch") == batch_id, F.col("keep_tag")).alias("keep_tag"))
        own = stage_bucketed(own, "digest_known", "digest", self.buckets)
        out = attach_groups(rows, own, "digest", "group_size", rows.count())
        kept = F.coalesce(F.col("row_tag") == F.col("keep_tag"), F.lit(False))
        return out.select("doc_id", "keep_id", "group_size", kept.alias("kept"), "digest", "row_tag", *carry)


def row_hash(docs: DataFrame) -> Column:
    """A hash of all columns (maps, which have no hash, as JSON)."""
    return F.xxhash64(*(F.to_json(c.name) if "map<" in c.dataType.simpleString() else F.col(c.name) for c in docs.schema.fields))


def keep_first_of_equal(docs: DataFrame) -> DataFrame:
    """The documents that stay, all columns unchanged, against an index of their own."""
    found = fresh_index(docs.sparkSession).deduplicate(docs, "documents", whole_rows=True)
    return found.where("kept").select("row.*")


def fresh_index(spark: SparkSession) -> DigestIndex:
    return DigestIndex(spark, f"digest_index_{uuid.uuid4().hex}")
