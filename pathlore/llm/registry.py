"""The thin queries of the operators over the given tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathlore.llm import bpe, exact_dedup, license_scan, packing, quality, sharding, simhash, suffix_dedup, token_rollup, toxicity


#: What the changes of op7_token_rollup go by: fewest characters of a document that stays, and the signs that revisions take out.
SHORT, SIGNS = 60, "#*$%&|<>"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = exact_dedup.fresh_index(spark).deduplicate(table(spark, sf_dir, "documents"), "documents")
    return found.select("doc_id", "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256"))


def op2_line_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.assess(table(spark, sf_dir, "documents"))


def op3_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.report(table(spark, sf_dir, "documents"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = toxicity.train_and_score(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return scored.select("doc_id", "held_out", "score", (F.col("score") >= 0.7).cast("int").alias("predicted"), "evidence")


def op5_hilbert_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


def op6_differencing_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard_by_bytes(table(spark, sf_dir, "documents"), 16)


def curation(docs: DataFrame) -> DataFrame:
    """Signed changes: documents of fewer than SHORT characters go, those with signs that are no prose are revised without these."""
    change = lambda sign, text: F.struct(F.lit(sign).alias("sign"), text.alias("text"))
    text = F.col("text")
    old, new = change(-1, text), change(1, F.translate(text, SIGNS, ""))
    rows = docs.where((F.length(text) < SHORT) | text.rlike(f"[{SIGNS}]"))
    changes = F.when(F.length(text) < SHORT, F.array(old)).otherwise(F.array(old, new))
    return rows.select("source", "lang", F.explode(changes).alias("change")).select("source", "lang", "change.text", "change.sign")


def op7_token_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two batches, each committed twice (the second time adds nothing): all documents come, then deletes and revisions.

    The totals as of both versions: 0 after the documents came, 1 after the changes.
    """
    docs = table(spark, sf_dir, "documents")
    counters = {"byte_bpe_50k/1": token_rollup.count_bpe(public_tokenizers.path("byte_bpe_50k.json")), "words/1": token_rollup.count_words}
    rollup = token_rollup.fresh_rollup(spark)
    for _ in range(2):
        rollup.commit("documents", docs, counters)
        rollup.commit("curation", curation(docs), counters)
    zero, one = (rollup.totals(v).withColumn("version", F.lit(v)) for v in rollup.versions())
    return zero.unionByName(one)


def op8_speculative_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_digests(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op9_simhash_vp_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents")).select("doc_id", "fingerprint", "component_id")


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan_licenses(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_exact_dedup, op2_line_quality, op3_suffix_dedup, op4_toxicity, op5_hilbert_packing, op6_differencing_shards, op7_token_rollup, op8_speculative_bpe, op9_simhash_vp_tree, op10_license_scan)}

ORACLES: dict[str, str] = {
    "op1_exact_dedup": """
        WITH d AS (
            SELECT doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS h
            FROM documents)
        SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
               doc_id = max(doc_id) OVER w AS kept, h AS text_sha256
        FROM d WINDOW w AS (PARTITION BY h)""",
}
