"""Packing takes one Python worker a task, and none beside the tasks' own."""

import public_tokenizers
import pytest
from pyspark.sql import functions as F

from pathlore.llm import packing

pytestmark = pytest.mark.filterwarnings("ignore")


def test_the_place_of_a_row_is_found_once(spark):
    docs = spark.range(300).select(F.col("id").alias("doc_id"), F.concat(F.lit("some words about "), F.col("id").cast("string")).alias("text"))
    packed = packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"), ranges=4)
    plan = packed._jdf.queryExecution().executedPlan().toString()
    assert plan.count("ArrowEvalPython") == 1
    assert "ExistingRDD" not in plan and "Join" not in plan
    pieces = packed.collect()
    assert sum(p.length for p in pieces) == sum({p.doc_id: p.doc_tokens for p in pieces}.values())
    at = sorted((p.sequence_id * 2048 + p.offset, p.length) for p in pieces)
    assert all(a + n == b for (a, n), (b, _) in zip(at, at[1:], strict=False)) and at[0][0] == 0


def test_a_tokenizer_is_forgotten_with_its_memory(monkeypatch):
    given = []
    monkeypatch.setattr(packing, "give_back", lambda: given.append(1))
    packing.tokenizer(public_tokenizers.path("word_bpe_49k.json"))
    packing.forget_tokenizers()
    packing.forget_tokenizers()
    assert not packing._LOADED and given == [1]
