"""The generated evaluation runs all its queries, stars among them, over both ontologies."""

from collections import Counter

import pytest
from pyspark.sql import functions as F

from pathlore import experiments, queries, workload
from pathlore.oracle import tables

DATA = "/root/testdata/sf0.001"


@pytest.mark.parametrize("onto", [workload.scaled_ontology(), workload.shop_18()], ids=["flat", "shop"])
def test_guided_queries_have_stars(onto):
    texts = workload.generate_queries(onto, guided=True)
    assert len(texts) == 100 and sum(")*" in t for t in texts) >= 20


@pytest.mark.parametrize("onto", [workload.scaled_ontology(), workload.shop_18()], ids=["flat", "shop"])
def test_free_queries_are_as_large_as_the_references(onto):
    sizes = [s["states_in"] for s in workload.rewriting_stats(onto, workload.generate_queries(onto))]
    assert 55 <= sum(n >= experiments.MANY_STATES for n in sizes) <= 70


def test_evaluation_takes_every_query(spark, monkeypatch):
    monkeypatch.setattr(experiments.statistics, "timed_answer", lambda work, timeout_s, spark: {"eval_ms": 1.0, "timed_out": False, "answers": 0})
    monkeypatch.setattr(experiments, "_EVALUATED", {})
    for name, kinds in (("evaluate_generated", experiments.FREE), ("evaluate_guided_flat", experiments.GUIDED[:1]), ("evaluate_guided_shop", experiments.GUIDED[1:])):
        rows = queries.QUERIES[name](spark, "/root/testdata/sf0.001").collect()
        assert Counter((r.ontology, r.guided) for r in rows) == dict.fromkeys(kinds, 100) and any(r.star for r in rows)
    summary = queries.QUERIES["evaluation_correlation"](spark, "/root/testdata/sf0.001").collect()
    assert len(summary) == 2 and all(r.queries == 100 and r.timeouts == 0 for r in summary)


def test_evaluation_of_a_few(spark, monkeypatch):
    """For real: free queries have no answers, guided ones may."""
    monkeypatch.setattr(experiments, "_EVALUATED", {})
    rows = experiments.evaluated(spark, "/root/testdata/sf0.001", experiments.FREE + experiments.GUIDED, 3)
    assert len(rows) == 12 and all(r[9] == 0 for r in rows if not r[1] and not r[8]) and any(r[9] for r in rows if r[1])


def test_ways_of_finding_jumps_agree():
    found = {(r[0], r[1]): r for r in experiments.baseline_costs()}
    for name in workload.QUERIES:
        feasible = {found[name, way][3] for way in experiments.WAYS if not found[name, way][4]}
        assert len(feasible) == 1 and not found[name, "saturate"][4]


def test_infeasible_queries_by_way():
    found = {(o, way): n for o, way, _, _, n in experiments.infeasible_by_way()}
    for o in ("flat", "shop"):
        assert found[o, "saturate"] == 0 and 55 <= found[o, "power set"] <= 70
    assert found["shop", "relevant"] > 50


def test_timeouts_give_back_what_they_staged(spark):
    import glob

    from pathlore.operators.staging import stage
    from pathlore.operators.statistics import timed_answer

    before = set(glob.glob("/tmp/checkpoints/pathlore/*"))
    assert timed_answer(lambda: stage(spark.range(10), "mine"), 60, spark)["answers"] == 10
    slow = timed_answer(lambda: stage(spark.range(1 << 40).where("id % 1000003 = -1"), "slow"), 0.5, spark)
    assert slow["timed_out"] and set(glob.glob("/tmp/checkpoints/pathlore/*")) <= before


def test_sizes_of_generated_queries_over_the_names_in_the_tables(spark):
    """States and moves by a way of their own; the names are the tables'."""
    names = tuple(workload.table_names(spark, DATA))
    assert {("FURNITURE", "Customer"), ("Event_view", "Event")} <= set(names)
    got = [tuple(r) for r in queries.QUERIES["generated_input_sizes"](spark, DATA).collect()]
    assert got == tables.input_sizes(experiments.ontologies(names)) != tables.input_sizes(experiments.ontologies())


def test_ontologies_grow_with_the_tables(spark, tmp_path):
    """A segment that only the given table names is a concept, and is counted."""
    for name in sorted({t for t, *_ in workload.VALUE_NAMES}):
        rows = spark.read.parquet(f"{DATA}/{name}.parquet")
        (rows.withColumn("c_mktsegment", F.lit("deep sea")) if name == "customer" else rows).write.parquet(f"{tmp_path}/{name}.parquet")
    assert ("deep_sea", "Customer") in workload.table_names(spark, str(tmp_path))
    count = lambda folder: {r.ontology: r.concepts for r in queries.QUERIES["ontology_stats"](spark, folder).collect()}["flat"]
    assert count(DATA) - count(str(tmp_path)) == len({n for n, above in workload.table_names(spark, DATA) if above == "Customer"}) - 1


def test_path_moves_of_every_user(spark):
    rows = queries.QUERIES["path_moves"](spark, DATA).collect()
    users = {r.user_id for r in spark.read.parquet(f"{DATA}/events.parquet").select("user_id").collect()}
    assert Counter(r.user_id for r in rows) == dict.fromkeys(users, 8)
