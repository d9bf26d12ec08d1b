"""Starts that share what a hub reaches, pairs that are linked from both ends, guards that are laid out: the same answers."""

import random
import time
from pathlib import Path

import pytest
import randoms
from pyspark.sql import functions as F
from test_evaluate import frames

from pathlore import workload
from pathlore.operators import evaluate, staging
from pathlore.operators.evaluate import Evaluator, answer
from pathlore.oracle import brute
from pathlore.plans.query import bind_existentials, parse_query
from pathlore.queries import QUERIES
from pathlore.sources.graph import NodeKind, PropertyGraph


def with_ends(g):
    g.ends = {r: ("node", "node") for r in g.roles}
    return g


@pytest.mark.parametrize("seed", range(2))
@pytest.mark.parametrize("text", ["ans(x,y) <- (r/s)*/t(x,y)", "ans(x,y) <- (r|^s)*/(s|t)*(x,y)", "ans(x,y) <- :A/((r|s)*/t)*/[p>=1](x,y)", "ans(x,y) <- r/(r|s|t)+(x,y) & <t>(y,z)"])
def test_crowds_give_the_same_pairs(spark, monkeypatch, text, seed):
    monkeypatch.setattr(evaluate, "CROWD_ROWS", 1)
    monkeypatch.setattr(evaluate, "CROWD_PER_NODE", 0)
    monkeypatch.setattr(evaluate, "LAID_OUT_BYTES", -1 if seed == 0 else 1 << 30)
    g = randoms.graph(random.Random(seed), 9)
    f = with_ends(frames(spark, g))
    q = bind_existentials(parse_query(text))
    ev = Evaluator(f, q.book.copy())
    got = {tuple(r) for r in answer(q, f, decode=False, evaluator=ev).collect()}
    assert got == brute.brute_answers(q, g)
    assert ev.stats.crowds or not got


@pytest.mark.parametrize("seed", range(2))
@pytest.mark.parametrize("text", ["ans(x,y) <- r/s(x,y) & t/(r|^s)(y,x)", "ans(x,y) <- (r|s|t)(x,y) & (r/s)*/t?(x,y)", "ans(x,y) <- (r|s)(x,y) & :A?/r/^r/(s|t)*/^t(x,y)", "ans(x,y,z) <- r(x,y) & (s|t)(y,z) & (r|^s)+(x,z)"])
def test_linked_pairs(spark, text, seed):
    g = randoms.graph(random.Random(seed), 8)
    f = frames(spark, g)
    f.single = {"r": (True, False), "t": (False, True)} if seed else {}
    q = bind_existentials(parse_query(text))
    assert {tuple(r) for r in answer(q, f, decode=False).collect()} == brute.brute_answers(q, g)


def test_each_connected_part_has_its_crowd(spark, monkeypatch):
    """Copies of a graph that nothing joins: one hub could serve the starts of one copy only."""
    monkeypatch.setattr(evaluate, "CROWD_ROWS", 1)
    monkeypatch.setattr(evaluate, "CROWD_PER_NODE", 0)
    ring = [(100 * copy + i, 100 * copy + (i + 1) % 6) for copy in range(5) for i in range(6)]
    edges = spark.createDataFrame(ring, "src long, dst long")
    g = PropertyGraph(spark, {"node": NodeKind(edges.select(F.col("src").alias("node_id")), {})}, {"r": edges})
    q = bind_existentials(parse_query("ans(x,y) <- r*(x,y)"))
    members = []
    own = Evaluator._expand
    monkeypatch.setattr(Evaluator, "_expand", lambda self, rows, crowds: (members.extend(crowds), own(self, rows, crowds))[1])
    found = answer(q, with_ends(g), decode=False)
    assert sorted(map(tuple, found.collect())) == [(a, b) for a, _ in ring for b, _ in ring if a // 100 == b // 100]
    assert members[0].count() == 30 and members[0].select("crowd").distinct().count() >= 5


@pytest.mark.parametrize("seed", range(3))
@pytest.mark.parametrize("text", ["ans(x,y) <- (r/^r)*(x,y)", "ans(x,y) <- s/(^r/r)*/t?(x,y)", "ans(x,y) <- (r/^r)*/(^s/s)*/t(x,y)", "ans(x,y) <- :A?/(r/^r)*/(t|^s)*(x,y)"])
def test_steps_there_and_back_go_by_connected_parts(spark, monkeypatch, text, seed):
    """Pairs, and their number without writing crowds out; nodes may be at either end of a step, and starts come to several parts."""
    monkeypatch.setattr(evaluate, "PART_ROWS", 0)
    monkeypatch.setattr(evaluate, "CROWD_PER_NODE", 0)
    monkeypatch.setattr(evaluate, "ONE_TASK_EDGES", evaluate.ONE_TASK_EDGES if seed else -1)
    g = randoms.graph(random.Random(seed), 9)
    f = with_ends(frames(spark, g))
    q = bind_existentials(parse_query(text))
    ev = Evaluator(f, q.book.copy())
    want = brute.brute_answers(q, g)
    got = [tuple(r) for r in answer(q, f, decode=False, evaluator=ev).collect()]
    assert sorted(got) == sorted(want) and (ev.stats.crowds or not got)
    assert evaluate.count_answers(q, f) == len(want)


def test_answers_are_not_sorted_out_again(spark, monkeypatch):
    """Distinct pairs of one kind of nodes stay distinct as natural keys, so a product of crowds need not be shuffled."""
    monkeypatch.setattr(evaluate, "CROWD_ROWS", 1)
    monkeypatch.setattr(evaluate, "CROWD_PER_NODE", 0)
    g = randoms.graph(random.Random(0), 9)
    q = bind_existentials(parse_query("ans(x,y) <- (r/s)*/t(x,y) & <t|r>(y,z)"))
    rows = answer(q, with_ends(frames(spark, g)))
    assert "Aggregate" not in rows._jdf.queryExecution().optimizedPlan().nodeName()
    assert sorted(map(tuple, rows.collect())) == sorted(brute.brute_answers(q, g))


def test_kinds_that_share_keys_are_still_sorted_out(spark):
    a, b = 1 << 56, 2 << 56
    nodes = lambda *ids: NodeKind(spark.createDataFrame([(i,) for i in ids], "node_id long"), {})
    g = PropertyGraph(spark, {"one": nodes(a + 1), "two": nodes(b + 1)}, {"r": spark.createDataFrame([(a + 1, a + 1)], "src long, dst long"), "s": spark.createDataFrame([(a + 1, b + 1)], "src long, dst long")})
    g.ends = {"r": ("one", "one"), "s": ("one", "two")}
    assert [tuple(r) for r in answer(bind_existentials(parse_query("ans(x,y) <- (r|s)(x,y)")), g).collect()] == [(1, 1)]


def test_shuffles_that_nothing_reads_are_given_back(spark, monkeypatch):
    env = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    files = lambda: {f for d in env.localDirsString() for f in Path(d).rglob("shuffle_*.data")}
    monkeypatch.setattr(staging, "SHUFFLED_BYTES", 1 << 60)
    before = files()
    staging.stage(spark.range(50_000).groupBy((F.col("id") % 999).alias("k")).count(), "counts")
    mine = files() - before
    assert mine and not staging.free_shuffles(spark)
    monkeypatch.setattr(staging, "SHUFFLED_BYTES", 1)
    for _ in range(40):
        staging.stage(spark.range(100).groupBy((F.col("id") % 9).alias("k")).count(), "counts")
        if not mine & files():
            break
        time.sleep(0.25)
    assert not mine & files()


def test_guards_turned_round_are_laid_out_once(spark, monkeypatch):
    monkeypatch.setattr(evaluate, "LAID_OUT_BYTES", -1)
    turned = evaluate.LaidBack({(0, 1): evaluate.Guard(spark.createDataFrame([(1, 2), (3, 2)], "src long, dst long"))})
    rows = turned[0, 1].pairs
    assert rows is turned[0, 1].pairs and sorted(map(tuple, rows.select("src", "dst").collect())) == [(2, 1), (2, 3)]
    turned.release()
    assert not spark.catalog.tableExists(rows._laid_table)


def test_gain_counts_give_back_what_each_query_staged(spark, monkeypatch, tmp_path):
    monkeypatch.setattr(workload, "QUERIES", {n: workload.QUERIES[n] for n in ("w4_local_supplier", "v1_licensed")})
    monkeypatch.setattr(staging, "shared_root", lambda _: f"file://{tmp_path}")
    rows = QUERIES["plain_vs_rewritten_gain"](spark, "/root/testdata/sf0.001")
    assert rows.dtypes == [("query", "string"), ("plain", "bigint"), ("certain", "bigint")]
    assert not list(tmp_path.iterdir())
    assert {r.query for r in rows.collect() if r.plain == 0 and r.certain > 0} == {"w4_local_supplier", "v1_licensed"}
