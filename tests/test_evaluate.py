"""The evaluator on DataFrames against run search in plain Python, and the registered queries against SQL."""

import glob
import os
import random

import duckdb
import pytest
import randoms

from pathlore import queries as registered
from pathlore import workload
from pathlore.operators import chase, consistency, statistics
from pathlore.operators.certain import certain_answers, plain_answers
from pathlore.operators.evaluate import Evaluator, answer, cycle_cut, parts_of
from pathlore.oracle import brute
from pathlore.plans.ontology import parse_ontology, shop
from pathlore.plans.query import bind_existentials, parse_query
from pathlore.plans.rewrite import RewriteOptions, rewrite
from pathlore.sources.graph import build_graph, graph_from_tables, strict_single_edge

DATA = "/root/testdata/sf0.001"


def frames(spark, g):
    nodes = spark.createDataFrame([(n, sorted(ls), g.props[n].get("p")) for n, ls in g.labels.items()], "node_id long, labels array<string>, p int")
    rows = [(next(iter(e.roles)).name, e.src, e.dst, e.props.get("k")) for e in g.edges]
    edges = spark.createDataFrame(rows, "role string, src long, dst long, k int")
    return graph_from_tables(nodes, edges, {x for ls in g.labels.values() for x in ls}, {r[0] for r in rows})


@pytest.mark.parametrize("seed", range(14))
def test_random_queries_on_frames(spark, seed):
    rng = random.Random(seed)
    onto, g = parse_ontology(randoms.ontology(rng, 6)), randoms.graph(rng, 5)
    q = rewrite(parse_query(randoms.query(rng)), onto, RewriteOptions(cap=2000)).query
    got = {tuple(r) for r in answer(q, frames(spark, g), decode=False).collect()}
    assert got == brute.brute_answers(q, g)


@pytest.mark.parametrize("text", ["ans(x,y) <- (r/s)*/t(x,y)", "ans(x) <- <(r|s/^t)*/:A>/r(x,y)", "ans(x,y) <- (r|^s)*(x,y)", "ans(x) <- (r/(s/^s)*)+(x,x)", "ans(x,y) <- :A/((r|s)*/t)*/[p>=1](x,y)"])
def test_cycles_on_frames(spark, text):
    rng = random.Random(len(text))
    g = randoms.graph(rng, 7)
    q = bind_existentials(parse_query(text))
    got = {tuple(r) for r in answer(q, frames(spark, g), decode=False).collect()}
    assert got == brute.brute_answers(q, g)


def test_pair_binding(spark):
    g = brute.TinyGraph.of({1: (set(), {}), 2: (set(), {})}, [("r", 1, 2, {"k": 1}), ("r", 1, 2, {"k": 9}), ("s", 1, 2)])
    f = frames(spark, g)
    ask = lambda text, how: answer(bind_existentials(parse_query(text)), f, binding=how, decode=False).count()
    assert ask("ans(x,y) <- {r,k>=5,k<=1}(x,y)", "edge") == 0 and ask("ans(x,y) <- {r,k>=5,k<=1}(x,y)", "pair") == 1
    assert ask("ans(x,y) <- {r,s}(x,y)", "edge") == 0 and ask("ans(x,y) <- {r,s}(x,y)", "pair") == 1


def test_missing_key_fails_every_test(spark):
    g = brute.TinyGraph.of({1: (set(), {"p": 1}), 2: (set(), {})}, [])
    assert [r[0] for r in answer(parse_query("ans(x) <- [p<>7](x)"), frames(spark, g), decode=False).collect()] == [1]


def test_empty_graph(spark):
    nodes = spark.createDataFrame([], "node_id long, labels array<string>, p int")
    edges = spark.createDataFrame([], "role string, src long, dst long, k int")
    g = graph_from_tables(nodes, edges, {"A"}, {"r"})
    assert answer(bind_existentials(parse_query("ans(x,y) <- r*/:A(x,y)")), g).count() == 0
    assert strict_single_edge(edges).count() == 0


def test_parts_and_cuts():
    moves = {(0, 1), (1, 2), (2, 1), (2, 3), (3, 3)}
    assert parts_of({0, 1, 2, 3}, moves) == [[0], [1, 2], [3]]
    assert cycle_cut([3], moves) == [3] and len(cycle_cut([1, 2], moves)) == 1


def test_chase_on_frames_equals_rewriting(spark):
    for seed in (3, 8, 21):
        rng = random.Random(seed)
        onto, g = parse_ontology(randoms.ontology(rng, 6)), randoms.graph(rng, 5)
        q, f = parse_query(randoms.query(rng)), frames(spark, g)
        plain = onto.without_existentials()
        a = {tuple(r) for r in certain_answers(q, f, plain, decode=False).collect()}
        b = {tuple(r) for r in plain_answers(q, chase.core_chase(f, plain), decode=False).collect()}
        assert a == b == brute.brute_answers(q, brute.bounded_chase(g, plain, 0))


def test_bounded_chase_on_frames(spark):
    onto = parse_ontology("concept A < exists r\nconcept exists ^r < B\nconcept B < exists s")
    g = brute.TinyGraph.of({1: ({"A"}, {}), 2: (set(), {})}, [])
    q = parse_query("ans(x) <- r/:B/s(x,y)")
    assert [r[0] for r in plain_answers(q, chase.bounded_chase(frames(spark, g), onto, 2), decode=False).collect()] == [1]
    assert plain_answers(q, chase.bounded_chase(frames(spark, g), onto, 1), decode=False).count() == 0


def test_violations(spark):
    onto = parse_ontology("disjoint concept A, B\ndisjoint role r, s\nconcept C < exists t\nconcept exists ^t < A\nconcept exists ^t < B")
    g = brute.TinyGraph.of({1: ({"A", "B"}, {}), 2: ({"C"}, {}), 3: (set(), {})}, [("r", 1, 2), ("s", 1, 2), ("r", 2, 3)])
    found = sorted((r.axiom, r.node, r.other) for r in consistency.violations(frames(spark, g), onto).collect())
    assert found == [("A disjoint B", 1, None), ("C is empty", 2, None), ("r disjoint s", 1, 2)]


def test_completeness_and_timeout(spark):
    a, b = spark.range(10), spark.range(5, 20)
    assert statistics.completeness(a, b) == (5 / 15, 0.5)
    assert statistics.timed_answer(lambda: spark.range(10), 60, spark)["answers"] == 10
    slow = statistics.timed_answer(lambda: spark.range(1 << 40).where("id % 1000003 = -1"), 0.5, spark)
    assert slow["timed_out"] and slow["answers"] is None


def test_no_cross_join_and_pruned_scans(spark):
    g = build_graph(spark, DATA, ("commerce",))
    q = rewrite(parse_query(workload.QUERIES["w4_local_supplier"]), shop()).query
    plan = answer(q, g)._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan
    assert "l_quantity" not in plan.split("== Physical Plan ==")[1]
    tested = certain_answers("ans(x,y) <- {hasItem,quantity>=50}(x,y)", g, shop())._jdf.queryExecution().toString()
    assert "GreaterThanOrEqual(l_quantity,50" in tested


def test_generated_queries_are_rewritten_and_answered(spark):
    onto = workload.shop_18()
    stats = list(workload.rewriting_stats(onto, workload.generate_queries(onto)))
    assert not any(s["infeasible"] for s in stats) and sorted(s["rewrite_ms"] for s in stats)[94] < 600
    assert len(onto.names()) == 53 and len(onto.role_names() | set(workload.DATA_ROLES)) == 18
    flat = workload.scaled_ontology()
    assert len(flat.names()) == 1230 and len(flat.role_names() | set(workload.DATA_ROLES)) == 1212 and not flat.generators()
    g = build_graph(spark, DATA, ("commerce",))
    for text in workload.generate_queries(onto, 4, seed=7, guided=True):
        assert certain_answers(text, g, onto).count() >= 0


def test_stats_of_an_evaluation(spark):
    g = build_graph(spark, DATA, ("activity",))
    q = rewrite(parse_query("ans(x,y) <- [turn=0]/(nextTurn/absent?)*(x,y)"), shop()).query
    ev = Evaluator(g, q.book)
    answer(q, g, evaluator=ev).count()
    assert ev.stats.rounds >= 7 and ev.stats.dead_moves >= 1


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for p in glob.glob(DATA + "/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}'")
    return con


ORACLES = registered.oracles()


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_registered_query_equals_sql(spark, duck, name):
    rows = registered.QUERIES[name](spark, DATA)
    found = duck.execute(ORACLES[name])
    names = [d[0] for d in found.description]
    assert sorted(rows.columns) == sorted(names)
    want = sorted(map(repr, ({n: v for n, v in sorted(zip(names, r, strict=True))} for r in found.fetchall())))
    assert sorted(repr(dict(sorted(r.asDict().items()))) for r in rows.collect()) == want


@pytest.mark.parametrize("name", sorted(set(registered.QUERIES) - set(ORACLES) - {"evaluate_generated", "evaluate_guided_flat", "evaluate_guided_shop", "evaluation_correlation"}))
def test_measures_have_rows(spark, name):
    assert registered.QUERIES[name](spark, DATA).count() > 0


def test_runtime_jumps_equal_the_rewriting(spark):
    from pathlore.operators.runtime_jumps import answer_with_runtime_jumps

    cases = [
        ("concept A < exists r\nconcept exists ^r < B\nrole s < t", "ans(x) <- t/r/:B(x,y)", [("s", 1, 2)], {1: (set(), {}), 2: ({"A"}, {})}),
        ("concept A < exists r\nconcept exists ^r < B\nconcept B < exists s\nrole ^r < q", "ans(x,y) <- r/s/^s/<^r>/q/t(x,y)", [("t", 2, 1)], {1: (set(), {}), 2: ({"A"}, {})}),
    ]
    for axioms, text, edges, nodes in cases:
        onto, g = parse_ontology(axioms), brute.TinyGraph.of(nodes, edges)
        q, f = parse_query(text), frames(spark, g)
        got = {tuple(r) for r in answer_with_runtime_jumps(q, f, onto, decode=False).collect()}
        assert got == brute.brute_answers(rewrite(q, onto).query, g) and got


def test_closure_frame_equals_driver(spark):
    from pathlore.operators.closure import direct_inclusions, saturate_concepts_df
    from pathlore.plans.ontology import saturate_concepts

    onto = shop()
    got = {(r.below, r.above) for r in saturate_concepts_df(direct_inclusions(spark, onto)).collect()}
    want = {(str(a.left), str(a.right)) for a in saturate_concepts(onto)}
    assert got == want
