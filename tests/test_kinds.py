"""Moves that the kinds of nodes rule out are left out before planning, and nothing else is."""

import random

import pytest
import randoms

from pathlore import workload
from pathlore.operators.certain import certain_answers
from pathlore.operators.evaluate import Evaluator, answer
from pathlore.oracle import brute
from pathlore.plans.ontology import shop
from pathlore.plans.query import bind_existentials, parse_query
from pathlore.plans.rewrite import rewrite
from pathlore.sources.graph import NodeKind, PropertyGraph, build_graph

DATA = "/root/testdata/sf0.001"


def test_impossible_queries_are_empty_without_a_job(spark):
    g = build_graph(spark, DATA)
    for text in ("ans(x,y) <- :Customer/hasItem(x,y)", "ans(x,y) <- :Part/(placed/hasItem)*/inRegion(x,y)", "ans(x) <- <performed/:Turn>(x,x)"):
        q = bind_existentials(parse_query(text))
        ev = Evaluator(g, q.book.copy())
        assert not ev.guards(q.atoms[0][0]) or not ev._useful(q.atoms[0][0])
        assert answer(q, g, evaluator=ev).count() == 0


def test_union_keeps_the_roles_of_the_kind(spark):
    g = build_graph(spark, DATA, ("commerce",))
    plan = certain_answers("ans(x,y) <- :Customer/locatedIn(x,y)", g, shop())._jdf.queryExecution().optimizedPlan().toString()
    assert "c_nationkey" in plan and "s_nationkey" not in plan and "n_regionkey" not in plan


@pytest.mark.parametrize("seed", range(4))
def test_typed_graphs_give_the_same(spark, seed):
    """Three kinds of nodes, roles between two of them each."""
    rng = random.Random(seed)
    kinds = {"a": [0, 1, 2], "b": [10, 11, 12], "c": [20, 21]}
    ends = {"r": ("a", "b"), "s": ("b", "c"), "t": ("a", "a")}
    edges = [(r, rng.choice(kinds[x]), rng.choice(kinds[y])) for r, (x, y) in ends.items() for _ in range(4)]
    labels = {"a": "A", "b": "B", "c": "C"}
    tiny = brute.TinyGraph.of({n: ({labels[k]}, {}) for k, ns in kinds.items() for n in ns}, edges)
    g = PropertyGraph(spark, {k: NodeKind(spark.createDataFrame([(n,) for n in ns], "node_id long"), {labels[k]: None}) for k, ns in kinds.items()})
    g.roles = {r: spark.createDataFrame([e[1:] for e in edges if e[0] == r], "src long, dst long") for r in ends}
    g.ends = ends
    for text in ("ans(x,y) <- (r|t|s)*(x,y)", "ans(x,y) <- :A/(t/r|s)*/^s?(x,y)", "ans(x) <- <(r|t)/(s|r)>/(t|s)/:A(x,y)", "ans(x,y) <- (t|r)/<s|^t>/(s|^r)(x,y) & :C(y)"):
        q = bind_existentials(parse_query(text))
        assert {tuple(r) for r in answer(q, g, decode=False).collect()} == brute.brute_answers(q, tiny), text


def test_free_queries_are_mostly_ruled_out(spark):
    g, onto = build_graph(spark, DATA), workload.shop_18()
    empty = 0
    for text in workload.generate_queries(onto, 100):
        q = rewrite(parse_query(text), onto).query
        ev = Evaluator(g, q.book.copy())
        empty += any(not ev._useful(n) for n, x, y in q.atoms)
    assert empty > 50 and randoms
