"""A small social network with companies, jobs and places: implied concepts, symmetric friendship, and four queries of different shapes."""

import pytest
from test_evaluate import frames

from pathlore.operators.certain import certain_answers, certain_answers_of_parts, plain_answers
from pathlore.operators.consistency import violations
from pathlore.operators.evaluate import answer, has_answer
from pathlore.oracle import brute
from pathlore.plans.ontology import parse_ontology
from pathlore.plans.query import UnsupportedQuery, bind_existentials, parse_query
from pathlore.plans.rewrite import RewriteOptions, rewrite
from pathlore.sources.graph import graph_from_tables, signature

ONTOLOGY = """
concept {born>=1997,born<=2012} < Young
concept exists ^hired < Employed
concept {seen>=20250101} < Fresh
disjoint concept Employed, Jobless
concept Town < Country
concept exists posted < Hiring
concept SoftwareFirm < exists hired.Coder
role knows < ^knows
"""
NODES = {
    1: ({"Person"}, {"born": 1990}), 2: ({"Person"}, {"born": 1999}), 3: ({"Person"}, {"born": 2005}), 4: ({"Person", "Jobless"}, {"born": 1980}),
    10: ({"SoftwareFirm", "Company"}, {"founded": 2001, "revenue": 500_000}), 11: ({"Company"}, {"founded": 1999, "revenue": 90_000}), 12: ({"Company"}, {"founded": 2000, "revenue": 200_000}),
    20: ({"Job"}, {"seen": 20250301}), 30: ({"Town"}, {}), 31: ({"Sea"}, {}),
}
EDGES = [
    ("hired", 10, 1, {"since": 2020}), ("hired", 11, 2, {"since": 2024}), ("knows", 1, 2), ("knows", 3, 2), ("viewed", 2, 20, {"time": 20240501}), ("posted", 10, 20), ("locatedIn", 10, 30),
    ("locatedIn", 11, 31), ("locatedIn", 12, 30), ("owns", 12, 10, {"since": 2021}), ("owns", 10, 11, {"since": 2022}), ("owns", 11, 12, {"since": 2010}), ("viewed", 3, 20, {"time": 20230101}),
]
QUERIES = {
    "firms of friends": ("ans(x,y) <- knows*/^hired(x,y) & <locatedIn/:Country>/:Hiring/:SoftwareFirm(y,z)", {(1, 10), (2, 10), (3, 10)}),
    "young friends of long employed": ("ans(x,y) <- {hired,since<=2023}/knows*/[born>=1996](x,y) & <{viewed,time>=20240101}>/knows(z,y)", {(10, 3)}),
    "owned firms": ("ans(x,y) <- [founded<=2003]/[revenue>=100000]/({owns,since>=2020}/<locatedIn/:Country>)*(x,y)", {(10, 10), (12, 12), (12, 10)}),
    "employer of a friend with a job": ("ans(x,y) <- :Company/hired/knows/:Young(x,y) & viewed/:Job/^posted(y,x)", {(10, 2)}),
    "coders somewhere": ("ans(x) <- hired/:Coder(x,y)", {(10,)}),
    "young ones": ("ans(x) <- :Young(x)", {(2,), (3,)}),
}


@pytest.fixture(scope="module")
def network(spark):
    keys = sorted({k for _, p in NODES.values() for k in p})
    nodes = spark.createDataFrame([(n, sorted(ls), *(p.get(k) for k in keys)) for n, (ls, p) in NODES.items()], "node_id long, labels array<string>, " + ", ".join(f"{k} long" for k in keys))
    edges = spark.createDataFrame([(e[0], e[1], e[2], (e[3] if len(e) > 3 else {}).get("since"), (e[3] if len(e) > 3 else {}).get("time")) for e in EDGES], "role string, src long, dst long, since long, time long")
    return graph_from_tables(nodes, edges, {x for ls, _ in NODES.values() for x in ls}, {e[0] for e in EDGES})


@pytest.mark.parametrize("name", QUERIES)
def test_answers_of_the_network(spark, network, name):
    text, want = QUERIES[name]
    onto, tiny = parse_ontology(ONTOLOGY), brute.TinyGraph.of(NODES, EDGES)
    chased = brute.bounded_chase(tiny, onto, 2)
    by_chase = brute.brute_answers(parse_query(text), chased, set(NODES)) if " & " not in text and "(x)" not in text else None
    got = {tuple(r) for r in certain_answers(text, network, onto, decode=False).collect()}
    assert got == want == brute.brute_answers(rewrite(parse_query(text), onto).query, tiny)
    assert by_chase is None or by_chase == want
    assert {tuple(r) for r in plain_answers(text, network, decode=False).collect()} <= want


def test_network_is_consistent_until_someone_is_hired(spark, network):
    onto = parse_ontology(ONTOLOGY)
    assert violations(network, onto).count() == 0
    onto.concepts += parse_ontology("disjoint concept Young, Employed").concepts
    assert [r.node for r in violations(network, onto).collect()] == [2]


def test_names_of_the_ontology_and_of_the_data(network):
    names = signature(parse_ontology(ONTOLOGY), network)
    assert {"Coder", "Young"} <= names["extended_concepts"] - names["reduced_concepts"] and "owns" in names["reduced_roles"] and names["reduced_roles"] <= names["extended_roles"]


def test_limits_existence_and_parts(spark, network):
    onto = parse_ontology(ONTOLOGY)
    q = rewrite(parse_query("ans(x,y) <- knows*(x,y)"), onto).query
    assert answer(q, network, decode=False, limit=2).count() == 2 and has_answer(q, network)
    assert not has_answer(bind_existentials(parse_query("ans(x,y) <- owns/knows(x,y)")), network)
    text = "ans(x,y) <- :Young(x) & :Town(y)"
    with pytest.raises(UnsupportedQuery):
        certain_answers_of_parts(text, network, onto)
    assert {tuple(r) for r in certain_answers_of_parts(text, network, onto, allow_product=True, decode=False).collect()} == {(2, 30), (3, 30)}


@pytest.mark.parametrize("seed", range(40))
def test_passes_until_nothing_is_new_add_no_answers(seed):
    import random

    import randoms

    rng = random.Random(seed)
    onto, g, q = parse_ontology(randoms.ontology(rng, 6)), randoms.graph(rng, 5), parse_query(randoms.query(rng))
    once, loop = (rewrite(q, onto, RewriteOptions(cap=2000, order=order)) for order in ("once", "loop"))
    assert brute.brute_answers(once.query, g) == brute.brute_answers(loop.query, g)
    assert loop.stats.transitions_out >= once.stats.transitions_out


@pytest.mark.parametrize("seed", range(3))
def test_packed_states_and_signatures_give_the_same(spark, seed):
    import random

    import randoms

    from pathlore.operators.evaluate import Evaluator
    from pathlore.operators.statistics import node_signature

    rng = random.Random(100 + seed)
    onto, g = parse_ontology(randoms.ontology(rng, 6)), randoms.graph(rng, 6)
    f = frames(spark, g)
    for text in ("ans(x,y) <- (r|^s)*/(s|t)*(x,y)", "ans(x) <- <r>/<(r|s|^t)*/<s>>(x,y)", "ans(x,y) <- :A?/(r/<t>|s)*(x,y)"):
        q = rewrite(parse_query(text), onto, RewriteOptions(cap=2000)).query
        got = answer(q, f, decode=False, evaluator=Evaluator(f, q.book.copy(), packed=True, signature=node_signature(f)))
        assert {tuple(r) for r in got.collect()} == brute.brute_answers(q, g)
