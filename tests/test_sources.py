"""Ontology files, graph files, and queries rendered as SQL."""

import random

import duckdb
import pytest
import randoms

from pathlore import workload
from pathlore.operators.certain import certain_answers
from pathlore.oracle import brute
from pathlore.plans.ontology import parse_ontology, shop
from pathlore.plans.query import parse_query
from pathlore.plans.render import UnboundedQuery, longest_run, to_pattern, to_sql
from pathlore.plans.rewrite import RewriteOptions, rewrite
from pathlore.plans.terms import DataTest, Role
from pathlore.sources import owl, sinks
from pathlore.sources.graph import build_graph

OWL = """
Prefix(:=<http://example.org/social#>)
Ontology(<http://example.org/social>
  Declaration(Class(:Coder))
  SubClassOf(:Coder :Worker)
  SubClassOf(DataSomeValuesFrom(:age DatatypeRestriction(xsd:integer xsd:minInclusive "18"^^xsd:integer xsd:maxInclusive "30"^^xsd:integer)) :Young)
  SubClassOf(:Firm ObjectSomeValuesFrom(:hires :Coder))
  SubClassOf(:Worker ObjectComplementOf(:Idle))
  SymmetricObjectProperty(:knows)
  InverseObjectProperties(:hires :hiredBy)
  ObjectPropertyDomain(:hires :Firm)
  ObjectPropertyRange(:hires :Worker)
  SubObjectPropertyOf(ObjectInverseOf(:leads) :follows)
  DisjointClasses(:Firm :Worker)
)"""


def test_owl_subset():
    onto = owl.load_owl_functional(OWL)
    want = parse_ontology(
        """concept Coder < Worker
           concept {age>=18,age<=30} < Young
           concept Firm < exists hires.Coder
           role knows < ^knows
           role hires < ^hiredBy
           role ^hiredBy < hires
           concept exists hires < Firm
           concept exists ^hires < Worker
           role ^leads < follows"""
    )
    strip = lambda o: {(str(a.left), str(a.right)) for a in [*o.concepts, *o.roles] if not a.negative and "hires_" not in str(a)}
    assert strip(onto) == strip(want) and sum(a.negative for a in onto.concepts) == 2
    g = brute.TinyGraph.of({1: ({"Firm"}, {}), 2: (set(), {"age": 20})}, [("leads", 1, 2)])
    ask = lambda t: brute.brute_answers(rewrite(parse_query(t), onto).query, g)
    assert ask("ans(x) <- hires/:Worker/hiredBy(x,y)") == {(1,)} and ask("ans(x) <- :Young(x)") == {(2,)} and ask("ans(x,y) <- follows(x,y)") == {(2, 1)}
    assert DataTest("age", ">=", 18) in next(iter(a.left.tests for a in onto.concepts if hasattr(a.left, "tests")))
    for bad in ("SubClassOf(:A DataHasValue(:p \"1\"^^xsd:integer))", "TransitiveObjectProperty(:r)"):
        with pytest.raises(owl.UnsupportedAxiom):
            owl.load_owl_functional(bad)


def test_owl_from_a_file(spark, tmp_path):
    (tmp_path / "o.ofn").write_text(OWL)
    assert owl.read_owl(spark, str(tmp_path / "o.ofn")).role_supers(Role("hires")) >= {Role("hires"), Role("hiredBy", True)}


def test_rendered_sql_equals_run_search():
    done = 0
    for seed in range(120):
        rng = random.Random(seed)
        onto, g = parse_ontology(randoms.ontology(rng, 5)), randoms.graph(rng, 3)
        q = rewrite(parse_query(randoms.query(rng)), onto, RewriteOptions(cap=1000)).query
        if q.book.size(*[n for n, _, _ in q.atoms])[1] > 60:
            continue
        con = duckdb.connect()
        con.execute("CREATE TABLE nodes (node_id BIGINT, labels VARCHAR[], p INT)")
        con.execute("CREATE TABLE edges (role VARCHAR, src BIGINT, dst BIGINT, k INT, p INT)")
        con.execute("CREATE MACRO array_contains(l, x) AS list_contains(l, x)")
        for n, ls in g.labels.items():
            con.execute("INSERT INTO nodes VALUES (?, ?, ?)", [n, sorted(ls), g.props[n].get("p")])
        for e in g.edges:
            con.execute("INSERT INTO edges VALUES (?, ?, ?, ?, NULL)", [next(iter(e.roles)).name, e.src, e.dst, e.props.get("k")])
        assert set(con.execute(to_sql(q, distinct=True)).fetchall()) == brute.brute_answers(q, g), seed
        done += any(longest_run(q.book, n) is None for n in q.book.reachable(*(n for n, _, _ in q.atoms)))
    assert done > 10


def test_rendered_sql_runs_on_spark(spark):
    spark.createDataFrame([(1, ["A"]), (2, []), (3, ["B"])], "node_id long, labels array<string>").createOrReplaceTempView("nodes")
    spark.createDataFrame([("r", 1, 2), ("s", 3, 2)], "role string, src long, dst long").createOrReplaceTempView("edges")
    q = rewrite(parse_query("ans(x,y) <- :A/r/^t/:B(x,y)"), parse_ontology("role s < t")).query
    assert [tuple(r) for r in spark.sql(to_sql(q)).collect()] == [(1, 3)]
    spark.createDataFrame([("r", i, i + 1) for i in range(20)], "role string, src long, dst long").createOrReplaceTempView("edges")
    spark.createDataFrame([(i, []) for i in range(21)], "node_id long, labels array<string>").createOrReplaceTempView("nodes")
    star = rewrite(parse_query("ans(x,y) <- (r/r)*(x,y)"), parse_ontology("role s < t")).query
    assert {tuple(r) for r in spark.sql(to_sql(star, acyclic_data=True)).collect()} == {(i, j) for i in range(21) for j in range(i, 21, 2)}
    with pytest.raises(UnboundedQuery):
        to_sql(star)
    assert "automaton 0" in to_pattern(q) and "^s" in to_pattern(q)


def test_graph_files(spark, tmp_path):
    g = build_graph(spark, "/root/testdata/sf0.001", ("commerce",))
    sinks.write_graph(g, str(tmp_path / "g"))
    back = sinks.read_graph(spark, str(tmp_path / "g"), list(g.roles), {k: list(v.labels) for k, v in g.kinds.items()})
    for name in ("w4_local_supplier", "v1_licensed"):
        a, b = (certain_answers(workload.QUERIES[name], x, shop()) for x in (g, back))
        assert {tuple(r) for r in a.collect()} == {tuple(r) for r in b.collect()}
    tables = sinks.write_bucketed_edges(g, "edges", 4)
    assert spark.table(tables["placed"]).count() == g.roles["placed"].count()


def test_open_properties(spark, tmp_path):
    (tmp_path / "p.csv").write_text("node_id,colour,size\n1,red,\n2,,5\n")
    (tmp_path / "p.json").write_text('{"node_id": 1, "colour": "red"}\n{"node_id": 2, "size": "5"}\n')
    for kind in ("csv", "json"):
        got = {r.node_id: r.props for r in sinks.import_properties(spark, str(tmp_path / f"p.{kind}"), kind).collect()}
        assert got == {1: {"colour": "red"}, 2: {"size": "5"}}
