"""Materialisation of implied facts among named nodes, and a bounded chase that adds unseen nodes.

Closures are computed on the driver, so every implied role and label is one union of scans; only existence rules need the
roles first.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathlore.plans.ontology import Exists, Name, Ontology, TestSet
from pathlore.plans.terms import TOP, EdgeStep, Role
from pathlore.sources.graph import NodeKind, PropertyGraph


def implied_edges(graph: PropertyGraph, onto: Ontology, role: Role) -> DataFrame | None:
    """src and dst of all edges that the axioms put under a role, on explicit edges."""
    found = []

    def add(step: EdgeStep) -> None:
        rows = graph.edges(next((r.name for r in step.roles), None), step.tests)
        if rows is not None:
            found.append(rows if step.explicit_way() > 0 else rows.select(F.col("dst").alias("src"), F.col("src").alias("dst")))

    for r in sorted(onto.role_subs(role)):
        add(EdgeStep(frozenset([r])))
        for tests, head in onto.test_roles(r.name):
            add(EdgeStep(frozenset(), tests, -1 if head.inverse != r.inverse else 1))
    return reduce(DataFrame.unionByName, found).distinct() if found else None


def implied_nodes(graph: PropertyGraph, onto: Ontology, name: str) -> DataFrame | None:
    """node_id of all nodes that get a label."""
    found = []
    for c in sorted(onto.concept_subs(Name(name)), key=str):
        match c:
            case Name(n):
                found.append(graph.label_nodes(n))
            case TestSet(tests):
                found.append(graph.tested_nodes(tests))
            case Exists(role):
                rows = implied_edges(graph, onto, role)
                found.append(None if rows is None else rows.select(F.col("src").alias("node_id")))
    found = [f for f in found if f is not None]
    return reduce(DataFrame.unionByName, found).distinct() if found else None


def core_chase(graph: PropertyGraph, onto: Ontology) -> PropertyGraph:
    """The graph with all implied roles and labels of named nodes. Explicit edges keep their properties."""
    plain = onto.without_existentials()
    out = PropertyGraph(graph.spark, dict(graph.kinds), dict(graph.roles), dict(graph.extra))
    for name in sorted(onto.role_names()):
        rows = implied_edges(graph, plain, Role(name))
        if rows is None:
            continue
        own = graph.roles.get(name)
        if own is not None:
            rows = rows.join(own.select("src", "dst"), ["src", "dst"], "left_anti")
        out.roles[name] = rows if own is None else own.unionByName(rows, allowMissingColumns=True)
    for name in sorted(onto.names()):
        rows = implied_nodes(graph, plain, name)
        if rows is not None:
            out.extra[name] = rows
    return out


def bounded_chase(graph: PropertyGraph, onto: Ontology, depth: int) -> PropertyGraph:
    """Adds unseen nodes level by level; a child's id is a hash of its parent and generator, so runs agree."""
    norm = onto.normalise()
    out = core_chase(graph, norm)
    level = {name: implied_nodes(graph, norm, name) for name in norm.names()} | {TOP: graph.all_nodes()}
    made: list[DataFrame] = []
    for _ in range(depth):
        born: dict[Role, DataFrame] = {}
        for g, triggers in norm.generators().items():
            parents = [level[t] for t in triggers if level.get(t) is not None]
            if parents:
                rows = reduce(DataFrame.unionByName, [p.select("node_id") for p in parents]).distinct()
                child = F.xxhash64(F.col("node_id"), F.lit(str(g))).bitwiseOR(F.lit(-(1 << 63)))
                born[g] = rows.select(F.col("node_id").alias("src"), child.alias("dst"))
        nxt: dict[str, DataFrame | None] = {}
        for g, rows in born.items():
            made.append(rows.select(F.col("dst").alias("node_id")))
            for r in sorted(norm.role_supers(g)):
                way = rows if not r.inverse else rows.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
                out.roles[r.name] = way if r.name not in out.roles else out.roles[r.name].unionByName(way, allowMissingColumns=True)
            for label in norm.labels_of_child(g):
                kids = rows.select(F.col("dst").alias("node_id"))
                if label != TOP:
                    out.extra[label] = kids if label not in out.extra else out.extra[label].unionByName(kids)
                nxt[label] = kids if nxt.get(label) is None else nxt[label].unionByName(kids)
        level = nxt
        if not born:
            break
    if made:
        out.kinds["unseen"] = NodeKind(reduce(DataFrame.unionByName, made).distinct(), {})
    return out
