"""Facts that break negative axioms."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathlore.operators.chase import implied_edges, implied_nodes
from pathlore.plans.ontology import Exists, Name, Ontology, TestSet
from pathlore.plans.terms import TOP, Role
from pathlore.sources.graph import PropertyGraph


def nodes_of(graph: PropertyGraph, onto: Ontology, c) -> DataFrame | None:
    match c:
        case Name(n) if n == TOP:
            return graph.all_nodes()
        case Name(n):
            return implied_nodes(graph, onto, n)
        case TestSet(tests):
            return graph.tested_nodes(tests)
        case Exists(role):
            rows = implied_edges(graph, onto, role)
            return None if rows is None else rows.select(F.col("src").alias("node_id")).distinct()


def violations(graph: PropertyGraph, onto: Ontology) -> DataFrame:
    """axiom, node, other: nodes under two disjoint concepts, pairs under two disjoint roles, nodes of concepts that cannot be."""
    norm = onto.normalise()
    found = []
    for a in norm.concepts:
        if a.negative:
            x, y = nodes_of(graph, norm, a.left), nodes_of(graph, norm, a.right)
            if x is not None and y is not None:
                found.append(x.join(y, "node_id", "left_semi").distinct().select(F.lit(f"{a.left} disjoint {a.right}").alias("axiom"), F.col("node_id").alias("node"), F.lit(None).cast("long").alias("other")))
    for a in norm.roles:
        if a.negative and isinstance(a.left, Role):
            x, y = implied_edges(graph, norm, a.left), implied_edges(graph, norm, a.right)
            if x is not None and y is not None:
                found.append(x.join(y, ["src", "dst"], "left_semi").distinct().select(F.lit(f"{a.left} disjoint {a.right}").alias("axiom"), F.col("src").alias("node"), F.col("dst").alias("other")))
    for name in sorted(unsatisfiable(norm)):
        rows = implied_nodes(graph, norm, name)
        if rows is not None:
            found.append(rows.select(F.lit(f"{name} is empty").alias("axiom"), F.col("node_id").alias("node"), F.lit(None).cast("long").alias("other")))
    return reduce(DataFrame.unionByName, found) if found else graph.spark.createDataFrame([], "axiom string, node long, other long")


def unsatisfiable(onto: Ontology) -> set[str]:
    """Names that no node can have: they imply both sides of a disjointness, or an unseen node that does."""
    negative = [a for a in onto.concepts if a.negative]
    bad_roles = set()
    for g in onto.generators():
        labels = onto.labels_of_child(g)
        inward = Exists(g.inv())

        def on_child(c, labels=labels, inward=inward) -> bool:
            return isinstance(c, Name) and c.name in labels or inward in onto.concept_subs(c)

        if any(on_child(a.left) and on_child(a.right) for a in negative) or any(a.negative and isinstance(a.left, Role) and {a.left, a.right} <= onto.role_supers(g) or a.negative and isinstance(a.left, Role) and {a.left, a.right} <= onto.role_supers(g.inv()) for a in onto.roles):
            bad_roles.add(g)
    grown = True
    while grown:  # a child that must have an impossible child is impossible
        more = {g for g in onto.generators() if g not in bad_roles and bad_roles & set(onto.children_of_child(g))}
        grown = bool(more)
        bad_roles |= more
    out = set()
    for n in onto.names():
        implies = lambda c, n=n: Name(n) in onto.concept_subs(c)
        if any(implies(a.left) and implies(a.right) for a in negative) or any(implies(Exists(g)) for g in bad_roles):
            out.add(n)
    return out
