"""Certain answers: rewrite, then evaluate on the raw graph."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame

from pathlore.operators.evaluate import answer
from pathlore.plans.ontology import Ontology
from pathlore.plans.query import ConjunctivePathQuery, UnsupportedQuery, bind_existentials, components, parse_query
from pathlore.plans.rewrite import RewriteOptions, rewrite
from pathlore.sources.graph import PropertyGraph


def certain_answers(query: str | ConjunctivePathQuery, graph: PropertyGraph, onto: Ontology, options: RewriteOptions = RewriteOptions(), **how) -> DataFrame:
    q = parse_query(query) if isinstance(query, str) else query
    result = rewrite(q, onto, options)
    if result.stats.infeasible:
        raise RuntimeError("the rewriting is infeasible within its cap")
    return answer(result.query, graph, **how)


def certain_answers_of_parts(query: str | ConjunctivePathQuery, graph: PropertyGraph, onto: Ontology, allow_product: bool = False, **how) -> DataFrame:
    """Certain answers of a query whose atoms fall into unconnected parts: each part is answered apart, then the answers are put together.

    Parts share no variable, so several with answer variables make a product, which the caller must ask for.
    """
    q = parse_query(query) if isinstance(query, str) else query
    parts = components(q)
    if len(parts) > 1 and not allow_product:
        raise UnsupportedQuery("the answers of unconnected parts make a product; ask for it by allow_product")
    found = [certain_answers(p, graph, onto, **how) for p in parts]
    return reduce(DataFrame.crossJoin, found).select(*q.answer)


def plain_answers(query: str | ConjunctivePathQuery, graph: PropertyGraph, **how) -> DataFrame:
    """The answers without any ontology."""
    q = parse_query(query) if isinstance(query, str) else query
    return answer(bind_existentials(q), graph, **how)
