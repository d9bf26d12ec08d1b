"""Path expressions as rows, and run search in plain Python over small components."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathlore.oracle.brute import TinyEdge, TinyGraph, brute_answers
from pathlore.plans.automaton import AutomatonBook, to_automaton
from pathlore.plans.query import ConjunctivePathQuery
from pathlore.plans.terms import Role


class PathSymbols:
    """A row for each move of the automata of a path expression: the automaton, its states, the symbol."""

    def eval(self, text: str | None) -> Iterator[tuple[int, int, str, int]]:
        if text is None:
            return
        book = AutomatonBook()
        root = to_automaton(text, book)
        for n in book.reachable(root):
            for x, symbol, y in book[n].moves:
                yield n, x, str(symbol), y


#: Table function: SELECT * FROM path_symbols('r/s*').
path_symbols = F.udtf(PathSymbols, returnType="automaton int, from_state int, symbol string, to_state int")


def run_components(nodes: DataFrame, edges: DataFrame, component: str, query: ConjunctivePathQuery) -> DataFrame:
    """Answers of a query by run search within each component, a task a component: for graphs of very many small components.

    ``nodes``: component, node_id, labels and properties; ``edges``: component, role, src, dst and properties. Null properties are absent.
    """
    props = [c for c in nodes.columns if c not in (component, "node_id", "labels")]
    edge_props = [c for c in edges.columns if c not in (component, "role", "src", "dst")]
    names = list(query.answer)

    def known(row: dict, keys: list[str]) -> dict:
        return {k: row[k] for k in keys if not pd.isna(row[k])}

    def search(ns: pd.DataFrame, es: pd.DataFrame) -> pd.DataFrame:
        rows = ns.to_dict("records")
        graph = TinyGraph({r["node_id"]: set(r["labels"]) for r in rows}, {r["node_id"]: known(r, props) for r in rows}, [TinyEdge(e["src"], e["dst"], {Role(e["role"])}, known(e, edge_props)) for e in es.to_dict("records")])
        return pd.DataFrame(sorted(brute_answers(query, graph)), columns=names, dtype="int64")

    return nodes.groupBy(component).cogroup(edges.groupBy(component)).applyInPandas(search, ", ".join(f"{v} long" for v in names))
