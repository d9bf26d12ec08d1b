"""The older way to skip unseen nodes: the query keeps its moves, and the evaluation jumps.

Baseline for the rewriting: jumps are tables of nodes looked up while evaluating, not moves of the query.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame

from pathlore.operators.chase import implied_nodes
from pathlore.operators.evaluate import Evaluator, Guard, answer
from pathlore.plans.ontology import Ontology
from pathlore.plans.query import ConjunctivePathQuery, bind_existentials
from pathlore.plans.skip_anonymous import FINISH, SkipTuple, skip_saturate
from pathlore.plans.skip_core import skip_core
from pathlore.plans.terms import TOP
from pathlore.sources.graph import PropertyGraph


@dataclass
class JumpingEvaluator(Evaluator):
    onto: Ontology | None = None
    jumps: dict[int, list[tuple[int, int, SkipTuple]]] = field(default_factory=dict)  # (from, to, tuple)
    typed: bool = False  # jumps go where the moves alone could not

    def guards(self, n: int) -> dict[tuple[int, int], Guard]:
        if n in self._guards:
            return self._guards[n]
        out = super().guards(n)
        for x, y, t in self.jumps.get(n, ()):
            start = self.graph.all_nodes() if t.concept == TOP else implied_nodes(self.graph, self.onto.without_existentials(), t.concept)
            tests = [self.starts_of(inner, s) for inner, s in sorted(t.rest)]
            if start is None or any(r is None for r in tests):
                continue
            nodes = reduce(lambda a, b: a.join(b, "node_id", "left_semi"), tests, start.select("node_id"))
            g = out.get((x, y), Guard())
            if not g.free:
                out[x, y] = Guard(g.pairs, nodes if g.nodes is None else g.nodes.unionByName(nodes))
        return out


def answer_with_runtime_jumps(query: ConjunctivePathQuery, graph: PropertyGraph, onto: Ontology, **how) -> DataFrame:
    """Certain answers with core moves in the query and jumps at evaluation time."""
    onto = onto.normalise()
    q = bind_existentials(query)
    q = ConjunctivePathQuery(q.answer, list(q.atoms), q.book.copy())
    roots = list(dict.fromkeys(n for n, _, _ in q.atoms))
    tuples = skip_saturate(q.book, onto, roots)
    jumps: dict[int, list[tuple[int, int, SkipTuple]]] = {}
    for n, found in tuples.items():
        end = None
        for t in found:
            if t.target == FINISH and end is None:
                end = q.book[n].state()
                q.book[n].finals.add(end)
            jumps.setdefault(n, []).append((t.state, end if t.target == FINISH else t.target, t))
    skip_core(q.book, roots, onto)
    return answer(q, graph, evaluator=JumpingEvaluator(graph, q.book, onto=onto, jumps=jumps), **how)
