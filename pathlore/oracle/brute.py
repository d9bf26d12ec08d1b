"""Independent oracles on tiny graphs in plain Python: run search and the bounded chase."""

from __future__ import annotations

import operator
from dataclasses import dataclass, field

from pathlore.plans.automaton import AutomatonBook
from pathlore.plans.ontology import Name, Ontology, TestSet
from pathlore.plans.query import ConjunctivePathQuery
from pathlore.plans.terms import TOP, EdgeStep, LabelTest, Nest, NodeTest, Role

COMPARE = {"=": operator.eq, "<>": operator.ne, "<": operator.lt, "<=": operator.le, ">": operator.gt, ">=": operator.ge}


@dataclass
class TinyEdge:
    src: object
    dst: object
    roles: set[Role]  # what holds along the edge
    props: dict = field(default_factory=dict)


@dataclass
class TinyGraph:
    labels: dict[object, set[str]]
    props: dict[object, dict]
    edges: list[TinyEdge]

    @classmethod
    def of(cls, nodes: dict[object, tuple[set[str], dict]], edges: list[tuple]) -> TinyGraph:
        """``edges`` are (role, src, dst) or (role, src, dst, props)."""
        return cls({n: set(x) for n, (x, _) in nodes.items()}, {n: dict(p) for n, (_, p) in nodes.items()}, [TinyEdge(e[1], e[2], {Role(e[0])}, dict(e[3]) if len(e) > 3 else {}) for e in edges])


def passes(props: dict, tests) -> bool:
    return all(t.key in props and props[t.key] is not None and COMPARE[t.op](props[t.key], t.value) for t in tests)


class BruteRuns:
    def __init__(self, graph: TinyGraph, book: AutomatonBook):
        self.graph, self.book = graph, book
        self.tests: dict[tuple, bool] = {}
        self.out: dict[object, list] = {n: [] for n in graph.labels}
        for e in graph.edges:
            self.out[e.src].append((e, True))
            self.out[e.dst].append((e, False))

    def moves(self, node, symbol):
        match symbol:
            case LabelTest(name):
                if name == TOP or name in self.graph.labels[node]:
                    yield node
            case NodeTest(tests):
                if passes(self.graph.props[node], tests):
                    yield node
            case Nest(inner, start):
                if self.starts_run(inner, start, node):
                    yield node
            case EdgeStep(roles, tests, way):
                for e, along in self.out[node]:
                    have = e.roles if along else {r.inv() for r in e.roles}
                    if roles <= have and passes(e.props, tests) and way in (0, 1 if along else -1):
                        yield e.dst if along else e.src

    def starts_run(self, n: int, start, node) -> bool:
        key = (n, start, node)
        if key not in self.tests:
            self.tests[key] = bool(self.ends(n, node, start))
        return self.tests[key]

    def ends(self, n: int, node, start=None) -> set:
        a = self.book[n]
        seen = {(node, s) for s in ([start] if start is not None else a.starts)}
        todo = list(seen)
        while todo:
            at, s = todo.pop()
            for x, symbol, y in a.moves:
                if x == s:
                    for to in self.moves(at, symbol):
                        if (to, y) not in seen:
                            seen.add((to, y))
                            todo.append((to, y))
        return {v for v, s in seen if s in a.finals}

    def pairs(self, n: int) -> set[tuple]:
        return {(v, w) for v in self.graph.labels for w in self.ends(n, v)}


def brute_answers(q: ConjunctivePathQuery, graph: TinyGraph, named: set | None = None) -> set[tuple]:
    """Answers by joining the pairs of all atoms, variables ranging over all nodes."""
    runs = BruteRuns(graph, q.book)
    rows: list[dict] = [{}]
    for n, x, y in q.atoms:
        pairs = runs.pairs(n)
        rows = [{**r, x: a, y: b} for r in rows for a, b in pairs if r.get(x, a) == a and r.get(y, b) == b and (x != y or a == b)]
    out = {tuple(r[v] for v in q.answer) for r in rows}
    return out if named is None else {t for t in out if set(t) <= named}


def close_edge(roles: set[Role], props: dict, onto: Ontology) -> set[Role]:
    """Everything that holds along an edge."""
    out = set()
    for r in set(roles):
        out |= onto.role_supers(r)
    for a in onto.roles:
        if not a.negative and isinstance(a.left, TestSet) and props and passes(props, a.left.tests):
            out |= onto.role_supers(a.right)
    return out


def bounded_chase(graph: TinyGraph, onto: Ontology, depth: int) -> TinyGraph:
    """The graph with all implied facts, unseen nodes down to ``depth`` edges below the named ones."""
    labels = {n: set(x) for n, x in graph.labels.items()}
    props = {n: dict(p) for n, p in graph.props.items()}
    edges = [TinyEdge(e.src, e.dst, close_edge(e.roles, e.props, onto), dict(e.props)) for e in graph.edges]
    level = dict.fromkeys(labels, 0)
    made: set[tuple] = set()

    def holds(node, c) -> bool:
        if isinstance(c, Name):
            return c.name == TOP or c.name in labels[node]
        if isinstance(c, TestSet):
            return passes(props[node], c.tests)
        return any(e.src == node and c.role in e.roles or e.dst == node and c.role.inv() in e.roles for e in edges)

    changed = True
    while changed:
        changed = False
        for a in onto.concepts:
            if a.negative:
                continue
            for node in list(labels):
                if not holds(node, a.left):
                    continue
                if isinstance(a.right, Name):
                    if a.right.name not in labels[node]:
                        labels[node].add(a.right.name)
                        changed = True
                elif (node, a.right.role) not in made and level[node] < depth:
                    made.add((node, a.right.role))
                    child = (node, str(a.right.role))
                    labels[child], props[child], level[child] = set(), {}, level[node] + 1
                    edges.append(TinyEdge(node, child, close_edge({a.right.role}, {}, onto)))
                    changed = True
    return TinyGraph(labels, props, edges)
