"""Rewritten queries as text: a path pattern to read, and SQL with a recursive common table expression to run."""

from __future__ import annotations

from pathlore.plans.automaton import AutomatonBook
from pathlore.plans.query import ConjunctivePathQuery
from pathlore.plans.terms import TOP, EdgeStep, LabelTest, Nest, NodeTest


def to_pattern(q: ConjunctivePathQuery) -> str:
    """One line an atom, then one an automaton: its moves grouped by pairs of states."""
    out = [f"ans({', '.join(q.answer)})"] + [f"  ({x})-[automaton {n}]->({y})" for n, x, y in q.atoms]
    for n in q.book.reachable(*[n for n, _, _ in q.atoms]):
        a = q.book[n]
        out.append(f"automaton {n}: from {sorted(a.starts)} to {sorted(a.finals)}")
        pairs: dict[tuple[int, int], list[str]] = {}
        for x, s, y in a.moves:
            pairs.setdefault((x, y), []).append(str(s))
        out += [f"  {x} -> {y}: {' | '.join(ss)}" for (x, y), ss in sorted(pairs.items())]
    return "\n".join(out)


def _literal(v) -> str:
    return "'" + v.replace("'", "''") + "'" if isinstance(v, str) else str(v) if isinstance(v, (int, float)) else f"'{v}'"


def _tests(tests, alias: str) -> list[str]:
    return [f"{alias}.{t.key} {t.op} {_literal(t.value)}" for t in sorted(tests, key=str)]


class UnboundedQuery(ValueError):
    pass


def longest_run(book: AutomatonBook, n: int) -> int | None:
    """Moves of the longest run of an automaton; None if it has a cycle."""
    ahead: dict[int, set[int]] = {}
    for x, _, y in book[n].moves:
        ahead.setdefault(x, set()).add(y)
    known: dict[int, int | None] = {}

    def length(s: int, path: frozenset[int]) -> int | None:
        if s in path:
            return None
        if s not in known:
            own = [length(t, path | {s}) for t in sorted(ahead.get(s, ()))]
            known[s] = None if None in own else max((1 + k for k in own), default=0)
        return known[s]

    own = [length(s, frozenset()) for s in range(book[n].states)]
    return None if None in own else max(own, default=0)


class SqlRenderer:
    """SQL over two open tables: nodes (node_id, labels array, properties) and edges (role, src, dst, properties).

    Each automaton becomes a table of moves (a, b, src, dst) and its runs. An automaton without a cycle is unrolled to the length
    of its longest run. One with a cycle becomes a recursive common table expression: with ``distinct`` one that drops rows seen
    before, which always ends, for engines that have it; otherwise one that ends only if the data have no cycle that
    the query follows, which the caller says by ``acyclic_data``. Nothing is cut off: what cannot be complete is refused.
    """

    def __init__(self, book: AutomatonBook, distinct: bool, acyclic_data: bool, nodes: str, edges: str):
        self.book, self.distinct, self.acyclic_data, self.nodes, self.edges, self.ctes, self.done = book, distinct, acyclic_data, nodes, edges, [], set()

    def move(self, x: int, s, y: int) -> str:
        head = f"SELECT {x} AS a, {y} AS b, "
        match s:
            case EdgeStep():
                way = s.explicit_way()
                if not way:
                    return ""
                cond = [f"e.role = {_literal(r.name)}" for r in s.roles] + _tests(s.tests, "e")
                src, dst = ("e.src", "e.dst") if way > 0 else ("e.dst", "e.src")
                return f"{head}{src} AS src, {dst} AS dst FROM {self.edges} e WHERE {' AND '.join(cond)}"
            case LabelTest(name):
                where = "" if name == TOP else f" WHERE array_contains(n.labels, {_literal(name)})"
                return f"{head}n.node_id AS src, n.node_id AS dst FROM {self.nodes} n{where}"
            case NodeTest(tests):
                return f"{head}n.node_id AS src, n.node_id AS dst FROM {self.nodes} n WHERE {' AND '.join(_tests(tests, 'n'))}"
            case Nest(inner, start):
                self.automaton(inner)
                return f"{head}r.src AS src, r.src AS dst FROM (SELECT DISTINCT src FROM runs{inner} WHERE first IN ({', '.join(map(str, [start] if start is not None else sorted(self.book[inner].starts)))})) r"
        raise TypeError(s)

    def automaton(self, n: int) -> None:
        if n in self.done:
            return
        self.done.add(n)
        a = self.book[n]
        firsts = sorted(a.starts | {s.start for m in self.book.automata.values() for s in m.nests() if s.automaton == n and s.start is not None})
        moves = [m for m in (self.move(*m) for m in a.moves) if m] or [f"SELECT 0 AS a, 0 AS b, n.node_id AS src, n.node_id AS dst FROM {self.nodes} n WHERE false"]
        self.ctes.append((f"moves{n}", " UNION ALL ".join(moves)))
        begin = " UNION ALL ".join(f"SELECT {s} AS first, {s} AS state, n.node_id AS src, n.node_id AS node FROM {self.nodes} n" for s in firsts)
        step = lambda table: f"SELECT w.first, m.b, w.src, m.dst FROM {table} w JOIN moves{n} m ON w.state = m.a AND w.node = m.src"
        longest = longest_run(self.book, n)
        if longest is None:
            if not (self.distinct or self.acyclic_data):
                raise UnboundedQuery("the query has a cycle: it needs an engine with distinct recursion, or data known to be acyclic")
            self.ctes.append((f"walk{n}(first, state, src, node)", f"{begin} {'UNION' if self.distinct else 'UNION ALL'} {step(f'walk{n}')}"))
            walk = f"walk{n}"
        else:
            self.ctes.append((f"walk{n}_0", begin))
            for i in range(1, longest + 1):
                self.ctes.append((f"walk{n}_{i}", f"SELECT first, state, src, node FROM walk{n}_{i - 1} UNION {step(f'walk{n}_{i - 1}')}"))
            walk = f"walk{n}_{longest}"
        finals = ", ".join(map(str, sorted(a.finals))) or "-1"
        self.ctes.append((f"runs{n}", f"SELECT DISTINCT first, src, node FROM {walk} WHERE state IN ({finals})"))


def to_sql(q: ConjunctivePathQuery, distinct: bool = False, acyclic_data: bool = False, nodes: str = "nodes", edges: str = "edges") -> str:
    """The query in SQL over the open tables; node ids are returned. Spark has no distinct recursion: see ``SqlRenderer``."""
    r = SqlRenderer(q.book, distinct, acyclic_data, nodes, edges)
    froms, seen, where = [], {}, []
    for i, (n, x, y) in enumerate(q.atoms):
        r.automaton(n)
        froms.append(f"runs{n} t{i}")
        where.append(f"t{i}.first IN ({', '.join(map(str, sorted(q.book[n].starts)))})")
        for v, c in ((x, f"t{i}.src"), (y, f"t{i}.node")):
            if v in seen:
                where.append(f"{seen[v]} = {c}")
            else:
                seen[v] = c
    ctes = ",\n".join(f"{name} AS ({body})" for name, body in r.ctes)
    return f"WITH RECURSIVE {ctes}\nSELECT DISTINCT {', '.join(f'{seen[v]} AS {v}' for v in q.answer)}\nFROM {', '.join(froms)}\nWHERE {' AND '.join(where)}"
