"""SQL for results that read few tables or none: literal rows found by ways of their own, not by the compiler that the queries run."""

from __future__ import annotations

import re

from pathlore import workload
from pathlore.plans.ontology import Ontology, shop
from pathlore.plans.query import parse_query
from pathlore.plans.rewrite import RewriteOptions, rewrite
from pathlore.plans.terms import Role

TOKEN = re.compile(r"[:^]?\w+|[()<>|/*]")


def literal(v) -> str:
    return "NULL" if v is None else str(v).lower() if isinstance(v, bool) else str(v) if isinstance(v, int) else "'" + str(v).replace("'", "''") + "'"


def values(columns: dict[str, str], rows: list[tuple]) -> str:
    """SELECT of literal rows; ``columns`` gives each name its SQL type."""
    casts = ", ".join(f"CAST(c{i} AS {kind}) AS {name}" for i, (name, kind) in enumerate(columns.items()))
    return f"SELECT {casts} FROM (VALUES {', '.join('(' + ', '.join(map(literal, r)) + ')' for r in rows)}) AS t({', '.join(f'c{i}' for i in range(len(columns)))})"


def input_size(path: str) -> tuple[int, int]:
    """States and transitions of a path's nested automaton, from which symbol may come after which.

    A state a symbol and one to start with; a transition for each symbol that may come first and for each pair of neighbours. Nested
    paths count by themselves. For paths of names, labels, nests, unions, concatenations and stars.
    """
    tokens, at, inner = TOKEN.findall(path), 0, [0, 0]
    after: set[tuple[int, int]] = set()
    symbols = 0

    def union(stop: str) -> tuple[bool, frozenset, frozenset]:
        nonlocal at
        empty, first, last = sequence()
        while at < len(tokens) and tokens[at] == "|":
            at += 1
            e, f, ll = sequence()
            empty, first, last = empty or e, first | f, last | ll
        if stop:
            assert tokens[at] == stop
            at += 1
        return empty, first, last

    def sequence() -> tuple[bool, frozenset, frozenset]:
        nonlocal at
        empty, first, last = True, frozenset(), frozenset()
        while True:
            e, f, ll = piece()
            after.update((x, y) for x in last for y in f)
            first, last, empty = (first | f if empty else first), (last | ll if e else ll), empty and e
            if at == len(tokens) or tokens[at] != "/":
                return empty, first, last
            at += 1

    def piece() -> tuple[bool, frozenset, frozenset]:
        nonlocal at, symbols
        token = tokens[at]
        at += 1
        if token == "(":
            found = union(")")
        else:
            if token == "<":
                depth, begin = 1, at
                while depth:
                    depth += (tokens[at] == "<") - (tokens[at] == ">")
                    at += 1
                for k, n in enumerate(input_size("".join(tokens[begin : at - 1]))):
                    inner[k] += n
            symbols += 1
            found = False, frozenset([symbols]), frozenset([symbols])
        while at < len(tokens) and tokens[at] == "*":
            at += 1
            after.update((x, y) for x in found[2] for y in found[1])
            found = True, found[1], found[2]
        return found

    first = union("")[1]
    return 1 + symbols + inner[0], len(first) + len(after) + inner[1]


def input_sizes(ontologies: dict[str, Ontology]) -> list[tuple]:
    """The rows of ``generated_input_sizes``; SQL cannot draw the queries, which take their names from the tables."""
    return [(name, guided, i, *input_size(text.removeprefix("ans(x,y) <- ").removesuffix("(x,y)"))) for name, onto in ontologies.items() for guided in (False, True) for i, text in enumerate(workload.generate_queries(onto, 100, guided=guided))]


def skip_tuples() -> str:
    """The minimal jumps, each candidate put to the reasoner by itself."""
    rows = []
    for name in sorted(workload.QUERIES):
        found = rewrite(parse_query(workload.QUERIES[name]), shop(), RewriteOptions(anonymous="exhaustive")).tuples
        rows += [(name, n, t.concept, t.state, str(t.target), str(sorted(t.rest))) for n, ts in found.items() for t in ts]
    return values({"query": "VARCHAR", "automaton": "INT", "concept": "VARCHAR", "state": "INT", "target": "VARCHAR", "rest": "VARCHAR"}, rows)


def ontology_sizes() -> str:
    """Names by pattern in the axioms' text, numbers of axioms by kind; with the classes that the tables name."""
    sets = []
    for kind, onto in (("flat", workload.scaled_ontology()), ("shop", shop()), ("shop_18", workload.shop_18())):
        sides = [str(side) for a in onto.concepts for side in (a.left, a.right)]
        concepts = {s for s in sides if re.fullmatch(r"\w+", s)}
        roles = {r for s in sides for r in re.findall(r"^exists \^?(\w+)$", s)} | {r for a in onto.roles for s in (a.left, a.right) for r in re.findall(r"^\^?(\w+)$", str(s))}
        made = {str(a.right) for a in onto.concepts if str(a.right).startswith("exists ") and not a.negative}
        pairs = sorted({(str(a.left), str(a.right)) for a in onto.concepts})
        sets.append((kind, sorted(concepts), pairs, (len(roles), len(onto.concepts), len(onto.roles), len(made))))
    named = " UNION ".join(f"SELECT '{p}' || regexp_replace({c}, '[^0-9A-Za-z]+', '_', 'g') AS name, '{above}' AS above FROM {t} WHERE {c} IS NOT NULL" for t, c, p, above in workload.VALUE_NAMES)
    one = lambda kind, concepts, pairs, n: (
        f"SELECT '{kind}' AS ontology, CAST((SELECT count(*) FROM ({values({'name': 'VARCHAR'}, [(c,) for c in concepts])} UNION SELECT name FROM named UNION SELECT above FROM named)) AS INT) AS concepts, {n[0]} AS roles, "
        f"CAST({n[1]} + (SELECT count(*) FROM (SELECT name, above FROM named EXCEPT {values({'name': 'VARCHAR', 'above': 'VARCHAR'}, pairs)})) AS INT) AS concept_axioms, {n[2]} AS role_axioms, {n[3]} AS existentials"
    )
    return f"WITH named AS ({named}) " + " UNION ALL ".join(one(*s) for s in sets)


def concept_closure(onto: Ontology) -> str:
    """The closure by recursion over the axioms."""
    rows = {(str(a.left), str(a.right)) for a in onto.concepts if not a.negative}
    for a in onto.roles:
        if isinstance(a.left, Role) and not a.negative:
            flip = lambda r: str(r)[1:] if str(r).startswith("^") else f"^{r}"
            rows |= {(f"exists {a.left}", f"exists {a.right}"), (f"exists {flip(a.left)}", f"exists {flip(a.right)}")}
    direct = values({"below": "VARCHAR", "above": "VARCHAR"}, sorted(rows))
    return f"WITH RECURSIVE direct AS ({direct}), closed(below, above) AS (SELECT below, above FROM direct UNION SELECT c.below, d.above FROM closed c JOIN direct d ON c.above = d.below) SELECT below, above FROM closed WHERE below <> above"


def oracles() -> dict[str, str]:
    return {"skip_tuples": skip_tuples(), "ontology_stats": ontology_sizes(), "concept_closure": concept_closure(workload.scaled_ontology())}
