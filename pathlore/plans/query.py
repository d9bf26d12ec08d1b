"""Conjunctive path queries: validation, splitting, and removal of variables that are not answered."""

from __future__ import annotations

from dataclasses import dataclass

from pathlore.plans.automaton import AutomatonBook, invert, to_automaton
from pathlore.plans.pathlang import parse_query_text
from pathlore.plans.terms import Nest


class UnsupportedQuery(ValueError):
    pass


@dataclass
class ConjunctivePathQuery:
    """``atoms`` are (automaton, left variable, right variable)."""

    answer: tuple[str, ...]
    atoms: list[tuple[int, str, str]]
    book: AutomatonBook

    def variables(self) -> list[str]:
        return list(dict.fromkeys(v for _, x, y in self.atoms for v in (x, y)))

    def joins(self) -> list[str]:
        return [v for v in self.variables() if sum(v in (x, y) for _, x, y in self.atoms) > 1]


def parse_query(text: str) -> ConjunctivePathQuery:
    answer, atoms = parse_query_text(text)
    book = AutomatonBook()
    q = ConjunctivePathQuery(answer, [(to_automaton(p, book), x, y) for p, x, y in atoms], book)
    missing = [v for v in answer if v not in q.variables()]
    if missing:
        raise UnsupportedQuery(f"answer variable {missing[0]} is in no atom")
    return q


def components(q: ConjunctivePathQuery) -> list[ConjunctivePathQuery]:
    """The connected parts of a query."""
    groups: list[tuple[set[str], list]] = []
    for atom in q.atoms:
        own, atoms = {atom[1], atom[2]}, [atom]
        for g in [g for g in groups if g[0] & own]:
            groups.remove(g)
            own, atoms = own | g[0], g[1] + atoms
        groups.append((own, atoms))
    return [ConjunctivePathQuery(tuple(v for v in q.answer if v in own), sorted(atoms, key=q.atoms.index), q.book) for own, atoms in groups]


def check_join_on_free(q: ConjunctivePathQuery) -> None:
    if not q.answer:
        raise UnsupportedQuery("a query without answer variables may match among unseen nodes only")
    if len(components(q)) > 1:
        raise UnsupportedQuery("the query is not connected; answer its components apart")
    for v in q.joins():
        if v not in q.answer:
            raise UnsupportedQuery(f"variable {v} joins atoms but is not answered")


def bind_existentials(q: ConjunctivePathQuery) -> ConjunctivePathQuery:
    """Atoms with one answered variable become tests on it; a left variable that is not answered inverts the path."""
    check_join_on_free(q)
    book = q.book.copy()
    atoms = []
    for a, x, y in q.atoms:
        if x == y or x in q.answer and y in q.answer:
            atoms.append((a, x, y))
            continue
        v, inner = (x, a) if x in q.answer else (y, invert(book, a))
        test = book.new()
        out = book[test]
        begin, end = out.state(), out.state()
        out.starts, out.finals = {begin}, {end}
        out.add(begin, Nest(inner), end)
        atoms.append((test, v, v))
    return ConjunctivePathQuery(q.answer, atoms, book)
