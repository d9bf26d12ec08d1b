"""Ontologies of concept and role inclusions, their text form and their closures.

Text form, one axiom a line (``#`` starts a comment)::

    role a, ^b < c              roles below a role;  role {k>=1} < c  for edges that pass tests
    concept A, exists ^r < B    names, TOP, existence of an edge, or {tests} below a name or an existence
    concept A < exists r.B      short for a fresh role below r that ends in B
    disjoint concept A, B       disjoint role r, s
"""

from __future__ import annotations

from collections import defaultdict
from dataclasses import dataclass, field
from functools import cached_property

from pathlore.plans.pathlang import PathSyntaxError, Reader
from pathlore.plans.terms import TOP, Role, show_tests


@dataclass(frozen=True, order=True)
class Name:
    name: str

    def __str__(self) -> str:
        return self.name


@dataclass(frozen=True, order=True)
class Exists:
    role: Role

    def __str__(self) -> str:
        return f"exists {self.role}"


@dataclass(frozen=True)
class TestSet:
    tests: frozenset

    def __str__(self) -> str:
        return "{" + show_tests(self.tests) + "}"


Basic = Name | Exists | TestSet
Everything = Name(TOP)


@dataclass(frozen=True)
class ConceptAxiom:
    left: Basic
    right: Basic  # a name or an existence; a negative axiom may have tests too
    negative: bool = False


@dataclass(frozen=True)
class RoleAxiom:
    left: Role | TestSet
    right: Role
    negative: bool = False


@dataclass
class Ontology:
    concepts: list[ConceptAxiom] = field(default_factory=list)
    roles: list[RoleAxiom] = field(default_factory=list)

    # ---- closures -------------------------------------------------------------------------------------------

    @cached_property
    def _role_edges(self) -> dict[Role, set[Role]]:
        """Directly below: for each role the roles of positive axioms under it, inverses included."""
        out: dict[Role, set[Role]] = defaultdict(set)
        for a in self.roles:
            if not a.negative and isinstance(a.left, Role):
                out[a.right].add(a.left)
                out[a.right.inv()].add(a.left.inv())
        return out

    def role_subs(self, role: Role) -> frozenset[Role]:
        """All roles below, itself included."""
        if role not in self._subs:
            seen, todo = {role}, [role]
            while todo:
                for x in self._role_edges.get(todo.pop(), ()):
                    if x not in seen:
                        seen.add(x)
                        todo.append(x)
            self._subs[role] = frozenset(seen)
        return self._subs[role]

    @cached_property
    def _subs(self) -> dict[Role, frozenset[Role]]:
        return {}

    @cached_property
    def _role_edges_up(self) -> dict[Role, set[Role]]:
        out: dict[Role, set[Role]] = defaultdict(set)
        for a, below in self._role_edges.items():
            for b in below:
                out[b].add(a)
        return out

    def role_supers(self, role: Role) -> frozenset[Role]:
        """All roles above, itself included."""
        seen, todo = {role}, [role]
        while todo:
            for x in self._role_edges_up.get(todo.pop(), ()):
                if x not in seen:
                    seen.add(x)
                    todo.append(x)
        return frozenset(seen)

    @cached_property
    def _test_roles(self) -> dict[str, list[tuple[frozenset, Role]]]:
        out: dict[str, list] = defaultdict(list)
        for a in self.roles:
            if not a.negative and isinstance(a.left, TestSet):
                out[a.right.name].append((a.left.tests, a.right))
        return out

    def test_roles(self, name: str) -> list[tuple[frozenset, Role]]:
        return self._test_roles.get(name, [])

    @cached_property
    def _concept_edges(self) -> dict[Basic, set[Basic]]:
        """Directly below a basic concept; existence follows the role hierarchy."""
        out: dict[Basic, set[Basic]] = defaultdict(set)
        for a in self.concepts:
            if not a.negative:
                out[a.right].add(a.left)
        for r in {r for a in self.concepts for r in self.roles_in(a)} | {r for a in self.roles for r in (a.left, a.right) if isinstance(r, Role)}:
            for x in (r, r.inv()):
                out[Exists(x)] |= {Exists(s) for s in self.role_subs(x) if s != x}
        return out

    @staticmethod
    def roles_in(a: ConceptAxiom) -> list[Role]:
        return [c.role for c in (a.left, a.right) if isinstance(c, Exists)]

    def concept_subs(self, concept: Basic) -> frozenset:
        """Everything that the saturated axioms put below a basic concept, itself included."""
        if concept not in self._below:
            seen, todo = {concept}, [concept]
            while todo:
                c = todo.pop()
                below = set(self._concept_edges.get(c, ()))
                if isinstance(c, Exists) and c not in self._concept_edges:
                    below |= {Exists(s) for s in self.role_subs(c.role)}
                for x in below - seen:
                    seen.add(x)
                    todo.append(x)
            self._below[concept] = frozenset(seen)
        return self._below[concept]

    @cached_property
    def _below(self) -> dict[Basic, frozenset]:
        return {}

    def names(self) -> set[str]:
        return {c.name for a in self.concepts for c in (a.left, a.right) if isinstance(c, Name)} - {TOP}

    def role_names(self) -> set[str]:
        return {r.name for a in self.concepts for r in self.roles_in(a)} | {r.name for a in self.roles for r in (a.left, a.right) if isinstance(r, Role)}

    def generators(self) -> dict[Role, list[str]]:
        """Roles that an axiom makes an unseen edge of, with the names that trigger them (after ``normalise``)."""
        out: dict[Role, list[str]] = defaultdict(list)
        for a in self.concepts:
            if not a.negative and isinstance(a.right, Exists) and isinstance(a.left, Name) and a.left.name not in out[a.right.role]:
                out[a.right.role].append(a.left.name)
        return dict(out)

    def labels_of_child(self, generator: Role) -> set[str]:
        """The names, TOP included, of an unseen node that hangs on an edge of the generator."""
        inward = Exists(generator.inv())
        return {TOP} | {n for n in self.names() if {inward, Everything} & self.concept_subs(Name(n))}

    def children_of_child(self, generator: Role) -> list[Role]:
        labels = self.labels_of_child(generator)
        return [g for g, triggers in self.generators().items() if labels & set(triggers)]

    # ---- forms ----------------------------------------------------------------------------------------------

    def normalise(self) -> Ontology:
        """The same meaning, with a name between every existence or test set and an existence that it implies."""
        out, fresh = [], {}
        for a in self.concepts:
            if not a.negative and isinstance(a.right, Exists) and not isinstance(a.left, Name):
                if a.left not in fresh:
                    fresh[a.left] = Name(f"_has_{len(fresh)}")
                    out.append(ConceptAxiom(a.left, fresh[a.left]))
                out.append(ConceptAxiom(fresh[a.left], a.right))
            else:
                out.append(a)
        return Ontology(list(dict.fromkeys(out)), list(dict.fromkeys(self.roles)))

    def without_existentials(self) -> Ontology:
        return Ontology([a for a in self.concepts if a.negative or not isinstance(a.right, Exists)], list(self.roles))


def saturate_concepts(onto: Ontology) -> list[ConceptAxiom]:
    """All positive inclusions between basic concepts that the axioms give (without those of a concept in itself)."""
    tops = {Name(n) for n in onto.names()} | {Exists(x) for r in onto.role_names() for x in (Role(r), Role(r, True))}
    return [ConceptAxiom(c, t) for t in sorted(tops, key=str) for c in sorted(onto.concept_subs(t), key=str) if c != t]


def _basic(r: Reader) -> Basic:
    if r.has("{"):
        r.take()
        roles, tests = r.members("}")
        if roles:
            raise PathSyntaxError("roles among tests")
        return TestSet(tests)
    word = r.name()
    if word == "exists":
        return Exists(r.role())
    return Name(word)


def _list(r: Reader, one) -> list:
    out = [one()]
    while r.has(","):
        r.take()
        out.append(one())
    return out


def parse_ontology(text: str) -> Ontology:
    onto, fresh = Ontology(), 0
    for raw in text.splitlines():
        line = raw.partition("#")[0].strip()
        if not line:
            continue
        filler = ""
        head, _, ending = line.rpartition(".")
        if head and " exists " in head.rpartition("<")[2] and ending.isidentifier():
            line, filler = head, ending
        r = Reader(line)
        kind = r.name()
        if kind == "disjoint":
            kind = r.name()
            both = _list(r, (lambda: _basic(r)) if kind == "concept" else r.role)
            for i, x in enumerate(both):
                for y in both[i + 1 :]:
                    (onto.concepts if kind == "concept" else onto.roles).append(ConceptAxiom(x, y, True) if kind == "concept" else RoleAxiom(x, y, True))
        elif kind == "role":
            below = _list(r, lambda: _basic(r) if r.has("{") else r.role())
            r.take("<")
            above = r.role()
            onto.roles += [RoleAxiom(x, above) for x in below]
        elif kind == "concept":
            below = _list(r, lambda: _basic(r))
            r.take("<")
            above = _basic(r)
            if isinstance(above, TestSet):
                raise PathSyntaxError(f"no axiom implies property values: {raw!r}")
            if filler:
                made = Role(f"{above.role.name}_to_{filler}_{fresh}")
                fresh += 1
                onto.concepts.append(ConceptAxiom(Exists(made.inv()), Name(filler)))
                onto.roles.append(RoleAxiom(made, above.role))
                above = Exists(made)
            onto.concepts += [ConceptAxiom(x, above) for x in below]
        else:
            raise PathSyntaxError(f"not an axiom: {raw!r}")
        if r.peek()[0]:
            raise PathSyntaxError(f"unexpected {r.peek()[1]!r} in {raw!r}")
    return onto


SHOP = """
    role customerNation, supplierNation, inRegion < locatedIn
    role placed < involvedIn
    role ^shippedBy < involvedIn
    role ^hasItem < itemOf
    role {quantity>=45, discount>=0.08} < bulkDeal
    role bulkDeal < deal
    role copyOf < sameText
    role sameText < ^sameText
    role ^nextTurn < follows
    role nextEvent < precedes
    role holdsLicence < accreditedBy
    role ^holdsLicence < licenceOf
    role handledBy < assignedTo
    concept Customer, Supplier < Party
    concept Supplier < Organisation
    concept exists placed < Buyer
    concept Buyer < Party
    concept {acctbal>=9000} < Wealthy
    concept {acctbal<=0} < Overdrawn
    concept {totalprice>=400000} < BigOrder
    concept {quality=1, toxic=0} < CleanText
    concept exists bulkDeal < BulkOrder
    concept exists ^bulkDeal < BulkPart
    concept View, Click, Purchase < Interaction
    concept Interaction, Signup < Activity
    concept Supplier < exists holdsLicence
    concept exists ^holdsLicence < Licence
    concept Licence < exists issuedBy
    concept exists ^issuedBy < Authority
    concept BulkOrder < exists handledBy
    concept exists ^handledBy < Agent
    concept exists assignedTo < Tracked
    disjoint concept Organisation, Customer
    disjoint role locatedIn, placed
"""


def shop() -> Ontology:
    return parse_ontology(SHOP)
