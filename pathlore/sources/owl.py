"""Ontologies from a subset of OWL functional syntax."""

from __future__ import annotations

import re

from pyspark.sql import SparkSession

from pathlore.plans.ontology import ConceptAxiom, Exists, Name, Ontology, RoleAxiom, TestSet
from pathlore.plans.terms import TOP, DataTest, Role

TOKEN = re.compile(r'\s*(?:([()=])|"([^"]*)"(?:\^\^(\S+?))?(?=[\s()])|([^\s()="]+))')
#: Facets of datatype restrictions and their comparisons.
FACETS = {"minInclusive": ">=", "maxInclusive": "<=", "minExclusive": ">", "maxExclusive": "<"}


class UnsupportedAxiom(ValueError):
    pass


def _short(name: str) -> str:
    name = name.strip("<>")
    return re.split(r"[#/:]", name)[-1]


def _tree(text: str):
    """Nested lists (head, arguments...) of an expression text."""
    stack: list[list] = [[]]
    at = 0
    text = re.sub(r"^\s*#.*$", "", text, flags=re.M)
    while at < len(text.rstrip()):
        m = TOKEN.match(text, at)
        if not m:
            raise UnsupportedAxiom(f"cannot read {text[at : at + 20]!r}")
        at = m.end()
        sign, string, kind, word = m.groups()
        if sign == "(":
            stack.append([stack[-1].pop()])
        elif sign == ")":
            done = stack.pop()
            stack[-1].append(done)
        elif string is not None:
            stack[-1].append(("literal", string, _short(kind or "string")))
        elif sign is None:
            stack[-1].append(word)
    return stack[0]


def _value(literal):
    _, text, kind = literal
    if kind in ("integer", "int", "long", "nonNegativeInteger"):
        return int(text)
    if kind in ("decimal", "double", "float"):
        return float(text)
    if kind == "boolean":
        return text == "true"
    return text


def _role(e) -> Role:
    if isinstance(e, list) and e[0] == "ObjectInverseOf":
        return _role(e[1]).inv()
    if isinstance(e, str):
        return Role(_short(e))
    raise UnsupportedAxiom(f"not a role: {e}")


def _tests(e) -> frozenset:
    key, rest = _short(e[1]), e[2]
    if e[0] == "DataHasValue":
        return frozenset([DataTest(key, "=", _value(rest))])
    if isinstance(rest, list) and rest[0] == "DatatypeRestriction":
        return frozenset(DataTest(key, FACETS[_short(f)], _value(v)) for f, v in zip(rest[2::2], rest[3::2], strict=True))
    raise UnsupportedAxiom(f"not a value test: {e}")


def load_owl_functional(text: str) -> Ontology:
    """SubClassOf, EquivalentClasses of names, sub-properties, inverses, symmetry, domain, range, disjointness; value tests on the left."""
    onto = Ontology()
    fresh = 0

    def concept(e):
        if isinstance(e, str):
            return Name(TOP if _short(e) == "Thing" else _short(e))
        if e[0] == "ObjectSomeValuesFrom" and e[2] == "owl:Thing":
            return Exists(_role(e[1]))
        if e[0] in ("DataSomeValuesFrom", "DataHasValue"):
            return TestSet(_tests(e))
        if e[0] == "ObjectIntersectionOf" and all(isinstance(x, list) and x[0].startswith("Data") for x in e[1:]):
            return TestSet(frozenset().union(*(_tests(x) for x in e[1:])))
        raise UnsupportedAxiom(f"not a basic concept: {e}")

    def include(left, right) -> None:
        nonlocal fresh
        if isinstance(right, list) and right[0] == "ObjectIntersectionOf":
            for r in right[1:]:
                include(left, r)
        elif isinstance(right, list) and right[0] == "ObjectComplementOf":
            onto.concepts.append(ConceptAxiom(concept(left), concept(right[1]), True))
        elif isinstance(right, list) and right[0] == "ObjectSomeValuesFrom" and right[2] != "owl:Thing":
            role, filler = _role(right[1]), concept(right[2])
            made = Role(f"{role.name}_some_{fresh}")
            fresh += 1
            onto.concepts.append(ConceptAxiom(concept(left), Exists(made)))
            onto.concepts.append(ConceptAxiom(Exists(made.inv()), filler))
            onto.roles.append(RoleAxiom(made, role))
        else:
            head = concept(right)
            if isinstance(head, TestSet):
                raise UnsupportedAxiom("no axiom implies property values")
            onto.concepts.append(ConceptAxiom(concept(left), head))

    def read(items) -> None:
        for e in items:
            if not isinstance(e, list):
                continue
            head, args = e[0], e[1:]
            match head:
                case "Ontology":
                    read(args)
                case "SubClassOf":
                    include(*args)
                case "EquivalentClasses":
                    for a in args:
                        for b in args:
                            if a is not b:
                                include(a, b)
                case "SubObjectPropertyOf":
                    onto.roles.append(RoleAxiom(_role(args[0]), _role(args[1])))
                case "InverseObjectProperties":
                    a, b = map(_role, args)
                    onto.roles += [RoleAxiom(a, b.inv()), RoleAxiom(b.inv(), a)]
                case "SymmetricObjectProperty":
                    onto.roles.append(RoleAxiom(_role(args[0]), _role(args[0]).inv()))
                case "ObjectPropertyDomain":
                    onto.concepts.append(ConceptAxiom(Exists(_role(args[0])), concept(args[1])))
                case "ObjectPropertyRange":
                    onto.concepts.append(ConceptAxiom(Exists(_role(args[0]).inv()), concept(args[1])))
                case "DisjointClasses":
                    found = [concept(a) for a in args]
                    onto.concepts += [ConceptAxiom(a, b, True) for i, a in enumerate(found) for b in found[i + 1 :]]
                case "DisjointObjectProperties":
                    found = [_role(a) for a in args]
                    onto.roles += [RoleAxiom(a, b, True) for i, a in enumerate(found) for b in found[i + 1 :]]
                case "Prefix" | "Declaration" | "AnnotationAssertion" | "Import" | "Annotation":
                    pass
                case _:
                    raise UnsupportedAxiom(f"{head} is not supported")

    read(_tree(text))
    return onto


def read_owl(spark: SparkSession, path: str) -> Ontology:
    """From a file that Spark can reach; ontologies are small enough for the driver."""
    return load_owl_functional("\n".join(r.value for r in spark.read.text(path, wholetext=True).collect()))
