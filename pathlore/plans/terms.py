"""Roles, tests and the symbols of the path alphabet."""

from __future__ import annotations

from dataclasses import dataclass

#: The concept that every node has.
TOP = "TOP"


@dataclass(frozen=True, order=True)
class Role:
    """A role name or its inverse."""

    name: str
    inverse: bool = False

    def inv(self) -> Role:
        return Role(self.name, not self.inverse)

    def __str__(self) -> str:
        return "^" * self.inverse + self.name


@dataclass(frozen=True)
class DataTest:
    """``key op value``; a missing key fails every test."""

    key: str
    op: str
    value: object

    def __str__(self) -> str:
        return f"{self.key}{self.op}{self.value!r}" if isinstance(self.value, str) else f"{self.key}{self.op}{self.value}"


def show_tests(tests) -> str:
    return ",".join(sorted(map(str, tests)))


@dataclass(frozen=True)
class EdgeStep:
    """One edge that has all the roles and passes all the tests.

    ``way`` is the direction in which the explicit edge must be traversed: 1 along it, -1 against it, 0 as the roles say.
    A step without roles goes along the edge unless told otherwise.
    """

    roles: frozenset[Role]
    tests: frozenset[DataTest] = frozenset()
    way: int = 0

    def __post_init__(self):
        if not self.roles:
            if not self.tests:
                raise ValueError("an edge step without roles and tests would match every pair")
            if not self.way:
                object.__setattr__(self, "way", 1)

    def inv(self) -> EdgeStep:
        return EdgeStep(frozenset(r.inv() for r in self.roles), self.tests, -self.way)

    def explicit_way(self) -> int:
        """The direction in which an explicit edge of the single role is traversed; 0 if it cannot be."""
        if len(self.roles) > 1:
            return 0
        own = next(((-1 if r.inverse else 1) for r in self.roles), self.way)
        return own if self.way in (0, own) else 0

    def __str__(self) -> str:
        inner = ",".join([*sorted(map(str, self.roles)), *sorted(map(str, self.tests))])
        return str(next(iter(self.roles))) if len(self.roles) == 1 and not self.tests else "^" * (not self.roles and self.way < 0) + "{" + inner + "}"


@dataclass(frozen=True)
class NodeTest:
    """Stay on a node that passes all the tests."""

    tests: frozenset[DataTest]

    def __str__(self) -> str:
        return f"[{show_tests(self.tests)}]"


@dataclass(frozen=True)
class LabelTest:
    """Stay on a node with the label."""

    name: str

    def __str__(self) -> str:
        return f":{self.name}"


@dataclass(frozen=True)
class Nest:
    """Stay on a node where a run of another automaton starts, at the given state or at its own starts."""

    automaton: int
    start: int | None = None

    def __str__(self) -> str:
        return f"<{self.automaton}{'' if self.start is None else f'@{self.start}'}>"

