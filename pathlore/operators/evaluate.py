"""Evaluation of automata on a graph as joins, semi-joins and semi-naive iteration.

Moves between the same two states are merged into one guard, so rewriting adds disjuncts and unions of scans rather than
joins. Automata are taken apart into strongly connected parts: between parts the plan is a plain DAG of joins; only a part
with a cycle is iterated, with new rows against visited ones, staged every round.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathlore.operators.staging import keep, release, stage, stage_pairs
from pathlore.plans.automaton import AutomatonBook, invert
from pathlore.plans.query import ConjunctivePathQuery
from pathlore.plans.terms import TOP, EdgeStep, LabelTest, Nest, NodeTest, Role
from pathlore.sources.graph import PropertyGraph, natural_key


#: Rounds after which the visited rows of an iteration are merged into one table.
MERGE_PARTS = 12
#: New rows of a round, and of these a node of the state that is iterated, from which on starts that reach a hub share what the hub reaches.
CROWD_ROWS, CROWD_PER_NODE = 200_000, 4
#: Rows that come to a loop of a step and its way back, from which on it is taken by connected parts if they also come in crowds.
PART_ROWS = 10_000
#: Edges whose connected parts are found by one task; more are laid to stars in rounds.
ONE_TASK_EDGES = 2_000_000
#: Rounds in which the starts of a connected part agree on its hub; bits for the numbers of the hubs chosen at once.
HUB_ROUNDS, CROWD_BITS = 8, 52
#: Bytes from which on the pairs of a guard that is iterated are laid out by their key once.
LAID_OUT_BYTES = 64 << 20


@dataclass
class Guard:
    """What leads from one state to another: pairs (src, dst) to follow, nodes to stay on, or staying freely."""

    pairs: DataFrame | None = None
    nodes: DataFrame | None = None
    free: bool = False

    @property
    def dead(self) -> bool:
        return self.pairs is None and self.nodes is None and not self.free


class LaidBack(dict):
    """Guards turned round, their pairs laid out by the other end when first asked for."""

    def __init__(self, guards: dict[tuple[int, int], Guard]):
        super().__init__()
        self.guards = guards

    def __missing__(self, move: tuple[int, int]) -> Guard:
        g = self.guards[move]
        turned = None if g.pairs is None else stage_pairs(g.pairs.select(F.col("dst").alias("src"), F.col("src").alias("dst")), "src", LAID_OUT_BYTES)
        self[move] = Guard(turned, g.nodes, g.free)
        return self[move]

    def release(self) -> None:
        for g in self.values():
            if g.pairs is not None:
                release(g.pairs)


@dataclass
class EvaluationStats:
    rounds: int = 0
    guards: int = 0
    dead_moves: int = 0
    crowds: int = 0


def components_in_task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """vertex and component (its least vertex) of all that edges join; all edges lie in one task."""
    held = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches]
    if not held:
        return
    src, dst = (np.concatenate(c) for c in zip(*held, strict=True))
    vertices, at = np.unique(np.concatenate([src, dst]), return_inverse=True)
    a, b = at[: len(src)], at[len(src) :]
    best = np.arange(len(vertices))
    while len(a):
        least = np.minimum(best[a], best[b])
        np.minimum.at(best, best[a], least)
        np.minimum.at(best, best[b], least)
        while (best[best] != best).any():
            best = best[best]
        open_ = best[a] != best[b]
        a, b = a[open_], b[open_]
    for i in range(0, len(vertices), 100_000):
        yield pa.RecordBatch.from_arrays([pa.array(vertices[i : i + 100_000]), pa.array(vertices[best[i : i + 100_000]])], ["vertex", "component"])


def parts_of(states: set[int], moves: set[tuple[int, int]]) -> list[list[int]]:
    """Strongly connected parts in topological order."""
    ahead = {s: {y for x, y in moves if x == s} for s in states}
    index: dict[int, int] = {}
    low: dict[int, int] = {}
    stack, out = [], []

    def visit(root: int) -> None:
        work = [(root, iter(sorted(ahead[root])))]
        index[root] = low[root] = len(index)
        stack.append(root)
        while work:
            s, rest = work[-1]
            for t in rest:
                if t not in index:
                    index[t] = low[t] = len(index)
                    stack.append(t)
                    work.append((t, iter(sorted(ahead[t]))))
                    break
                if t in stack:
                    low[s] = min(low[s], index[t])
            else:
                work.pop()
                if work:
                    low[work[-1][0]] = min(low[work[-1][0]], low[s])
                if low[s] == index[s]:
                    part = []
                    while True:
                        part.append(stack.pop())
                        if part[-1] == s:
                            break
                    out.append(sorted(part))

    for s in sorted(states):
        if s not in index:
            visit(s)
    return out[::-1]


@dataclass
class Evaluator:
    graph: PropertyGraph
    book: AutomatonBook
    binding: str = "edge"
    max_rounds: int = 1000
    #: node_id, out_roles, in_roles (see ``statistics.node_signature``): one-edge nested tests become filters on it, without a join.
    signature: DataFrame | None = None
    #: Keep the states of an iteration as bits of one row a pair instead of a row a state; pays where many states hold the same pairs.
    packed: bool = False
    stats: EvaluationStats = field(default_factory=EvaluationStats)
    _starts: dict[tuple, DataFrame | None] = field(default_factory=dict)
    _guards: dict[int, dict[tuple[int, int], Guard]] = field(default_factory=dict)
    _crowds: int = 0
    _ahead: dict[int, list[set[str]]] = field(default_factory=dict)
    _behind: dict[int, list[set[str]]] = field(default_factory=dict)
    #: Leave out moves that the kinds of nodes rule out, before anything is planned.
    typed: bool = True

    # ---- kinds: what the catalog alone rules out -------------------------------------------------------------------

    def _all_kinds(self) -> set[str]:
        return {*self.graph.kinds, "?"}

    def _passes(self, symbol) -> list[tuple[set[str], set[str]]]:
        """Kinds that a move may start at, and those that it then may lead to; for a test both are one and the same kind."""
        all_ = self._all_kinds()
        match symbol:
            case LabelTest(name):
                found = all_ if name == TOP or name in self.graph.extra else {k for k, v in self.graph.kinds.items() if name in v.labels}
                return [({k}, {k}) for k in found]
            case NodeTest(tests):
                return [({k}, {k}) for k, v in self.graph.kinds.items() if {t.key for t in tests} <= set(v.props)]
            case Nest(inner, start):
                behind = self._kinds_behind(inner)
                return [({k}, {k}) for k in set().union(*(behind[s] for s in ([start] if start is not None else self.book[inner].starts)))]
        way, keys = symbol.explicit_way(), {t.key for t in symbol.tests}
        if self.binding == "pair" and len(symbol.roles) + len(symbol.tests) > 1:
            return [(all_, all_)]
        out = []
        for name in [r.name for r in symbol.roles][:1] or sorted(self.graph.roles):
            if way and name in self.graph.roles and keys <= self.graph.role_keys(name):
                a, b = ({k} for k in self.graph.ends[name]) if name in self.graph.ends else (all_, all_)
                out.append((a, b) if way > 0 else (b, a))
        return out

    def _kinds_behind(self, n: int) -> list[set[str]]:
        """Of each state, the kinds of nodes from which a run may still be accepted."""
        if n not in self._behind:
            a = self.book[n]
            found = self._behind[n] = [self._all_kinds() if s in a.finals else set() for s in range(a.states)]
            moves = [(x, self._passes(s), y) for x, s, y in a.moves]
            grown = True
            while grown:
                grown = False
                for x, passes, y in moves:
                    more = {k for f, t in passes if t & found[y] for k in f} - found[x]
                    grown |= bool(more)
                    found[x] |= more
        return self._behind[n]

    def _kinds_ahead(self, n: int) -> list[set[str]]:
        """Of each state, the kinds of nodes that a run from a start may reach; all for automata that nested tests may restart."""
        if n not in self._ahead:
            a, all_ = self.book[n], self._all_kinds()
            nested = any(s.automaton == n for m in self.book.automata.values() for s in m.nests())
            found = self._ahead[n] = [set(all_) if nested or s in a.starts else set() for s in range(a.states)]
            moves = [(x, self._passes(s), y) for x, s, y in a.moves]
            grown = True
            while grown:
                grown = False
                for x, passes, y in moves:
                    more = {k for f, t in passes if f & found[x] for k in t} - found[y]
                    grown |= bool(more)
                    found[y] |= more
        return self._ahead[n]

    def _possible(self, n: int, x: int, symbol, y: int) -> bool:
        ahead, behind = self._kinds_ahead(n)[x], self._kinds_behind(n)[y]
        return any(f & ahead and t & behind for f, t in self._passes(symbol))

    # ---- guards --------------------------------------------------------------------------------------------------

    def step_pairs(self, step: EdgeStep) -> DataFrame | None:
        if self.binding == "pair" and len(step.roles) + len(step.tests) > 1:
            return self.same_pair(step)
        way = step.explicit_way()
        if not way:
            return None
        role = next((r.name for r in step.roles), None)
        rows = self.graph.edges(role, step.tests)
        return None if rows is None else rows if way > 0 else rows.select(F.col("dst").alias("src"), F.col("src").alias("dst"))

    def same_pair(self, step: EdgeStep) -> DataFrame | None:
        """Every role and test holds of the pair, possibly by different edges."""
        found = []
        for r in sorted(step.roles):
            found.append(self.step_pairs(EdgeStep(frozenset([r]))))
        for t in sorted(step.tests, key=str):
            found.append(self.step_pairs(EdgeStep(frozenset(), frozenset([t]), step.way or 1)))
        if any(f is None for f in found):
            return None
        return reduce(lambda a, b: a.join(b, ["src", "dst"], "left_semi"), found)

    def one_edge(self, nest: Nest) -> Role | None:
        """The role of a nested test that asks for one edge of it and nothing else."""
        a = self.book[nest.automaton]
        starts = {nest.start} if nest.start is not None else a.starts
        if len(a.moves) != 1 or starts & a.finals:
            return None
        ((x, s, y),) = a.moves
        return next(iter(s.roles)) if isinstance(s, EdgeStep) and len(s.roles) == 1 and not s.tests and not s.way and x in starts and y in a.finals else None

    def signed(self, roles: set[Role]) -> DataFrame:
        """node_id of the nodes with an edge of one of the roles, from the signature."""
        ways = [(c, sorted(r.name for r in roles if r.inverse == inverse)) for c, inverse in (("out_roles", False), ("in_roles", True))]
        return self.signature.where(reduce(Column.__or__, [F.arrays_overlap(c, F.array(*map(F.lit, names))) for c, names in ways if names])).select("node_id")

    def guards(self, n: int) -> dict[tuple[int, int], Guard]:
        """One guard for each pair of states with a move; moves that the data cannot make are left out."""
        if n in self._guards:
            return self._guards[n]
        by_pair: dict[tuple[int, int], list] = {}
        for x, s, y in self.book[n].moves:
            if self.typed and not self._possible(n, x, s, y):
                self.stats.dead_moves += 1
                continue
            by_pair.setdefault((x, y), []).append(s)
        out = {}
        for pair, symbols in by_pair.items():
            pairs, nodes, free = [], [], False
            if self.signature is not None:
                ends = [self.one_edge(s) for s in symbols if isinstance(s, Nest)]
                symbols = [s for s in symbols if not (isinstance(s, Nest) and self.one_edge(s))]
                if any(ends):
                    nodes.append(self.signed({r for r in ends if r}))
            for s in symbols:
                match s:
                    case EdgeStep():
                        pairs.append(self.step_pairs(s))
                    case LabelTest(name) if name == TOP:
                        free = True
                    case LabelTest(name):
                        nodes.append(self.graph.label_nodes(name))
                    case NodeTest(tests):
                        nodes.append(self.graph.tested_nodes(tests))
                    case Nest(inner, start):
                        nodes.append(self.starts_of(inner, start))
            self.stats.dead_moves += sum(p is None for p in [*pairs, *nodes])
            pairs, nodes = [p for p in pairs if p is not None], [p for p in nodes if p is not None]
            g = Guard(reduce(DataFrame.unionByName, pairs) if pairs else None, reduce(DataFrame.unionByName, nodes) if nodes and not free else None, free)
            if not g.dead:
                out[pair] = g
                self.stats.guards += 1
        self._guards[n] = out
        return out

    # ---- nested tests: nodes from which an accepting run starts ---------------------------------------------------

    def starts_of(self, n: int, start: int | None = None) -> DataFrame | None:
        """node_id of the nodes where a run can start; found backwards from the final states, so linear in the graph."""
        if (n, start) not in self._starts:
            a = self.book[n]
            ends = self._backward(n)
            found = [ends[s] for s in ([start] if start is not None else sorted(a.starts)) if s in ends]
            rows = reduce(DataFrame.unionByName, found) if found else None
            self._starts[n, start] = None if rows is None else keep(rows.distinct())
        return self._starts[n, start]

    def before(self, g: Guard, then: DataFrame | None, final: bool = False) -> list[DataFrame]:
        """Nodes from which the guard leads into the set; a final state accepts every node."""
        out = []
        if g.pairs is not None:
            rows = g.pairs if final else g.pairs.join(then.withColumnRenamed("node_id", "dst"), "dst", "left_semi")
            out.append(rows.select(F.col("src").alias("node_id")))
        if g.nodes is not None:
            out.append(g.nodes if final else g.nodes.join(then, "node_id", "left_semi"))
        if g.free:
            out.append(self.graph.all_nodes() if final else then)
        return out

    def _backward(self, n: int) -> dict[int, DataFrame]:
        if (n, "all") in self._starts:
            return self._starts[n, "all"]
        a, guards = self.book[n], self.guards(n)
        sets: dict[int, DataFrame] = {}

        for part in reversed(parts_of(set(range(a.states)), set(guards))):
            for s in part:
                if s in a.finals:
                    sets[s] = self.graph.all_nodes()
            outer = {s: [] for s in part}
            for (x, y), g in guards.items():
                if x in outer and (y in sets or y in a.finals) and (y not in part or y in a.finals) and x not in a.finals:
                    outer[x] += self.before(g, sets.get(y), y in a.finals)
            seeds = {s: reduce(DataFrame.unionByName, rows).distinct() for s, rows in outer.items() if rows}
            inner = {p: g for p, g in guards.items() if p[0] in part and p[1] in part and p[0] not in a.finals and p[1] not in a.finals}
            if not inner:
                sets |= seeds
                continue
            if seeds:
                links = {(y, x): (lambda rows, g=g: self.before(g, rows)) for (x, y), g in inner.items()}
                sets |= self._fixpoint(seeds, links, part)
        self._starts[n, "all"] = sets
        return sets

    # ---- pairs ---------------------------------------------------------------------------------------------------

    def advance(self, rows: DataFrame | None, g: Guard) -> list[DataFrame]:
        """``rows`` (src, node) after the guard; None stands for all (v, v)."""
        out = []
        if g.pairs is not None:
            out.append(g.pairs.select("src", F.col("dst").alias("node")) if rows is None else rows.join(g.pairs.select(F.col("src").alias("node"), F.col("dst").alias("_to")), "node").select("src", F.col("_to").alias("node")))
        if g.nodes is not None:
            same = g.nodes.select("node_id")
            out.append(same.select(F.col("node_id").alias("src"), F.col("node_id").alias("node")) if rows is None else rows.join(same.withColumnRenamed("node_id", "node"), "node", "left_semi").select("src", "node"))
        if g.free:
            out.append(self.identity() if rows is None else rows)
        return out

    def identity(self) -> DataFrame:
        return self.graph.all_nodes().select(F.col("node_id").alias("src"), F.col("node_id").alias("node"))

    def pairs_of(self, n: int, seeds: DataFrame | None = None, ends: DataFrame | None = None) -> DataFrame:
        """(src, node) for every run; ``seeds`` (node_id) restricts where runs start, ``ends`` (node_id) where they end."""
        rows, crowds = self._runs(n, seeds, ends)
        return self._expand(rows, crowds)

    def _runs(self, n: int, seeds: DataFrame | None = None, ends: DataFrame | None = None) -> tuple[DataFrame, list[DataFrame]]:
        """As ``pairs_of``, with crowds in their members' place."""
        crowds: list[DataFrame] = []
        at = self._states(n, seeds, self._useful(n), crowds)
        found = [at[s] if at[s] is not None else self.identity() for s in sorted(self.book[n].finals) if s in at]
        if not found:
            return self.graph.spark.createDataFrame([], "src long, node long"), []
        rows = reduce(DataFrame.unionByName, found).distinct()
        if ends is not None:
            rows = rows.join(ends.withColumnRenamed("node_id", "node"), "node", "left_semi").select("src", "node")
        return rows, crowds

    def count_pairs(self, n: int) -> int:
        """The number of rows of ``pairs_of``: the first crowds are counted, members times nodes, and not written out."""
        rows, crowds = self._runs(n)
        if not crowds:
            return rows.count()
        others, of_crowds = self._apart(self._expand(rows, crowds[1:]), crowds[0])
        sizes = crowds[0].groupBy(F.col("crowd").alias("src")).agg(F.count("*").alias("members"))
        held = of_crowds.groupBy("src").agg(F.count("*").alias("nodes")).join(sizes, "src")
        return others.count() + (held.agg(F.sum(F.col("members") * F.col("nodes"))).first()[0] or 0)

    @staticmethod
    def _apart(rows: DataFrame, members: DataFrame) -> tuple[DataFrame, DataFrame]:
        """The rows of starts that are no crowd, without those that the start's crowd has; and the crowds' rows."""
        rows = keep(rows)
        own = members.select(F.col("member").alias("src"), F.col("crowd").alias("_crowd"))
        of_crowds = rows.join(members.select(F.col("crowd").alias("src")).distinct(), "src", "left_semi")
        others = rows.join(members.select(F.col("crowd").alias("src")).distinct(), "src", "left_anti").join(own, "src", "left")
        return others.join(of_crowds.select(F.col("src").alias("_crowd"), "node"), ["_crowd", "node"], "left_anti").select("src", "node"), of_crowds

    def _expand(self, rows: DataFrame, crowds: list[DataFrame]) -> DataFrame:
        """Replace crowds by their members, the last crowd first: it may hold earlier ones.

        Distinct rows stay distinct: a member, which is in one crowd, loses the rows of its own that its crowd has, so the product is not sorted out again.
        """
        for members in reversed(crowds):
            others, of_crowds = self._apart(rows, members)
            own = members.select(F.col("member").alias("src"), F.col("crowd").alias("_crowd"))
            rows = others.unionByName(of_crowds.withColumnRenamed("src", "_crowd").join(own, "_crowd").select("src", "node"))
        return rows

    def one_kind(self, n: int) -> bool:
        """Whether all runs start at nodes of one kind and end at nodes of one: then their natural keys tell them apart."""
        a = self.book[n]
        ends = [set().union(*(found[s] for s in states)) for found, states in ((self._kinds_behind(n), a.starts), (self._kinds_ahead(n), a.finals))]
        return all(len(kinds) == 1 and "?" not in kinds for kinds in ends)

    # ---- loops of a step and its way back: connected parts ----------------------------------------------------------

    def _there_and_back(self, n: int, inner: dict[tuple[int, int], Guard]) -> bool:
        """Whether two states' moves are the same edges, there and back, and nothing else."""
        if self.binding != "edge" or len(inner) != 2 or any(g.nodes is not None or g.free for g in inner.values()):
            return False
        ways: dict[tuple[int, int], set] = {p: set() for p in inner}
        for x, s, y in self.book[n].moves:
            if (x, y) in ways and not (self.typed and not self._possible(n, x, s, y)) and self.step_pairs(s) is not None:
                ways[x, y].add((next((r.name for r in s.roles), None), s.tests, s.explicit_way()))
        (p, q), (back, again) = inner
        return (p, q) == (again, back) and ways[p, q] == {(role, tests, -way) for role, tests, way in ways[q, p]}

    def _components(self, pairs: DataFrame) -> DataFrame:
        """vertex and component (its least vertex) of all that pairs join: edges are laid to the least neighbour, of greater and of lesser vertices in turn, until all are stars."""
        if pairs.count() <= ONE_TASK_EDGES:
            return stage(pairs.repartition(1).mapInArrow(components_in_task, "vertex long, component long"), "parts")
        edges, before = stage(pairs.select(F.greatest("src", "dst").alias("high"), F.least("src", "dst").alias("low")).distinct(), "links"), None
        for _ in range(self.max_rounds):
            least = edges.select(F.col("high").alias("v"), F.col("low").alias("w")).unionByName(edges.select(F.col("low").alias("v"), F.col("high").alias("w")))
            least = least.groupBy("v").agg(F.least(F.min("w"), F.col("v")).alias("to"))
            large = edges.join(least.withColumnRenamed("v", "low"), "low").select("high", F.col("to").alias("low")).distinct()
            least = large.groupBy("high").agg(F.min("low").alias("to"))
            small = large.join(least, "high").where("low <> to").select(F.col("low").alias("high"), F.col("to").alias("low")).unionByName(least.select("high", F.col("to").alias("low")))
            old, edges = edges, stage(small.distinct(), "links")
            release(old)
            now = tuple(edges.agg(F.count("*"), F.bit_xor(F.xxhash64("high", "low"))).first())
            if now == before:
                roots = edges.select(F.col("low").alias("vertex")).distinct().select("vertex", F.col("vertex").alias("component"))
                return edges.select(F.col("high").alias("vertex"), F.col("low").alias("component")).unionByName(roots)
            before = now
        raise RuntimeError("the components did not settle")

    def _by_parts(self, seeds: dict[int, DataFrame], inner: dict[tuple[int, int], Guard], crowds: list[DataFrame]) -> dict[int, DataFrame]:
        """All rows of a loop of a step and its way back: what a node reaches is its connected part.

        Starts that come to the same parts are members of one crowd. Rows at nodes without an edge stay as they are.
        """
        self.stats.crowds += 1
        (p, q), g = next(iter(inner.items()))
        #: Nodes at the second state have numbers below zero: a node that may be at both states is two vertices.
        found = self._components(g.pairs.select("src", (-1 - F.col("dst")).alias("dst")))
        of = {p: found.where("vertex >= 0").select(F.col("vertex").alias("node"), "component"), q: found.where("vertex < 0").select((-1 - F.col("vertex")).alias("node"), "component")}
        came = reduce(DataFrame.unionByName, [rows.join(of[s], "node").select("src", "component") for s, rows in seeds.items()])
        sets = stage(came.groupBy("src").agg(F.sort_array(F.collect_set("component")).alias("parts")), "parts")
        self._crowds += 1
        number = F.lit(-1 - (self._crowds << CROWD_BITS)) - F.monotonically_increasing_id()
        numbered = stage(sets.select("parts").distinct().select("parts", number.alias("crowd")), "crowds")
        crowds.append(stage(sets.join(numbered, "parts").select("crowd", F.col("src").alias("member")), "members"))
        each = numbered.select(F.col("crowd").alias("src"), F.explode("parts").alias("component"))
        out = {s: each.join(of[s], "component").select("src", "node") for s in (p, q)}
        return {s: rows.unionByName(seeds[s].join(of[s], "node", "left_anti").select("src", "node")) if s in seeds else rows for s, rows in out.items()}

    def _states(self, n: int, seeds: DataFrame | None, within: set[int], crowds: list[DataFrame]) -> dict[int, DataFrame | None]:
        """(src, node) at each of the states ``within``; None: all (v, v). A src below zero is a crowd, whose members are in ``crowds``."""
        a, guards = self.book[n], self.guards(n)
        at: dict[int, DataFrame | None] = {}
        begin = None if seeds is None else seeds.select(F.col("node_id").alias("src"), F.col("node_id").alias("node")).distinct()
        for part in parts_of(within, {p for p in guards if set(p) <= within}):
            incoming: dict[int, list] = {s: [] for s in part}
            for (x, y), g in guards.items():
                if y in incoming and x in at and x not in part:
                    incoming[y] += self.advance(at[x], g)
            inner = {p: g for p, g in guards.items() if p[0] in part and p[1] in part}
            for s in part:
                if s in a.starts:
                    if not incoming[s] and not inner and begin is None:
                        at[s] = None
                    else:
                        incoming[s].append(self.identity() if begin is None else begin)
            rows = {s: reduce(DataFrame.unionByName, r) for s, r in incoming.items() if r}
            if not inner:
                at |= {s: r.distinct() for s, r in rows.items()}
                continue
            if not rows:
                continue
            populations = self._populations(n, part)
            if not self.packed and populations and self._there_and_back(n, inner):
                rows = {s: stage(r.distinct(), "seeds") for s, r in rows.items()}
                if sum(r.count() for r in rows.values()) >= max(PART_ROWS, CROWD_PER_NODE * min(populations.values())):
                    at |= self._by_parts(rows, inner, crowds)
                    continue
            laid = {k: Guard(None if g.pairs is None else stage_pairs(g.pairs, "src", LAID_OUT_BYTES), g.nodes, g.free) for k, g in inner.items()}
            links = {k: (lambda r, g=g: self.advance(r, g)) for k, g in laid.items()}
            turned = LaidBack(inner)
            back = {(y, x): (lambda r, k=(x, y): self.advance(r, turned[k])) for x, y in inner}
            at |= self._fixpoint(rows, links, part, populations, back, crowds)
            turned.release()
        return at

    def linked(self, n: int, pairs: DataFrame) -> DataFrame:
        """Those of the pairs (src, dst) that a run of the automaton joins.

        Runs are sought from both ends and meet at a cut of the automaton, so a hub between the two sides is never multiplied out: the
        cut lies where the least of the moves before it lead from one node to many, and of those behind it backwards.
        """
        useful = self._useful(n)
        order = parts_of(useful, {p for p in self.guards(n) if set(p) <= useful})
        moves = [p for p in self.guards(n) if set(p) <= useful]

        def cost(k: int) -> tuple[int, int]:
            left = {s for part in order[:k] for s in part}
            wide = sum(self._fans_out(n, p, True) for p in moves if set(p) <= left) + sum(self._fans_out(n, p, False) for p in moves if p[1] not in left)
            return wide, abs(2 * k - len(order))

        left = {s for part in order[: min(range(1, len(order) + 1), key=cost)] for s in part} if order else set()
        right = useful - left
        crowds: tuple[list, list] = ([], [])
        ahead = self._states(n, pairs.select(F.col("src").alias("node_id")).distinct(), left, crowds[0])
        turned = invert(self.book, n)
        gates = {x for x, y in moves if x in left and y in right}
        behind = {}
        if right:
            behind = self._states(turned, pairs.select(F.col("dst").alias("node_id")).distinct(), right, crowds[1])
            for s in sorted(gates):
                rows = [r for (x, y), g in self.guards(turned).items() if y == s and x in behind for r in self.advance(behind[x], g)]
                if rows:
                    behind[s] = reduce(DataFrame.unionByName, rows).distinct()
        found = []
        for s in sorted(left & set(ahead)):
            here = self._expand(ahead[s], crowds[0])
            if s in self.book[n].finals:
                found.append(pairs.join(here.withColumnRenamed("node", "dst"), ["src", "dst"], "left_semi"))
            if s in gates and s in behind:
                there = self._expand(behind[s], crowds[1]).select(F.col("src").alias("dst"), "node")
                found.append(pairs.join(here, "src").join(there, ["dst", "node"], "left_semi").select("src", "dst"))
        return reduce(DataFrame.unionByName, found).distinct() if found else pairs.limit(0)

    def _fans_out(self, n: int, move: tuple[int, int], ahead: bool) -> bool:
        """Whether the moves between two states may lead from one node to many (backwards: into one from many)."""
        for x, s, y in self.book[n].moves:
            if (x, y) == move and isinstance(s, EdgeStep):
                role = next(iter(s.roles), None)
                if role is None or self.graph.single.get(role.name, (False, False))[int(ahead == role.inverse)] is False and role.name in self.graph.roles:
                    return True
        return False

    def _useful(self, n: int) -> set[int]:
        """States on a way from a start to a final state by guards that the data can make."""
        a, guards = self.book[n], self.guards(n)
        ahead, back = set(a.starts), set(a.finals)
        while True:
            more = {y for x, y in guards if x in ahead} - ahead
            less = {x for x, y in guards if y in back} - back
            if not more and not less:
                return ahead & back
            ahead |= more
            back |= less

    def _populations(self, n: int, part: list[int]) -> dict[int, int]:
        """How many nodes a state can hold, from the kinds that its edges lead to; states without an estimate are absent."""
        out = {}
        for s in part:
            kinds: set[str] | None = set()
            for x, symbol, y in self.book[n].moves:
                if y != s or kinds is None or x == y:
                    continue
                role = next(iter(symbol.roles), None) if isinstance(symbol, EdgeStep) else None
                if role is None or role.name not in self.graph.roles:
                    kinds = kinds if isinstance(symbol, EdgeStep) and role is not None else None
                elif role.name in self.graph.ends:
                    kinds.add(self.graph.ends[role.name][0 if role.inverse else 1])
                else:
                    kinds = None
            if kinds:
                out[s] = sum(self.graph.kind_size(k) for k in kinds if k in self.graph.kinds)
        return out

    def _fixpoint(self, seeds: dict[int, DataFrame], links: dict[tuple[int, int], Callable], part: list[int], populations: dict[int, int] | None = None, back: dict[tuple[int, int], Callable] | None = None, crowds: list[DataFrame] | None = None) -> dict[int, DataFrame]:
        """All rows of the states of a cyclic part, semi-naively.

        Only the states that cut all cycles are iterated: a round takes their new rows through the other states, which are
        in topological order then, in one plan. Visited rows stay as the parts in which they came and are merged when there
        are many. Only the number of a round's rows comes to the driver. Once pairs come in crowds (many starts at each
        node; ``back`` and ``crowds`` given), or will by the next round, the starts that reach a hub share what it reaches, see ``_crowd``.
        """
        cut = cycle_cut(part, set(links), populations)
        rest = [p[0] for p in parts_of(set(part) - set(cut), {k for k in links if not set(k) & set(cut)})]
        columns = next(iter(seeds.values())).columns
        prune: Callable[[DataFrame], DataFrame] = lambda rows: rows
        shared: dict[int, DataFrame] = {}

        def spread(at: dict[int, DataFrame], more: dict[int, DataFrame]) -> dict[int, DataFrame]:
            out = dict(at)
            for s in rest:
                found = [r for (x, y), f in links.items() if y == s and x in out for r in f(out[x])] + ([more[s]] if s in more else [])
                if found:
                    out[s] = reduce(DataFrame.unionByName, found).distinct()
            return out

        def back_to_cut(at: dict[int, DataFrame]) -> list[DataFrame]:
            return [r.select(*columns, F.lit(y).alias("state")) for (x, y), f in links.items() if y in cut and x in at for r in f(at[x])]

        bit = {s: 1 << i for i, s in enumerate(cut)}
        packed = self.packed and 1 < len(cut) < 63
        bit_of = F.element_at(F.create_map(*(F.lit(x) for s in cut for x in (s, bit[s]))), F.col("state")).cast("long")

        def pack(rows: DataFrame) -> DataFrame:
            """Distinct rows, of packed states one row for all."""
            return rows.groupBy(*columns).agg(F.bit_or(bit_of).alias("states")) if packed else rows.distinct()

        def news(rows: DataFrame, parts: list[DataFrame]) -> DataFrame:
            """What no earlier round brought."""
            seen = reduce(DataFrame.unionByName, parts)
            if not packed:
                return rows.join(seen, [*columns, "state"], "left_anti")
            seen = seen.groupBy(*columns).agg(F.bit_or("states").alias("_seen"))
            left = F.col("states").bitwiseAND(F.bitwise_not(F.coalesce("_seen", F.lit(0).cast("long"))))
            return rows.join(seen, columns, "left").select(*columns, left.alias("states")).where("states <> 0")

        def by_state(rows: DataFrame) -> dict[int, DataFrame]:
            return {s: rows.where(F.col("states").bitwiseAND(F.lit(bit[s])) != 0 if packed else F.col("state") == s).select(*columns) for s in cut}

        first = back_to_cut(spread({}, seeds)) + [seeds[s].select(*columns, F.lit(s).alias("state")) for s in cut if s in seeds]
        if not first:
            return spread({}, seeds)
        fresh = stage(pack(reduce(DataFrame.unionByName, first)), "fresh")
        parts = [fresh]
        last = None
        may_crowd = not packed and back is not None and crowds is not None and set(cut) <= set(populations or {})
        for _ in range(self.max_rounds):
            if may_crowd:
                many = fresh.agg(F.count("*").alias("n"), F.countDistinct("src").alias("starts")).first()
                #: Rows of the next round, if rows go on to grow as they did in this one.
                ahead, last = many.n * many.n // max(1, last or many.starts), many.n
            if may_crowd and max(many.n, ahead) >= max(CROWD_ROWS, CROWD_PER_NODE * sum(populations[s] for s in cut)):
                may_crowd = False
                prune, shared = self._crowd(seeds, fresh, links, back, part, cut, populations, crowds)
                pruned = stage(prune(fresh), "fresh")
                parts = [stage(prune(p), "seen") for p in parts if p is not fresh] + [pruned]
                fresh = pruned
            moved = back_to_cut(spread(by_state(fresh), {}))
            if not moved:
                break
            self.stats.rounds += 1
            if len(parts) > MERGE_PARTS:
                merged = stage(reduce(DataFrame.unionByName, parts), "seen")
                for old in parts:
                    if old is not fresh:
                        release(old)
                parts = [merged]
            fresh = stage(prune(news(pack(reduce(DataFrame.unionByName, moved)), parts)), "fresh")
            if fresh.isEmpty():
                break
            parts.append(fresh)
        else:
            raise RuntimeError("the iteration did not end")
        own = by_state(reduce(DataFrame.unionByName, parts))
        return spread({s: r.unionByName(shared[s]) if s in shared else r for s, r in own.items()}, seeds)

    def _hubs(self, fresh: DataFrame) -> DataFrame:
        """crowd (a number below zero), node and state: of each connected part of the new rows the node, in a state, with most of them.

        Starts and nodes tell one another the greatest that they know of for a few rounds. If these are too few for a part, it gets
        several hubs, which costs time and no answer.
        """
        popular = fresh.groupBy("node", "state").agg(F.count("*").alias("n"))
        known = popular.select("node", "state", F.struct("n", (-F.col("state")).alias("s"), (-F.col("node")).alias("v")).alias("best"))
        before = None
        for _ in range(HUB_ROUNDS):
            of_start = fresh.join(known, ["node", "state"]).groupBy("src").agg(F.max("best").alias("best"))
            hubs = stage(of_start.select("src", "best"), "hubs")
            if (n := hubs.select("best").distinct().count()) == 1 or n == before:
                break
            before = n
            known = fresh.join(hubs, "src").groupBy("node", "state").agg(F.max("best").alias("best"))
        chosen = hubs.select("best").distinct().select((-F.col("best.v")).alias("node"), (-F.col("best.s")).cast("int").alias("state"))
        self._crowds += 1
        return stage(chosen.select((F.lit(-1 - (self._crowds << CROWD_BITS)) - F.monotonically_increasing_id()).alias("crowd"), "node", "state"), "hubs")

    def _crowd(self, seeds: dict[int, DataFrame], fresh: DataFrame, links: dict, back: dict, part: list[int], cut: list[int], populations: dict[int, int], crowds: list[DataFrame]) -> tuple[Callable, dict[int, DataFrame]]:
        """Let all starts that reach a hub share what the hub reaches.

        A hub is the node, in a state, with most of a connected part's new rows. What hubs reach, and what reaches them, are sets of nodes of each
        hub, found in time linear in the graph where parts do not overlap. The starts among the latter become members of a hub's crowd, one each, which takes
        their place in the rows that the hub gives; of their own they keep only rows elsewhere. Members take the crowd's place again in the result.
        """
        self.stats.crowds += 1
        hubs = self._hubs(fresh)
        states = [r.state for r in hubs.select("state").distinct().collect()]  # as many as the automaton has at most
        at = lambda s: hubs.where(F.col("state") == s).select(F.col("crowd").alias("src"), "node")
        reached = self._fixpoint({s: at(s) for s in states}, links, part, populations)
        reached = stage(reduce(DataFrame.unionByName, [reached[s].select("src", "node", F.lit(s).alias("state")) for s in cut if s in reached]).distinct(), "reached")
        reaching = self._fixpoint({s: at(s) for s in states}, back, part, populations)
        members = [rows.join(reaching[s].select("node", F.col("src").alias("crowd")), "node").select("crowd", "src") for s, rows in seeds.items() if s in reaching]
        members = stage(reduce(DataFrame.unionByName, members).groupBy("src").agg(F.max("crowd").alias("crowd")).select("crowd", F.col("src").alias("member")), "members")
        crowds.append(members)
        covered = reached.select(F.col("src").alias("crowd"), "node", "state")
        in_crowd = members.select(F.col("member").alias("src"), "crowd")

        def prune(rows: DataFrame) -> DataFrame:
            return rows.join(in_crowd, "src", "left").join(covered, ["crowd", "node", "state"], "left_anti").select(*rows.columns)

        joined = members.select(F.col("crowd").alias("src")).distinct()
        used = stage(reached.join(joined, "src", "left_semi").select("src", "node", "state"), "shared")
        return prune, {s: used.where(F.col("state") == s).select("src", "node") for s in cut}


def cycle_cut(part: list[int], moves: set[tuple[int, int]], populations: dict[int, int] | None = None) -> list[int]:
    """States without which the part has no cycle: greedily the one that can hold fewest nodes, then the one on most moves."""
    held = populations or {}
    left, cut = set(part), []
    while True:
        own = {(x, y) for x, y in moves if x in left and y in left}
        loops = [p for p in parts_of(left, own) if len(p) > 1 or (p[0], p[0]) in own]
        if not loops:
            return cut
        states = {s for p in loops for s in p}
        worst = max(sorted(states), key=lambda s: ((s, s) in own, -held.get(s, max(held.values(), default=0)), sum(x == s for x, y in own if y in states) * sum(y == s for x, y in own if x in states)))
        cut.append(worst)
        left.remove(worst)


def selective(book: AutomatonBook, n: int, states: set[int], out: bool) -> int:
    """How selective the moves at one end are: 2 for value tests and nested tests, 1 for labels, 0 for plain edges or loops."""
    a, best = book[n], 3
    for x, s, y in a.moves:
        if (x if out else y) in states:
            best = min(best, 2 if isinstance(s, (NodeTest, Nest)) or isinstance(s, EdgeStep) and s.tests else 1 if isinstance(s, LabelTest) and s.name != TOP else 0)
    return 0 if best == 3 or a.starts & a.finals else best


def first_nodes(ev: Evaluator, n: int) -> DataFrame | None:
    """The nodes that pass the first guards of an automaton, where these are tests only; None if any edge may come first."""
    a, found = ev.book[n], []
    if a.starts & a.finals:
        return None
    for (x, _), g in ev.guards(n).items():
        if x in a.starts:
            if g.nodes is None or g.pairs is not None or g.free:
                return None
            found.append(g.nodes.select("node_id"))
    return reduce(DataFrame.unionByName, found).distinct() if found else None


def starts_at_right(ev: Evaluator, n: int, left: DataFrame | None, right: DataFrame | None) -> bool:
    """Whether a binary atom is better run backwards. Runs with cycles keep all their start nodes, so these are counted."""
    a = ev.book[n]
    if all(len(part) == 1 and (part[0], part[0]) not in ev.guards(n) for part in parts_of(set(range(a.states)), set(ev.guards(n)))):
        return left is None and (right is not None or selective(ev.book, n, a.finals, False) > selective(ev.book, n, a.starts, True))
    ends = [left if left is not None else first_nodes(ev, n), right if right is not None else first_nodes(ev, invert(ev.book, n))]
    if ends[0] is None or ends[1] is None:
        return ends[1] is not None
    return ends[1].count() < ends[0].count()


def has_answer(q: ConjunctivePathQuery, graph: PropertyGraph, **how) -> bool:
    """Whether there is an answer: Spark stops at the first."""
    return not answer(q, graph, **how).isEmpty()


def count_answers(q: ConjunctivePathQuery, graph: PropertyGraph) -> int:
    """The number of rows of ``answer``. Of one binary atom it is found without writing out crowds, where kinds of nodes keep keys apart."""
    ev = Evaluator(graph, q.book.copy())
    if len(q.atoms) == 1 and q.atoms[0][1] != q.atoms[0][2] and set(q.answer) == set(q.atoms[0][1:]):
        n = q.atoms[0][0]
        if starts_at_right(ev, n, None, None):
            n = invert(ev.book, n)
        if ev.one_kind(n):
            return ev.count_pairs(n)
    return answer(q, graph, evaluator=ev).count()


def answer(q: ConjunctivePathQuery, graph: PropertyGraph, binding: str = "edge", bindings: dict[str, DataFrame] | None = None, decode: bool = True, evaluator: Evaluator | None = None, limit: int | None = None) -> DataFrame:
    """Answers of a query whose variables are all answered (see ``bind_existentials``), one column a variable.

    Unary atoms come first and seed the binary ones; a binary atom starts at the end that is bound or more selective.
    ``bindings`` restricts variables to the node_id of a table. Columns hold natural keys unless ``decode`` is off.
    ``limit``: any that many answers.
    """
    ev = evaluator or Evaluator(graph, q.book.copy(), binding)
    book = ev.book
    sets: dict[str, list[DataFrame]] = {v: [rows.select("node_id")] for v, rows in (bindings or {}).items()}
    joined: DataFrame | None = None
    done: set[str] = set()
    #: Whether natural keys tell the answers of all atoms with two variables apart.
    apart = True

    def of(v: str) -> DataFrame | None:
        return reduce(lambda a, b: a.join(b, "node_id", "left_semi"), sets[v]) if sets.get(v) else None

    binary = []
    for n, x, y in q.atoms:
        a = book[n]
        only = [s for _, s, _ in a.moves]
        if x == y and all(not isinstance(s, EdgeStep) for s in only):
            rows = ev.starts_of(n)
            sets.setdefault(x, []).append(rows if rows is not None else graph.spark.createDataFrame([], "node_id long"))
        else:
            binary.append((n, x, y))
    while binary:
        known = done | set(sets)
        n, x, y = min(binary, key=lambda b: (-len({b[1], b[2]} & done), -len({b[1], b[2]} & known), q.atoms.index(b)))
        binary.remove((n, x, y))
        apart = apart and x != y and ev.typed and ev.one_kind(n)
        if x != y and {x, y} <= done:
            known = stage(joined.select(F.col(x).alias("src"), F.col(y).alias("dst")).distinct(), "known")
            rows = ev.linked(n, known).select(F.col("src").alias(x), F.col("dst").alias(y))
            joined = rows if set(joined.columns) == {x, y} else joined.join(rows, [x, y], "left_semi")
            continue
        left = of(x) if x not in done else joined.select(F.col(x).alias("node_id")).distinct()
        right = of(y) if y not in done else joined.select(F.col(y).alias("node_id")).distinct()
        if starts_at_right(ev, n, left, right):
            rows = ev.pairs_of(invert(book, n), right, left).select(F.col("node").alias("src"), F.col("src").alias("node"))
        else:
            rows = ev.pairs_of(n, left, right)
        if x == y:
            rows = rows.where("src = node").select(F.col("src").alias(x))
        else:
            rows = rows.select(F.col("src").alias(x), F.col("node").alias(y))
        joined = rows if joined is None else joined.join(rows, [v for v in dict.fromkeys((x, y)) if v in done], "inner")
        done |= {x, y}
    #: Runs are distinct pairs, and joins of distinct rows are distinct while no variable is left out: only sets may repeat a node.
    whole = done <= set(q.answer)
    for v in q.answer:
        if v not in done:
            if joined is not None:
                raise ValueError(f"variable {v} is not connected")
            joined, whole, apart = of(v).withColumnRenamed("node_id", v), False, False
            done.add(v)
    out = joined.select(*q.answer)
    if not whole and (limit is not None or not decode):
        out = out.distinct()
    out = out if limit is None else out.limit(limit)
    if not decode:
        return out
    out = out.select(*(natural_key(v).alias(v) for v in q.answer))
    return out if whole and apart else out.distinct()


