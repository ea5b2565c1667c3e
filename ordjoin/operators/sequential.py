"""Pipelined enumerators over relations that fit one process: one answer a step, in rank order, with no k given.

They serve small or pruned inputs on the driver and single partitions, and check the bulk form. Groups are Python lists
in group order; every step touches a number of rows that depends on the query alone.
"""

from __future__ import annotations

import heapq
import operator
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

from pyspark.sql import DataFrame

from ordjoin.operators.dp import Prepared, ranked, semijoin_reduce
from ordjoin.plans.jointree import JoinTree, join_tree
from ordjoin.plans.model import ConjunctiveQuery
from ordjoin.plans.ranking import Rank

MAX_LOCAL_ROWS = 2_000_000


@dataclass
class EnumStats:
    """Counters of an enumeration."""

    answers: int = 0
    pushes: int = 0
    most_open: int = 0
    visits: int = 0
    most_pushes_a_step: int = 0
    pops: list[tuple] = field(default_factory=list)


@dataclass
class Groups:
    """``rows[i][key]``: rows of atom i that meet the key, in group order, as (values, own weight, optimum)."""

    tree: JoinTree
    rows: list[dict[tuple, list[tuple]]]

    def __post_init__(self) -> None:
        order = self.tree.order
        self.at = [self.tree.order.index(self.tree.parent[i]) if self.tree.parent[i] is not None else -1 for i in order]
        self.pick = []
        for n, i in enumerate(order):
            mine = self.tree.shared(i)
            above = self.tree.query.atoms[order[self.at[n]]].variables if self.at[n] >= 0 else ()
            self.pick.append(tuple(above.index(v) for v in mine))

    def group(self, n: int, prefix: list[tuple]) -> list[tuple]:
        """Group of the n-th atom in the order under a prefix of rows."""
        if self.at[n] < 0:
            return self.rows[0].get((), [])
        values = prefix[self.at[n]][0]
        return self.rows[n].get(tuple(values[j] for j in self.pick[n]), [])

    @property
    def length(self) -> int:
        return len(self.tree.order)

    def answer(self, rows: list[tuple]) -> dict:
        out: dict = {}
        for i, r in zip(self.tree.order, rows, strict=True):
            out.update(zip(self.tree.query.atoms[i].variables, r[0], strict=True))
        return {v: out[v] for v in self.tree.query.head}


def _collected(frames: dict[int, DataFrame], limit: int) -> dict[int, list]:
    out = {}
    for i, df in frames.items():
        out[i] = df.limit(limit + 1).collect()
        if len(out[i]) > limit:
            raise MemoryError("too many rows for one process; prune by a bound or use the bulk form")
    return out


def collect_groups(p: Prepared, by_optimum: bool = True, limit: int = MAX_LOCAL_ROWS) -> Groups:
    """Bring prepared relations to this process; refuses more than ``limit`` rows."""
    return local_groups(p.tree, _collected(p.frames, limit), by_optimum)


def local_groups(tree: JoinTree, frames: dict[int, list], by_optimum: bool) -> Groups:
    out: list[dict[tuple, list[tuple]]] = []
    for i in tree.order:
        names, shared, groups = tree.query.atoms[i].variables, tree.shared(i), {}
        for r in frames[i]:
            values = tuple(r[v] for v in names)
            row = (values, r["_w"] if by_optimum else None, r["_opt"] if by_optimum else None)
            groups.setdefault(tuple(r[v] for v in shared), []).append(row)
        for g in groups.values():
            g.sort(key=(lambda x: (x[2], x[0])) if by_optimum else (lambda x: x[0]))
        out.append(groups)
    return Groups(tree, out)


class LexStack:
    """Lexicographic order with a stack of suspended alternatives."""

    def __init__(self, groups: Groups, stats: EnumStats | None = None) -> None:
        self.g, self.stats = groups, stats or EnumStats()

    def __iter__(self) -> Iterator[dict]:
        g, s = self.g, self.stats
        root = g.group(0, [])
        stack: list[tuple[list[tuple], list[int]]] = [([root[0]], [0])] if root else []
        while stack:
            rows, places = stack.pop()
            pushed = 0
            s.pops.append(tuple(places))
            rows, places = list(rows), list(places)
            # the alternative at the suspended level comes after everything below it, so it goes in first
            alternatives = [(len(rows) - 1, places[-1] + 1)]
            while len(rows) < g.length:
                s.visits += 1
                group = g.group(len(rows), rows)
                rows.append(group[0])
                places.append(0)
                alternatives.append((len(rows) - 1, 1))
            for level, place in alternatives:
                group = g.group(level, rows[:level])
                if place < len(group):
                    stack.append(([*rows[:level], group[place]], [*places[:level], place]))
                    pushed += 1
            s.pushes += pushed
            s.most_pushes_a_step = max(s.most_pushes_a_step, pushed)
            s.most_open = max(s.most_open, len(stack))
            s.answers += 1
            yield g.answer(rows)


def lex_depth_first(groups: Groups) -> Iterator[dict]:
    """The same order by recursion."""

    def grow(rows: list[tuple]) -> Iterator[dict]:
        if len(rows) == groups.length:
            yield groups.answer(rows)
            return
        for row in groups.group(len(rows), rows):
            yield from grow([*rows, row])

    yield from grow([])


class SumHeap:
    """Rank order with a priority queue of prefixes that end at a deviation.

    ``priority``: ``extend`` combines fixed weights with the optima of open groups; ``delta`` swaps one optimum for
    another in the priority of the answer at hand, which needs an inverse.
    """

    def __init__(self, groups: Groups, times: Callable = operator.add, one: object = 0, priority: str = "extend", minus: Callable | None = operator.sub, stats: EnumStats | None = None) -> None:
        self.g, self.times, self.one, self.priority, self.minus, self.stats = groups, times, one, priority, minus, stats or EnumStats()
        if priority == "delta" and minus is None:
            raise ValueError("this ranking has no inverse")

    def _extended(self, rows: list[tuple]) -> object:
        """Weight of the best completion: own weights of fixed rows and the optima of all open groups."""
        g, total = self.g, self.one
        for r in rows:
            total = self.times(total, r[1])
        for n in range(len(rows), g.length):
            if g.at[n] < len(rows):
                total = self.times(total, g.group(n, rows)[0][2])
        return total

    def __iter__(self) -> Iterator[tuple[object, dict]]:
        g, s = self.g, self.stats
        root = g.group(0, [])
        heap: list[tuple] = []
        if root:
            heap.append((root[0][2], root[0][0], [root[0]], [0]))
        while heap:
            prio, _, rows, places = heapq.heappop(heap)
            s.pops.append((prio, tuple(places)))
            deviating = len(rows) - 1
            rows, places = list(rows), list(places)
            while len(rows) < g.length:
                s.visits += 1
                rows.append(g.group(len(rows), rows)[0])
                places.append(0)
            pushed = 0
            for level in range(deviating, g.length):
                group = g.group(level, rows[:level])
                place = places[level] + 1
                if place < len(group):
                    head = [*rows[:level], group[place]]
                    new = self.times(self.minus(prio, group[place - 1][2]), group[place][2]) if self.priority == "delta" else self._extended(head)
                    heapq.heappush(heap, (new, tuple(v for r in head for v in r[0]), head, [*places[:level], place]))
                    pushed += 1
            s.pushes += pushed
            s.most_pushes_a_step = max(s.most_pushes_a_step, pushed)
            s.most_open = max(s.most_open, len(heap))
            s.answers += 1
            yield prio, g.answer(rows)


def enumerate_sum(q: ConjunctiveQuery, rank: Rank, tree: JoinTree | None = None, priority: str = "extend", stats: EnumStats | None = None) -> Iterator[tuple[object, dict]]:
    """(weight state, answer) in rank order on the driver, for relations that fit it. Kinds: sum, max, min, product, local_sum."""
    plain = {"sum": operator.add, "local_sum": operator.add, "product": operator.mul, "max": max, "min": min}
    desc = rank.descends
    times = {"max": min, "min": max}.get(rank.kind, plain[rank.kind]) if desc else plain[rank.kind]
    base = {"product": 1}.get(rank.kind, 0)
    if rank.kind in ("max", "min"):
        combine, times = times, lambda a, b: b if a is None else a if b is None else combine(a, b)
        base = None
    groups = collect_groups(ranked(q, rank, tree))
    minus = operator.sub if rank.kind in ("sum", "local_sum") else None
    yield from SumHeap(groups, times, base, priority, minus, stats)


def enumerate_lex(q: ConjunctiveQuery, tree: JoinTree | None = None, stats: EnumStats | None = None) -> Iterator[dict]:
    """Answers in the lexicographic order of the tree's variables, on the driver."""
    tree = tree or join_tree(q)
    reduced = _collected(semijoin_reduce(q, tree), MAX_LOCAL_ROWS)
    yield from LexStack(local_groups(tree, reduced, by_optimum=False), stats)
