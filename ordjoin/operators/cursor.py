"""Anytime enumeration: batches in rank order, with no k given."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F

from ordjoin.operators.dp import Prepared, ranked
from ordjoin.operators.levels import _extend, _start, literal, sum_topk
from ordjoin.plans.jointree import JoinTree
from ordjoin.plans.model import ConjunctiveQuery
from ordjoin.plans.ranking import Rank


class OrderedCursor:
    """Batches of growing size over relations that are prepared once.

    A batch reruns the levels for all answers so far, which are counted by ``rnk``; as sizes grow by ``growth``, the
    total work stays within a constant of a single run for the last answer. Use as a context manager, or ``close`` it.
    """

    def __init__(self, q: ConjunctiveQuery, rank: Rank, first: int = 100, growth: int = 2, tree: JoinTree | None = None, prepared: Prepared | None = None) -> None:
        self.q, self.rank, self.size, self.growth, self.given = q, rank, first, growth, 0
        self.prepared = prepared or ranked(q, rank, tree).hold()
        self.done = False

    def next_batch(self) -> DataFrame:
        """The next answers, with their global ``rnk``; empty at the end."""
        total = self.given + self.size
        out = sum_topk(self.q, self.rank, total, prepared=self.prepared).where(F.col("rnk") > self.given)
        got = out.count()
        self.done = got < self.size
        self.given += got
        self.size *= self.growth
        return out

    def __iter__(self) -> Iterator[Row]:
        while not self.done:
            yield from self.next_batch().orderBy("rnk").toLocalIterator()

    def close(self) -> None:
        self.prepared.close()

    def __enter__(self) -> OrderedCursor:
        return self

    def __exit__(self, *_: object) -> None:
        self.close()


def answers_within(p: Prepared, tau: object, above: object | None = None) -> DataFrame:
    """All answers of weight state ``tau`` or less (and over ``above``), unordered: every level keeps what can still
    get there, without a limit on rows."""
    frontier, met = None, []
    for i in p.tree.order:
        fresh = [v for v in p.tree.query.atoms[i].variables if v not in met]
        frontier = _start(p).where(F.col("_prio") <= literal(tau)) if frontier is None else _extend(p, frontier, 2**62, i, fresh, 0, tau, False)
        met += fresh
    out = frontier.where(F.col("_prio") > literal(above)) if above is not None else frontier
    return out.select(*p.tree.query.head, p.rank.decode(F.col("_prio")).alias("weight"))


class RisingBound:
    """Answers between one bound and the next, again and again, without making earlier ones anew.

    The prefixes that some answer within the last bound has are kept, level by level, on the executors. A new bound adds
    deviations: rows that extend a kept prefix to a best completion between the two bounds, and all that follows from
    them. A round costs a join of the kept prefixes with their groups and what it adds. Use as a context manager.
    """

    def __init__(self, q: ConjunctiveQuery, rank: Rank, tree: JoinTree | None = None) -> None:
        self.p = ranked(q, rank, tree).hold()
        self.kept: list[list[tuple[DataFrame, int]]] = [[] for _ in self.p.tree.order]
        self.low: object | None = None

    def up_to(self, tau: object) -> DataFrame:
        """All answers of weight state ``tau`` or less that no earlier call gave, unordered."""
        p, met, new, rows = self.p, [], None, 0
        for n, i in enumerate(p.tree.order):
            fresh = [v for v in p.tree.query.atoms[i].variables if v not in met]
            met += fresh
            if new is None:
                level = _start(p).where(F.col("_prio") <= literal(tau))
                level = level if self.low is None else level.where(F.col("_prio") > literal(self.low))
            else:
                level = _extend(p, new, rows, i, fresh, 0, tau, False)  # new prefixes have given nothing yet
                for df, many in self.kept[n - 1]:  # kept ones have given all up to the last bound
                    level = level.unionByName(_extend(p, df, many, i, fresh, 0, tau, False).where(F.col("_prio") > literal(self.low)))
                self.kept[n - 1].append((new, rows))
            new = level.persist()
            rows = new.count()
        self.kept[-1].append((new, rows))
        self.low = tau
        return new.select(*p.tree.query.head, p.rank.decode(F.col("_prio")).alias("weight"))

    def close(self) -> None:
        for level in self.kept:
            for df, _ in level:
                df.unpersist()
        self.p.close()

    def __enter__(self) -> RisingBound:
        return self

    def __exit__(self, *_: object) -> None:
        self.close()


def frontier_rounds(q: ConjunctiveQuery, rank: Rank, tau0: int, step: int, growth: float = 2.0, most: int = 64) -> Iterator[DataFrame]:
    """Rounds of a rising bound: each gives all answers between the last bound and the next (integer SUM)."""
    with RisingBound(q, rank) as rounds:
        tau = tau0
        for _ in range(most):
            yield rounds.up_to(tau)
            tau, step = tau + step, max(1, int(step * growth))
