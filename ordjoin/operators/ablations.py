"""The design choices switched off one by one: the same answers, more work. Counters show what each one saves."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ordjoin.operators.dp import Prepared, ranked, semijoin_reduce, with_all
from ordjoin.operators.sequential import EnumStats, Groups, LexStack, SumHeap, local_groups
from ordjoin.plans.jointree import JoinTree, join_tree
from ordjoin.plans.model import ConjunctiveQuery
from ordjoin.plans.ranking import Rank


@dataclass
class SearchStats(EnumStats):
    """``dead``: prefixes that had no completion."""

    dead: int = 0


def _rows(frames: dict[int, DataFrame]) -> dict[int, list]:
    return {i: df.collect() for i, df in frames.items()}


def backtrack(q: ConjunctiveQuery, tree: JoinTree | None = None, reduced: bool = False, stats: SearchStats | None = None) -> Iterator[dict]:
    """Answers in the tree's lexicographic order by search; without reduction it runs into dead ends. Small inputs only."""
    tree, stats = tree or join_tree(q), stats or SearchStats()
    frames = semijoin_reduce(q, tree) if reduced else {i: a.frame for i, a in enumerate(q.atoms)}
    groups = local_groups(tree, _rows(frames), by_optimum=False)

    def grow(rows: list[tuple]) -> Iterator[dict]:
        if len(rows) == groups.length:
            stats.answers += 1
            yield groups.answer(rows)
            return
        stats.visits += 1
        before = stats.answers
        for row in groups.group(len(rows), rows):
            yield from grow([*rows, row])
        if stats.answers == before:
            stats.dead += 1

    yield from grow([])


def optima_without_memo(groups: Groups) -> tuple[int, int]:
    """(evaluations of a group's optimum when each use recomputes it, with one memo a group)."""
    tree = groups.tree
    order = tree.order
    below = {n: [m for m in range(len(order)) if groups.at[m] == n] for n in range(len(order))}
    seen: set[tuple[int, tuple]] = set()
    plain = 0

    def visit(n: int, key: tuple) -> None:
        nonlocal plain
        plain += 1
        seen.add((n, key))
        for row in groups.rows[n].get(key, []):
            for m in below[n]:
                visit(m, tuple(row[0][j] for j in groups.pick[m]))

    visit(0, ())
    return plain, len(seen)


def stack_against_queue(q: ConjunctiveQuery, tree: JoinTree | None = None) -> tuple[EnumStats, EnumStats]:
    """Counters of one lexicographic enumeration by the stack, and by the priority queue with value vectors as weights."""
    tree = tree or join_tree(q)
    rows = _rows(semijoin_reduce(q, tree))
    plain = local_groups(tree, rows, by_optimum=False)
    stack, queue = EnumStats(), EnumStats()
    for _ in LexStack(plain, stack):
        pass
    order = tree.met()
    charged = tree.charged()
    vectors = Groups(tree, [dict(g) for g in plain.rows])
    for n in reversed(range(len(tree.order))):
        i = tree.order[n]
        names = tree.query.atoms[i].variables
        for key, group in vectors.rows[n].items():
            new = []
            for values, *_ in group:
                own = tuple(values[names.index(v)] if v in names and charged[v] == i else 0 for v in order)
                best = own
                for m in (m for m in range(len(tree.order)) if vectors.at[m] == n):
                    best = tuple(a + b for a, b in zip(best, vectors.rows[m][tuple(values[j] for j in vectors.pick[m])][0][2], strict=True))
                new.append((values, own, best))
            vectors.rows[n][key] = sorted(new, key=lambda r: (r[2], r[0]))
    zero = tuple(0 for _ in order)
    for _ in SumHeap(vectors, lambda a, b: tuple(x + y for x, y in zip(a, b, strict=True)), zero, minus=None, stats=queue):
        pass
    return stack, queue


def reduction_sizes(q: ConjunctiveQuery, tree: JoinTree | None = None) -> DataFrame:
    """(relation, raw_rows, reduced_rows, full_rows): rows of each atom as given, after the bottom-up pass, after both."""
    tree = tree or join_tree(q)
    one, both = semijoin_reduce(q, tree), semijoin_reduce(q, tree, full=True)
    out = None
    for i, a in enumerate(q.atoms):
        row = None
        for name, df in (("raw_rows", a.frame), ("reduced_rows", one[i]), ("full_rows", both[i])):
            n = df.agg(F.count(F.lit(1)).alias(name))
            row = n if row is None else row.crossJoin(n)  # single rows
        row = row.select(F.lit(a.name).alias("relation"), "raw_rows", "reduced_rows", "full_rows")
        out = row if out is None else out.unionByName(row)
    return out


def group_counts(q: ConjunctiveQuery, rank: Rank) -> DataFrame:
    """(relation, entries, groups, largest): rows and join groups of each reduced relation, and its largest group."""
    p: Prepared = ranked(q, rank)
    out = None
    for i in p.tree.order:
        df, keys = with_all(p.frames[i], p.tree.shared(i))
        sizes = df.groupBy(*keys).agg(F.count(F.lit(1)).alias("size"))
        row = sizes.agg(F.coalesce(F.sum("size"), F.lit(0)).alias("entries"), F.count(F.lit(1)).alias("groups"), F.coalesce(F.max("size"), F.lit(0)).alias("largest"))
        row = row.select(F.lit(p.tree.query.atoms[i].name).alias("relation"), "entries", "groups", "largest")
        out = row if out is None else out.unionByName(row)
    return out
