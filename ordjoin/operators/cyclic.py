"""Cyclic queries: tree decompositions with materialised bags, and heavy/light splits of the four-cycle."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass
from itertools import permutations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ordjoin.operators.levels import sum_topk
from ordjoin.operators.predicates import branches_topk
from ordjoin.plans.hypergraph import fractional_cover, is_acyclic
from ordjoin.plans.jointree import join_tree
from ordjoin.plans.model import Atom, ConjunctiveQuery
from ordjoin.plans.ranking import Rank


@dataclass(frozen=True)
class Decomposition:
    bags: tuple[frozenset[str], ...]
    width: float


def decompose(q: ConjunctiveQuery) -> Decomposition:
    """Bags of least fractional width among all elimination orders of the variables that stand in two atoms or more.

    Other variables (weights, mostly) come along with their atom when bags are built.
    """
    if is_acyclic(q.edges):
        return Decomposition(tuple(dict.fromkeys(q.edges)), 1.0)
    joins = [v for v in q.variables if sum(v in e for e in q.edges) > 1]
    edges = [e & set(joins) for e in q.edges]
    best: Decomposition | None = None
    for order in permutations(joins):
        left, bags = [set(e) for e in edges], []
        for v in order:
            bag = set().union(*[e for e in left if v in e])
            bags.append(frozenset(bag))
            left = [e for e in left if v not in e] + [bag - {v}]
        bags += [frozenset(e) for e in left if e]
        bags = [b for b in dict.fromkeys(bags) if not any(b < c for c in bags)]
        width = max(fractional_cover([e & b for e in edges if e & b], [1.0] * sum(bool(e & b) for e in edges)) for b in bags)
        if best is None or (width, len(bags)) < (best.width, len(best.bags)):
            best = Decomposition(tuple(bags), width)
    return best


def materialize_bags(q: ConjunctiveQuery, d: Decomposition) -> ConjunctiveQuery:
    """An acyclic query with one atom a bag: the join of the atoms given to it, restricted by all others inside.

    Every atom goes to one bag, so repeated rows keep their number; variables that a bag's own atoms don't bring come
    from distinct projections of others.
    """
    private = {v for v in q.variables if sum(v in e for e in q.edges) == 1}
    given: dict[int, list[int]] = {n: [] for n in range(len(d.bags))}
    for i, e in enumerate(q.edges):
        given[next(n for n, b in enumerate(d.bags) if e - private <= b)].append(i)
    atoms = []
    for n, shared in enumerate(d.bags):
        bag = shared | {v for i in given[n] for v in q.edges[i]}
        df: DataFrame | None = None
        todo = list(given[n])
        while todo:
            i = next((x for x in todo if df is not None and set(q.atoms[x].variables) & set(df.columns)), todo[0])
            todo.remove(i)
            df = q.atoms[i].frame if df is None else _joined(df, q.atoms[i].frame)
        others = sorted((i for i, e in enumerate(q.edges) if i not in given[n] and e & shared), key=lambda i: -len(q.edges[i] & shared))
        for i in others:
            part = q.atoms[i].frame.select(*sorted(q.edges[i] & shared)).distinct()
            have = set() if df is None else set(df.columns)
            if set(part.columns) <= have:
                df = df.join(part, part.columns, "left_semi")
            elif not bag <= have:
                df = part if df is None else _joined(df, part)
        atoms.append(Atom(f"bag_{n}", df.select(*[v for v in q.variables if v in bag]), tuple(v for v in q.variables if v in bag)))
    return ConjunctiveQuery(tuple(atoms), q.head, tuple(a.name for a in atoms))


def _joined(a: DataFrame, b: DataFrame) -> DataFrame:
    on = [c for c in b.columns if c in a.columns]
    return a.join(b, on) if on else a.crossJoin(b)


def cyclic_topk(q: ConjunctiveQuery, rank: Rank, k: int) -> DataFrame:
    """The k best answers of any query: by bags where it is cyclic."""
    flat = materialize_bags(q, decompose(q))
    return sum_topk(flat, rank, k, join_tree(flat))


def heavy_light_4cycle(a: Atom, b: Atom, c: Atom, d: Atom, threshold: int | None = None) -> list[ConjunctiveQuery]:
    """Disjoint acyclic branches of A(x,y) B(y,z) C(z,t) D(t,x): bags of at most n**1.5 rows.

    x is heavy if its degree in A is over the threshold (the root of the rows, if not given), z by its degree in C.
    Heavy x: walk both ways from x; light x and heavy z: both ways from z; both light: meet at t and y. Further columns
    of an atom (weights) come along.
    """
    x, y = a.variables[:2]
    z, t = c.variables[:2]
    if threshold is None:
        threshold = max(1, int(max(v.frame.count() for v in (a, b, c, d)) ** 0.5))
    hx = a.frame.groupBy(x).count().where(F.col("count") > threshold).select(x)
    hz = c.frame.groupBy(z).count().where(F.col("count") > threshold).select(z)
    ax, cz = a.frame.join(hx, x, "left_semi"), c.frame.join(hz, z, "left_semi")
    light_a, light_c = a.frame.join(hx, x, "left_anti"), c.frame.join(hz, z, "left_anti")
    light_d, light_b = d.frame.join(hx, x, "left_anti"), b.frame.join(hz, z, "left_anti")

    def branch(left: DataFrame, right: DataFrame) -> ConjunctiveQuery:
        atoms = (Atom("left", left, tuple(left.columns)), Atom("right", right, tuple(right.columns)))
        head = tuple(dict.fromkeys(v for atom in (a, b, c, d) for v in atom.variables))
        return ConjunctiveQuery(atoms, head, ("left", "right"))

    heavy_b, heavy_d = b.frame.join(hz, z, "left_semi"), d.frame.join(hx, x, "left_semi")
    return [
        branch(ax.join(b.frame, y), heavy_d.join(c.frame, t)),
        branch(heavy_b.join(light_a, y), cz.join(light_d, t)),
        branch(light_d.join(light_a, x), light_b.join(light_c, z)),
    ]


def four_cycle_topk(a: Atom, b: Atom, c: Atom, d: Atom, rank: Rank, k: int, threshold: int | None = None) -> DataFrame:
    return branches_topk(heavy_light_4cycle(a, b, c, d, threshold), rank, k, dedup=False)


def bag_sizes(q: ConjunctiveQuery) -> Sequence[int]:
    return [x.frame.count() for x in q.atoms]
