"""Rankings as algebras over Spark columns: how weights combine inside an answer and which one is better."""

from __future__ import annotations

import random
from collections.abc import Callable, Mapping, Sequence
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ordjoin.plans.jointree import JoinTree
from ordjoin.plans.model import ConjunctiveQuery

Weights = Mapping[str, Column]


@dataclass(frozen=True)
class Semiring:
    """``plus`` chooses inside a group (an aggregate), ``times`` combines parts of an answer, ``one`` is neutral."""

    name: str
    plus: Callable[[Column], Column]
    times: Callable[[Column, Column], Column]
    one: Column | None
    inverse: Callable[[Column, Column], Column] | None = None

    def product(self, parts: Sequence[Column]) -> Column:
        parts = [p for p in parts if p is not None]
        return reduce(self.times, parts) if parts else self.one


def _add(a: Column, b: Column) -> Column:
    return a + b


def min_plus() -> Semiring:
    return Semiring("min-plus", F.min, _add, F.lit(0).cast("long"), lambda a, b: a - b)


def boolean() -> Semiring:
    return Semiring("boolean", F.max, lambda a, b: a & b, F.lit(True))


def counting() -> Semiring:
    def times(a: Column, b: Column) -> Column:
        return (a * b).cast("decimal(38,0)")

    return Semiring("counting", lambda c: F.sum(c).cast("decimal(38,0)"), times, F.lit(1).cast("decimal(38,0)"))


def vectors(length: int) -> Semiring:
    """Rank vectors, added place by place and compared lexicographically."""
    zero = F.array(*[F.lit(0).cast("long")] * length)
    return Semiring("vectors", F.min, lambda a, b: F.zip_with(a, b, lambda x, y: x + y), zero, lambda a, b: F.zip_with(a, b, lambda x, y: x - y))


def values(empty: Mapping[str, Column]) -> Semiring:
    """Structs with a place for each variable, filled in by the atom that is charged for it and compared in that order."""

    def fill(a: Column, b: Column) -> Column:
        return F.struct(*[F.coalesce(a[v], b[v]).alias(v) for v in empty])

    return Semiring("values", F.min, fill, F.struct(*[c.alias(v) for v, c in empty.items()]))


@dataclass(frozen=True)
class Rank:
    """``terms``: (variables it needs, weight column) pairs; each is charged to one atom.

    ``cancellative``: from equal parts, the rest decides (SUM, vectors); only then may a group be cut by position.
    ``decode`` gives the weight to show from the state. ``descends``: states are negated weights.
    """

    kind: str
    terms: tuple[tuple[tuple[str, ...], Column], ...]
    algebra: Semiring
    cancellative: bool
    decode: Callable[[Column], Column] = field(default=lambda c: c)
    order: tuple[tuple[str, bool], ...] = ()
    descends: bool = False

    # -- constructors ------------------------------------------------------------------------------------------------
    @staticmethod
    def sum(weights: Weights | Sequence[str], desc: bool = False) -> Rank:
        """Sum of functions of single variables; integers or decimals keep it exact."""
        return Rank("sum", _terms(weights, -1 if desc else 1), min_plus(), True, (lambda c: -c) if desc else (lambda c: c), descends=desc)

    @staticmethod
    def max(weights: Weights | Sequence[str], desc: bool = False) -> Rank:
        """Largest weight of an answer (bottleneck)."""
        return Rank("max", _terms(weights, -1 if desc else 1), Semiring("max", F.min, F.least if desc else F.greatest, None), False, (lambda c: -c) if desc else (lambda c: c), descends=desc)

    @staticmethod
    def min(weights: Weights | Sequence[str], desc: bool = False) -> Rank:
        return Rank("min", _terms(weights, -1 if desc else 1), Semiring("min", F.min, F.greatest if desc else F.least, None), False, (lambda c: -c) if desc else (lambda c: c), descends=desc)

    @staticmethod
    def product(weights: Weights | Sequence[str]) -> Rank:
        """Product of non-negative weights (zero absorbs, so it isn't cancellative)."""
        wide = tuple((v, w.cast("decimal(38,0)")) for v, w in _terms(weights, 1))
        return Rank("product", wide, Semiring("min-times", F.min, lambda a, b: (a * b).cast("decimal(38,0)"), F.lit(1).cast("decimal(38,0)")), False)

    @staticmethod
    def leximax(weights: Weights | Sequence[str]) -> Rank:
        """Largest weight first, then the second largest, and so on."""
        single = tuple((v, F.array(w)) for v, w in _terms(weights, 1))
        merge = Semiring("leximax", F.min, lambda a, b: F.reverse(F.array_sort(F.concat(a, b))), F.array().cast("array<bigint>"))
        return Rank("leximax", single, merge, True)

    @staticmethod
    def local_sum(parts: Sequence[tuple[Sequence[str], Column]], desc: bool = False) -> Rank:
        """Sum of functions, each of variables that stand together in one atom."""
        sign = -1 if desc else 1
        return Rank("local_sum", tuple((tuple(v), sign * w) for v, w in parts), min_plus(), True, (lambda c: -c) if desc else (lambda c: c), descends=desc)

    @staticmethod
    def chain(first: Rank, second: Rank) -> Rank:
        """By ``first``, ties by ``second``. Monotone only if ``first`` is cancellative."""
        if not first.cancellative:
            raise ValueError("the leading ranking of a chain must be cancellative")
        one_a, one_b = first.algebra.one, second.algebra.one

        def lift(c: Column | None, d: Column | None) -> Column:
            return F.struct((c if c is not None else F.lit(None).cast("long")).alias("a"), (d if d is not None else F.lit(None).cast("long")).alias("b"))

        terms = (*[(v, lift(w, one_b)) for v, w in first.terms], *[(v, lift(one_a, w)) for v, w in second.terms])
        times = lambda x, y: F.struct(first.algebra.times(x["a"], y["a"]).alias("a"), second.algebra.times(x["b"], y["b"]).alias("b"))
        show = lambda c: F.struct(first.decode(c["a"]).alias("a"), second.decode(c["b"]).alias("b"))
        return Rank("chain", terms, Semiring("chain", F.min, times, lift(one_a, one_b)), first.cancellative and second.cancellative, show)

    @staticmethod
    def lex(order: Sequence[str | tuple[str, bool]]) -> Rank:
        """Lexicographic by variables; (variable, True) is descending."""
        pairs = tuple((v, False) if isinstance(v, str) else v for v in order)
        return Rank("lex", (), min_plus(), True, order=pairs)

    @staticmethod
    def black_box(expression: Column) -> Rank:
        """Any function of the whole answer: only a materialised result can be ranked by it."""
        return Rank("black_box", (((), expression),), min_plus(), False)

    @property
    def variables(self) -> set[str]:
        return {v for vs, _ in self.terms for v in vs} | {v for v, _ in self.order}

    def cost(self) -> Column:
        """State of a whole answer from its variables."""
        return self.algebra.product([w for _, w in self.terms])


def asc(v: str) -> tuple[str, bool]:
    return v, False


def desc(v: str) -> tuple[str, bool]:
    return v, True


def _terms(weights: Weights | Sequence[str], sign: int) -> tuple[tuple[tuple[str, ...], Column], ...]:
    pairs = weights.items() if isinstance(weights, Mapping) else [(v, F.col(v)) for v in weights]
    return tuple(((v,), (w if sign > 0 else -w)) for v, w in pairs)


def lookup(q: ConjunctiveQuery, variable: str, values: DataFrame, weight: str) -> ConjunctiveQuery:
    """A value-to-weight table as one more atom; rank by its variable ``weight``."""
    from ordjoin.plans.model import atom, cq

    return cq([*q.atoms, atom(f"weight_of_{variable}", values, [variable, weight])], [*q.head, weight], [*q.relations, f"weight_of_{variable}"])


def assign_weights(rank: Rank, tree: JoinTree) -> dict[int, Column]:
    """Atom -> its part of the weight: each term at the first atom in the order that holds its variables."""
    parts: dict[int, list[Column]] = {i: [] for i in tree.order}
    for needs, column in rank.terms:
        home = next((i for i in tree.order if set(needs) <= set(tree.query.atoms[i].variables)), None)
        if home is None:
            raise ValueError(f"no atom holds {needs}; the ranking isn't local to this tree")
        parts[home].append(column)
    one = rank.algebra.one if rank.algebra.one is not None else F.lit(None).cast("long")
    return {i: rank.algebra.product(p) if p else one for i, p in parts.items()}


def classify(rank: Rank, tree: JoinTree) -> str:
    """``subset-monotone``, ``tree-local`` (monotone for this tree) or ``black box``."""
    if rank.kind == "black_box":
        return "black box"
    for needs, _ in rank.terms:
        if not any(set(needs) <= set(a.variables) for a in tree.query.atoms):
            return "black box"
    return "tree-local" if any(len(needs) > 1 for needs, _ in rank.terms) else "subset-monotone"


def check_subset_monotone(f: Callable[[list], object], domain: Sequence[object], most: int = 4, tries: int = 4000, seed: int = 1) -> tuple | None:
    """Look for weight multisets with f(a) <= f(b) but not f(a + c) <= f(b + c); None if none was found.

    ``a`` and ``b`` have one size, as prefixes over the same relations do.
    """
    rng = random.Random(seed)
    for _ in range(tries):
        n = rng.randint(1, most)
        a, b, c = ([rng.choice(domain) for _ in range(m)] for m in (n, n, rng.randint(1, most)))
        if f(a) <= f(b) and not f(a + c) <= f(b + c):
            return a, b, c
    return None
