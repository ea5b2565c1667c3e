"""Inequalities and non-equalities as unions of acyclic queries over equalities."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import replace
from functools import partial

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ordjoin.operators.dp import ranked, through_weights
from ordjoin.operators.levels import PlanStats, dense_codes, literal, sum_topk
from ordjoin.operators.union import ordered_union
from ordjoin.plans.jointree import JoinTree, join_tree
from ordjoin.plans.model import Atom, ConjunctiveQuery
from ordjoin.plans.ranking import Rank, Semiring, assign_weights


def _home(q: ConjunctiveQuery, v: str, other: str) -> int:
    """An atom with v; if one holds both variables, that one."""
    both = [i for i, a in enumerate(q.atoms) if v in a.variables and other in a.variables]
    return both[0] if both else next(i for i, a in enumerate(q.atoms) if v in a.variables)


def _adjacent(q: ConjunctiveQuery, x: str, y: str) -> tuple[int, int]:
    """Atoms of x and y that are neighbours in a join tree."""
    from ordjoin.plans.jointree import all_trees

    for tree in all_trees(q):
        for i, p in enumerate(tree.parent):
            if p is not None:
                for a, b in ((i, p), (p, i)):
                    if x in q.atoms[a].variables and y in q.atoms[b].variables:
                        return a, b
    raise ValueError(f"{x} and {y} stand in no adjacent nodes")


def _coded(q: ConjunctiveQuery, i: int, v: str, j: int, w: str) -> tuple[DataFrame, DataFrame, DataFrame, int]:
    """Both relations with dense codes of one merged domain, and its bits."""
    values = q.atoms[i].frame.select(F.col(v).alias("_v")).unionByName(q.atoms[j].frame.select(F.col(w).alias("_v")))
    codes = dense_codes(values, "_v", "_code")
    top = codes.agg(F.max("_code").alias("m")).first()["m"]
    bits = max(1, int(top or 0).bit_length())
    left = q.atoms[i].frame.join(codes.withColumnRenamed("_v", v), v)
    right = q.atoms[j].frame.join(codes.withColumnRenamed("_v", w), w)
    return left, right, codes, bits


def lt_rewrite(q: ConjunctiveQuery, x: str, y: str, strict: bool = True, shift: object | None = None) -> ConjunctiveQuery:
    """x < y (or x <= y, or with ``shift`` x < y - shift) as equality on a dyadic code: each pair meets exactly once.

    At the highest bit where the codes differ x has 0 and y has 1, and the bits above agree. So x's relation gets a
    copy for each 0-bit of its code, keyed by (bit, bits above), and y's one for each 1-bit: at most rows * log(domain)
    rows, and a plain equi-join. Answers gain two helper variables that the head leaves out.
    """
    return _dyadic(q, x, y, F.col(y) - F.lit(shift) if shift is not None else F.col(y), strict)


def _dyadic(q: ConjunctiveQuery, x: str, y: str, moved: Column, strict: bool) -> ConjunctiveQuery:
    """Codes are doubled, so that y's may be raised by one where equality counts."""
    one = next((i for i, a in enumerate(q.atoms) if {x, y} <= set(a.variables)), None)
    if one is not None:
        keep = F.col(x) < moved if strict else F.col(x) <= moved
        return replace(q, atoms=tuple(a.with_frame(a.frame.where(keep)) if i == one else a for i, a in enumerate(q.atoms)))
    i, j = _adjacent(q, x, y)
    kind = dict(q.atoms[i].frame.dtypes)[x]
    left, right = q.atoms[i].frame, q.atoms[j].frame.withColumn("_moved", moved.cast(kind))
    codes = dense_codes(left.select(F.col(x).alias("_v")).unionByName(right.select(F.col("_moved").alias("_v"))), "_v", "_code").withColumn("_code", F.col("_code") * 2)
    top = codes.agg(F.max("_code").alias("m")).first()["m"]
    bits = max(1, (int(top or 0) + 1).bit_length())
    left = left.join(codes.withColumnRenamed("_v", x), x)
    right = right.join(codes.withColumnRenamed("_v", "_moved"), "_moved").drop("_moved").withColumn("_code", F.col("_code") + (0 if strict else 1))
    bit, above = f"bit_{x}_{y}", f"above_{x}_{y}"

    def copies(df: DataFrame, wanted: int) -> DataFrame:
        out = df.withColumn(bit, F.explode(F.sequence(F.lit(0), F.lit(bits - 1)))).where(F.expr(f"shiftright(_code, `{bit}`) & 1") == wanted)
        return out.withColumn(above, F.expr(f"shiftright(_code, `{bit}` + 1)")).drop("_code")

    atoms = list(q.atoms)
    atoms[i] = Atom(atoms[i].name, copies(left, 0).select(*atoms[i].variables, bit, above), (*atoms[i].variables, bit, above))
    atoms[j] = Atom(atoms[j].name, copies(right, 1).select(*atoms[j].variables, bit, above), (*atoms[j].variables, bit, above))
    return replace(q, atoms=tuple(atoms))


def le_rewrite(q: ConjunctiveQuery, x: str, y: str) -> ConjunctiveQuery:
    return lt_rewrite(q, x, y, strict=False)


def band_branches(q: ConjunctiveQuery, x: str, y: str, width: object) -> list[ConjunctiveQuery]:
    """x < y and y - x <= width, as disjoint acyclic branches: x < y without those further apart.

    For a width c: x's bucket floor(x / c) equals y's and x < y; or y's bucket is the next one and y - c <= x.
    """
    i, j = _adjacent(q, x, y)

    def keyed(first: int) -> ConjunctiveQuery:
        name = f"bucket_{x}_{y}"
        atoms = list(q.atoms)
        atoms[i] = Atom(atoms[i].name, atoms[i].frame.withColumn(name, F.floor(F.col(x) / F.lit(width)) + first), (*atoms[i].variables, name))
        atoms[j] = Atom(atoms[j].name, atoms[j].frame.withColumn(name, F.floor(F.col(y) / F.lit(width))), (*atoms[j].variables, name))
        return replace(q, atoms=tuple(atoms))

    return [_dyadic(keyed(0), x, y, F.col(y), True), _dyadic_reversed(keyed(1), x, y, width)]


def _dyadic_reversed(q: ConjunctiveQuery, x: str, y: str, width: object) -> ConjunctiveQuery:
    """y - width <= x: the roles of both sides swap."""
    i, j = _adjacent(q, x, y)
    kind = dict(q.atoms[i].frame.dtypes)[x]
    low = f"low_{y}"
    atoms = list(q.atoms)
    atoms[j] = Atom(atoms[j].name, atoms[j].frame.withColumn(low, (F.col(y) - F.lit(width)).cast(kind)), (*atoms[j].variables, low))
    return _dyadic(replace(q, atoms=tuple(atoms)), low, x, F.col(x), False)


def long_inequality(q: ConjunctiveQuery, x: str, y: str, rank: Rank, k: int, first: int = 1024) -> DataFrame:
    """x < y with ends far apart: ordered answers are filtered, with more asked for until k pass. No guarantee."""
    size = max(first, k)
    while True:
        got = sum_topk(q, rank, size)
        passed = got.where(F.col(x) < F.col(y))
        if passed.count() >= k or got.count() < size:
            return passed.withColumn("rnk", F.row_number().over(Window.orderBy("rnk")).cast("long")).where(F.col("rnk") <= k)
        size *= 4


def neq_branches(q: ConjunctiveQuery, x: str, y: str) -> list[ConjunctiveQuery]:
    """x <> y wherever they stand, by a family of two-colourings: the bits of dense codes.

    Branch (b, v) keeps rows whose x has bit b equal to v and rows whose y has not: every answer with different codes is
    in at least one and at most log2(domain) branches, each acyclic as the query.
    """
    i, j = _home(q, x, y), _home(q, y, x)
    if i == j:
        return [replace(q, atoms=tuple(a.with_frame(a.frame.where(F.col(x) != F.col(y))) if n == i else a for n, a in enumerate(q.atoms)))]
    left, right, _, bits = _coded(q, i, x, j, y)
    out = []
    for b in range(bits):
        for v in (0, 1):
            bit = F.shiftright("_code", b).bitwiseAND(1)
            atoms = list(q.atoms)
            atoms[i] = atoms[i].with_frame(left.where(bit == v).select(*atoms[i].variables))
            atoms[j] = atoms[j].with_frame(right.where(bit == 1 - v).select(*atoms[j].variables))
            out.append(replace(q, atoms=tuple(atoms)))
    return out


def neq_random_branches(q: ConjunctiveQuery, x: str, y: str, colourings: int = 16) -> list[ConjunctiveQuery]:
    """The same with random two-colourings; misses a pair with probability 2**-colourings."""
    i, j = _home(q, x, y), _home(q, y, x)
    out = []
    for n in range(colourings):
        for v in (0, 1):
            atoms = list(q.atoms)
            atoms[i] = atoms[i].with_frame(atoms[i].frame.where(F.xxhash64(F.lit(n), F.col(x)).bitwiseAND(1) == v))
            atoms[j] = atoms[j].with_frame(atoms[j].frame.where(F.xxhash64(F.lit(n), F.col(y)).bitwiseAND(1) == 1 - v))
            out.append(replace(q, atoms=tuple(atoms)))
    return out


def branches_topk(branches: Sequence[ConjunctiveQuery], rank: Rank, k: int, dedup: bool = True) -> DataFrame:
    """The k best answers of a union of acyclic queries. Each branch gives its k best with ties (helper variables play
    no part in the order), and repeats between branches go."""
    head = branches[0].head
    tops = [sum_topk(b, rank, k, join_tree(b), ties="all") for b in branches]
    return ordered_union(tops, head, k, dedup)


def neq_topk(q: ConjunctiveQuery, x: str, y: str, rank: Rank, k: int) -> DataFrame:
    return branches_topk(neq_branches(q, x, y), rank, k)


def nae_branches(q: ConjunctiveQuery, pairs: Sequence[tuple[str, str]]) -> list[ConjunctiveQuery]:
    """Not all pairs equal: some pair differs; an answer repeats at most once for each pair and bit."""
    return [b for x, y in pairs for b in neq_branches(q, x, y)]


def _path(tree: JoinTree, i: int, j: int) -> list[int]:
    """Atoms between two atoms of a join tree, with both."""

    def up(n: int) -> list[int]:
        out = [n]
        while tree.parent[out[-1]] is not None:
            out.append(tree.parent[out[-1]])
        return out

    a, b = up(i), up(j)
    meet = next(n for n in a if n in b)
    return [*a[: a.index(meet) + 1], *reversed(b[: b.index(meet)])]


def neq_coloured(q: ConjunctiveQuery, x: str, y: str) -> tuple[ConjunctiveQuery, int]:
    """The branches of ``neq_branches`` for x and y of different atoms as one acyclic query, and how often it may give an
    answer (bits).

    A helper variable holds the branch, 2 * bit + value: x's relation has a copy for each bit of its code, y's one for each
    bit with the other value, and each relation between them in the tree one for every branch.
    """
    i, j = _home(q, x, y), _home(q, y, x)
    left, right, _, bits = _coded(q, i, x, j, y)
    colour, atoms = f"colour_{x}_{y}", list(q.atoms)

    def copies(n: int, df: DataFrame, branch: str, most: int) -> Atom:
        out = df.withColumn("_n", F.explode(F.sequence(F.lit(0), F.lit(most - 1)))).withColumn(colour, F.expr(branch).cast("int"))
        return Atom(q.atoms[n].name, out.select(*q.atoms[n].variables, colour), (*q.atoms[n].variables, colour))

    for n in _path(join_tree(q), i, j):
        atoms[n] = copies(n, q.atoms[n].frame, "_n", 2 * bits)
    atoms[i] = copies(i, left, "2 * _n + (shiftright(_code, _n) & 1)", bits)
    atoms[j] = copies(j, right, "2 * _n + 1 - (shiftright(_code, _n) & 1)", bits)
    return ConjunctiveQuery(tuple(atoms), q.head, tuple(a.name for a in atoms)), bits


def _settled(rank: Rank, tree: JoinTree, order: Sequence[str]) -> Rank:
    """A cancellative ranking with ties settled by the values of variables, for one tree: no two answers are equal.

    A state is a struct of the weight's state and a place for each variable, filled in by the atom that meets it first.
    """
    kinds = {v: t for a in tree.query.atoms for v, t in a.frame.select(*a.variables).dtypes}
    weights, charged = assign_weights(rank, tree), tree.charged()

    def state(weight: Column, own: Sequence[str]) -> Column:
        return F.struct(weight.alias("_state"), *[(F.col(v) if v in own else F.lit(None).cast(kinds[v])).alias(v) for v in order])

    def times(x: Column, y: Column) -> Column:
        return F.struct(rank.algebra.times(x["_state"], y["_state"]).alias("_state"), *[F.coalesce(x[v], y[v]).alias(v) for v in order])

    terms = tuple((a.variables, state(weights[i], [v for v in a.variables if charged[v] == i])) for i, a in enumerate(tree.query.atoms))
    return Rank("settled", terms, Semiring("settled", F.min, times, state(rank.algebra.one, [])), True, lambda c: rank.decode(c["_state"]))


def _first(branch: ConjunctiveQuery, rank: Rank, order: Sequence[str], k: int, settled: bool, ties: str = "ids") -> tuple[DataFrame, object | None]:
    """A branch's k best answers, and the state of the k-th; None if it has fewer, which are then all."""
    tree, stats = join_tree(replace(branch, head=tuple(order))), PlanStats()
    got = sum_topk(tree.query, _settled(rank, tree, order) if settled else rank, k, tree, ties=ties, stats=stats)
    return got, stats.bounds[-1] if stats.bounds else None


def _set_down(df: DataFrame) -> DataFrame:
    """A frame's rows without the plan that made them, in the checkpoint folder if there is one, else on the executors.

    Spark prints a cached frame's plan wherever it is read, so plans over caches of caches fill the driver's memory.
    """
    return df.checkpoint() if df.sparkSession.sparkContext.getCheckpointDir() else df.localCheckpoint(storageLevel=StorageLevel.MEMORY_AND_DISK)


def _within(q: ConjunctiveQuery, rank: Rank, tau: object) -> ConjunctiveQuery:
    """Relations cut to rows that some answer within the bound uses, set down."""
    with ranked(q, rank).hold() as p:
        cut = {i: _set_down(df.where(F.col("_through") <= literal(tau)).select(*q.atoms[i].variables)) for i, df in through_weights(p).items()}
    return replace(q, atoms=tuple(a.with_frame(cut[i]) for i, a in enumerate(q.atoms)))


def nae_topk(q: ConjunctiveQuery, pairs: Sequence[tuple[str, str]], rank: Rank, k: int) -> DataFrame:
    """The k best answers in which some pair differs, over relations that are sets; ties by the head, then the rest.

    One top-k run for each pair, whatever its domain: all its branches are one query (``neq_coloured``). The k-th answer
    of one branch (a pair in one atom, else a random half) bounds the k-th answer of the union, so rows that no answer
    within the bound uses go first: by weight, then by weight and values (``_settled``), under which no answers tie. So
    no frontier holds more than k rows, or k for each bit of a coloured domain, however many answers share the k-th
    weight. Only rankings that aren't cancellative take all ties along. Without a bound (no branch tried has k answers)
    all rows are coloured.
    """
    held = [a.frame.persist(StorageLevel.MEMORY_AND_DISK) for a in q.atoms]
    q = replace(q, atoms=tuple(a.with_frame(df) for a, df in zip(q.atoms, held, strict=True)))
    order = list(dict.fromkeys([*q.head, *q.variables]))
    try:
        together = [(x, y) for x, y in pairs if _home(q, x, y) == _home(q, y, x)]
        apart = [p for p in pairs if p not in together]
        tries = [(p, 0, neq_branches) for p in together] + [(p, v, partial(neq_random_branches, colourings=1)) for p in apart for v in (0, 1)]
        tops: dict[tuple[str, str], DataFrame] = {}
        for pair, v, branches in tries if k > 0 else ():
            top, tau = _first(branches(q, *pair)[v], rank, order, k, False)
            if tau is None and pair in together:
                tops[pair] = top
            if tau is not None:
                q = _within(q, rank, tau)
                if rank.cancellative:
                    top, tau = _first(branches(q, *pair)[v], rank, order, k, True)
                    q = _within(q, _settled(rank, join_tree(q), order), tau)
                    tops |= {pair: top} if pair in together else {}
                break
        for pair in pairs:
            if pair not in tops:
                branch, repeats = (neq_branches(q, *pair)[0], 1) if pair in together else neq_coloured(q, *pair)
                tops[pair] = _first(branch, rank, order, k * repeats, rank.cancellative, "ids" if rank.cancellative else "all")[0]
        return ordered_union(list(tops.values()), order, k, dedup=True).select(*q.head, "weight", "rnk")
    finally:
        for df in held:
            df.unpersist()


def lt_topk(q: ConjunctiveQuery, x: str, y: str, rank: Rank, k: int, strict: bool = True) -> DataFrame:
    return branches_topk([lt_rewrite(q, x, y, strict)], rank, k, dedup=False)
