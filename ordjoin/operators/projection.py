"""Queries with projection: free-connex rewriting, and fixing head variables level by level for the others."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ordjoin.operators.levels import _pinned, sum_topk
from ordjoin.plans.hypergraph import is_free_connex
from ordjoin.plans.jointree import join_tree
from ordjoin.plans.model import Atom, ConjunctiveQuery
from ordjoin.plans.ranking import Rank, Semiring, assign_weights, boolean


class NotFreeConnex(ValueError):
    """Existential variables can't be folded away in linear time."""


def free_connex_rewrite(q: ConjunctiveQuery) -> ConjunctiveQuery:
    """A full acyclic query over head variables with the same distinct answers.

    Existential variables of one atom are projected away, atoms inside others become semijoins, until nothing changes.
    """
    atoms = [(a.name, a.frame, set(a.variables)) for a in q.atoms]
    head = set(q.head)
    changed = True
    while changed:
        changed = False
        for n, (name, df, variables) in enumerate(atoms):
            lone = {v for v in variables - head if sum(v in x[2] for x in atoms) == 1}
            if lone:
                rest = sorted(variables - lone)
                kept = df.select(*rest).distinct() if rest else df.select(F.lit(1).alias("_any")).limit(1)
                atoms[n] = (name, kept, set(rest))
                changed = True
        for n, (_, df, variables) in enumerate(atoms):
            m = next((j for j in range(len(atoms)) if j != n and variables <= atoms[j][2]), None)
            if m is not None:
                name, other, names = atoms[m]
                on = sorted(variables)
                atoms[m] = (name, other.join(df.select(*on).distinct(), on, "left_semi") if on else other.join(F.broadcast(df.limit(1).select(F.lit(1).alias("_any"))), F.lit(True), "left_semi"), names)
                del atoms[n]
                changed = True
                break
    if any(v - head for _, _, v in atoms):
        raise NotFreeConnex(f"{sorted(set().union(*[v for _, _, v in atoms]) - head)} stay")
    rebuilt = tuple(Atom(name, df.select(*sorted(v)).distinct(), tuple(sorted(v))) for name, df, v in atoms)
    return ConjunctiveQuery(rebuilt, q.head, tuple(a.name for a in rebuilt))


def project_topk(q: ConjunctiveQuery, rank: Rank, k: int) -> DataFrame:
    """The k best distinct head tuples: by rewriting where the query is free-connex, else level by level."""
    if is_free_connex(q):
        full = free_connex_rewrite(q)
        return sum_topk(full, rank, k, join_tree(full))
    return project_rank_topk(q, rank, k)


def _best_next(q: ConjunctiveQuery, prefixes: DataFrame, fixed: Sequence[str], v: str, algebra: Semiring, rank: Rank | None) -> DataFrame:
    """(_pid, v, _prio): per prefix and next value, the best completion; absent if there is none.

    One bottom-up pass serves all prefixes: relations that hold fixed variables are joined with the prefix table and
    carry its id; subtrees without fixed variables send one message for all.
    """
    root = next(i for i, a in enumerate(q.atoms) if v in a.variables)
    tree = join_tree(q, root)
    weights = assign_weights(rank, tree) if rank is not None else {i: F.lit(True) for i in tree.order}
    sent: dict[int, DataFrame] = {}
    for i in reversed(tree.order):
        a = q.atoms[i]
        df = a.frame.withColumn("_w", weights[i])
        own = [x for x in fixed if x in a.variables]
        if own:
            df = df.join(F.broadcast(prefixes.select("_pid", *own)), own)
        opt = F.col("_w")
        for c in tree.children(i):
            message = sent[c]
            on = [*tree.shared(c), *(["_pid"] if "_pid" in message.columns and "_pid" in df.columns else [])]
            df = df.join(message, on) if on else df.join(F.broadcast(message), F.lit(True))  # without shared variables a message is one row, or one a prefix
            opt = algebra.times(opt, F.col(f"_m{c}"))
        df = df.withColumn("_opt", opt)
        pid = ["_pid"] if "_pid" in df.columns else []
        if i == root:
            out = df.groupBy(*pid, v).agg(algebra.plus(F.col("_opt")).alias("_prio"))
            return out if pid else out.join(F.broadcast(prefixes.select("_pid")), F.lit(True))
        sent[i] = df.groupBy(*tree.shared(i), *pid).agg(algebra.plus(F.col("_opt")).alias(f"_m{i}"))
    raise AssertionError


def _level_by_level(q: ConjunctiveQuery, names: Sequence[str], k: int, algebra: Semiring, rank: Rank | None, down: dict[str, bool]) -> DataFrame:
    """At most k prefixes of head values after each variable. Distinct prefixes have disjoint answers, so the cut is
    exact, as for the full query."""
    spark = q.atoms[0].frame.sparkSession
    prefixes = spark.createDataFrame([(0,)], "_pid long")
    done: list[str] = []
    for v in names:
        level = _best_next(q, prefixes, done, v, algebra, rank)
        if done:
            level = level.join(F.broadcast(prefixes.drop("_prio")), "_pid")
        done.append(v)
        by = [*(["_prio"] if rank is not None else []), *[F.col(x).desc() if down.get(x) else F.col(x).asc() for x in done]]
        cut, rows, _ = _pinned(level.select(*done, "_prio").orderBy(*by).limit(k))
        prefixes = cut.withColumn("_pid", F.row_number().over(Window.orderBy(*by)).cast("long"))  # at most k rows
        if not rows:
            break
    for v in names:
        if v not in prefixes.columns:
            kind = dict(next(a for a in q.atoms if v in a.variables).frame.dtypes)[v]
            prefixes = prefixes.withColumn(v, F.lit(None).cast(kind))
    return prefixes.withColumnRenamed("_pid", "rnk")


def project_lex_topk(q: ConjunctiveQuery, order: Sequence[str | tuple[str, bool]], k: int) -> DataFrame:
    """First k distinct head tuples in a lexicographic order, for any acyclic query."""
    pairs = Rank.lex(order).order
    names = [v for v, _ in pairs]
    return _level_by_level(q, [*names, *[v for v in q.head if v not in names]], k, boolean(), None, dict(pairs)).select(*q.head, "rnk")


def project_rank_topk(q: ConjunctiveQuery, rank: Rank, k: int) -> DataFrame:
    """The k best distinct head tuples under a monotone ranking of head variables, for any acyclic query."""
    if not rank.variables <= set(q.head):
        raise ValueError("the ranking uses variables that are projected away")
    out = _level_by_level(q, list(q.head), k, rank.algebra, rank, {})
    return out.select(*q.head, rank.decode(F.col("_prio")).alias("weight"), "rnk")


def project_dedup_stream(q: ConjunctiveQuery, rank: Rank, k: int, first: int = 256) -> DataFrame:
    """Enumerate the full query and drop repeated heads; it may repeat one head without bound before the next."""
    full = ConjunctiveQuery(q.atoms, q.variables, q.relations)
    size = max(first, k)
    while True:
        got = sum_topk(full, rank, size, ties="all")
        heads = got.select(*q.head, "weight").distinct()
        rows = got.count()
        if heads.count() >= k or rows < size:
            numbered = heads.withColumn("rnk", F.row_number().over(Window.orderBy("weight", *q.head)).cast("long"))
            return numbered.where(F.col("rnk") <= k)
        size = max(size * 2, rows + 1)
