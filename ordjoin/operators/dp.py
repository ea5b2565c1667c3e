"""Bottom-up dynamic programming over a join tree: one implementation for all semirings.

A message is one aggregate row per join key, so it is the memo of its group; joining it with the parent both drops
dangling rows and accumulates. Per tree edge: a map-side aggregated shuffle of the child and one join.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ordjoin.plans.jointree import JoinTree, join_tree
from ordjoin.plans.model import ConjunctiveQuery
from ordjoin.plans.ranking import Rank, Semiring, assign_weights, boolean, counting

ALL = "_all"  # join column of an edge without shared variables: one group


def with_all(df: DataFrame, keys: Sequence[str]) -> tuple[DataFrame, list[str]]:
    return (df, list(keys)) if keys else (df.withColumn(ALL, F.lit(1)), [ALL])


@dataclass
class Prepared:
    """Reduced relations with ``_w`` (own weight), ``_opt`` (best in the subtree) and ``_m<child>`` (children's messages)."""

    tree: JoinTree
    algebra: Semiring
    rank: Rank | None
    frames: dict[int, DataFrame] = field(default_factory=dict)
    held: list[DataFrame] = field(default_factory=list)

    @property
    def root(self) -> int:
        return self.tree.order[0]

    def hold(self) -> Prepared:
        """Keep the reduced relations for repeated use (memory, then local disk; lineage rebuilds lost parts)."""
        for i, df in self.frames.items():
            self.frames[i] = df.persist(StorageLevel.MEMORY_AND_DISK)
            self.held.append(self.frames[i])
        return self

    def close(self) -> None:
        for df in self.held:
            df.unpersist()
        self.held.clear()

    def __enter__(self) -> Prepared:
        return self

    def __exit__(self, *_: object) -> None:
        self.close()


def messages(tree: JoinTree, algebra: Semiring, weights: dict[int, Column], rank: Rank | None = None) -> Prepared:
    """Annotate each relation bottom-up; rows without a completion below them go."""
    out = Prepared(tree, algebra, rank)
    sent: dict[int, tuple[DataFrame, list[str]]] = {}
    for i in reversed(tree.order):
        a = tree.query.atoms[i]
        df = a.frame.withColumn("_w", weights[i])
        opt = F.col("_w")
        for c in tree.children(i):
            message, keys = sent[c]
            if keys == [ALL]:
                df = df.withColumn(ALL, F.lit(1))
            df = df.join(message, keys)
            opt = algebra.times(opt, F.col(f"_m{c}"))
        df = df.withColumn("_opt", opt).select(*a.variables, "_w", "_opt", *[f"_m{c}" for c in tree.children(i)])
        out.frames[i] = df
        if tree.parent[i] is not None:
            keyed, keys = with_all(df, tree.shared(i))
            sent[i] = keyed.groupBy(*keys).agg(algebra.plus(F.col("_opt")).alias(f"_m{i}")), keys
    return out


def ranked(q: ConjunctiveQuery, rank: Rank, tree: JoinTree | None = None) -> Prepared:
    tree = tree or join_tree(q)
    return messages(tree, rank.algebra, assign_weights(rank, tree), rank)


def semijoin_reduce(q: ConjunctiveQuery, tree: JoinTree | None = None, full: bool = False) -> dict[int, DataFrame]:
    """Bottom-up semijoins; rows of a child that meet no parent stay, unless ``full`` adds the top-down pass."""
    tree = tree or join_tree(q)
    frames = {i: a.frame for i, a in enumerate(q.atoms)}

    def keep(i: int, other: int, names: tuple[str, ...]) -> None:
        left, keys = with_all(frames[i], names)
        right, _ = with_all(frames[other], names)
        frames[i] = left.join(right.select(*keys).distinct(), keys, "left_semi").select(*q.atoms[i].variables)

    for i in reversed(tree.order):
        if tree.parent[i] is not None:
            keep(tree.parent[i], i, tree.shared(i))
    if full:
        for i in tree.order[1:]:
            keep(i, tree.parent[i], tree.shared(i))
    return frames


def dangling(q: ConjunctiveQuery, tree: JoinTree | None = None) -> dict[int, DataFrame]:
    """Rows that the bottom-up pass removes, per atom."""
    reduced = semijoin_reduce(q, tree)
    return {i: a.frame.exceptAll(reduced[i]) for i, a in enumerate(q.atoms)}


def count_prepared(tree: JoinTree) -> Prepared:
    return messages(tree, counting(), {i: F.lit(1).cast("decimal(38,0)") for i in tree.order})


def count_answers(q: ConjunctiveQuery) -> DataFrame:
    """One row: the number of answers of a full acyclic query, which are never built (bag semantics)."""
    p = count_prepared(join_tree(q))
    return p.frames[p.root].agg(F.coalesce(F.sum("_opt"), F.lit(0)).cast("decimal(38,0)").alias("answers"))


def exists(q: ConjunctiveQuery) -> bool:
    """The Boolean query: is there an answer?"""
    tree = join_tree(q)
    p = messages(tree, boolean(), {i: F.lit(True) for i in tree.order})
    return not p.frames[p.root].isEmpty()


def through_weights(p: Prepared) -> dict[int, DataFrame]:
    """Add ``_through``, the weight of the best answer that uses each row (rows that no answer uses go).

    The best weight outside a row's subtree comes down from the parent: all that the parent's best answer has but this
    child's message. It is recombined from the other parts, so rankings without an inverse are served too.
    """
    tree, times = p.tree, p.algebra.times
    out = {p.root: p.frames[p.root].withColumn("_through", F.col("_opt"))}
    outside: dict[int, Column | None] = {p.root: None}
    frames = dict(p.frames)
    for i in tree.order:
        df = frames[i]
        for c in tree.children(i):
            rest = p.algebra.product([F.col("_w"), *[F.col(f"_m{d}") for d in tree.children(i) if d != c], *([F.col("_out")] if outside[i] is not None else [])])
            keyed, keys = with_all(df, tree.shared(c))
            down = keyed.groupBy(*keys).agg(p.algebra.plus(rest).alias("_out"))
            child, _ = with_all(frames[c], tree.shared(c))
            frames[c] = child.join(down, keys).select(*tree.query.atoms[c].variables, *[x for x in frames[c].columns if x.startswith("_")], "_out")
            outside[c] = F.col("_out")
            out[c] = frames[c].withColumn("_through", times(F.col("_opt"), F.col("_out"))).drop("_out")
    return out


def tau_from_root(p: Prepared, k: int) -> object | None:
    """The k-th smallest optimum of the root's rows bounds the k-th answer; None if the root has fewer rows."""
    rows = p.frames[p.root].select("_opt").orderBy("_opt").limit(k).agg(F.count(F.lit(1)).alias("n"), F.max("_opt").alias("t")).first()
    return rows["t"] if rows["n"] >= k else None


def prune(p: Prepared, tau: object) -> Prepared:
    """Relations cut to rows that some answer of weight ``tau`` or less uses."""
    frames = {i: df.where(F.col("_through") <= F.lit(tau)).drop("_through") for i, df in through_weights(p).items()}
    return Prepared(p.tree, p.algebra, p.rank, frames)
