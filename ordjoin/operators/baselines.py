"""What ordered enumeration is compared with: join then rank, the engine's own plans, and older or naive methods."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ordjoin.operators.dp import semijoin_reduce
from ordjoin.operators.levels import _keep, full_join
from ordjoin.plans.jointree import join_tree
from ordjoin.plans.model import ConjunctiveQuery
from ordjoin.plans.ranking import Rank


def _weighted(df: DataFrame, rank: Rank) -> DataFrame:
    return df.withColumn("_state", rank.terms[0][1] if rank.kind == "black_box" else rank.cost())


def _shown(df: DataFrame, q: ConjunctiveQuery, rank: Rank) -> DataFrame:
    return df.select(*q.head, (F.col("_state") if rank.kind == "black_box" else rank.decode(F.col("_state"))).alias("weight"))


def batch_reduce_join_sort(q: ConjunctiveQuery, rank: Rank) -> DataFrame:
    """Reduce both ways, compute the complete result, sort it."""
    out = _weighted(full_join(q, semijoin_reduce(q, full=True)), rank).orderBy("_state", *join_tree(q).met())
    return _shown(out, q, rank)


def engine_join_sort(q: ConjunctiveQuery, rank: Rank, hint: str | None = None) -> DataFrame:
    """Plain joins in the order written and a sort: the engine's own plan. ``hint``: a join hint for every join, such as
    ``merge``, ``shuffle_hash`` or ``broadcast`` (for relations of a known size)."""
    return _shown(_weighted(_plain(q, hint), rank).orderBy("_state", *q.variables), q, rank)


def _plain(q: ConjunctiveQuery, hint: str | None = None) -> DataFrame:
    out = q.atoms[0].frame
    for a in q.atoms[1:]:
        on = [v for v in a.variables if v in out.columns]
        right = a.frame.hint(hint) if hint else a.frame
        out = out.join(right, on) if on else out.crossJoin(a.frame)
    return out


def engine_topk(q: ConjunctiveQuery, rank: Rank, k: int, ids: list[str] | None = None, hint: str | None = None) -> DataFrame:
    """The same with a limit, and ``rnk``."""
    by = ids or list(join_tree(q).met())
    top = _weighted(_plain(q, hint), rank).orderBy("_state", *by).limit(k)
    numbered = top.withColumn("rnk", F.row_number().over(Window.orderBy("_state", *by)).cast("long"))  # k rows
    return numbered.select(*q.head, (F.col("_state") if rank.kind == "black_box" else rank.decode(F.col("_state"))).alias("weight"), "rnk")


def batch_incremental_sort(q: ConjunctiveQuery, rank: Rank, parts: int = 64) -> Iterator[DataFrame]:
    """Complete result, range partitioned by weight; a partition is sorted only when it is asked for. The partitions stay
    persisted until ``levels.release()``."""
    rows = _keep(_weighted(full_join(q, semijoin_reduce(q, full=True)), rank).repartitionByRange(parts, "_state").withColumn("_part", F.spark_partition_id()))
    for part in range(parts):
        yield _shown(rows.where(F.col("_part") == part).orderBy("_state", *q.variables), q, rank)


def naive_product(q: ConjunctiveQuery) -> DataFrame:
    """Cartesian product, then filter, then project (tiny inputs only)."""
    out: DataFrame | None = None
    same: list[Column] = []
    home: dict[str, str] = {}
    for i, a in enumerate(q.atoms):
        df = a.frame.select(*[F.col(v).alias(f"{v}__{i}") for v in a.variables])
        for v in a.variables:
            if v in home:
                same.append(F.col(home[v]) == F.col(f"{v}__{i}"))
            else:
                home[v] = f"{v}__{i}"
        out = df if out is None else out.crossJoin(df)
    for c in same:
        out = out.where(c)
    return out.select(*[F.col(home[v]).alias(v) for v in q.head])


def table_at_a_time(q: ConjunctiveQuery, k: int) -> DataFrame:
    """Left-deep joins without reduction, then any k rows."""
    return _plain(q).select(*q.head).limit(k)


def greedy_first(q: ConjunctiveQuery, rank: Rank) -> dict | None:
    """Negative control: the cheapest row of each relation in turn, ignoring what must follow. May be late or wrong."""
    from ordjoin.plans.ranking import assign_weights

    tree = join_tree(q)
    weights = assign_weights(rank, tree)
    got: dict = {}
    frames = semijoin_reduce(q, tree)
    for i in tree.order:
        df = frames[i].withColumn("_w", weights[i])
        for v in q.atoms[i].variables:
            if v in got:
                df = df.where(F.col(v) == got[v])
        row = df.orderBy("_w", *q.atoms[i].variables).first()
        if row is None:
            return None
        got.update({v: row[v] for v in q.atoms[i].variables})
    return got


def rank_join_topk(q: ConjunctiveQuery, rank: Rank, k: int, step: int = 1024) -> tuple[DataFrame, int]:
    """Older top-k join of two relations: read both in weight order, in growing prefixes, until k results are no worse
    than the best that an unseen row could give. Returns the answers and the rows read."""
    from ordjoin.plans.ranking import assign_weights

    if len(q.atoms) != 2:
        raise ValueError("two relations only")
    tree = join_tree(q)
    a, b = (q.atoms[i].frame.withColumn("_w", w) for i, w in sorted(assign_weights(rank, tree).items()))
    a, b = a.persist(), b.persist()
    try:
        least = [x.agg(F.min("_w")).first()[0] for x in (a, b)]
        sizes = [a.count(), b.count()]
        on = [v for v in q.atoms[0].variables if v in q.atoms[1].variables]
        while True:
            pa, pb = (x.orderBy("_w").limit(step) for x in (a, b))
            rows = pa.withColumnRenamed("_w", "_wa").join(pb.withColumnRenamed("_w", "_wb"), on).withColumn("_state", F.col("_wa") + F.col("_wb")).orderBy("_state", *tree.met()).limit(k)
            got = rows.select("_state").collect()
            ends = [x.agg(F.max("_w")).first()[0] for x in (pa, pb)]
            if step >= max(sizes):
                return _shown(rows, q, rank), min(step, sizes[0]) + min(step, sizes[1])
            bound = min(ends[0] + least[1], ends[1] + least[0])
            if len(got) >= k and got[-1]["_state"] < bound:
                return _shown(rows, q, rank), 2 * step
            step *= 2
    finally:
        a.unpersist(), b.unpersist()
