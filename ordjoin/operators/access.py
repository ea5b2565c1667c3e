"""Direct access to answers by position, selection, and aggregates over joins that are never built."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import replace
from decimal import Decimal

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ordjoin.operators.dp import count_prepared, ranked, with_all
from ordjoin.operators.levels import _keep, _pinned, _sorts, layered
from ordjoin.plans.hypergraph import complete_order, disruptive_trios, is_connex
from ordjoin.plans.jointree import JoinTree, join_tree, order_consistent_tree
from ordjoin.plans.model import ConjunctiveQuery
from ordjoin.plans.ranking import Rank

WIDE = "decimal(38,0)"


def can_access(q: ConjunctiveQuery, order: Sequence[str | tuple[str, bool]]) -> bool:
    """No disruptive trio, and acyclic also with an atom of the ordered variables."""
    names = [v for v, _ in Rank.lex(order).order]
    return not disruptive_trios(q, names) and is_connex(q, names) and complete_order(q, names) is not None


def running_total(df: DataFrame, keys: Sequence[str], value: str, by: Sequence) -> DataFrame:
    """Add ``_before``: the sum of ``value`` over rows before this one in its group. One group for all rows (no keys) is
    range partitioned, summed by partition, and shifted by the partitions before, so no task gets all rows."""
    if keys:
        w = Window.partitionBy(*keys).orderBy(*by).rowsBetween(Window.unboundedPreceding, -1)
        return df.withColumn("_before", F.coalesce(F.sum(value).over(w), F.lit(0)).cast(WIDE))
    parts = _keep(df.repartitionByRange(*by).withColumn("_part", F.spark_partition_id()))
    sums = sorted((r["_part"], r["s"]) for r in parts.groupBy("_part").agg(F.sum(value).cast(WIDE).alias("s")).collect())  # one row a partition
    table, total = [], Decimal(0)
    for part, s in sums:
        table.append((part, total))
        total += s
    shifts = df.sparkSession.createDataFrame(table, f"_part int, _shift {WIDE}")
    w = Window.partitionBy("_part").orderBy(*by).rowsBetween(Window.unboundedPreceding, -1)
    inside = parts.withColumn("_inside", F.coalesce(F.sum(value).over(w), F.lit(0)))
    return inside.join(F.broadcast(shifts), "_part").withColumn("_before", (F.col("_inside") + F.col("_shift")).cast(WIDE)).drop("_part", "_inside", "_shift")


def _access_tree(q: ConjunctiveQuery, names: Sequence[str]) -> JoinTree:
    full = complete_order(q, names)
    if full is None:
        raise ValueError("the order has a disruptive trio")
    return order_consistent_tree(q, names) or layered(q, full)


def direct_access(q: ConjunctiveQuery, order: Sequence[str | tuple[str, bool]], positions: Sequence[int]) -> DataFrame:
    """Answers at positions (from 1) of a lexicographic order: ``position`` and head. Positions past the end give none.

    Counts come bottom-up; each level turns a remainder into an entry of one group by prefix sums. All positions go down
    together, one join a level.
    """
    rank = Rank.lex(order)
    names, down = [v for v, _ in rank.order], dict(rank.order)
    tree = _access_tree(q, names)
    p = count_prepared(tree).hold()
    try:
        total = p.frames[p.root].agg(F.coalesce(F.sum("_opt"), F.lit(0)).cast(WIDE)).first()[0]
        spark = p.frames[p.root].sparkSession
        wanted = [(int(x), Decimal(int(x) - 1), total) for x in positions if 1 <= x <= total]
        state = spark.createDataFrame(wanted, f"position long, _q {WIDE}, _all {WIDE}")
        met: list[str] = []
        for i in tree.order:
            fresh = [v for v in tree.query.atoms[i].variables if v not in met]
            keys = list(tree.shared(i))
            entries = p.frames[i]
            if keys:
                entries = entries.join(F.broadcast(state.select(*keys).distinct()), keys)
            entries = running_total(entries, keys, "_opt", _sorts(names, fresh, down) or [F.lit(0)])
            entries = entries.withColumnRenamed("_opt", "_cnt").drop("_w")
            others = F.lit(1) if i == p.root else F.expr(f"_all div _m{i}")  # the count of this group divides the product
            here = state.withColumn("_others", others.cast(WIDE))
            left, on = with_all(here, keys)
            right, _ = with_all(entries, keys)
            low, high = (F.col("_before") * F.col("_others")).cast(WIDE), ((F.col("_before") + F.col("_cnt")) * F.col("_others")).cast(WIDE)
            step = F.broadcast(left).join(right, on).where((low <= F.col("_q")) & (F.col("_q") < high))
            step = step.withColumn("_q", (F.col("_q") - low).cast(WIDE)).withColumn("_all", (F.col("_others") * F.col("_cnt")).cast(WIDE))
            kept = [c for c in state.columns if c not in (f"_m{i}", "_q", "_all")]
            met += fresh
            state, _, _ = _pinned(step.select(*kept, *fresh, "_q", "_all", *[f"_m{c}" for c in tree.children(i)]))
        return state.select("position", *q.head)
    finally:
        p.close()


def enumerate_by_access(q: ConjunctiveQuery, order: Sequence[str | tuple[str, bool]], k: int) -> DataFrame:
    return direct_access(q, order, range(1, k + 1))


def median_answer(q: ConjunctiveQuery, order: Sequence[str | tuple[str, bool]]) -> DataFrame:
    from ordjoin.operators.dp import count_answers

    n = int(count_answers(q).first()["answers"])
    return direct_access(q, order, [(n + 1) // 2])


def sum_access(q: ConjunctiveQuery, rank: Rank, positions: Sequence[int]) -> DataFrame:
    """Answers at positions of a SUM order, where one atom holds all ranked variables; others are refused."""
    root = next((i for i, a in enumerate(q.atoms) if rank.variables <= set(a.variables)), None)
    if root is None:
        raise ValueError("no atom holds all ranked variables")
    a = q.atoms[root]
    state = a.with_frame(a.frame.withColumn("_state", rank.cost()))
    keyed = ConjunctiveQuery(tuple(state if i == root else x for i, x in enumerate(q.atoms)), q.head, q.relations)
    named = [x.with_frame(x.frame.withColumnRenamed("_state", "state")) for x in keyed.atoms]
    atoms = tuple(replace(x, variables=("state", *x.variables)) if i == root else x for i, x in enumerate(named))
    got = direct_access(ConjunctiveQuery(atoms, (*q.head, "state"), q.relations), ["state"], positions)
    return got.withColumn("weight", rank.decode(F.col("state"))).drop("state")


def weight_histogram(q: ConjunctiveQuery, rank: Rank) -> DataFrame:
    """(weight, answers) of all answers of an integer SUM, without building them: messages map weights to counts."""
    from ordjoin.plans.ranking import assign_weights

    tree = join_tree(q)
    weights = assign_weights(rank, tree)
    sent: dict[int, tuple[DataFrame, list[str]]] = {}
    for i in reversed(tree.order):
        df = q.atoms[i].frame.withColumn("_s", weights[i]).withColumn("_c", F.lit(1).cast(WIDE))
        needed = sorted({v for c in tree.children(i) for v in tree.shared(c)} | set(tree.shared(i)))
        df = df.groupBy(*needed, "_s").agg(F.sum("_c").cast(WIDE).alias("_c"))
        for c in tree.children(i):
            message, keys = sent[c]
            left, _ = with_all(df, tree.shared(c))
            df = left.join(message, keys).withColumn("_s", F.col("_s") + F.col("_ms")).withColumn("_c", (F.col("_c") * F.col("_mc")).cast(WIDE)).drop("_ms", "_mc", "_all")
            left_over = sorted({v for d in tree.children(i)[tree.children(i).index(c) + 1 :] for v in tree.shared(d)} | set(tree.shared(i)))
            df = df.groupBy(*left_over, "_s").agg(F.sum("_c").cast(WIDE).alias("_c"))
        if tree.parent[i] is None:
            return df.select(rank.decode(F.col("_s")).alias("weight"), F.col("_c").alias("answers"))
        out, keys = with_all(df, tree.shared(i))
        sent[i] = out.select(*keys, F.col("_s").alias("_ms"), F.col("_c").alias("_mc")), keys
    raise AssertionError


def select_nth(q: ConjunctiveQuery, rank: Rank, position: int) -> DataFrame:
    """The weight of the answer at a position (from 1) of an integer SUM order, and how many answers lie before it."""
    hist = weight_histogram(q, rank)
    order = F.col("weight").desc() if rank.descends else F.col("weight").asc()
    w = Window.orderBy(order).rowsBetween(Window.unboundedPreceding, Window.currentRow)  # one row a weight
    run = hist.withColumn("_upto", F.sum("answers").over(w))
    hit = run.where((F.col("_upto") >= position) & (F.col("_upto") - F.col("answers") < position))
    return hit.select(F.lit(position).cast("long").alias("position"), "weight", (F.col("_upto") - F.col("answers")).cast(WIDE).alias("before"), "answers")


def agg_over_join(q: ConjunctiveQuery, variable: str, by: Sequence[str] = ()) -> DataFrame:
    """count, sum, min, max and avg of a variable over all answers (grouped by variables of the same atom)."""
    root = next(i for i, a in enumerate(q.atoms) if {variable, *by} <= set(a.variables))
    p = count_prepared(join_tree(q, root))
    n, x = F.sum("_opt").cast(WIDE), F.sum((F.col(variable).cast(WIDE) * F.col("_opt")).cast(WIDE)).cast(WIDE)
    return p.frames[root].groupBy(*by).agg(n.alias("answers"), x.alias("total"), F.min(variable).alias("least"), F.max(variable).alias("most"), (x / n).cast("double").alias("mean"))


def best_through(q: ConjunctiveQuery, rank: Rank, i: int) -> DataFrame:
    """Each row of relation i that some answer uses, with the weight of the best such answer."""
    from ordjoin.operators.dp import through_weights

    return through_weights(ranked(q, rank))[i].select(*q.atoms[i].variables, rank.decode(F.col("_through")).alias("weight"))
