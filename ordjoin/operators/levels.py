"""Exact top-k in rounds over the relation order: a frontier of at most k prefixes is extended by one relation a time.

A prefix's priority is the weight of its best completion. Two prefixes of one length have disjoint completions, which
compare by (priority, values) as their prefixes do, so k better prefixes leave no top-k answer to a worse one, and each
level may be cut to k. Entries of a group are cut before they meet the frontier: by value (no better than the bound that
the last level gives, with the best prefix of their group), and for cancellative rankings by place in the group (k).
The frontier is the small side of every join and is broadcast; relations are never shuffled here. Number of rounds: the
number of relations, whatever k and the data. A frontier of up to ``PIN_ROWS`` rows passes through the driver; a larger
one (a large k, or ties without end) stays on the executors, is cut by range partitions and their counts, and is joined
by shuffle beyond ``BROADCAST_ROWS``. What results keep persisted then goes with ``release()``.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field
from decimal import Decimal
from math import prod

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ordjoin.operators.dp import ALL, Prepared, ranked, semijoin_reduce, with_all
from ordjoin.plans.hypergraph import complete_order, disruptive_trios
from ordjoin.plans.jointree import JoinTree, join_tree, layers, order_consistent_tree
from ordjoin.plans.model import Atom, ConjunctiveQuery
from ordjoin.plans.ranking import Rank, Semiring, values, vectors

PIN_ROWS = 200_000  # frontiers up to this pass through the driver
BROADCAST_ROWS = 2_000_000  # frontiers beyond this join by shuffle
_KEPT: list[DataFrame] = []


@dataclass
class PlanStats:
    """Rows of the frontier at each level, and the bound after it."""

    levels: list[int] = field(default_factory=list)
    bounds: list[object] = field(default_factory=list)


def literal(value: object) -> Column:
    """A column of a driver value: also of a struct state."""
    if isinstance(value, dict):
        return F.struct(*[literal(v).alias(k) for k, v in value.items()])
    if isinstance(value, list):
        return F.array(*[literal(v) for v in value])
    return F.lit(value)


def _keep(df: DataFrame) -> DataFrame:
    """Persisted until ``release()``, as a result still reads it."""
    _KEPT.append(df.persist(StorageLevel.MEMORY_AND_DISK))
    return _KEPT[-1]


def release() -> None:
    """Drop what results of large k, unbounded ties and dense codes keep persisted; call it once they have been read."""
    while _KEPT:
        _KEPT.pop().unpersist()


def _pinned(df: DataFrame) -> tuple[DataFrame, int, object]:
    """A small frame as rows held by the driver, their number and last priority."""
    rows = df.toArrow()
    last = rows.column("_prio")[-1].as_py() if rows.num_rows and "_prio" in rows.column_names else None
    spark = df.sparkSession
    return spark.createDataFrame(rows if rows.num_rows else [], df.schema), rows.num_rows, last


def numbered(df: DataFrame, by: Sequence[Column], name: str) -> DataFrame:
    """Add the place (from 1) of each row in a total order, without a task that gets all rows.

    Rows are range partitioned; each partition's offset comes from the counts of those before it.
    """
    parts = _keep(df.repartitionByRange(*by).withColumn("_part", F.spark_partition_id()))
    counts = sorted((r["_part"], r["count"]) for r in parts.groupBy("_part").count().collect())  # one row a partition
    offset, table = 0, []
    for part, n in counts:
        table.append((part, offset))
        offset += n
    offsets = df.sparkSession.createDataFrame(table, "_part int, _offset long")
    inside = F.row_number().over(Window.partitionBy("_part").orderBy(*by))
    return parts.withColumn("_row", inside).join(F.broadcast(offsets), "_part").withColumn(name, (F.col("_row") + F.col("_offset")).cast("long")).drop("_part", "_row", "_offset")


def first_rows(df: DataFrame, by: Sequence[Column], k: int) -> DataFrame:
    """The k first rows in an order."""
    if k <= PIN_ROWS:
        return df.orderBy(*by).limit(k)
    return numbered(df, by, "_nth").where(F.col("_nth") <= k).drop("_nth")


def _cut(level: DataFrame, by: Sequence[Column], k: int, ties: str = "ids") -> tuple[DataFrame, int, object]:
    """The level's k first rows (with ``all``, also those tied with the last), their number and last priority."""
    if ties != "all":
        level = first_rows(level, by, k)
        if k <= PIN_ROWS:
            return _pinned(level)
    else:
        end = first_rows(level.select("_prio"), [F.col("_prio")], k).agg(F.count(F.lit(1)).alias("n"), F.max("_prio").alias("last")).toArrow()
        if end.column("n")[0].as_py() >= k:
            level = level.where(F.col("_prio") <= literal(end.column("last")[0].as_py()))
    level = level.persist(StorageLevel.MEMORY_AND_DISK)
    rows = level.count()
    if rows <= PIN_ROWS:
        out = _pinned(level.orderBy(*by))
        level.unpersist()
        return out
    _KEPT.append(level)
    return level, rows, level.agg(F.max("_prio").alias("last")).toArrow().column("last")[0].as_py() if "_prio" in level.columns else None


def _small(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def sum_topk(q: ConjunctiveQuery, rank: Rank, k: int, tree: JoinTree | None = None, ties: str = "ids", prepared: Prepared | None = None, stats: PlanStats | None = None, bound: bool = True, places: bool = True) -> DataFrame:
    """The k best answers of a full acyclic query: variables, ``weight`` and ``rnk`` (1 to k).

    ``ties``: ``ids`` orders equal weights by variables along the relation order and is deterministic; ``arbitrary``
    leaves them open; ``all`` returns all answers tied with the k-th. A k of 0 or an empty result gives no rows.
    ``bound`` and ``places`` switch the two cuts of entries off, which changes the work and not the answers.
    """
    if k <= 0:
        p = prepared or ranked(q, rank, tree)
        return _finish(_start(p), 0, p, list(p.tree.met()), 0)
    own = prepared is None
    p = prepared or ranked(q, rank, tree).hold()
    try:
        return _run(p, k, ties, stats if stats is not None else PlanStats(), bound, places)
    finally:
        if own:
            p.close()


def _start(p: Prepared) -> DataFrame:
    return p.frames[p.root].withColumnRenamed("_w", "_fixed").withColumnRenamed("_opt", "_prio")


def _run(p: Prepared, k: int, ties: str, stats: PlanStats, bound: bool, places: bool) -> DataFrame:
    tree = p.tree
    met: list[str] = []
    frontier, rows, tau = None, 0, None
    for i in tree.order:
        fresh = [v for v in tree.query.atoms[i].variables if v not in met]
        level = _start(p) if frontier is None else _extend(p, frontier, rows, i, fresh, k, tau, places and ties != "all")
        met += fresh
        frontier, rows, last = _cut(level, [F.col("_prio"), *[F.col(v) for v in (met if ties == "ids" else ())]], k, ties)
        tau = last if bound and rows >= k else None
        stats.levels.append(rows)
        stats.bounds.append(tau)
        if not rows:
            break
    return _finish(frontier, rows, p, list(tree.met()), k)


def _extend(p: Prepared, frontier: DataFrame, rows: int, i: int, fresh: list[str], k: int, tau: object, places: bool) -> DataFrame:
    tree, algebra = p.tree, p.algebra
    open_now = [c for c in frontier.columns if c.startswith("_m") and c != f"_m{i}"]
    rest = algebra.product([F.col("_fixed"), *[F.col(c) for c in open_now]])
    left, keys = with_all(frontier, tree.shared(i))
    left = left.withColumn("_rest", rest)
    entries = p.frames[i].select(*tree.query.atoms[i].variables, F.col("_w").alias("_wi"), "_opt", *[f"_m{c}" for c in tree.children(i)])
    entries, _ = with_all(entries, tree.shared(i))
    per_key = left.groupBy(*keys).agg(F.min("_rest").alias("_least"))
    entries = entries.join(_small(per_key, rows), keys)
    if tau is not None:
        entries = entries.where(algebra.times(F.col("_least"), F.col("_opt")) <= literal(tau))
    entries = entries.drop("_least")
    if p.rank.cancellative and places:
        place = F.row_number().over(Window.partitionBy(*keys).orderBy("_opt", *[v for v in fresh]))
        entries = entries.withColumn("_pos", place).where(F.col("_pos") <= k).drop("_pos")
    out = _small(left, rows).join(entries, keys)
    out = out.withColumn("_prio", algebra.times(F.col("_rest"), F.col("_opt")))
    if tau is not None:
        out = out.where(F.col("_prio") <= literal(tau))
    kept = [c for c in frontier.columns if c not in ("_fixed", "_prio", f"_m{i}")]
    return out.select(*kept, *fresh, *[f"_m{c}" for c in tree.children(i)], algebra.times(F.col("_fixed"), F.col("_wi")).alias("_fixed"), "_prio")


def _finish(frontier: DataFrame, rows: int, p: Prepared, met: list[str], k: int) -> DataFrame:
    """Answers with weight and place; columns of levels that were never reached (no answers) get their types."""
    for i in p.tree.order:
        for v in p.tree.query.atoms[i].variables:
            if v not in frontier.columns:
                frontier = frontier.withColumn(v, F.lit(None).cast(dict(p.tree.query.atoms[i].frame.dtypes)[v]))
    by = [F.col("_prio"), *[F.col(v) for v in met]]
    if rows > PIN_ROWS:
        ranked_rows = numbered(frontier, by, "rnk")
    else:
        ranked_rows = frontier.where(F.lit(k > 0)).withColumn("rnk", F.row_number().over(Window.orderBy(*by)).cast("long"))
    return ranked_rows.select(*p.tree.query.head, p.rank.decode(F.col("_prio")).alias("weight"), "rnk")


def best_answer(q: ConjunctiveQuery, rank: Rank) -> DataFrame:
    """The first answer alone."""
    return sum_topk(q, rank, 1)


# -- lexicographic orders --------------------------------------------------------------------------------------------


def layered(q: ConjunctiveQuery, order: Sequence[str]) -> JoinTree:
    """A tree with one node a variable for a full order without a disruptive trio.

    Node i holds variable i and its earlier neighbours, as the distinct projection of a fully reduced atom. Every atom
    lies inside the node of its last variable and is joined there row by row, so an answer comes as often as the query
    has it, whatever the order.
    """
    base = join_tree(q)
    reduced = semijoin_reduce(q, base, full=True)
    place = {v: n for n, v in enumerate(order)}
    atoms, parents = [], []
    for variables, parent in layers(q, order):
        own = [j for j, a in enumerate(q.atoms) if max(a.variables, key=place.__getitem__) == variables[-1]]
        whole = next((j for j in own if set(q.atoms[j].variables) == set(variables)), None)
        if whole is not None:
            df = reduced[whole].select(*variables)
        else:
            home = next(i for i, a in enumerate(q.atoms) if set(variables) <= set(a.variables))
            df = reduced[home].select(*variables).distinct()
        for j in own:
            if j != whole:
                df = df.join(reduced[j], list(q.atoms[j].variables)).select(*variables)
        atoms.append(Atom(f"layer_{variables[-1]}", df, variables))
        parents.append(parent if parent >= 0 else None)
    parents = [None if i == 0 else (0 if x is None else x) for i, x in enumerate(parents)]
    lq = ConjunctiveQuery(tuple(atoms), q.head, tuple(a.name for a in atoms))
    return JoinTree(lq, tuple(range(len(atoms))), tuple(parents))


def lex_topk(q: ConjunctiveQuery, order: Sequence[str | tuple[str, bool]], k: int) -> DataFrame:
    """The k first answers in a lexicographic order: head variables and ``rnk``.

    The order may name some variables only; the others follow in the order of the tree. An answer comes as often as the
    join has it, whatever the order. Orders with a disruptive trio are ranked through the ordered values themselves
    (``lex_as_values``), or through rank vectors (``lex_as_sum``) where a descending variable isn't a number.
    """
    rank = Rank.lex(order)
    names = [v for v, _ in rank.order]
    if disruptive_trios(q, names) or complete_order(q, names) is None:
        weights, tree = lex_as_values(q, rank) or lex_as_sum(q, rank)
        return sum_topk(tree.query, weights, k, tree).drop("weight")
    tree = order_consistent_tree(q, names) or layered(q, complete_order(q, names))
    down = dict(rank.order)
    frames = semijoin_reduce(tree.query, tree)
    frontier, rows, met = None, 0, []
    for i in tree.order:
        fresh = [v for v in tree.query.atoms[i].variables if v not in met]
        if frontier is None:
            level = frames[i]
        else:
            left, keys = with_all(frontier, tree.shared(i))
            right, _ = with_all(frames[i], tree.shared(i))
            level = _small(left, rows).join(right, keys).select(*met, *fresh)
        met += fresh
        frontier, rows, _ = _cut(level, _sorts(names, met, down), k)
    by = _sorts(names, met, down)
    placed = numbered(frontier, by, "rnk") if rows > PIN_ROWS else frontier.withColumn("rnk", F.row_number().over(Window.orderBy(*by)).cast("long"))
    return placed.select(*q.head, "rnk")


def _sorts(names: Sequence[str], met: Sequence[str], down: dict[str, bool]) -> list[Column]:
    known = [v for v in names if v in met]
    return [F.col(v).desc() if down.get(v) else F.col(v).asc() for v in [*known, *[v for v in met if v not in known]]]


def lex_all(q: ConjunctiveQuery, order: Sequence[str | tuple[str, bool]]) -> DataFrame:
    """All answers, globally sorted: one range partitioning and local sorts."""
    rank = Rank.lex(order)
    names = [v for v, _ in rank.order]
    out = full_join(q)
    return out.orderBy(*_sorts(names, [*names, *[v for v in q.variables if v not in names]], dict(rank.order))).select(*q.head)


def full_join(q: ConjunctiveQuery, frames: dict[int, DataFrame] | None = None, hint: str | None = None) -> DataFrame:
    """The full join result along the tree (all variables); ``hint``: a join hint for each relation that is added."""
    tree = join_tree(q)
    frames = frames or {i: a.frame for i, a in enumerate(q.atoms)}
    out: DataFrame | None = None
    for i in tree.order:
        if out is None:
            out = frames[i].select(*q.atoms[i].variables)
        else:
            left, keys = with_all(out, tree.shared(i))
            right, _ = with_all(frames[i].select(*q.atoms[i].variables), tree.shared(i))
            out = left.join(right.hint(hint) if hint else right, keys).drop(ALL)
    return out


def dense_codes(values: DataFrame, column: str, code: str = "code", descending: bool = False) -> DataFrame:
    """(column, code): place of each distinct value in sorted order from 0, without an unpartitioned window."""
    by = F.col(column).desc() if descending else F.col(column).asc()
    return numbered(values.select(column).distinct(), [by], code).select(column, (F.col(code) - 1).alias(code))


def lex_as_values(q: ConjunctiveQuery, rank: Rank) -> tuple[Rank, JoinTree] | None:
    """The order as a ranking whose state is a struct with a place for each ordered variable's value.

    An atom fills in the places of its own variables, and structs compare place by place, so no codes and no passes over
    domains are needed. None where a descending variable can't be negated.
    """
    kinds = {v: t for a in q.atoms for v, t in a.frame.select(*a.variables).dtypes}
    if any(down and not kinds[v].startswith(("tinyint", "smallint", "int", "bigint", "decimal", "float", "double")) for v, down in rank.order):
        return None
    names = [v for v, _ in rank.order]
    empty = {v: F.lit(None).cast(kinds[v]) for v in names}
    terms = tuple(((v,), F.struct(*[(((-F.col(v)) if down else F.col(v)).cast(kinds[v]) if x == v else empty[x]).alias(x) for x in names])) for v, down in rank.order)
    return Rank("lex_values", terms, values(empty), True), join_tree(q)


def lex_as_sum(q: ConjunctiveQuery, rank: Rank, numeric: bool = False) -> tuple[Rank, JoinTree]:
    """A SUM ranking that orders answers lexicographically, also with disruptive trios, and the tree to run it on.

    Each ordered variable gets its value's dense place in the sorted domain. States are rank vectors, or with
    ``numeric`` single DECIMAL(38,0) numbers: a code counts as often as the domains of the variables after it have
    combinations; that is refused where it could overflow.
    """
    names = [v for v, _ in rank.order]
    m, frames, sizes = len(names), {i: a.frame for i, a in enumerate(q.atoms)}, []
    for v, down in rank.order:
        holders = [i for i, a in enumerate(q.atoms) if v in a.variables]
        domain = frames[holders[0]].select(v)
        for i in holders[1:]:
            domain = domain.unionByName(frames[i].select(v))
        codes = dense_codes(domain, v, f"_code_{v}", down)
        if numeric:
            sizes.append(codes.count())
        for i in holders[:1]:
            frames[i] = frames[i].join(codes, v)
    homes = {v: next(i for i, a in enumerate(q.atoms) if v in a.variables) for v in names}
    atoms = []
    for i, a in enumerate(q.atoms):
        extra = [f"_code_{v}" for v in names if homes[v] == i]
        atoms.append(Atom(a.name, frames[i].select(*a.variables, *[F.col(c).alias(c[1:]) for c in extra]), (*a.variables, *[c[1:] for c in extra])))
    lq = ConjunctiveQuery(tuple(atoms), q.head, q.relations)
    if numeric:
        if prod(sizes) >= 10**38:
            raise OverflowError("codes don't fit in DECIMAL(38,0)")
        step = [F.lit(Decimal(prod(sizes[j + 1 :]))).cast("decimal(38,0)") for j in range(m)]  # a plain int literal ends at 64 bits
        terms = tuple(((f"code_{v}",), (F.col(f"code_{v}").cast("decimal(38,0)") * step[j]).cast("decimal(38,0)")) for j, v in enumerate(names))
        algebra = Semiring("min-plus", F.min, lambda a, b: (a + b).cast("decimal(38,0)"), F.lit(0).cast("decimal(38,0)"))
    else:
        terms = tuple(((f"code_{v}",), F.array(*[F.col(f"code_{v}") if x == j else F.lit(0).cast("long") for x in range(m)])) for j, v in enumerate(names))
        algebra = vectors(m)
    return Rank("lex_vectors", terms, algebra, True), join_tree(lq)


def unranked(q: ConjunctiveQuery, k: int) -> DataFrame:
    """Any k answers: the reduction makes every prefix extensible, then a limit stops the joins."""
    return full_join(q, semijoin_reduce(q)).select(*q.head).limit(k)


def per_group_topk(q: ConjunctiveQuery, rank: Rank, group: str, k: int) -> DataFrame:
    """The k best answers for each value of one variable: ``rnk`` counts inside it.

    Rows of the relation that holds the variable are cut to those that can be among their group's first k, by the
    group's own bound; then all is joined and ranked inside the groups.
    """
    root = next(i for i, a in enumerate(q.atoms) if group in a.variables)
    p = ranked(q, rank, join_tree(q, root))
    order = Window.partitionBy(group).orderBy("_opt")
    bound = p.frames[root].withColumn("_pos", F.row_number().over(order)).where(F.col("_pos") <= k).groupBy(group).agg(F.max("_opt").alias("_tau"), F.count(F.lit(1)).alias("_n"))
    heads = p.frames[root].join(bound, group).where((F.col("_n") < k) | (F.col("_opt") <= F.col("_tau"))).select(*q.atoms[root].variables)
    cut = ConjunctiveQuery(tuple(a.with_frame(heads) if i == root else a for i, a in enumerate(q.atoms)), q.head, q.relations)
    answers = full_join(cut).withColumn("weight", rank.decode(rank.cost()))
    place = F.row_number().over(Window.partitionBy(group).orderBy(rank.cost(), *[v for v in q.variables]))
    return answers.withColumn("rnk", place.cast("long")).where(F.col("rnk") <= k).select(*q.head, "weight", "rnk")
