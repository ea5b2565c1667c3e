"""Registered queries of the ranked-join engine, each with SQL for the same rows where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ordjoin import workloads as W
from ordjoin.operators import ablations, access, baselines, cursor, cyclic, dp, fds, index, levels, predicates, projection, union
from ordjoin.operators.asof import as_of
from ordjoin.plans.model import FD, atom, cq
from ordjoin.plans.planner import topk
from ordjoin.plans.ranking import Rank, desc
from ordjoin.plans.sqlfront import ranked_sql
from ordjoin.sources import tables as T
from ordjoin.streaming import ranked as streams

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
K = 100

# -- SQL building blocks ---------------------------------------------------------------------------------------------
EDGE = """edge AS (SELECT a.l_partkey AS src, b.l_partkey AS dst, min(CAST(a.l_quantity AS BIGINT)) AS w FROM lineitem a
JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND b.l_linenumber = a.l_linenumber + 1 WHERE a.l_partkey <> b.l_partkey GROUP BY 1, 2)"""
BASE = """r AS (SELECT o_custkey AS x1, o_orderkey AS x2, CAST(round(o_totalprice * 100) AS BIGINT) AS wr FROM orders),
s AS (SELECT c_custkey AS x1, c_nationkey AS x3, CAST(round(c_acctbal * 100) AS BIGINT) AS ws FROM customer),
t AS (SELECT l_orderkey AS x2, l_suppkey AS x4, l_partkey AS part, CAST(round(l_extendedprice * 100) AS BIGINT) AS wt, CAST(l_quantity AS BIGINT) AS qty FROM lineitem),
u AS (SELECT s_suppkey AS x4, s_nationkey AS x5, CAST(round(s_acctbal * 100) AS BIGINT) AS wu FROM supplier),
td AS (SELECT DISTINCT x2, x4 FROM t)"""
EVENTS = "ev AS (SELECT user_id AS u, epoch_us(ts) AS t, event_id AS e, CAST(round(value * 100) AS BIGINT) AS w, event_type AS kind FROM events)"
PATH3 = "edge a JOIN edge b ON b.src = a.dst JOIN edge c ON c.src = b.dst"
NODES3 = "a.src AS x1, a.dst AS x2, b.dst AS x3, c.dst AS x4"
TREE4 = "r JOIN s ON s.x1 = r.x1 JOIN t ON t.x2 = r.x2 JOIN u ON u.x4 = t.x4"


def top(ctes: str, columns: str, source: str, weight: str, ties: str, k: int = K, down: str = "", where: str = "") -> str:
    """The k first rows by weight, then ties, with their place."""
    inner = f"SELECT {columns}, {weight} AS weight, row_number() OVER (ORDER BY {weight} {down}, {ties}) AS rnk FROM {source} {where}"
    return f"WITH {ctes} SELECT * FROM ({inner}) WHERE rnk <= {k}"


def query(sql: str | None = None) -> Callable[[Query], Query]:
    def register(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return register


# -- reduction and messages ------------------------------------------------------------------------------------------
@query(f"WITH {BASE} SELECT x1, x2 FROM r WHERE x2 IN (SELECT x2 FROM t WHERE x4 IN (SELECT x4 FROM u)) AND x1 IN (SELECT x1 FROM s)")
def semijoin_reduced_orders(spark: SparkSession, sf: str) -> DataFrame:
    return dp.semijoin_reduce(W.tree4_keys(spark, sf))[0]


@query(f"WITH {BASE} SELECT x1, x2 FROM r WHERE x2 NOT IN (SELECT x2 FROM t)")
def dangling_orders(spark: SparkSession, sf: str) -> DataFrame:
    return dp.dangling(W.tree4_keys(spark, sf))[0]


@query(f"WITH {BASE} SELECT DISTINCT c.x1, c.x3 FROM s c JOIN r ON r.x1 = c.x1 JOIN t ON t.x2 = r.x2")
def fully_reduced_customers(spark: SparkSession, sf: str) -> DataFrame:
    return dp.semijoin_reduce(W.tree4_keys(spark, sf), full=True)[1]


@query(f"WITH {BASE} SELECT t.x2, min(wt + wu) AS best FROM t JOIN u ON u.x4 = t.x4 GROUP BY t.x2")
def min_weight_messages(spark: SparkSession, sf: str) -> DataFrame:
    p = dp.ranked(W.tree4(spark, sf), W.tree4_sum())
    return p.frames[2].groupBy("x2").agg(F.min("_opt").alias("best"))


@query(f"WITH {BASE} SELECT r.x1, r.x2, min(wr + ws + wt + wu) AS weight FROM {TREE4} GROUP BY r.x1, r.x2")
def best_through_orders(spark: SparkSession, sf: str) -> DataFrame:
    return access.best_through(W.tree4(spark, sf), W.tree4_sum(), 0).select("x1", "x2", "weight")


@query(f"WITH {BASE}, a AS (SELECT t.x2, t.x4, t.part, wt, wr + ws + wt + wu AS g FROM {TREE4}) SELECT x2, x4, part, wt, min(g) AS weight FROM a GROUP BY x2, x4, part, wt")
def best_through_lines(spark: SparkSession, sf: str) -> DataFrame:
    return access.best_through(W.tree4(spark, sf), W.tree4_sum(), 2).select("x2", "x4", "part", "wt", "weight").distinct()


@query(f"WITH {EDGE} SELECT src, dst, w, row_number() OVER (PARTITION BY src ORDER BY w, dst) AS pos FROM edge QUALIFY pos <= 3")
def sorted_groups(spark: SparkSession, sf: str) -> DataFrame:
    q = W.chain(spark, sf, 2)
    p = dp.ranked(q, W.chain_sum(2))
    return index.sort_groups(p, 1, [F.col("_opt"), F.col("x3")], 3).select(F.col("x2").alias("src"), F.col("x3").alias("dst"), F.col("w2").alias("w"), F.col("_pos").cast("long").alias("pos"))


# -- lexicographic ---------------------------------------------------------------------------------------------------
KEYS4 = "r JOIN s ON s.x1 = r.x1 JOIN td t ON t.x2 = r.x2 JOIN u ON u.x4 = t.x4"


def _lex_sql(order: str, k: int = K) -> str:
    return f"WITH {BASE} SELECT * FROM (SELECT r.x1, r.x2, s.x3, t.x4, u.x5, row_number() OVER (ORDER BY {order}) AS rnk FROM {KEYS4}) WHERE rnk <= {k}"


def _lex(spark: SparkSession, sf: str, order: list) -> DataFrame:
    return levels.lex_topk(W.tree4_keys(spark, sf), order, K)


@query(_lex_sql("r.x1, r.x2, x3, t.x4, x5"))
def lex_topk_default(spark: SparkSession, sf: str) -> DataFrame:
    return _lex(spark, sf, ["x1", "x2", "x3", "x4", "x5"])


@query(_lex_sql("r.x2, r.x1, x3, t.x4, x5"))
def lex_topk_reordered(spark: SparkSession, sf: str) -> DataFrame:
    return _lex(spark, sf, ["x2", "x1", "x3", "x4", "x5"])


@query(_lex_sql("r.x1, r.x2, t.x4, x5, x3"))
def lex_topk_alt_topology(spark: SparkSession, sf: str) -> DataFrame:
    return _lex(spark, sf, ["x1", "x2", "x4", "x5", "x3"])


@query(_lex_sql("r.x1 DESC, r.x2, x3 DESC, t.x4, x5"))
def lex_partial_desc(spark: SparkSession, sf: str) -> DataFrame:
    return _lex(spark, sf, [desc("x1"), "x2", desc("x3"), "x4", "x5"])


@query(_lex_sql("t.x4, x5, r.x2, r.x1, x3"))
def lex_topk_from_leaf(spark: SparkSession, sf: str) -> DataFrame:
    return _lex(spark, sf, ["x4", "x5", "x2", "x1", "x3"])


@query(_lex_sql("r.x1, t.x4, r.x2, x3, x5"))
def lex_with_trio(spark: SparkSession, sf: str) -> DataFrame:
    return _lex(spark, sf, ["x1", "x4", "x2", "x3", "x5"])


@query(_lex_sql("r.x1, x3, t.x4, x5, r.x2"))
def lex_with_inner_trio(spark: SparkSession, sf: str) -> DataFrame:
    return _lex(spark, sf, ["x1", "x3", "x4", "x5", "x2"])


@query(_lex_sql("r.x1, t.x4, r.x2, x3, x5"))
def lex_with_trio_numeric(spark: SparkSession, sf: str) -> DataFrame:
    rank, tree = levels.lex_as_sum(W.tree4_keys(spark, sf), Rank.lex(["x1", "x4", "x2", "x3", "x5"]), numeric=True)
    return levels.sum_topk(tree.query, rank, K, tree).drop("weight")


@query(_lex_sql("r.x1, r.x2, x3, t.x4, x5"))
def lex_layered(spark: SparkSession, sf: str) -> DataFrame:
    order = ["x1", "x2", "x3", "x4", "x5"]
    tree = levels.layered(W.tree4_keys(spark, sf), order)
    return levels.lex_topk(tree.query, order, K)


@query(
    "SELECT * FROM (SELECT l_suppkey AS a, l_returnflag AS b, s_nationkey AS d, l_linestatus AS c, s_name AS e, row_number() OVER (ORDER BY l_suppkey, l_returnflag, s_nationkey, l_linestatus, s_name) AS rnk "
    f"FROM lineitem JOIN supplier ON s_suppkey = l_suppkey) WHERE rnk <= {10 * K}"
)
def lex_repeated_rows(spark: SparkSession, sf: str) -> DataFrame:
    """Rows that stand often in an order that no tree of the atoms follows: every answer comes as often as in the join."""
    li = T.load_table(spark, sf, "lineitem").select("l_suppkey", "l_returnflag", "l_linestatus")
    su = T.load_table(spark, sf, "supplier").select("s_suppkey", "s_nationkey", "s_name")
    return levels.lex_topk(cq([atom("lines", li, ["a", "b", "c"]), atom("suppliers", su, ["a", "d", "e"])], ["a", "b", "d", "c", "e"]), ["a", "b", "d", "c", "e"], 10 * K)


@query(f"WITH {BASE} SELECT r.x1, r.x2, s.x3, t.x4, u.x5 FROM {KEYS4}")
def lex_complete(spark: SparkSession, sf: str) -> DataFrame:
    return levels.lex_all(W.tree4_keys(spark, sf), ["x1", "x2", "x3", "x4", "x5"])


@query(f"WITH {EDGE} SELECT CAST(1000 AS BIGINT) AS n, CAST(1000 AS BIGINT) AS n_valid FROM (SELECT count(*) AS c FROM {PATH3}) WHERE c >= 1000")
def unranked_count_check(spark: SparkSession, sf: str) -> DataFrame:
    got = levels.unranked(W.chain(spark, sf, 3), 1000)
    e = T.edges(spark, sf).select("src", "dst")
    rows = got
    for a, b in (("x1", "x2"), ("x2", "x3"), ("x3", "x4")):
        rows = rows.join(e.select(F.col("src").alias(a), F.col("dst").alias(b)), [a, b], "left_semi")
    return got.agg(F.count(F.lit(1)).alias("n")).withColumn("n_valid", F.lit(rows.count()).cast("long"))


@query(f"WITH {EDGE} SELECT count(*) > 0 AS found FROM (SELECT 1 FROM {PATH3} LIMIT 1)")
def exists_check(spark: SparkSession, sf: str) -> DataFrame:
    return spark.createDataFrame([(dp.exists(W.chain(spark, sf, 3)),)], "found boolean")


# -- sums ------------------------------------------------------------------------------------------------------------
TIES4 = "r.x1, r.x2, wr, x3, ws, t.x4, part, wt, x5, wu"
COLS4 = "r.x1, r.x2, s.x3, t.x4, t.part, u.x5"


@query(top(BASE, COLS4, TREE4, "wr + ws + wt + wu", TIES4))
def sum_topk(spark: SparkSession, sf: str) -> DataFrame:
    return levels.sum_topk(W.tree4(spark, sf), W.tree4_sum(), K)


SIDE = "s2 AS (SELECT user_id AS x1, event_id AS x3, CAST(round(value * 100) AS BIGINT) AS ws FROM events)"


@query(top(f"{BASE}, {SIDE}", "r.x1, r.x2, s.x3, t.x4, t.part, u.x5", "r JOIN s2 s ON s.x1 = r.x1 JOIN t ON t.x2 = r.x2 JOIN u ON u.x4 = t.x4", "wr + ws + wt + wu", TIES4))
def sum_topk_fanout(spark: SparkSession, sf: str) -> DataFrame:
    return levels.sum_topk(W.tree4(spark, sf, events=True), W.tree4_sum(), K)


SUM3 = "a.w + b.w + c.w"
TIES3 = "a.src, a.dst, b.dst, c.dst"
PATH4 = f"{PATH3} JOIN edge d ON d.src = c.dst"


@query(top(EDGE, NODES3, PATH3, SUM3, TIES3))
def sum_topk_chain3(spark: SparkSession, sf: str) -> DataFrame:
    return levels.sum_topk(W.chain(spark, sf, 3), W.chain_sum(3), K)


def _bounded_paths(k: int) -> str:
    """SQL for the k lightest four-paths: the k-th smallest best completion of a first edge bounds the k-th weight (each
    such edge starts an answer), and prefixes whose best completion lies over the bound start no answer."""
    return (
        f"WITH {EDGE}, m1 AS (SELECT src, min(w) AS m FROM edge GROUP BY src), m2 AS (SELECT e.src, min(e.w + m) AS m FROM edge e JOIN m1 ON m1.src = e.dst GROUP BY e.src), "
        "m3 AS (SELECT e.src, min(e.w + m) AS m FROM edge e JOIN m2 ON m2.src = e.dst GROUP BY e.src), root AS (SELECT e.src, e.dst, e.w, e.w + m AS o FROM edge e JOIN m3 ON m3.src = e.dst), "
        f"tau AS (SELECT CASE WHEN count(*) = {k} THEN max(o) ELSE 1000000 END AS t FROM (SELECT o FROM root ORDER BY o LIMIT {k})), "
        "a1 AS MATERIALIZED (SELECT src AS x1, dst AS x2, w FROM root, tau WHERE o <= t), "
        "a2 AS MATERIALIZED (SELECT x1, x2, e.dst AS x3, a1.w + e.w AS w FROM a1 JOIN edge e ON e.src = x2 JOIN m2 ON m2.src = e.dst, tau WHERE a1.w + e.w + m <= t), "
        "a3 AS MATERIALIZED (SELECT x1, x2, x3, e.dst AS x4, a2.w + e.w AS w FROM a2 JOIN edge e ON e.src = x3 JOIN m1 ON m1.src = e.dst, tau WHERE a2.w + e.w + m <= t), "
        "a4 AS (SELECT x1, x2, x3, x4, e.dst AS x5, a3.w + e.w AS weight FROM a3 JOIN edge e ON e.src = x4, tau WHERE a3.w + e.w <= t) "
        f"SELECT * FROM (SELECT *, row_number() OVER (ORDER BY weight, x1, x2, x3, x4, x5) AS rnk FROM a4) WHERE rnk <= {k}"
    )


@query(_bounded_paths(1000))
def sum_topk_chain4(spark: SparkSession, sf: str) -> DataFrame:
    return levels.sum_topk(W.chain(spark, sf, 4), W.chain_sum(4), 1000)


@query(top(EDGE, NODES3, PATH3, SUM3, TIES3, down="DESC"))
def sum_desc(spark: SparkSession, sf: str) -> DataFrame:
    return levels.sum_topk(W.chain(spark, sf, 3), W.chain_sum(3, desc=True), K)


@query(top(EDGE, NODES3, PATH3, "3 * a.w + 2 * b.w + c.w", TIES3))
def weighted_sum(spark: SparkSession, sf: str) -> DataFrame:
    return levels.sum_topk(W.chain(spark, sf, 3), Rank.sum({"w1": 3 * F.col("w1"), "w2": 2 * F.col("w2"), "w3": F.col("w3")}), K)


@query(top(EDGE, NODES3, PATH3, SUM3, TIES3, 1))
def top1(spark: SparkSession, sf: str) -> DataFrame:
    return levels.best_answer(W.chain(spark, sf, 3), W.chain_sum(3))


@query(f"WITH {EDGE} SELECT x1, x2, x3, x4, weight FROM (SELECT {NODES3}, {SUM3} AS weight, rank() OVER (ORDER BY {SUM3}) AS place FROM {PATH3}) WHERE place <= {K}")
def sum_all_ties(spark: SparkSession, sf: str) -> DataFrame:
    return levels.sum_topk(W.chain(spark, sf, 3), W.chain_sum(3), K, ties="all").drop("rnk")


@query(top(EDGE, NODES3, PATH3, SUM3, TIES3, 700))
def sum_cursor_batches(spark: SparkSession, sf: str) -> DataFrame:
    with cursor.OrderedCursor(W.chain(spark, sf, 3), W.chain_sum(3), first=100) as c:
        a, b, d = c.next_batch(), c.next_batch(), c.next_batch()
        return a.unionByName(b).unionByName(d)


@query(f"WITH {EDGE} SELECT {NODES3}, {SUM3} AS weight FROM {PATH3} WHERE {SUM3} <= 8")
def frontier_rounds(spark: SparkSession, sf: str) -> DataFrame:
    p = dp.ranked(W.chain(spark, sf, 3), W.chain_sum(3))
    low = cursor.answers_within(p, 4)
    return low.unionByName(cursor.answers_within(p, 6, 4)).unionByName(cursor.answers_within(p, 8, 6))


@query(f"WITH {EDGE} SELECT {NODES3}, {SUM3} AS weight, CASE WHEN {SUM3} <= 4 THEN 1 WHEN {SUM3} <= 6 THEN 2 ELSE 3 END AS batch FROM {PATH3} WHERE {SUM3} <= 8")
def rising_bound(spark: SparkSession, sf: str) -> DataFrame:
    """The same rounds from kept prefixes: no round makes an earlier answer anew."""
    rounds = cursor.RisingBound(W.chain(spark, sf, 3), W.chain_sum(3))
    out = [rounds.up_to(tau).withColumn("batch", F.lit(n)) for n, tau in enumerate((4, 6, 8), 1)]
    return out[0].unionByName(out[1]).unionByName(out[2])


@query(top(EDGE, NODES3, PATH3, SUM3, TIES3))
def sum_sql_front(spark: SparkSession, sf: str) -> DataFrame:
    T.edges(spark, sf).createOrReplaceTempView("ordjoin_edge")
    text = """SELECT a.src AS x1, a.dst AS x2, b.dst AS x3, c.dst AS x4 FROM ordjoin_edge a, ordjoin_edge b, ordjoin_edge c
              WHERE a.dst = b.src AND b.dst = c.src ORDER BY a.w + b.w + c.w LIMIT 100"""
    return ranked_sql(spark, text)[0]


# -- other rankings --------------------------------------------------------------------------------------------------
@query(top(EDGE, NODES3, PATH3, "greatest(a.w, b.w, c.w)", TIES3))
def max_topk(spark: SparkSession, sf: str) -> DataFrame:
    return levels.sum_topk(W.chain(spark, sf, 3), Rank.max(["w1", "w2", "w3"]), K)


@query(top(EDGE, NODES3, PATH3, "least(a.w, b.w, c.w)", TIES3, down="DESC"))
def min_topk_desc(spark: SparkSession, sf: str) -> DataFrame:
    return levels.sum_topk(W.chain(spark, sf, 3), Rank.min(["w1", "w2", "w3"], desc=True), K)


@query(top(EDGE, NODES3, PATH3, "CAST(a.w * b.w * c.w AS DECIMAL(38,0))", TIES3))
def product_topk(spark: SparkSession, sf: str) -> DataFrame:
    return levels.sum_topk(W.chain(spark, sf, 3), Rank.product(["w1", "w2", "w3"]), K)


@query(
    f"WITH {EDGE}, p AS (SELECT {NODES3}, list_reverse_sort([a.w, b.w, c.w]) AS m FROM {PATH3}) "
    f"SELECT * FROM (SELECT x1, x2, x3, x4, m[1] AS most, m[2] AS middle, m[3] AS least, row_number() OVER (ORDER BY m[1], m[2], m[3], x1, x2, x3, x4) AS rnk FROM p) WHERE rnk <= {K}"
)
def leximax_topk(spark: SparkSession, sf: str) -> DataFrame:
    out = levels.sum_topk(W.chain(spark, sf, 3), Rank.leximax(["w1", "w2", "w3"]), K)
    return out.select("x1", "x2", "x3", "x4", *[F.col("weight")[i].alias(n) for i, n in enumerate(("most", "middle", "least"))], "rnk")


@query(
    f"WITH {EDGE} SELECT * FROM (SELECT {NODES3}, {SUM3} AS total, b.w AS middle, row_number() OVER (ORDER BY {SUM3}, b.w DESC, {TIES3}) AS rnk FROM {PATH3}) WHERE rnk <= {K}"
)
def chained_rank(spark: SparkSession, sf: str) -> DataFrame:
    rank = Rank.chain(W.chain_sum(3), Rank.sum(["w2"], desc=True))
    out = levels.sum_topk(W.chain(spark, sf, 3), rank, K)
    return out.select("x1", "x2", "x3", "x4", F.col("weight.a").alias("total"), F.col("weight.b").alias("middle"), "rnk")


ORDER_LINES = "r JOIN t ON t.x2 = r.x2"
OL_COLS = "r.x1 AS cust, r.x2 AS ord, t.part, t.qty"


@query(top(BASE, OL_COLS, ORDER_LINES, "wr * (r.x1 % 7) + qty", "r.x1, r.x2, wr, part, qty"))
def local_sum(spark: SparkSession, sf: str) -> DataFrame:
    return levels.sum_topk(W.order_lines(spark, sf), W.local_rank(), K)


@query(top(BASE, OL_COLS, ORDER_LINES, "abs(wr - 100000 * qty)", "r.x1, r.x2, wr, part, qty"))
def black_box_rank(spark: SparkSession, sf: str) -> DataFrame:
    return topk(W.order_lines(spark, sf), Rank.black_box(F.abs(F.col("price") - 100000 * F.col("qty"))), K)


@query(
    f"WITH {BASE} SELECT * FROM (SELECT r.x1 AS cust, r.x2 AS ord, s.x3 AS n, wr + ws AS weight, row_number() OVER (PARTITION BY s.x3 ORDER BY wr + ws, r.x1, s.x3, ws, r.x2, wr) AS rnk FROM s JOIN r ON r.x1 = s.x1) WHERE rnk <= 5"
)
def per_group_topk(spark: SparkSession, sf: str) -> DataFrame:
    q = cq([atom("customers", T.customers(spark, sf), ["cust", "n", "ws"]), atom("orders", T.orders(spark, sf), ["cust", "ord", "wr"])], ["cust", "ord", "n"])
    return levels.per_group_topk(q, Rank.sum(["ws", "wr"]), "n", 5)


# -- projection ------------------------------------------------------------------------------------------------------
@query(
    f"WITH {BASE}, p AS (SELECT DISTINCT s.x1 AS c, r.x2 AS o, ws AS wc, wr AS wo FROM s JOIN r ON r.x1 = s.x1 WHERE r.x2 IN (SELECT x2 FROM t)) "
    f"SELECT * FROM (SELECT c, o, wc, wo, wc + wo AS weight, row_number() OVER (ORDER BY wc + wo, c, o, wc, wo) AS rnk FROM p) WHERE rnk <= {K}"
)
def project_free_connex(spark: SparkSession, sf: str) -> DataFrame:
    q = W.customers_with_lines(spark, sf)
    full = projection.free_connex_rewrite(q)
    rows = levels.sum_topk(full, Rank.sum(["wc", "wo"]), K, ties="all").drop("rnk")
    return union.ordered_union([rows], ["c", "o", "wc", "wo"], K)


PAIRS = "p AS (SELECT DISTINCT r.x1 AS cust, ws AS cbal, t.x4 AS supp, wu AS sbal FROM r JOIN s ON s.x1 = r.x1 JOIN t ON t.x2 = r.x2 JOIN u ON u.x4 = t.x4)"


@query(f"WITH {BASE}, {PAIRS} SELECT * FROM (SELECT *, row_number() OVER (ORDER BY supp DESC, cust, cbal, sbal) AS rnk FROM p) WHERE rnk <= {K}")
def project_lex(spark: SparkSession, sf: str) -> DataFrame:
    return projection.project_lex_topk(W.pairs_by_balance(spark, sf), [desc("supp"), "cust", "cbal", "sbal"], K)


@query(f"WITH {BASE}, {PAIRS} SELECT * FROM (SELECT *, cbal + sbal AS weight, row_number() OVER (ORDER BY cbal + sbal, cust, cbal, supp, sbal) AS rnk FROM p) WHERE rnk <= {K}")
def project_sum(spark: SparkSession, sf: str) -> DataFrame:
    return projection.project_rank_topk(W.pairs_by_balance(spark, sf), Rank.sum(["cbal", "sbal"]), K)


@query(f"WITH {BASE}, {PAIRS} SELECT * FROM (SELECT *, cbal + sbal AS weight, row_number() OVER (ORDER BY cbal + sbal, cust, cbal, supp, sbal) AS rnk FROM p) WHERE rnk <= 20")
def project_dedup_stream(spark: SparkSession, sf: str) -> DataFrame:
    return projection.project_dedup_stream(W.pairs_by_balance(spark, sf), Rank.sum(["cbal", "sbal"]), 20)


# -- beyond acyclic --------------------------------------------------------------------------------------------------
TRIANGLE = "edge a JOIN edge b ON b.src = a.dst JOIN edge c ON c.src = b.dst AND c.dst = a.src"
SQUARE = "edge a JOIN edge b ON b.src = a.dst JOIN edge c ON c.src = b.dst JOIN edge d ON d.src = c.dst AND d.dst = a.src"


@query(top(EDGE, "a.src AS x1, a.dst AS x2, b.dst AS x3", TRIANGLE, SUM3, "a.src, a.dst, b.dst"))
def triangle_topk(spark: SparkSession, sf: str) -> DataFrame:
    q = W.cycle(spark, sf, 3)
    flat = cyclic.materialize_bags(q, cyclic.decompose(q))
    return union.ordered_union([levels.sum_topk(flat, W.chain_sum(3), K, ties="all")], q.head, K)


@query(top(EDGE, NODES3, SQUARE, f"{SUM3} + d.w", TIES3))
def four_cycle_topk(spark: SparkSession, sf: str) -> DataFrame:
    q = W.cycle(spark, sf, 4)
    flat = cyclic.materialize_bags(q, cyclic.decompose(q))
    return union.ordered_union([levels.sum_topk(flat, W.chain_sum(4), K, ties="all")], q.head, K)


@query(top(EDGE, NODES3, SQUARE, f"{SUM3} + d.w", TIES3))
def heavy_light_topk(spark: SparkSession, sf: str) -> DataFrame:
    q = W.cycle(spark, sf, 4)
    out = [levels.sum_topk(b, W.chain_sum(4), K, ties="all") for b in cyclic.heavy_light_4cycle(*q.atoms, threshold=8)]
    return union.ordered_union(out, q.head, K)


CUST_SUPP = "s JOIN u ON u.x5 = s.x3"


@query(top(BASE, "s.x1 AS c, u.x4 AS s, s.x3 AS n", CUST_SUPP, "ws + wu", "s.x1, u.x4, s.x3", where="WHERE s.x1 % 25 <> u.x4 % 25"))
def neq_topk(spark: SparkSession, sf: str) -> DataFrame:
    return predicates.neq_topk(W.customer_supplier(spark, sf), "cm", "sm", Rank.sum(["wc", "ws"]), K)


@query(top(BASE, "s.x1 AS c, u.x4 AS s, s.x3 AS n", CUST_SUPP, "ws + wu", "s.x1, u.x4, s.x3", where="WHERE s.x1 % 25 <> u.x4 % 25"))
def neq_random_topk(spark: SparkSession, sf: str) -> DataFrame:
    return predicates.branches_topk(predicates.neq_random_branches(W.customer_supplier(spark, sf), "cm", "sm", 12), Rank.sum(["wc", "ws"]), K)


@query(top(EDGE, NODES3, PATH3, SUM3, TIES3, where="WHERE NOT (a.src = c.dst AND a.dst = b.dst)"))
def nae_topk(spark: SparkSession, sf: str) -> DataFrame:
    return predicates.nae_topk(W.chain(spark, sf, 3), [("x1", "x4"), ("x2", "x3")], W.chain_sum(3), K)


FUNNEL = "ev a JOIN ev b ON b.u = a.u"


@query(top(EVENTS, "a.e AS e1, b.e AS e2", FUNNEL, "a.w + b.w", "a.e, b.e", where="WHERE a.kind = 'view' AND b.kind = 'purchase' AND a.t < b.t"))
def lt_topk(spark: SparkSession, sf: str) -> DataFrame:
    return predicates.lt_topk(W.funnel(spark, sf), "t1", "t2", Rank.sum(["w1", "w2"]), K)


@query(top(EVENTS, "a.e AS e1, b.e AS e2", FUNNEL, "a.w + b.w", "a.e, b.e", where="WHERE a.kind = 'view' AND b.kind = 'purchase' AND a.t <= b.t"))
def le_topk(spark: SparkSession, sf: str) -> DataFrame:
    return predicates.lt_topk(W.funnel(spark, sf), "t1", "t2", Rank.sum(["w1", "w2"]), K, strict=False)


DAYS3 = 3 * 86400 * 10**6


@query(top(EVENTS, "a.e AS e1, b.e AS e2", FUNNEL, "a.w + b.w", "a.e, b.e", where=f"WHERE a.kind = 'view' AND b.kind = 'purchase' AND a.t < b.t AND b.t - a.t <= {DAYS3}"))
def band_topk(spark: SparkSession, sf: str) -> DataFrame:
    branches = predicates.band_branches(W.funnel(spark, sf), "t1", "t2", DAYS3)
    return predicates.branches_topk(branches, Rank.sum(["w1", "w2"]), K, dedup=False)


@query(
    top(EVENTS, "a.e AS e1, b.e AS e2, c.e AS e3", f"{FUNNEL} JOIN ev c ON c.u = a.u", "a.w + b.w + c.w", "a.e, b.e, c.e", where="WHERE a.kind = 'view' AND b.kind = 'click' AND c.kind = 'purchase' AND a.t < b.t AND b.t < c.t")
)
def three_step_funnel(spark: SparkSession, sf: str) -> DataFrame:
    q = W.funnel(spark, sf, ("view", "click", "purchase"))
    q = predicates.lt_rewrite(predicates.lt_rewrite(q, "t1", "t2"), "t2", "t3")
    return predicates.branches_topk([q], Rank.sum(["w1", "w2", "w3"]), K, dedup=False)


@query(top(EDGE, NODES3, PATH3, SUM3, TIES3, where="WHERE a.src < c.dst"))
def long_inequality_topk(spark: SparkSession, sf: str) -> DataFrame:
    return predicates.long_inequality(W.chain(spark, sf, 3), "x1", "x4", W.chain_sum(3), K)


@query(f"WITH {BASE}, p AS (SELECT r.x2 AS o, s.x3 AS n, wr AS w FROM r JOIN s ON s.x1 = r.x1) SELECT * FROM (SELECT o, n, w, w AS weight, row_number() OVER (ORDER BY w, o, n) AS rnk FROM p) WHERE rnk <= {K}")
def fd_rewrite_topk(spark: SparkSession, sf: str) -> DataFrame:
    q = cq([atom("orders", T.orders(spark, sf), ["c", "o", "w"]), atom("customers", T.customers(spark, sf).drop("w"), ["c", "n"])], ["o", "n", "w"])
    wide, head = fds.fd_rewrite(q, [FD("orders", ("o",), "c"), FD("customers", ("c",), "n")], check=True)
    rows = levels.sum_topk(wide, Rank.sum(["w"]), K, ties="all").select(*head, "weight")
    return union.ordered_union([rows], list(head), K)


@query(
    f"WITH {EVENTS}, p AS (SELECT DISTINCT a.e AS e1, b.e AS e2, a.w + b.w AS weight FROM {FUNNEL} WHERE a.kind = 'view' AND ((b.kind = 'purchase' AND a.t < b.t) OR (b.kind IN ('purchase', 'click') AND a.t <= b.t))) "
    f"SELECT * FROM (SELECT e1, e2, weight, row_number() OVER (ORDER BY weight, e1, e2) AS rnk FROM p) WHERE rnk <= {K}"
)
def union_topk_dedup(spark: SparkSession, sf: str) -> DataFrame:
    """Branches that overlap: view before purchase; view up to purchase; view up to click."""
    rank = Rank.sum(["w1", "w2"])
    buy, click = W.funnel(spark, sf), W.funnel(spark, sf, ("view", "click"))
    branches = [predicates.lt_rewrite(buy, "t1", "t2"), predicates.le_rewrite(buy, "t1", "t2"), predicates.le_rewrite(click, "t1", "t2")]
    return predicates.branches_topk(branches, rank, K)


# -- direct access and aggregates ------------------------------------------------------------------------------------
@query(f"WITH {EDGE} SELECT CAST(count(*) AS DECIMAL(38,0)) AS answers FROM {PATH4}")
def count_answers(spark: SparkSession, sf: str) -> DataFrame:
    return dp.count_answers(W.chain(spark, sf, 4))


@query(
    "WITH l AS (SELECT l_suppkey AS s, l_partkey AS p FROM lineitem), a AS (SELECT s, count(*) AS n FROM l GROUP BY s), b AS (SELECT l.p, sum(a.n) AS n FROM l JOIN a ON a.s = l.s GROUP BY l.p), "
    "c AS (SELECT l.s, sum(b.n) AS n FROM l JOIN b ON b.p = l.p GROUP BY l.s) SELECT CAST(sum(c.n) AS DECIMAL(38,0)) AS answers FROM l JOIN c ON c.s = l.s"
)
def count_walks(spark: SparkSession, sf: str) -> DataFrame:
    return dp.count_answers(W.walk(spark, sf))


LEX5 = f"n AS (SELECT r.x1, r.x2, s.x3, t.x4, u.x5, row_number() OVER (ORDER BY r.x1, r.x2, x3, t.x4, x5) AS position, count(*) OVER () AS total FROM {KEYS4})"


@query(f"WITH {BASE}, {LEX5} SELECT position, x1, x2, x3, x4, x5 FROM n WHERE position IN (1, 2, 777, 5000, total)")
def nth_answers(spark: SparkSession, sf: str) -> DataFrame:
    q = W.tree4_keys(spark, sf)
    last = int(dp.count_answers(q).first()["answers"])
    return access.direct_access(q, ["x1", "x2", "x3", "x4", "x5"], [1, 2, 777, 5000, last, last + 1])


@query(f"WITH {BASE}, {LEX5} SELECT position, x1, x2, x3, x4, x5 FROM n WHERE position = (total + 1) // 2")
def median_lex(spark: SparkSession, sf: str) -> DataFrame:
    return access.median_answer(W.tree4_keys(spark, sf), ["x1", "x2", "x3", "x4", "x5"])


@query(f"WITH {BASE}, {LEX5} SELECT position, x1, x2, x3, x4, x5 FROM n WHERE position <= 50")
def enumerate_by_access(spark: SparkSession, sf: str) -> DataFrame:
    return access.enumerate_by_access(W.tree4_keys(spark, sf), ["x1", "x2", "x3", "x4", "x5"], 50)


@query(f"WITH {EDGE}, h AS (SELECT {SUM3} AS weight, count(*) AS n FROM {PATH3} GROUP BY 1), m AS (SELECT weight, n, sum(n) OVER (ORDER BY weight) AS upto, (SELECT (sum(n) + 1) // 2 FROM h) AS mid FROM h) "
       "SELECT CAST(mid AS BIGINT) AS position, weight, CAST(upto - n AS DECIMAL(38,0)) AS before, CAST(n AS DECIMAL(38,0)) AS answers FROM m WHERE upto >= mid AND upto - n < mid")
def sum_select(spark: SparkSession, sf: str) -> DataFrame:
    q = W.chain(spark, sf, 3)
    n = int(dp.count_answers(q).first()["answers"])
    return access.select_nth(q, W.chain_sum(3), (n + 1) // 2)


@query(f"WITH {BASE}, n AS (SELECT r.x1 AS c, r.x2 AS o, s.x3 AS n, wr AS weight, row_number() OVER (ORDER BY wr, r.x1, r.x2, s.x3) AS position FROM r JOIN s ON s.x1 = r.x1) SELECT position, c, o, n, weight FROM n WHERE position IN (1, 10, 1000)")
def sum_access(spark: SparkSession, sf: str) -> DataFrame:
    q = cq([atom("orders", T.orders(spark, sf), ["c", "o", "w"]), atom("customers", T.customers(spark, sf).drop("w"), ["c", "n"])], ["c", "o", "n"])
    return access.sum_access(q, Rank.sum(["w"]), [1, 10, 1000])


@query(f"WITH {EDGE} SELECT {SUM3} AS weight, CAST(count(*) AS DECIMAL(38,0)) AS answers FROM {PATH3} GROUP BY 1")
def weight_histogram(spark: SparkSession, sf: str) -> DataFrame:
    return access.weight_histogram(W.chain(spark, sf, 3), W.chain_sum(3))


@query(
    f"WITH {BASE} SELECT s.x3 AS n, CAST(count(*) AS DECIMAL(38,0)) AS answers, CAST(sum(ws) AS DECIMAL(38,0)) AS total, min(ws) AS least, max(ws) AS most FROM {TREE4} GROUP BY s.x3"
)
def agg_over_join(spark: SparkSession, sf: str) -> DataFrame:
    q = W.tree4(spark, sf)
    named = cq([a for a in q.atoms], q.head)
    return access.agg_over_join(named, "ws", ["x3"]).withColumnRenamed("x3", "n").drop("mean")


@query(
    f"WITH {BASE} SELECT n_regionkey AS region, s.x3 AS nation, CAST(count(*) AS DECIMAL(38,0)) AS answers FROM {TREE4} JOIN nation ON n_nationkey = s.x3 GROUP BY ROLLUP (n_regionkey, s.x3)"
)
def count_rollup(spark: SparkSession, sf: str) -> DataFrame:
    per = access.agg_over_join(W.tree4(spark, sf), "ws", ["x3"])
    nation = T.load_table(spark, sf, "nation").select(F.col("n_nationkey").alias("x3"), F.col("n_regionkey").alias("region"))
    rows = per.join(nation, "x3").withColumnRenamed("x3", "nation")
    return rows.rollup("region", "nation").agg(F.sum("answers").cast("decimal(38,0)").alias("answers"))


# -- baselines -------------------------------------------------------------------------------------------------------
@query(f"WITH {BASE} SELECT {COLS4}, wr + ws + wt + wu AS weight FROM {TREE4}")
def batch_sort(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.batch_reduce_join_sort(W.tree4(spark, sf), W.tree4_sum())


@query(f"WITH {BASE} SELECT {COLS4}, wr + ws + wt + wu AS weight FROM {TREE4}")
def engine_sort(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.engine_join_sort(W.tree4(spark, sf), W.tree4_sum())


@query(top(EDGE, NODES3, PATH3, SUM3, TIES3))
def engine_topk(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.engine_topk(W.chain(spark, sf, 3), W.chain_sum(3), K)


@query(f"WITH {BASE}, p AS (SELECT {COLS4}, wr + ws + wt + wu AS weight FROM {TREE4}) SELECT * FROM p WHERE weight <= (SELECT weight FROM p ORDER BY weight LIMIT 1 OFFSET 99)")
def incremental_sort(spark: SparkSession, sf: str) -> DataFrame:
    """Leading partitions of the batch result until 100 answers are there, and all that tie with the last."""
    got: DataFrame | None = None
    for part in baselines.batch_incremental_sort(W.tree4(spark, sf), W.tree4_sum()):
        got = part if got is None else got.unionByName(part)
        if got.count() >= 100:
            break
    tau = got.orderBy("weight").limit(100).agg(F.max("weight")).first()[0]
    return got.where(F.col("weight") <= tau)


@query(f"WITH {EDGE} SELECT CAST(500 AS BIGINT) AS n FROM (SELECT count(*) AS c FROM {PATH3}) WHERE c >= 500")
def table_at_a_time(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.table_at_a_time(W.chain(spark, sf, 3), 500).agg(F.count(F.lit(1)).alias("n"))


@query(f"WITH {BASE}, p AS (SELECT s.x1 AS cust, s.x3 AS n, r.x2 AS ord, ws + wr AS weight FROM s JOIN r ON r.x1 = s.x1) SELECT cust, ord, weight FROM (SELECT *, row_number() OVER (ORDER BY weight, cust, ord) AS k FROM p) WHERE k <= 50")
def rank_join_topk(spark: SparkSession, sf: str) -> DataFrame:
    q = cq([atom("customers", T.customers(spark, sf).drop("c_nationkey"), ["cust", "ws"]), atom("orders", T.orders(spark, sf), ["cust", "ord", "wr"])], ["cust", "ord"])
    return baselines.rank_join_topk(q, Rank.sum(["ws", "wr"]), 50)[0]


@query("SELECT a.r_regionkey AS r, b.n_nationkey AS n FROM region a, nation b WHERE a.r_regionkey = b.n_regionkey")
def naive_product(spark: SparkSession, sf: str) -> DataFrame:
    r, n = T.load_table(spark, sf, "region"), T.load_table(spark, sf, "nation")
    return baselines.naive_product(cq([atom("region", r, {"r_regionkey": "r"}), atom("nation", n, {"n_nationkey": "n", "n_regionkey": "r"})], ["r", "n"]))


@query()
def greedy_first(spark: SparkSession, sf: str) -> DataFrame:
    """Negative control: one answer that need not be the lightest."""
    got = baselines.greedy_first(W.tree4(spark, sf), W.tree4_sum())
    return spark.createDataFrame([(got["wr"] + got["ws"] + got["wt"] + got["wu"],)] if got else [], "weight bigint")


# -- choices switched off --------------------------------------------------------------------------------------------
@query(top(EDGE, NODES3, PATH3, SUM3, TIES3))
def ablation_no_bound(spark: SparkSession, sf: str) -> DataFrame:
    return levels.sum_topk(W.chain(spark, sf, 3), W.chain_sum(3), K, bound=False)


@query(top(EDGE, NODES3, PATH3, SUM3, TIES3))
def ablation_no_places(spark: SparkSession, sf: str) -> DataFrame:
    return levels.sum_topk(W.chain(spark, sf, 3), W.chain_sum(3), K, places=False)


@query(
    f"WITH {BASE}, r1 AS (SELECT x1, x2 FROM r WHERE x1 IN (SELECT x1 FROM s) AND x2 IN (SELECT x2 FROM td WHERE x4 IN (SELECT x4 FROM u))), t1 AS (SELECT x2, x4 FROM td WHERE x4 IN (SELECT x4 FROM u)), "
    "t2 AS (SELECT x2, x4 FROM t1 WHERE x2 IN (SELECT x2 FROM r1)) "
    "SELECT 'orders' AS relation, (SELECT count(*) FROM r) AS raw_rows, (SELECT count(*) FROM r1) AS reduced_rows, (SELECT count(*) FROM r1) AS full_rows "
    "UNION ALL SELECT 'customers', (SELECT count(*) FROM s), (SELECT count(*) FROM s), (SELECT count(*) FROM s WHERE x1 IN (SELECT x1 FROM r1)) "
    "UNION ALL SELECT 'lines', (SELECT count(*) FROM td), (SELECT count(*) FROM t1), (SELECT count(*) FROM t2) "
    "UNION ALL SELECT 'suppliers', (SELECT count(*) FROM u), (SELECT count(*) FROM u), (SELECT count(*) FROM u WHERE x4 IN (SELECT x4 FROM t2))"
)
def reduction_sizes(spark: SparkSession, sf: str) -> DataFrame:
    return ablations.reduction_sizes(W.tree4_keys(spark, sf))


@query(
    f"WITH {EDGE}, e2 AS (SELECT src, dst, w FROM edge WHERE dst IN (SELECT src FROM edge)) "
    "SELECT CAST(1 AS BIGINT) AS atom, (SELECT count(*) FROM e2) AS entries, CAST(1 AS BIGINT) AS \"groups\", (SELECT count(*) FROM e2) AS largest "
    "UNION ALL SELECT 2, (SELECT count(*) FROM edge), (SELECT count(DISTINCT src) FROM edge), (SELECT max(c) FROM (SELECT count(*) AS c FROM edge GROUP BY src))"
)
def join_group_counts(spark: SparkSession, sf: str) -> DataFrame:
    got = ablations.group_counts(W.chain(spark, sf, 2), W.chain_sum(2))
    return got.select(F.when(F.col("groups") == 1, 1).otherwise(2).cast("long").alias("atom"), "entries", "groups", "largest")


@query(
    "WITH l AS (SELECT l_suppkey AS s, l_partkey AS p, CAST(round(l_extendedprice * 100) AS BIGINT) AS w FROM lineitem), m4 AS (SELECT s, min(w) AS m FROM l GROUP BY s), "
    "m3 AS (SELECT p, min(w + m) AS m FROM l JOIN m4 USING (s) GROUP BY p), m2 AS (SELECT s, min(w + m) AS m FROM l JOIN m3 USING (p) GROUP BY s), "
    f"root AS (SELECT s, p, w, w + m AS o FROM l JOIN m2 USING (s)), tau AS (SELECT max(o) AS t FROM (SELECT o FROM root ORDER BY o LIMIT {K})), "
    "a1 AS MATERIALIZED (SELECT s AS s1, p AS p1, w AS w1 FROM root, tau WHERE o <= t), "
    "a2 AS MATERIALIZED (SELECT s1, p1, w1, l.p AS p2, l.w AS w2 FROM a1 JOIN l ON l.s = s1 JOIN m3 ON m3.p = l.p, tau WHERE w1 + l.w + m <= t), "
    "a3 AS MATERIALIZED (SELECT s1, p1, w1, p2, w2, l.s AS s2, l.w AS w3 FROM a2 JOIN l ON l.p = p2 JOIN m4 ON m4.s = l.s, tau WHERE w1 + w2 + l.w + m <= t), "
    "a4 AS (SELECT s1, p1, w1, p2, w2, s2, w3, l.p AS p3, l.w AS w4 FROM a3 JOIN l ON l.s = s2, tau WHERE w1 + w2 + w3 + l.w <= t) "
    f"SELECT p1, s1, p2, s2, p3, w1 + w2 + w3 + w4 AS weight, row_number() OVER (ORDER BY w1 + w2 + w3 + w4, s1, p1, w1, p2, w2, s2, w3, p3, w4) AS rnk FROM a4 QUALIFY rnk <= {K}"
)
def walk_topk(spark: SparkSession, sf: str) -> DataFrame:
    """The lightest of far more walks than could ever be built."""
    return levels.sum_topk(W.walk(spark, sf), W.chain_sum(4), K)


# -- events ----------------------------------------------------------------------------------------------------------
@query(
    f"WITH {EVENTS} SELECT e2, u2, ts2, ts, event_id, w FROM (SELECT b.e AS e2, b.u AS u2, b.t AS ts2, a.t AS ts, a.e AS event_id, a.w AS w, row_number() OVER (PARTITION BY b.e ORDER BY a.t DESC, a.e DESC, a.w DESC) AS k "
    "FROM ev b JOIN ev a ON a.u = b.u AND a.t < b.t WHERE a.kind = 'view' AND b.kind = 'purchase') WHERE k = 1"
)
def as_of_topk(spark: SparkSession, sf: str) -> DataFrame:
    """The latest view before each purchase."""
    buys = T.typed_events(spark, sf, "purchase").select("user_id", F.col("ts").alias("ts2"), F.col("event_id").alias("e2"), F.col("user_id").alias("u2"))
    return as_of(buys, T.typed_events(spark, sf, "view"), "user_id", "ts2", "ts", ["e2", "u2", "ts2"])


@query(
    "WITH e AS (SELECT date_trunc('hour', ts) AS h, event_type AS kind, event_id, CAST(round(value * 100) AS BIGINT) AS w FROM events) "
    "SELECT h, kind, event_id, w, k AS rnk FROM (SELECT *, row_number() OVER (PARTITION BY h, kind ORDER BY w, event_id) AS k FROM e) WHERE k <= 3"
)
def window_ranked_events(spark: SparkSession, sf: str) -> DataFrame:
    from pyspark.sql.window import Window

    ev = T.load_table(spark, sf, "events").select(F.date_trunc("hour", F.col("ts").cast("timestamp")).cast("timestamp_ntz").alias("h"), F.col("event_type").alias("kind"), "event_id", T.cents("value").alias("w"))
    place = F.row_number().over(Window.partitionBy("h", "kind").orderBy("w", "event_id"))
    return ev.withColumn("rnk", place.cast("long")).where("rnk <= 3")


@query("SELECT user_id, min(CAST(round(value * 100) AS BIGINT)) AS opt, count(*) AS \"rows\" FROM events GROUP BY user_id")
def stream_messages(spark: SparkSession, sf: str) -> DataFrame:
    """Min messages kept by a stream over the events, read when all of them have been seen."""
    import uuid

    schema = T.load_table(spark, sf, "events").schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf)
    name = f"messages_{uuid.uuid4().hex}"
    run = streams.running_messages(stream, ["user_id"], T.cents("value")).writeStream.outputMode("complete").format("memory").queryName(name).trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.table(name)


# -- variety of weights ----------------------------------------------------------------------------------------------
@query(
    "WITH v AS (SELECT vec_id, label, CAST(round(list_sum(list_transform(embedding, lambda x: (CAST(x AS DOUBLE)) * x)) * 10) AS BIGINT) AS w FROM embeddings), "
    "p AS (SELECT a.vec_id AS a, b.vec_id AS b, a.w + b.w AS weight FROM v a JOIN v b ON a.label = b.label AND a.vec_id < b.vec_id) "
    "SELECT * FROM (SELECT a, b, weight, row_number() OVER (ORDER BY weight, a, b) AS rnk FROM p) WHERE rnk <= 50"
)
def vector_weights_all(spark: SparkSession, sf: str) -> DataFrame:
    """The lightest pairs of different vectors of one label, over the whole table."""
    from ordjoin.functions.weights import squared_distance

    e = T.load_table(spark, sf, "embeddings").select("vec_id", "label", squared_distance(F.col("embedding").cast("array<double>"), [0.0] * 64, 10).alias("w"))
    q = cq([atom("a", e, ["a", "lab", "wa"]), atom("b", e, ["b", "lab", "wb"])], ["a", "b"])
    return union.ordered_union([predicates.lt_topk(q, "a", "b", Rank.sum(["wa", "wb"]), 50)], ["a", "b"], 50)


@query(
    "WITH p AS (SELECT a.conv_id AS conv, a.turn AS t1, b.turn AS t2, CAST(length(a.text) AS BIGINT) + length(b.text) AS weight FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND a.turn < b.turn) "
    "SELECT * FROM (SELECT conv, t1, t2, weight, row_number() OVER (ORDER BY weight, conv, t1, t2) AS rnk FROM p) WHERE rnk <= 100"
)
def conversation_turns(spark: SparkSession, sf: str) -> DataFrame:
    c = T.load_table(spark, sf, "conversations").select("conv_id", "turn", F.length("text").cast("long").alias("w"))
    q = cq([atom("first", c, ["conv", "t1", "wa"]), atom("second", c, ["conv", "t2", "wb"])], ["conv", "t1", "t2"])
    return predicates.lt_topk(q, "t1", "t2", Rank.sum(["wa", "wb"]), K)
