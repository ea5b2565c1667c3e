"""The experiment workloads as queries over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ordjoin.plans.model import ConjunctiveQuery, atom, cq
from ordjoin.plans.ranking import Rank
from ordjoin.sources import tables as T

#: fixed values: the small example database
MINI = {
    "r": [(0, 0), (1, 1), (2, 2)],
    "s": [(0, 1), (1, 1), (1, 2), (2, 3), (2, 5)],
    "t": [(0, 0), (1, 3), (2, 2)],
    "u": [(2, 1), (2, 2), (3, 8), (3, 9)],
}


def mini_tables(spark: SparkSession) -> dict[str, DataFrame]:
    return {k: spark.createDataFrame(v, "a bigint, b bigint") for k, v in MINI.items()}


def mini(spark: SparkSession) -> ConjunctiveQuery:
    t = mini_tables(spark)
    return cq([atom("r", t["r"], ["x1", "x2"]), atom("s", t["s"], ["x1", "x3"]), atom("t", t["t"], ["x2", "x4"]), atom("u", t["u"], ["x4", "x5"])])


def chain(spark: SparkSession, sf_dir: str, length: int) -> ConjunctiveQuery:
    """Paths of ``length`` edges: self-joins of one relation; the head holds the nodes."""
    e = T.edges(spark, sf_dir)
    atoms = [atom("edge", e, [f"x{i}", f"x{i + 1}", f"w{i}"]) for i in range(1, length + 1)]
    return cq(atoms, [f"x{i}" for i in range(1, length + 2)], ["edge"] * length)


def chain_sum(length: int, desc: bool = False) -> Rank:
    return Rank.sum([f"w{i}" for i in range(1, length + 1)], desc)


def tree4(spark: SparkSession, sf_dir: str, events: bool = False) -> ConjunctiveQuery:
    """Orders with their customers, lines and suppliers: the shape of the small example. ``events`` puts the customers'
    events in place of the customers, which fans out."""
    side = T.load_table(spark, sf_dir, "events").select("user_id", "event_id", T.cents("value").alias("w")) if events else T.customers(spark, sf_dir)
    return cq(
        [
            atom("orders", T.orders(spark, sf_dir), ["x1", "x2", "wr"]),
            atom("side", side, ["x1", "x3", "ws"]),
            atom("lines", T.lines(spark, sf_dir), ["x2", "x4", "part", "wt"]),
            atom("suppliers", T.suppliers(spark, sf_dir), ["x4", "x5", "wu"]),
        ],
        ["x1", "x2", "x3", "x4", "part", "x5"],
    )


def tree4_keys(spark: SparkSession, sf_dir: str) -> ConjunctiveQuery:
    """The same with key columns alone, as sets."""
    return cq(
        [
            atom("orders", T.orders(spark, sf_dir).select("o_custkey", "o_orderkey"), ["x1", "x2"]),
            atom("customers", T.customers(spark, sf_dir).select("c_custkey", "c_nationkey"), ["x1", "x3"]),
            atom("lines", T.lines(spark, sf_dir).select("l_orderkey", "l_suppkey").distinct(), ["x2", "x4"]),
            atom("suppliers", T.suppliers(spark, sf_dir).select("s_suppkey", "s_nationkey"), ["x4", "x5"]),
        ]
    )


def tree4_sum(desc: bool = False) -> Rank:
    return Rank.sum(["wr", "ws", "wt", "wu"], desc)


def walk(spark: SparkSession, sf_dir: str, most_quantity: int | None = None) -> ConjunctiveQuery:
    """Four lines in a row: same supplier, same part, same supplier. Far too many answers to build."""
    li = T.load_table(spark, sf_dir, "lineitem")
    li = li.where(F.col("l_quantity") <= most_quantity) if most_quantity else li
    li = li.select("l_suppkey", "l_partkey", T.cents("l_extendedprice").alias("w"))
    return cq(
        [atom("line", li, ["s1", "p1", "w1"]), atom("line", li, ["s1", "p2", "w2"]), atom("line", li, ["s2", "p2", "w3"]), atom("line", li, ["s2", "p3", "w4"])],
        ["p1", "s1", "p2", "s2", "p3"],
        ["line"] * 4,
    )


def order_lines(spark: SparkSession, sf_dir: str) -> ConjunctiveQuery:
    li = T.load_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", F.col("l_quantity").cast("long").alias("q"))
    return cq([atom("orders", T.orders(spark, sf_dir), ["cust", "ord", "price"]), atom("lines", li, ["ord", "part", "qty"])], ["cust", "ord", "part", "qty"])


def local_rank() -> Rank:
    return Rank.local_sum([(("cust", "price"), F.col("price") * (F.col("cust") % 7)), (("qty",), F.col("qty"))])


def customer_supplier(spark: SparkSession, sf_dir: str) -> ConjunctiveQuery:
    c = T.customers(spark, sf_dir).withColumn("m", F.col("c_custkey") % 25)
    s = T.suppliers(spark, sf_dir).withColumn("m", F.col("s_suppkey") % 25)
    return cq([atom("customers", c, {"c_custkey": "c", "c_nationkey": "n", "w": "wc", "m": "cm"}), atom("suppliers", s, {"s_suppkey": "s", "s_nationkey": "n", "w": "ws", "m": "sm"})], ["c", "s", "n"])


def funnel(spark: SparkSession, sf_dir: str, kinds: tuple[str, ...] = ("view", "purchase")) -> ConjunctiveQuery:
    """Events of given types of one user; their times are t1, t2, ..."""
    atoms = [atom(k, T.typed_events(spark, sf_dir, k), ["u", f"t{i}", f"e{i}", f"w{i}"]) for i, k in enumerate(kinds, 1)]
    return cq(atoms, [f"e{i}" for i in range(1, len(kinds) + 1)])


def cycle(spark: SparkSession, sf_dir: str, length: int) -> ConjunctiveQuery:
    e = T.edges(spark, sf_dir)
    atoms = [atom("edge", e, [f"x{i}", f"x{i % length + 1}", f"w{i}"]) for i in range(1, length + 1)]
    return cq(atoms, [f"x{i}" for i in range(1, length + 1)], ["edge"] * length)


def pairs_by_balance(spark: SparkSession, sf_dir: str) -> ConjunctiveQuery:
    """Customer and supplier of some order, with both balances; the order is projected away (not free-connex)."""
    o = T.orders(spark, sf_dir).join(T.customers(spark, sf_dir).select(F.col("c_custkey").alias("o_custkey"), F.col("w").alias("bal")), "o_custkey").select("o_custkey", "o_orderkey", "bal")
    li = T.lines(spark, sf_dir).join(T.suppliers(spark, sf_dir).select(F.col("s_suppkey").alias("l_suppkey"), F.col("w").alias("sbal")), "l_suppkey").select("l_orderkey", "l_suppkey", "sbal").distinct()
    return cq([atom("orders", o, ["cust", "ord", "cbal"]), atom("lines", li, ["ord", "supp", "sbal"])], ["cust", "cbal", "supp", "sbal"])


def customers_with_lines(spark: SparkSession, sf_dir: str) -> ConjunctiveQuery:
    """Free-connex: customers' orders for which some line exists."""
    return cq(
        [
            atom("customers", T.customers(spark, sf_dir), ["c", "n", "wc"]),
            atom("orders", T.orders(spark, sf_dir), ["c", "o", "wo"]),
            atom("lines", T.lines(spark, sf_dir).select("l_orderkey", "l_suppkey"), ["o", "supp"]),
        ],
        ["c", "o", "wc", "wo"],
    )
