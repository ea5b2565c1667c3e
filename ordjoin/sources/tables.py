"""Reading relations and writing ranked answers."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ordjoin.functions.weights import cents, micros

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_tables(spark: SparkSession, sf_dir: str, names: Sequence[str] = TABLES) -> dict[str, DataFrame]:
    """Lazy frames by name; only columns that a query uses are read."""
    return {n: load_table(spark, sf_dir, n) for n in names}


def read_relation(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, **options: str) -> DataFrame:
    """A relation from any format that Spark reads (parquet, orc, csv, json)."""
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_ranked(answers: DataFrame, path: str, kind: str = "parquet", mode: str = "errorifexists") -> None:
    """Answers in files whose order is the rank order."""
    answers.repartitionByRange("rnk").sortWithinPartitions("rnk").write.mode(mode).format(kind).save(path)


def edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src, dst, w): parts on successive lines of one order, with the lightest quantity of the first line.

    The join and the aggregate share no key, so this is two shuffles of narrow rows.
    """
    li = load_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_quantity")
    nxt = li.select("l_orderkey", (F.col("l_linenumber") - 1).alias("l_linenumber"), F.col("l_partkey").alias("dst"))
    pairs = li.join(nxt, ["l_orderkey", "l_linenumber"]).where("l_partkey <> dst")
    return pairs.groupBy(F.col("l_partkey").alias("src"), "dst").agg(F.min(F.col("l_quantity").cast("long")).alias("w"))


def orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load_table(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", cents("o_totalprice").alias("w"))


def customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load_table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", cents("c_acctbal").alias("w"))


def lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_partkey", cents("l_extendedprice").alias("w"))


def suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load_table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey", cents("s_acctbal").alias("w"))


def typed_events(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    """(user_id, ts in microseconds, event_id, w) of one event type."""
    ev = load_table(spark, sf_dir, "events").where(F.col("event_type") == kind)
    return ev.select("user_id", micros("ts").alias("ts"), "event_id", cents("value").alias("w"))
