from __future__ import annotations

import datetime as dt

from pyspark.sql import functions as F

from ordjoin.operators.parallel import per_key_topk
from ordjoin.plans.model import atom, cq
from ordjoin.plans.ranking import Rank
from ordjoin.sources.tables import read_relation, write_ranked
from ordjoin.streaming import ranked as R

ROWS = [(i % 3, dt.datetime(2024, 1, 1, 0, i), i * 7 % 11) for i in range(30)]


def files(spark, path, parts=3):
    df = spark.createDataFrame(ROWS, "k bigint, ts timestamp, w bigint")
    df.repartition(parts).write.parquet(path)
    return spark.readStream.schema(df.schema).parquet(path)


def run(writer):
    q = writer.trigger(availableNow=True).start()
    q.awaitTermination()


def test_ranked_batches(spark, tmp_path):
    names = spark.createDataFrame([(0, 5), (1, 1)], "k bigint, v bigint")
    got = []
    stream = files(spark, str(tmp_path / "in"), 1)
    build = lambda b: cq([atom("events", b.select("k", "w"), ["k", "w"]), atom("names", names, ["k", "v"])], ["k", "w", "v"])
    run(R.ranked_batches(stream, build, Rank.sum(["w", "v"]), 2, lambda df, _: got.extend(df.orderBy("rnk").collect())))
    want = sorted((w + v, k) for k, _, w in ROWS for n, v in ((0, 5), (1, 1)) if n == k)[:2]
    assert [(r["weight"], r["k"]) for r in got] == want


def test_running_messages_and_windows(spark, tmp_path):
    stream = files(spark, str(tmp_path / "in"))
    run(R.running_messages(stream, ["k"], F.col("w")).writeStream.outputMode("complete").format("memory").queryName("msg"))
    assert {r["k"]: r["opt"] for r in spark.table("msg").collect()} == {k: min(w for a, _, w in ROWS if a == k) for k in range(3)}
    run(R.windowed_best(stream, "ts", "1 hour", "10 minutes", None, ["k"], F.col("w")).writeStream.outputMode("complete").format("memory").queryName("win"))
    assert spark.table("win").agg(F.sum("rows")).first()[0] == 30 and spark.table("win").count() == 9
    run(R.session_best(stream, "ts", "1 hour", "2 minutes", ["k"], F.col("w")).writeStream.outputMode("complete").format("memory").queryName("ses"))
    assert spark.table("ses").agg(F.sum("rows")).first()[0] == 30


def test_interval_join(spark, tmp_path):
    a, b = files(spark, str(tmp_path / "a")), files(spark, str(tmp_path / "b"))
    joined = R.interval_join(a.withColumnRenamed("w", "wa"), b.withColumnsRenamed({"ts": "ts2", "w": "wb"}), "k", "ts", "ts2", "5 minutes", "1 hour")
    run(joined.writeStream.outputMode("append").format("memory").queryName("pairs"))
    want = sum(x[0] == y[0] and dt.timedelta(0) < y[1] - x[1] <= dt.timedelta(minutes=5) for x in ROWS for y in ROWS)
    assert spark.table("pairs").count() == want


def test_per_key_enumeration(spark):
    left = spark.createDataFrame([(k, a, a * 3 % 7) for k in range(3) for a in range(5)], "k bigint, a bigint, w bigint")
    right = spark.createDataFrame([(k, b, b * 5 % 6) for k in range(3) for b in range(4)], "k bigint, b bigint, v bigint")
    q = cq([atom("l", left, ["k", "a", "w"]), atom("r", right, ["k", "b", "v"])], ["k", "a", "b"])
    got = per_key_topk(q, Rank.sum(["w", "v"]), "k", 3).collect()
    for k in range(3):
        want = sorted(a * 3 % 7 + b * 5 % 6 for a in range(5) for b in range(4))[:3]
        assert [r["weight"] for r in sorted(got, key=lambda r: r["rnk"]) if r["k"] == k] == want


def test_sinks(spark, tmp_path):
    df = spark.range(1, 101).selectExpr("id as rnk", "id * 2 as weight")
    for kind in ("parquet", "json"):
        path = str(tmp_path / kind)
        write_ranked(df, path, kind)
        assert read_relation(spark, path, kind).count() == 100
