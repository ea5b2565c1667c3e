"""Repeated rows, ties without end, large k, choices switched off, saved relations, table functions, own weights."""

from __future__ import annotations

import itertools
import random
import uuid
from collections import Counter

import pandas as pd
import pytest
from pyspark.sql import functions as F

from ordjoin.functions import tables
from ordjoin.functions.weights import user_weight
from ordjoin.operators import ablations, access, dp, index, levels, measures
from ordjoin.plans.model import atom, cq
from ordjoin.plans.ranking import Rank, desc
from ordjoin.streaming.ranked import best_k_so_far
from ordjoin.workloads import mini


@pytest.fixture
def repeated(spark):
    rng = random.Random(5)
    r = [(rng.randrange(3), rng.randrange(3), rng.randrange(2)) for _ in range(14)]
    s = [(rng.randrange(3), rng.randrange(3), rng.randrange(2)) for _ in range(10)]
    q = cq([atom("r", spark.createDataFrame(r, "a bigint, b bigint, c bigint"), ["a", "b", "c"]), atom("s", spark.createDataFrame(s, "a bigint, d bigint, e bigint"), ["a", "d", "e"])], ["a", "b", "c", "d", "e"])
    return q, [(*x, *y[1:]) for x in r for y in s if x[0] == y[0]]


def test_repeated_rows_in_every_order(repeated):
    q, answers = repeated
    assert max(Counter(answers).values()) > 1
    for order in (["a", "b", "c", "d", "e"], ["a", "b", "d", "c", "e"], ["a", "d", "b", "e", "c"], ["e", "a", "d", "b", "c"], ["d", "c", "a", "b", "e"]):
        want = sorted(answers, key=lambda t: [t["abcde".index(v)] for v in order])
        for k in (7, 10_000):
            got = [tuple(r[v] for v in "abcde") for r in levels.lex_topk(q, order, k).orderBy("rnk").collect()]
            assert got == want[:k], order


def test_access_counts_repeated_rows(repeated):
    q, answers = repeated
    order = ["a", "b", "d", "c", "e"]
    want = sorted(answers, key=lambda t: [t["abcde".index(v)] for v in order])
    assert int(dp.count_answers(q).first()["answers"]) == len(want)
    got = {r["position"]: tuple(r[v] for v in "abcde") for r in access.direct_access(q, order, [1, 5, len(want) // 2, len(want), len(want) + 1]).collect()}
    assert got == {i: want[i - 1] for i in (1, 5, len(want) // 2, len(want))}


def test_seven_atoms_keep_repeated_rows(spark):
    e = spark.createDataFrame([(0, 0), (0, 0), (0, 1), (1, 0)], "x bigint, y bigint")
    q = cq([atom("e", e, [f"v{i}", f"v{i + 1}"]) for i in range(7)], [f"v{i}" for i in range(8)], ["e"] * 7)
    got = levels.lex_topk(q, [f"v{i}" for i in range(8)], 5).orderBy("rnk").collect()
    assert [tuple(r[f"v{i}"] for i in range(8)) for r in got] == [(0,) * 8] * 5  # 2**7 of them stand first


@pytest.mark.parametrize("pin", [3, 200_000])
def test_large_frontiers(spark, monkeypatch, pin):
    monkeypatch.setattr(levels, "PIN_ROWS", pin)
    monkeypatch.setattr(levels, "BROADCAST_ROWS", 2 * pin)
    rng = random.Random(7)
    rows = [(i % 12, (i * 7) % 12, 1) for i in range(60)]
    same = spark.createDataFrame(rows, "x bigint, y bigint, w bigint")
    q = cq([atom("e", same, ["a", "b", "u"]), atom("e", same, ["b", "c", "v"])], ["a", "b", "c"], ["e", "e"])
    paths = sorted((a, b, c) for a, b, _ in rows for b2, c, _ in rows if b2 == b)
    got = levels.sum_topk(q, Rank.sum(["u", "v"]), 5, ties="all").collect()
    assert sorted((r["a"], r["b"], r["c"]) for r in got) == paths and sorted(r["rnk"] for r in got) == list(range(1, len(paths) + 1))
    mixed = [(x, y, rng.randrange(6)) for x, y, _ in rows]
    e = spark.createDataFrame(mixed, "x bigint, y bigint, w bigint")
    q = cq([atom("e", e, ["a", "b", "u"]), atom("e", e, ["b", "c", "v"])], ["a", "b", "c", "u", "v"], ["e", "e"])
    want = sorted((u + v, a, b, u, c, v) for a, b, u in mixed for b2, c, v in mixed if b2 == b)
    got = [(r["weight"], r["a"], r["b"], r["u"], r["c"], r["v"]) for r in levels.sum_topk(q, Rank.sum(["u", "v"]), 40).orderBy("rnk").collect()]
    assert got == want[:40]
    tied = [w for w in want if w[0] <= want[19][0]]
    assert sorted(r["weight"] for r in levels.sum_topk(q, Rank.sum(["u", "v"]), 20, ties="all").collect()) == [w[0] for w in tied]
    order = ["b", "a", "c"]
    want = sorted(((b, a, c) for _, a, b, _, c, _ in want))
    assert [(r["b"], r["a"], r["c"]) for r in levels.lex_topk(cq(q.atoms, ["a", "b", "c"], ["e", "e"]), order, 30).orderBy("rnk").collect()] == want[:30]
    levels.release()
    assert not levels._KEPT


def test_values_order_as_vectors_do(spark):
    rng = random.Random(11)
    e = spark.createDataFrame([(rng.randrange(5), rng.randrange(5)) for _ in range(18)], "x bigint, y bigint").distinct()
    q = cq([atom("e", e, ["a", "b"]), atom("f", e, ["b", "c"])], ["a", "b", "c"])
    for order in (["a", "c", "b"], [desc("a"), "c", desc("b")]):
        rank = Rank.lex(order)
        shown = []
        for weights, tree in (levels.lex_as_values(q, rank), levels.lex_as_sum(q, rank)):
            shown.append([(r["a"], r["b"], r["c"]) for r in levels.sum_topk(tree.query, weights, 12, tree).orderBy("rnk").collect()])
        assert shown[0] == shown[1] and len(shown[0]) == 12
    words = spark.createDataFrame([("x", "p"), ("y", "q"), ("z", "p")], "s string, t string")
    q = cq([atom("l", words, ["a", "b"]), atom("r", words, {"s": "c", "t": "b"})], ["a", "b", "c"])
    assert levels.lex_as_values(q, Rank.lex([desc("a"), "c", "b"])) is None
    got = [(r["a"], r["c"], r["b"]) for r in levels.lex_topk(q, [desc("a"), "c", "b"], 3).orderBy("rnk").collect()]
    assert got == [("z", "x", "p"), ("z", "z", "p"), ("y", "y", "q")]
    levels.release()


def test_choices_switched_off(spark):
    q, rank = mini(spark), Rank.sum(["x1", "x2", "x3", "x4", "x5"])
    plain = levels.sum_topk(q, rank, 6).orderBy("rnk").collect()
    for off in ({"bound": False}, {"places": False}, {"bound": False, "places": False}):
        assert levels.sum_topk(q, rank, 6, **off).orderBy("rnk").collect() == plain
    raw, cut = ablations.SearchStats(), ablations.SearchStats()
    a, b = list(ablations.backtrack(q, stats=raw)), list(ablations.backtrack(q, reduced=True, stats=cut))
    assert a == b and len(a) == 8 and raw.dead > 0 and cut.dead == 0 and raw.visits > cut.visits
    stack, queue = ablations.stack_against_queue(q)
    assert stack.answers == queue.answers == 8 and stack.most_open <= queue.most_open
    layer = [(i, j) for i in range(4) for j in range(4)]
    e = spark.createDataFrame(layer, "x bigint, y bigint")
    chain = cq([atom("e", e, [f"v{i}", f"v{i + 1}"]) for i in range(5)], [f"v{i}" for i in range(6)], ["e"] * 5)
    from ordjoin.operators.sequential import collect_groups

    without, memo = ablations.optima_without_memo(collect_groups(dp.ranked(chain, Rank.sum([f"v{i}" for i in range(6)]))))
    assert memo == 1 + 4 * 4 and without == 1 + 16 + 16 * 4 + 16 * 16 + 16 * 64
    sizes = {r["relation"]: (r["raw_rows"], r["reduced_rows"], r["full_rows"]) for r in ablations.reduction_sizes(q).collect()}
    assert sizes == {"r": (3, 2, 2), "s": (5, 5, 4), "t": (3, 2, 2), "u": (4, 4, 4)}
    groups = {r["relation"]: (r["entries"], r["groups"], r["largest"]) for r in ablations.group_counts(q, rank).collect()}
    assert groups == {"r": (2, 1, 2), "s": (5, 3, 2), "t": (2, 2, 1), "u": (4, 2, 2)}


def test_rising_bound(spark):
    from ordjoin.operators.cursor import RisingBound, frontier_rounds

    rng = random.Random(17)
    rows = [(rng.randrange(6), rng.randrange(6), rng.randrange(9)) for _ in range(30)]
    e = spark.createDataFrame(rows, "x bigint, y bigint, w bigint")
    q = cq([atom("e", e, [f"v{i}", f"v{i + 1}", f"w{i}"]) for i in range(3)], ["v0", "w0", "v1", "w1", "v2", "w2", "v3"], ["e"] * 3)
    rank = Rank.sum(["w0", "w1", "w2"])
    want = Counter((u + v + w, a, u, b, v, c, w, d) for a, b, u in rows for b2, c, v in rows if b2 == b for c2, d, w in rows if c2 == c)
    shown = lambda df: Counter((r["weight"], *(r[x] for x in q.head)) for r in df.collect())
    with RisingBound(q, rank) as rounds:
        low = -1
        for tau in (0, 3, 4, 9, 40):
            assert shown(rounds.up_to(tau)) == Counter({k: n for k, n in want.items() if low < k[0] <= tau}), tau
            low = tau
    got = Counter()
    for part in frontier_rounds(q, rank, 2, 3, most=5):
        got += shown(part)
    assert got == Counter({k: n for k, n in want.items() if k[0] <= 2 + 3 + 6 + 12 + 24})


def test_engine_measures(spark):
    before = measures.last_job(spark)
    spark.range(100_000).repartition(3, "id").groupBy((F.col("id") % 7).alias("g")).count().collect()
    seen = measures.spark_metrics(spark, before + 1)
    assert seen["jobs"] >= 1 and seen["tasks"] > 0 and seen["shuffle_bytes"] > 0 and seen["spilled_bytes"] == 0


def test_saved_relations_keep_their_buckets(spark, tmp_path):
    rank = Rank.sum(["x1", "x2", "x3", "x4", "x5"])
    p = dp.ranked(mini(spark), rank)
    name = f"saved_{uuid.uuid4().hex}"
    index.save_prepared(p, str(tmp_path), 4, name)
    want = levels.sum_topk(mini(spark), rank, 5).orderBy("rnk").collect()
    for forget in (False, True):
        if forget:
            for i in (1, 2, 3):
                spark.sql(f"drop table if exists {name}_{i}")
        again = index.load_prepared(spark, str(tmp_path), rank)
        assert levels.sum_topk(again.tree.query, rank, 5, prepared=again).orderBy("rnk").collect() == want
        child = next(i for i in again.tree.order if again.tree.shared(i) == ("x1",))
        plan = again.frames[child].groupBy("x1").agg(F.min("_opt"))._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in plan
    for i in (1, 2, 3):
        spark.sql(f"drop table if exists {name}_{i}")


def test_join_groups(spark):
    p = dp.ranked(mini(spark), Rank.sum(["x1", "x2", "x3", "x4", "x5"]))
    child = next(i for i in p.tree.order if p.tree.shared(i) == ("x1",))
    got = {r["x1"]: (r["size"], [x["x3"] for x in r["rows"]]) for r in index.join_groups(p, child, [F.col("_opt")], 1).collect()}
    assert got == {0: (1, [1]), 1: (2, [1]), 2: (2, [3])}


def test_own_weights(spark):
    def heavy(x: pd.Series) -> pd.Series:
        return (x * 10) % 7

    q = mini(spark)
    weigh = user_weight(heavy)
    rank = Rank.sum({"x3": weigh("x3"), "x5": weigh("x5")})
    got = [(r["weight"], r["x3"], r["x5"]) for r in levels.sum_topk(q, rank, 8).orderBy("rnk").collect()]
    want = sorted((x3 * 10 % 7 + x5 * 10 % 7) for x3, x5 in [*itertools.product((1, 2), (8, 9)), *itertools.product((3, 5), (1, 2))])
    assert [w for w, *_ in got] == want and all(w == x3 * 10 % 7 + x5 * 10 % 7 for w, x3, x5 in got)


def test_table_function(spark):
    tables.register(spark)
    spark.createDataFrame([(1, 5, "a"), (1, 2, "b"), (1, 9, "c"), (2, 4, "d")], "g bigint, w bigint, name string").createOrReplaceTempView("for_table_function")
    got = spark.sql("select g, w, name, rnk from first_of_each(table(for_table_function) partition by g order by (w, name), 2)").collect()
    assert sorted(tuple(r) for r in got) == [(1, 2, "b", 1), (1, 5, "a", 2), (2, 4, "d", 1)]


def test_best_k_in_a_stream(spark, tmp_path):
    rng = random.Random(3)
    rows = [(rng.choice("xyz"), rng.randrange(100), i) for i in range(90)]
    for n in range(3):
        spark.createDataFrame(rows[n * 30 : n * 30 + 30], "g string, w bigint, id bigint").coalesce(1).write.json(str(tmp_path / "in" / str(n)))
    name = f"best_{uuid.uuid4().hex}"
    stream = spark.readStream.schema("g string, w bigint, id bigint").option("maxFilesPerTrigger", 1).json(str(tmp_path / "in" / "*"))
    run = best_k_so_far(stream, "g", "w", "id", 4).writeStream.format("memory").queryName(name).outputMode("update").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start()
    run.awaitTermination()
    last = {}
    for r in spark.table(name).collect():
        last.setdefault(r["g"], []).append((r["w"], r["id"], r["rnk"]))
    for g, seen in last.items():
        want = [(w, i, n + 1) for n, (w, i) in enumerate(sorted((w, i) for x, w, i in rows if x == g)[:4])]
        assert set(want) <= set(seen)


def test_merged_cursors(spark):
    from ordjoin.operators.cursor import OrderedCursor
    from ordjoin.operators.union import merge_cursors

    a = spark.createDataFrame([(1, 2, 5), (1, 3, 1), (2, 3, 4)], "x bigint, y bigint, w bigint")
    b = spark.createDataFrame([(1, 3, 1), (4, 4, 2)], "x bigint, y bigint, w bigint")
    queries = [cq([atom("e", e, ["x", "y", "w"])], ["x", "y"]) for e in (a, b)]
    for dedup, want in ((True, [(1, 1, 3), (2, 4, 4), (4, 2, 3), (5, 1, 2)]), (False, [(1, 1, 3), (1, 1, 3), (2, 4, 4), (4, 2, 3), (5, 1, 2)])):
        with OrderedCursor(queries[0], Rank.sum(["w"]), 2) as p, OrderedCursor(queries[1], Rank.sum(["w"]), 2) as q:
            assert [(r["weight"], r["x"], r["y"]) for r in merge_cursors([p, q], dedup)] == want


def test_join_hints(spark):
    from ordjoin.operators import baselines

    q, rank = mini(spark), Rank.sum(["x1", "x2", "x3", "x4", "x5"])
    want = baselines.engine_topk(q, rank, 8).orderBy("rnk").collect()
    for hint, node in (("merge", "SortMergeJoin"), ("shuffle_hash", "ShuffledHashJoin"), ("broadcast", "BroadcastHashJoin")):
        df = baselines.engine_topk(q, rank, 8, hint=hint)
        assert node in df._jdf.queryExecution().executedPlan().toString()
        assert df.orderBy("rnk").collect() == want
        assert node in levels.full_join(q, hint=hint)._jdf.queryExecution().executedPlan().toString()


def test_self_joins_split(spark):
    from ordjoin.plans.model import split_self_joins

    e = spark.createDataFrame([(1, 2), (2, 3)], "x bigint, y bigint")
    q = cq([atom("e", e, ["a", "b"]), atom("e", e, ["b", "c"])], ["a", "b", "c"], ["e", "e"])
    assert not q.is_self_join_free() and split_self_joins(q).is_self_join_free()
    assert [tuple(r) for r in levels.lex_topk(split_self_joins(q), ["a", "b", "c"], 3).select("a", "b", "c").collect()] == [(1, 2, 3)]
    single = cq([atom("e", e, ["a", "b"])], ["a", "b"], ["e"])
    assert split_self_joins(single).relations == ("e",)
