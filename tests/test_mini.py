"""The small example database: every number that the prose gives."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from ordjoin import workloads as W
from ordjoin.operators import access, baselines, cursor, dp, index, levels, measures, projection
from ordjoin.operators import sequential as S
from ordjoin.plans.model import atom, cq, parse_rule
from ordjoin.plans.ranking import Rank, desc

V = ["x1", "x2", "x3", "x4", "x5"]
SUM = ["22321:10", "22322:11", "22521:12", "22522:13", "11138:14", "11139:15", "11238:15", "11239:16"]
LEX = ["11138", "11139", "11238", "11239", "22321", "22322", "22521", "22522"]


@pytest.fixture(scope="module")
def q(spark):
    return W.mini(spark)


def shown(df):
    return ["".join(str(r[v]) for v in V) + (f":{r['weight']}" if "weight" in df.columns else "") for r in df.orderBy("rnk").collect()]


def test_sum_in_both_directions(q):
    assert shown(levels.sum_topk(q, Rank.sum(V), 20)) == SUM
    assert [x.split(":")[1] for x in shown(levels.sum_topk(q, Rank.sum(V, desc=True), 20))] == ["16", "15", "15", "14", "13", "12", "11", "10"]


@pytest.mark.parametrize("k", [0, 1, 2, 7, 8, 9])
def test_prefixes_of_the_order(q, k):
    assert shown(levels.sum_topk(q, Rank.sum(V), k)) == SUM[:k]
    assert len(levels.sum_topk(q, Rank.sum(V), k, ties="arbitrary").collect()) == min(k, 8)


def test_ties_with_the_last(q):
    assert len(shown(levels.sum_topk(q, Rank.sum(V), 6, ties="all"))) == 7


def test_lexicographic_orders(q):
    assert shown(levels.lex_topk(q, V, 20)) == LEX
    assert shown(levels.lex_topk(q, ["x1", "x2", "x4", "x5", "x3"], 20)) == ["11138", "11238", "11139", "11239", "22321", "22521", "22322", "22522"]
    assert shown(levels.lex_topk(q, ["x1", "x4", "x2"], 20)) == LEX
    assert shown(levels.lex_topk(q, [desc("x1"), "x2"], 3)) == LEX[4:7]
    tree = levels.layered(q, V)
    assert shown(levels.lex_topk(tree.query, V, 20)) == LEX


def test_reduction_keeps_the_dangling_child(q):
    rows = {i: sorted(map(tuple, df.collect())) for i, df in dp.semijoin_reduce(q).items()}
    assert rows[0] == [(1, 1), (2, 2)] and rows[2] == [(1, 3), (2, 2)] and (0, 1) in rows[1]
    assert sorted(map(tuple, dp.semijoin_reduce(q, full=True)[1].collect())) == [(1, 1), (1, 2), (2, 3), (2, 5)]
    assert [tuple(r) for r in dp.dangling(q)[0].collect()] == [(0, 0)]


def test_optima(q):
    p = dp.ranked(q, Rank.sum(V))
    opt = {i: {tuple(r[v] for v in q.atoms[i].variables): r["_opt"] for r in df.collect()} for i, df in p.frames.items()}
    assert opt[3] == {(2, 1): 1, (2, 2): 2, (3, 8): 8, (3, 9): 9}
    assert opt[2] == {(2, 2): 3, (1, 3): 11} and opt[0] == {(2, 2): 10, (1, 1): 14}
    through = dp.through_weights(p)
    assert {tuple(r[v] for v in ("x1", "x3")): r["_through"] for r in through[1].collect()} == {(1, 1): 14, (1, 2): 15, (2, 3): 10, (2, 5): 12}
    assert dp.tau_from_root(p, 2) == 14 and dp.tau_from_root(p, 3) is None
    assert dp.prune(p, 12).frames[0].count() == 1


def test_queue_after_the_first_answer(q):
    stats = S.EnumStats()
    run = S.enumerate_sum(q, Rank.sum(V), stats=stats)
    assert next(run)[0] == 10
    groups = S.collect_groups(dp.ranked(q, Rank.sum(V)))
    heap = S.SumHeap(groups)
    steps = [w for w, _ in heap]
    assert steps == [10, 11, 12, 13, 14, 15, 15, 16]
    assert heap.stats.pops[1][0] == 11 and heap.stats.most_open <= len(q.atoms) * 8
    assert heap.stats.most_pushes_a_step <= len(q.atoms) and heap.stats.visits <= heap.stats.answers * len(q.atoms)


@pytest.mark.parametrize("priority", ["extend", "delta"])
def test_priorities_agree(q, priority):
    assert ["".join(str(a[v]) for v in V) + f":{w}" for w, a in S.enumerate_sum(q, Rank.sum(V), priority=priority)] == SUM


def test_stack_and_recursion(q):
    stats = S.EnumStats()
    assert ["".join(str(a[v]) for v in V) for a in S.enumerate_lex(q, stats=stats)] == LEX
    assert stats.most_pushes_a_step <= len(q.atoms)
    reduced = {i: df.collect() for i, df in dp.semijoin_reduce(q).items()}
    groups = S.local_groups(dp.join_tree(q), reduced, by_optimum=False)
    assert ["".join(str(a[v]) for v in V) for a in S.lex_depth_first(groups)] == LEX


def test_greedy_is_late(q):
    got = baselines.greedy_first(q, Rank.sum(V))
    assert sum(got.values()) == 14


def test_other_rankings(q):
    assert [x.split(":")[1] for x in shown(levels.sum_topk(q, Rank.max(V), 20))] == ["3", "3", "5", "5", "8", "8", "9", "9"]
    assert [x.split(":")[1] for x in shown(levels.sum_topk(q, Rank.min(V), 20))] == ["1"] * 6 + ["2"] * 2
    assert [x.split(":")[1] for x in shown(levels.sum_topk(q, Rank.product(V), 3))] == ["24", "24", "27"]
    assert [w for w, _ in S.enumerate_sum(q, Rank.max(V))] == [3, 3, 5, 5, 8, 8, 9, 9]


def test_counts_and_access(q):
    assert int(dp.count_answers(q).first()["answers"]) == 8 and dp.exists(q)
    got = access.direct_access(q, V, [8, 1, 3, 9]).collect()
    assert {r["position"]: "".join(str(r[v]) for v in V) for r in got} == {1: LEX[0], 3: LEX[2], 8: LEX[7]}
    assert access.can_access(q, V) and not access.can_access(q, ["x1", "x4", "x2"])
    hist = {r["weight"]: int(r["answers"]) for r in access.weight_histogram(q, Rank.sum(V)).collect()}
    assert hist == {10: 1, 11: 1, 12: 1, 13: 1, 14: 1, 15: 2, 16: 1}
    assert access.select_nth(q, Rank.sum(V), 6).first()["weight"] == 15


def test_baselines_agree(q):
    rank = Rank.sum(V)
    for df in (baselines.batch_reduce_join_sort(q, rank), baselines.engine_join_sort(q, rank)):
        assert ["".join(str(r[v]) for v in V) + f":{r['weight']}" for r in df.collect()] == SUM
    assert shown(baselines.engine_topk(q, rank, 3)) == SUM[:3]
    assert baselines.naive_product(q).count() == 8 and baselines.table_at_a_time(q, 5).count() == 5
    assert sum(p.count() for p in baselines.batch_incremental_sort(q, rank, 4)) == 8


def test_cursor(q):
    with cursor.OrderedCursor(q, Rank.sum(V), first=3) as c:
        assert shown(c.next_batch()) == SUM[:3]
        assert [r["weight"] for r in c] == [13, 14, 15, 15, 16]


def test_measures(q):
    curve = measures.tt_curve(lambda: S.enumerate_sum(q, Rank.sum(V)), [1, 4])
    assert [k for k, _ in curve.points] == [1, 4, 8] and curve.first <= curve.last
    assert measures.is_ranked(levels.sum_topk(q, Rank.sum(V), 8))


def test_saved_relations(q, spark, tmp_path):
    p = dp.ranked(q, Rank.sum(V))
    index.save_prepared(p, str(tmp_path / "p"))
    again = index.load_prepared(spark, str(tmp_path / "p"), Rank.sum(V))
    assert shown(levels.sum_topk(again.tree.query, Rank.sum(V), 5, prepared=again)) == SUM[:5]


def test_rule_text(spark):
    t = W.mini_tables(spark)
    q = parse_rule("q(x, y) :- r(x, 2), s(a=x, b=y)", t)
    assert sorted(map(tuple, levels.full_join(q).select("x", "y").collect())) == [(2, 3), (2, 5)]
    assert levels.full_join(parse_rule("q(x) :- r(x, x)", t)).count() == 3
    with pytest.raises(ValueError):
        parse_rule("q(z) :- r(x, y)", t)


def test_edge_cases(spark):
    t = W.mini_tables(spark)
    none = t["s"].limit(0)
    q = cq([atom("r", t["r"], ["x", "y"]), atom("s", none, ["x", "z"])])
    assert levels.sum_topk(q, Rank.sum(["x"]), 5).collect() == [] and not dp.exists(q)
    apart = cq([atom("r", t["r"], ["x", "y"]), atom("s", t["s"], ["z", "w"])])
    got = levels.sum_topk(apart, Rank.sum(["x", "w"]), 4).orderBy("rnk").collect()
    assert [r["weight"] for r in got] == [1, 1, 2, 2]
    nulls = spark.createDataFrame([(1, None), (None, 2), (1, 3)], "a bigint, b bigint")
    assert cq([atom("n", nulls, ["x", "y"])]).atoms[0].frame.count() == 1
    twice = cq([atom("d", t["r"].unionByName(t["r"]), ["x", "y"])])
    assert len(levels.sum_topk(twice, Rank.sum(["x"]), 4).collect()) == 4
    one = cq([atom("r", t["r"], ["x", "y"])])
    assert [r["x"] for r in levels.sum_topk(one, Rank.sum(["y"], desc=True), 2).orderBy("rnk").collect()] == [2, 1]


def test_projection_on_the_example(spark):
    t = W.mini_tables(spark)
    q = cq([atom("r", t["r"], ["x", "y"]), atom("t", t["t"], ["y", "z"]), atom("u", t["u"], ["z", "v"])], ["x", "v"])
    got = projection.project_rank_topk(q, Rank.sum(["x", "v"]), 10).orderBy("rnk").collect()
    assert [(r["x"], r["v"], r["weight"]) for r in got] == [(2, 1, 3), (2, 2, 4), (1, 8, 9), (1, 9, 10)]
    with pytest.raises(projection.NotFreeConnex):
        projection.free_connex_rewrite(q)
    lex = projection.project_lex_topk(q, ["v", "x"], 3).orderBy("rnk").collect()
    assert [(r["x"], r["v"]) for r in lex] == [(2, 1), (2, 2), (1, 8)]
    easy = cq([atom("r", t["r"], ["x", "y"]), atom("t", t["t"], ["y", "z"])], ["x", "y"])
    assert sorted(map(tuple, levels.full_join(projection.free_connex_rewrite(easy)).select("x", "y").collect())) == [(0, 0), (1, 1), (2, 2)]


def test_lookup_weights(spark, q):
    from ordjoin.plans.ranking import lookup

    values = spark.createDataFrame([(3, 100), (5, 1), (1, 50), (2, 60)], "v bigint, w bigint")
    wide = lookup(q, "x3", values, "score")
    got = levels.sum_topk(wide, Rank.sum({"score": F.col("score")}), 3).orderBy("rnk").collect()
    assert [r["weight"] for r in got] == [1, 1, 50]
