"""Random small instances: bulk, sequential and brute force agree, whatever tree and order."""

from __future__ import annotations

import random
from itertools import product

import pytest

from ordjoin.operators import access, cyclic, dp, levels, predicates, projection
from ordjoin.operators import sequential as S
from ordjoin.plans.jointree import all_trees, join_tree
from ordjoin.plans.model import atom, cq
from ordjoin.plans.ranking import Rank

SHAPES = {"chain": ["ab", "bc", "cd"], "star": ["ab", "ac", "ad"], "tree": ["ab", "ac", "bd", "de"], "wide": ["abc", "bcd", "de"]}


def build(spark, shape, rng, rows=9, domain=4, head=None):
    data = [[tuple(rng.randrange(-1, domain) for _ in names) for _ in range(rows)] for names in shape]
    atoms = [atom(f"r{i}", spark.createDataFrame(d, ", ".join(f"{v} bigint" for v in names)), list(names)) for i, (names, d) in enumerate(zip(shape, data, strict=True))]
    answers = []
    for rows_ in product(*data):
        got: dict = {}
        if all(got.setdefault(v, x) == x for names, r in zip(shape, rows_, strict=True) for v, x in zip(names, r, strict=True)):
            answers.append(got)
    return cq(atoms, head), answers


@pytest.mark.parametrize("name", SHAPES)
def test_top_k(spark, name):
    rng = random.Random(name)
    q, answers = build(spark, SHAPES[name], rng)
    for tree in list(all_trees(q))[:3]:
        met = tree.met()
        for rank, f in ((Rank.sum(met), sum), (Rank.max(met), max)):
            want = sorted((f(a.values()), tuple(a[v] for v in met)) for a in answers)
            for k in (1, 5, len(want) + 1):
                got = levels.sum_topk(q, rank, k, tree).orderBy("rnk").collect()
                assert [(r["weight"], tuple(r[v] for v in met)) for r in got] == want[:k]
        seq = [(w, tuple(a[v] for v in met)) for w, a in S.enumerate_sum(q, Rank.sum(met), tree)]
        want = sorted((sum(a.values()), tuple(a[v] for v in met)) for a in answers)
        assert [w for w, _ in seq] == [w for w, _ in want] and sorted(seq) == want
        assert int(dp.count_answers(q).first()["answers"]) == len(answers)


def test_lexicographic_by_every_order(spark):
    from ordjoin.plans.hypergraph import disruptive_trios

    q, answers = build(spark, SHAPES["chain"], random.Random(3), rows=7)
    distinct = {tuple(sorted(a.items())) for a in answers}
    for order in ("abcd", "bacd", "cbad", "dcba", "bcad", "adbc"):
        want = sorted(tuple(dict(a)[v] for v in order) for a in distinct)
        sets = cq([a.with_frame(a.frame.distinct()) for a in q.atoms])
        got = [tuple(r[v] for v in order) for r in levels.lex_topk(sets, list(order), 50).orderBy("rnk").collect()]
        assert got == want[:50]
        if not disruptive_trios(q, order):
            at = access.direct_access(sets, list(order), range(1, len(want) + 1)).orderBy("position").collect()
            assert [tuple(r[v] for v in order) for r in at] == want


def test_projection(spark):
    q, answers = build(spark, SHAPES["chain"], random.Random(5), rows=10, head=["a", "d"])
    want = sorted({(a["a"] + a["d"], a["a"], a["d"]) for a in answers})
    for run in (projection.project_rank_topk, projection.project_dedup_stream):
        got = run(q, Rank.sum(["a", "d"]), 6).orderBy("rnk").collect()
        assert [(r["weight"], r["a"], r["d"]) for r in got] == want[:6]


def test_inequalities(spark):
    rng = random.Random(7)
    q, answers = build(spark, ["ab", "bc"], rng, rows=12, domain=6)
    rank = Rank.sum(["a", "b", "c"])

    def best(keep):
        rows = sorted((sum(a.values()), a["a"], a["b"], a["c"]) for a in answers if keep(a))
        return rows[:10]

    def got(df):
        return [(r["weight"], r["a"], r["b"], r["c"]) for r in df.orderBy("rnk").collect()]

    assert got(predicates.lt_topk(q, "a", "c", rank, 10)) == best(lambda a: a["a"] < a["c"])
    assert got(predicates.lt_topk(q, "a", "c", rank, 10, strict=False)) == best(lambda a: a["a"] <= a["c"])
    band = predicates.branches_topk(predicates.band_branches(q, "a", "c", 2), rank, 10, dedup=False)
    assert got(band) == best(lambda a: 0 < a["c"] - a["a"] <= 2)
    sets, distinct = cq([a.with_frame(a.frame.distinct()) for a in q.atoms]), {tuple(a.items()) for a in answers}
    answers = [dict(a) for a in distinct]
    assert got(predicates.neq_topk(sets, "a", "c", rank, 10)) == best(lambda a: a["a"] != a["c"])
    assert got(predicates.nae_topk(sets, [("a", "c"), ("b", "c")], rank, 10)) == best(lambda a: (a["a"], a["b"]) != (a["c"], a["c"]))


def test_cycles(spark):
    rng = random.Random(11)
    for shape in (["ab", "bc", "ca"], ["ab", "bc", "cd", "da"]):
        q, answers = build(spark, shape, rng, rows=14, domain=5)
        want = sorted(sum(a.values()) for a in answers)
        got = cyclic.cyclic_topk(q, Rank.sum(q.variables), 12).orderBy("rnk").collect()
        assert [r["weight"] for r in got] == want[:12]
        if len(shape) == 4:
            out = cyclic.four_cycle_topk(*q.atoms, Rank.sum(q.variables), 12, threshold=2).orderBy("rnk").collect()
            assert [r["weight"] for r in out] == want[:12]


def test_hub(spark):
    """One key has every row; all weights are equal."""
    n = 300
    left = spark.range(n).selectExpr("id as a", "0 as b", "1 as w")
    right = spark.range(n).selectExpr("0 as b", "id as c", "1 as v")
    q = cq([atom("l", left, ["a", "b", "w"]), atom("r", right, ["b", "c", "v"])])
    stats = levels.PlanStats()
    got = levels.sum_topk(q, Rank.sum(["w", "v"]), 7, stats=stats).orderBy("rnk").collect()
    assert [(r["a"], r["c"]) for r in got] == [(0, i) for i in range(7)] and stats.levels == [7, 7]
    assert int(dp.count_answers(q).first()["answers"]) == n * n
    assert join_tree(q).order == (0, 1)


def test_numeric_codes_beyond_64_bits(spark):
    """Ten ordered variables of 150 values: the first one's place value is no 64-bit number."""
    names, n = list("abcdefghij"), 150
    value = lambda r, j: (r * (7, 11, 13)[j % 3] + j) % n
    rows = [[value(r, j) for j in range(10)] for r in range(n)]
    left = spark.createDataFrame([r[:5] for r in rows], ", ".join(f"{v} long" for v in names[:5]))
    right = spark.createDataFrame([r[4:] for r in rows], ", ".join(f"{v} long" for v in names[4:]))
    q = cq([atom("l", left, names[:5]), atom("r", right, names[4:])])
    order = ["j", "a", "h", "b", "c", "d", "e", "f", "g", "i"]
    rank, tree = levels.lex_as_sum(q, Rank.lex(order), numeric=True)
    got = levels.sum_topk(tree.query, rank, 20, tree).orderBy("rnk").collect()
    want = sorted(tuple(dict(zip(names, a + b[1:], strict=True))[v] for v in order) for a in (r[:5] for r in rows) for b in (r[4:] for r in rows) if a[4] == b[0])
    assert [tuple(r[v] for v in order) for r in got] == want[:20]


def test_not_all_equal_in_one_run_a_pair(spark, monkeypatch):
    """Ends of a path of three: the number of top-k runs doesn't follow the domain, with and without a bound."""
    rng = random.Random(13)
    q, answers = build(spark, ["ab", "bc", "cd"], rng, rows=14, domain=5)
    q = cq([a.with_frame(a.frame.distinct()) for a in q.atoms])
    distinct = [dict(t) for t in {tuple(a.items()) for a in answers}]
    runs = []
    monkeypatch.setattr(predicates, "sum_topk", lambda *a, **o: runs.append(1) or levels.sum_topk(*a, **o))
    for pairs in ([("a", "d"), ("b", "c")], [("a", "d")]):
        want = sorted((sum(a.values()), *a.values()) for a in distinct if any(a[x] != a[y] for x, y in pairs))
        for k in (3, len(want) + 1):
            runs.clear()
            got = predicates.nae_topk(q, pairs, Rank.sum(q.variables), k).orderBy("rnk").collect()
            assert [(r["weight"], r["a"], r["b"], r["c"], r["d"]) for r in got] == want[:k]
            assert len(runs) <= 4


def test_not_all_equal_holds_no_ties(spark, monkeypatch):
    """Equal weights everywhere: no frontier follows the number of ties, and these go by the head's order."""
    n, k, bits = 7, 5, 3
    pairs = [(i, j) for i in range(n) for j in range(n)]
    frames = [spark.createDataFrame([(*p, 1) for p in pairs], f"{a} long, {b} long, w{a} long") for a, b in ("ab", "bc", "cd")]
    q = cq([atom(f"r{i}", df, df.columns) for i, df in enumerate(frames)], ["d", "b", "a", "c"])
    answers = sorted((d, b, a, c) for a, b in pairs for c, d in pairs)
    frontiers = []
    monkeypatch.setattr(levels, "_cut", lambda *a, f=levels._cut: frontiers.append(f(*a)) or frontiers[-1])
    for unequal in ([("a", "d"), ("b", "c")], [("a", "d")]):
        want = [t for t in answers if any(dict(zip("dbac", t))[x] != dict(zip("dbac", t))[y] for x, y in unequal)]
        got = predicates.nae_topk(q, unequal, Rank.sum(["wa", "wb", "wc"]), k).orderBy("rnk").collect()
        assert [tuple(r) for r in got] == [(*t, 3, i) for i, t in enumerate(want[:k], 1)]
    assert max(rows for _, rows, _ in frontiers) <= k * bits
