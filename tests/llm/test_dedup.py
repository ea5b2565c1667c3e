from __future__ import annotations

import hashlib
import random
import re

import pytest
from pyspark.sql import functions as F

from ordjoin.llm import near_duplicates as N
from ordjoin.llm import substring_dedup as S
from ordjoin.llm.components import components
from ordjoin.llm.suffix_dedup import remove_repeats

W = re.compile("[^\x20\x09-\x0d]+")
LAST = 2**63 - 1


def order(i):
    return LAST if i is None else i


def brute_words(rows, window):
    first: dict = {}
    words = [W.findall(t or "") for _, t in rows]
    for (i, _), w in zip(rows, words, strict=True):
        for j in range(len(w) - window + 1):
            k = tuple(w[j : j + window])
            first[k] = min(first.get(k, LAST), order(i))
    out = []
    for (i, _), w in zip(rows, words, strict=True):
        gone = set()
        for j in range(len(w) - window + 1):
            if first[tuple(w[j : j + window])] < order(i):
                gone.update(range(j, j + window))
        left = " ".join(x for n, x in enumerate(w) if n not in gone)
        out.append((i, len(w), len(gone), hashlib.sha256(left.encode()).hexdigest()))
    return sorted(out, key=repr)


def brute_bytes(rows, window):
    count: dict = {}
    bodies = [(i, (t or "").encode()) for i, t in rows]
    for _, b in bodies:
        for j in range(len(b) - window + 1):
            count[b[j : j + window]] = count.get(b[j : j + window], 0) + 1
    out = []
    for i, b in bodies:
        gone = bytearray(len(b))
        for j in range(len(b) - window + 1):
            if count[b[j : j + window]] > 1:
                gone[j : j + window] = b"\1" * window
        left = bytes(x for x, g in zip(b, gone, strict=True) if not g)
        out.append((i, len(b), sum(gone), len([x for x in bytes(gone).split(b"\0") if x]), hashlib.sha256(left).hexdigest()))
    return sorted(out, key=repr)


def rows_of(df):
    return [(r["doc_id"], r["text"]) for r in df.collect()]


def got_words(df):
    return sorted(((r["doc_id"], r["n"], r["n_removed"], r["kept_sha256"]) for r in df.collect()), key=repr)


@pytest.mark.parametrize(("window", "gram", "batches"), [(50, 12, 2), (5, 2, 3), (8, 8, 1)])
def test_word_windows(corpus, window, gram, batches):
    assert got_words(S.deduplicate(corpus, batches, window, gram)) == brute_words(rows_of(corpus), window)


@pytest.mark.parametrize("window", [200, 24])
def test_byte_windows(corpus, window):
    out = remove_repeats(corpus, window, min(32, window // 2))
    assert sorted(((r["doc_id"], r["n"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in out.collect()), key=repr) == brute_bytes(rows_of(corpus), window)


def test_random_small_alphabets(spark):
    rng = random.Random(1)
    for case in range(3):
        rows = [(i, " ".join(rng.choice("abc") for _ in range(rng.randrange(0, 40)))) for i in range(25)]
        df = spark.createDataFrame(rows, "doc_id bigint, text string")
        assert got_words(S.deduplicate(df, 2, 6, 3)) == brute_words(rows, 6)
        out = remove_repeats(df, 10 + case, 4)
        assert sorted(((r["doc_id"], r["n"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in out.collect()), key=repr) == brute_bytes(rows, 10 + case)


@pytest.mark.parametrize("hot", [1, 3])
def test_hot_triggers_go_by_blocks(spark, corpus, monkeypatch, hot):
    from ordjoin.llm import windows

    monkeypatch.setattr(windows, "HOT", hot)
    rng = random.Random(6)
    rows = [(i, " ".join(rng.choice("abc") for _ in range(rng.randrange(0, 60)))) for i in range(30)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    assert got_words(S.deduplicate(df, 2, 6, 3)) == brute_words(rows, 6)
    for docs, window, gram in ((df, 11, 4), (corpus, 200, 32)):
        out = remove_repeats(docs, window, gram)
        assert sorted(((r["doc_id"], r["n"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in out.collect()), key=repr) == brute_bytes(rows_of(docs), window)


def test_whole_groups():
    import pyarrow as pa

    from ordjoin.llm.common import whole_groups

    rng = random.Random(1)
    for least in (1, 4, 100):
        keys = sorted(rng.randrange(12) for _ in range(60))
        table = pa.table({"k": pa.array(keys, pa.int64()), "v": pa.array(range(60))})
        cuts = sorted(rng.sample(range(61), 8))
        batches = [table.slice(a, b - a).to_batches()[0] for a, b in zip([0, *cuts], [*cuts, 60], strict=True) if b > a]
        got = list(whole_groups(iter(batches), 1, least))
        assert [v for t in got for v in t.column("v").to_pylist()] == list(range(60))
        seen = [set(t.column("k").to_pylist()) for t in got]
        assert all(not (a & b) for i, a in enumerate(seen) for b in seen[:i]) and all(t.num_rows >= least for t in got[:-1])
        assert least > 1 or all(len(s) == 1 for s in seen)


def test_orders_are_suffix_arrays():
    import numpy as np

    from ordjoin.llm import windows

    rng = np.random.default_rng(3)
    rows, group = rng.integers(0, 2, (50, 9)).astype(np.uint8), np.sort(rng.integers(0, 4, 50))
    order, common = windows._order(rows, group)
    listed = [(int(group[i]), bytes(rows[i])) for i in order]
    assert listed == sorted(listed)
    for depth in range(10):
        names = windows._interval(order, common, depth)
        assert all((names[i] == names[j]) == (group[i] == group[j] and (rows[i][:depth] == rows[j][:depth]).all()) for i in range(50) for j in range(50))


def test_index_over_batches_and_compaction(spark):
    rng = random.Random(2)
    pool = [" ".join(rng.choice("abcdefgh") for _ in range(12)) for _ in range(6)]
    rows = [(i, " ".join([rng.choice(pool), str(i), rng.choice(pool)])) for i in range(40)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    index, got = S.FingerprintIndex(spark, buckets=4, fanout=2), []
    for a in range(0, 40, 10):
        got += S.remove_known(df.where((F.col("doc_id") >= a) & (F.col("doc_id") < a + 10)), index, 8, 3).collect()
        assert len(index.runs) < 2 or a == 0
    assert sorted(((r["doc_id"], r["n"], r["n_removed"], r["kept_sha256"]) for r in got), key=repr) == brute_words(rows, 8)
    index.drop()


def test_cleaned_keeps_columns(corpus):
    odd = corpus.withColumns({"ord": F.lit(1), "key": F.lit("k"), "spans": F.lit(2.0), "body": F.lit("b")})
    out = S.cleaned(odd)
    assert out.columns == odd.columns and out.count() == odd.count()
    texts = {r["doc_id"]: r["text"] for r in out.where("doc_id in (100, 101)").collect()}
    assert texts[101] == "" and len(texts[100].split()) == 120


def test_empty_table(empty):
    assert remove_repeats(empty).collect() == [] and S.deduplicate(empty).collect() == []
    assert N.classes(empty).collect() == [] and N.one_of_each(empty).collect() == []


def brute_classes(rows, width, percent):
    sets = []
    for _, t in rows:
        w = W.findall(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets.append(frozenset(tuple(w[k : k + width]) for k in range(len(w) - width + 1)) if len(w) >= width else frozenset([tuple(w)]) if w else frozenset())
    parent = list(range(len(rows)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j]):
                parent[find(i)] = find(j)
    least: dict = {}
    for i, (d, _) in enumerate(rows):
        least[find(i)] = min(least.get(find(i), LAST), order(d))
    return [(d, len(sets[i]), None if least[find(i)] == LAST else least[find(i)]) for i, (d, _) in enumerate(rows)], find


@pytest.mark.parametrize(("width", "percent"), [(4, 85), (5, 80), (1, 50), (2, 30)])
def test_classes(corpus, width, percent):
    want, _ = brute_classes(rows_of(corpus), width, percent)
    got = [(r["doc_id"], r["n_shingles"], r["component_id"]) for r in N.classes(corpus, width, percent).collect()]
    assert sorted(got, key=repr) == sorted(want, key=repr)


def test_classes_of_many_near_sets(spark):
    rng = random.Random(9)
    words = [f"v{i}" for i in range(60)]
    rows = []
    for i in range(220):
        base = words[(i % 4) * 12 : (i % 4) * 12 + 24]
        rows.append((i, " ".join(w for w in base if rng.random() > 0.08)))
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    for percent in (70, 85, 95):
        want, _ = brute_classes(rows, 1, percent)
        assert sorted((r["doc_id"], r["n_shingles"], r["component_id"]) for r in N.classes(df, 1, percent).collect()) == sorted(want)


def test_keys_move_once_to_their_blocks(spark, monkeypatch):
    plans, write, limit = {}, N.settle, "spark.sql.autoBroadcastJoinThreshold"
    monkeypatch.setattr(N, "settle", lambda df, name: (plans.update({name: df._jdf.queryExecution().executedPlan().toString()}), write(df, name))[1])
    nodes = spark.createDataFrame([(1, 5, [10, 11, 12]), (2, 6, [11, 13]), (3, 7, [11, 10]), (4, 8, [])], "node long, n long, keys array<long>")
    before = spark.conf.get(limit)
    spark.conf.set(limit, "-1")
    try:
        got = sorted(tuple(r) for r in N._blocks(nodes).select("block", "node", "n", "many").collect())
    finally:
        spark.conf.set(limit, before)
    assert got == [(10, 1, 5, 2), (10, 3, 7, 2), (11, 1, 5, 3), (11, 2, 6, 3), (11, 3, 7, 3)]
    assert plans["all-blocks"].count("Exchange hashpartitioning(block") == 1


def test_vectors_move_with_pairs_alone(spark, monkeypatch):
    from ordjoin.operators.measures import last_job, spark_metrics

    rng, moved, write, limit = random.Random(21), {}, N.settle, "spark.sql.autoBroadcastJoinThreshold"

    def measured(df, name):
        start, out = last_job(spark) + 1, write(df, name)
        spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
        moved[name] = moved.get(name, 0) + spark_metrics(spark, start)["shuffle_bytes"]
        return out

    monkeypatch.setattr(N, "settle", measured)
    rows = [(i, " ".join(f"w{rng.randrange(10**6)}" for _ in range(150))) for i in range(400)]
    rows += [(400 + i, f"{rows[i][1]} more") for i in range(4)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    before = spark.conf.get(limit)
    spark.conf.set(limit, "-1")
    try:
        got = {r["doc_id"]: r["component_id"] for r in N.classes(df, 4, 85).collect()}
    finally:
        spark.conf.set(limit, before)
    assert got == {i: i if i < 400 else i - 400 for i in range(404)}
    assert moved["pairs"] + moved["more"] < 404 * 40  # 128 groups and more of each text would be over 404 * 64


def test_count_vectors():
    import numpy as np

    rng = np.random.default_rng(5)
    top = np.uint64(1 << 63)
    for s in (np.arange(1, 2, dtype=np.uint64), np.unique(rng.integers(0, 1 << 63, 900, np.uint64) * 2), np.arange(900, dtype=np.uint64), np.arange(70_000, dtype=np.uint64) + top):
        point = N.count_vector(s)
        counts = N.counts_of(point)
        groups, many = np.unique(s >> np.uint64(64 - int(len(counts)).bit_length() + 1), return_counts=True)
        assert counts.sum(dtype=np.int64) == len(s) and (counts[groups] == many).all()
        assert point[0] == (0 if many.max() < 16 else 2)
        assert N.bound(counts, counts) == len(s) and N.coarse([counts]).sum() == len(s)
        assert N.bound(counts, N.counts_of(N.count_vector(s[: len(s) // 2 + 1]))) == len(s) // 2 + 1
    mid = N.count_vector(np.arange(100, dtype=np.uint64))
    assert mid[0] == 1 and N.counts_of(mid)[0] == 100 and N.counts_of(mid).sum() == 100


def test_classes_whatever_cells_are_told(spark, monkeypatch):
    rng = random.Random(9)
    words = [f"v{i}" for i in range(60)]
    rows = []
    for i in range(120):
        base = words[(i % 4) * 12 : (i % 4) * 12 + 24]
        rows.append((i, " ".join(w for w in base if rng.random() > 0.08)))
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    want, _ = brute_classes(rows, 1, 85)
    monkeypatch.setattr(N, "CHUNK", 16)
    for told in (1, 3):
        monkeypatch.setattr(N, "LEAST_CELLS", told)
        assert sorted((r["doc_id"], r["n_shingles"], r["component_id"]) for r in N.classes(df, 1, 85).collect()) == sorted(want)


def test_numbers_of_links(spark, corpus):
    rng = random.Random(12)
    words = [f"v{i}" for i in range(90)]
    rows = []
    for i in range(160):
        text = words[(i % 2) * 40 : (i % 2) * 40 + 40]
        for _ in range(rng.randrange(4)):
            text[rng.randrange(40)] = f"x{rng.randrange(30)}"
        rows.append((i, " ".join(text)))
    for df, width, percent in ((spark.createDataFrame(rows, "doc_id bigint, text string"), 1, 85), (spark.createDataFrame(rows, "doc_id bigint, text string"), 2, 80), (corpus, 4, 85)):
        sets = []
        for r in df.collect():
            w = W.findall((r["text"] or "").lower() if (r["text"] or "").isascii() else r["text"])
            sets.append((r["doc_id"], frozenset(tuple(w[k : k + width]) for k in range(max(len(w) - width + 1, min(len(w), 1))))))
        different = {s for _, s in sets if s}
        want = sorted((repr(d), sum(100 * len(s & o) >= percent * len(s | o) for o in different if o != s) if s else 0) for d, s in sets)
        assert sorted((repr(r["doc_id"]), r["n_links"]) for r in N.classes(df, width, percent).collect()) == want


def test_one_of_each(corpus):
    rows = rows_of(corpus)
    want, find = brute_classes(rows, 5, 80)
    classes = {find(i) for i, (_, n, _) in enumerate(want) if n}
    empties = sum(n == 0 for _, n, _ in want)
    out = N.one_of_each(corpus)
    assert out.columns == corpus.columns and out.count() == len(classes) + empties
    assert {100} == {r["doc_id"] for r in out.collect()} & {100, 101, 102, 103}


def test_tree_join_loses_no_pair():
    import numpy as np

    rng = np.random.default_rng(0)
    points = rng.integers(0, 4, (90, 16)).astype(np.uint16)
    sizes = points.sum(1).astype(np.int64)
    found = set()
    for x, y in N.CountTree(points[:50], sizes[:50]).join(N.CountTree(points[50:], sizes[50:]), 70):
        found |= {(int(a), int(b)) for a, b in zip(x, y, strict=True)}
    want = {(a, b) for a in range(50) for b in range(40) if np.minimum(points[a], points[50 + b]).sum() >= N.needed(sizes[a], sizes[50 + b], 70) and 100 * min(sizes[a], sizes[50 + b]) >= 70 * max(sizes[a], sizes[50 + b])}
    assert want <= found


def test_components(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 102), (101, 102), (7, 7)], "a bigint, b bigint")
    got = {r["node"]: r["root"] for r in components(links).collect()}
    assert {got[i] for i in range(41)} == {0} and {got[i] for i in (100, 101, 102)} == {100} and len(got) == 44


def test_overlaps():
    import numpy as np

    rng = np.random.default_rng(4)
    for n, m, pool in ((1, 1, 3), (40, 25, 30), (60, 60, 2000), (0, 5, 9)):
        a, b = ([np.unique(rng.integers(0, pool, rng.integers(0, 25))) for _ in range(k)] for k in (n, m))
        want = [[len(set(x.tolist()) & set(y.tolist())) for y in b] for x in a]
        assert N.overlaps(a, b).astype(int).tolist() == want


def test_numbers_of_links_in_chunks(spark, monkeypatch):
    rng = random.Random(13)
    words = [f"v{i}" for i in range(70)]
    rows = []
    for i in range(150):
        text = words[:60]
        for _ in range(rng.randrange(7)):
            text[rng.randrange(60)] = f"x{rng.randrange(20)}"
        rows.append((i, " ".join(text)))
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    want = sorted((r["doc_id"], r["n_links"]) for r in N.classes(df, 1, 90).collect())
    sets = [frozenset(t.split()) for _, t in rows]
    assert want == [(i, sum(s != o and 100 * len(s & o) >= 90 * len(s | o) for o in set(sets))) for i, s in enumerate(sets)]
    for name, value in (("COUNT_CHUNK", 16), ("COUNT_ROWS", 5), ("COLUMNS", 7), ("CHUNK", 8), ("PAIRS_A_TASK", 4)):
        monkeypatch.setattr(N, name, value)
    assert sorted((r["doc_id"], r["n_links"]) for r in N.classes(df, 1, 90).collect()) == want
