from __future__ import annotations

import math
import random
import re
import zlib
from collections import Counter

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from ordjoin.llm import class_lm, decontamination, host_reputation, license_scan, packing, quality_rules, sharding

W = re.compile("[^\x20\x09-\x0d]+")


def lower(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


# -- quality ---------------------------------------------------------------------------------------------------------
def test_quality_measures_against_brute_force(corpus):
    def brute(t):
        t = t or ""
        w = W.findall(t)
        lines = [x for x in t.split("\n") if W.search(x)]
        grams = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
        n = Counter(grams)
        covered = {j for i, g in enumerate(grams) if n[g] > 1 for j in range(i, i + 5)}
        return len(w), sum(map(len, w)), sum(t.count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(covered)

    extra = corpus.sparkSession.createDataFrame([(900, "a b c d e f a b c d e x a b c d e"), (901, "x\n\nx\n x\ny#*|\ny#*|"), (902, "p q " * 9)], "doc_id bigint, text string")
    docs = corpus.select("doc_id", "text").unionByName(extra).withColumn("n_words", F.lit("clash"))
    for r in quality_rules.judge(docs).collect():
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == brute(r["text"]), r["doc_id"]
        assert r["kept"] == (r["rejected_by"] is None)


def test_quality_cascade(corpus, empty):
    kept = {r["doc_id"] for r in quality_rules.judge(corpus).where("kept").collect()}
    assert {r["doc_id"] for r in quality_rules.passing(corpus).collect()} == kept
    assert 100 in kept and not kept & {300, 301, 302, 303, 400}
    order = quality_rules.ordered(corpus, quality_rules.rules_on_text())
    rates = [(share + 1e-6) / max(cost, 1e-6) for _, share, cost in order]
    assert rates == sorted(rates, reverse=True)
    assert quality_rules.judge(empty).collect() == [] and quality_rules.passing(empty).collect() == []


def test_quality_sql(corpus):
    con = duckdb.connect()
    con.register("documents", corpus.toArrow())
    want = con.sql(quality_rules.ORACLE).fetchall()
    got = [tuple(r) for r in quality_rules.judge(corpus).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words").collect()]
    assert sorted((x[:6] for x in want), key=repr) == sorted(got, key=repr)


# -- packing ---------------------------------------------------------------------------------------------------------
PATH = None


def tokenizer_path():
    P = pytest.importorskip("public_tokenizers")
    return P.path("word_bpe_49k.json")


def test_tokenizer_equals_the_library():
    from tokenizers import Tokenizer

    path = tokenizer_path()
    library, ours = Tokenizer.from_file(path), packing.WordTokenizer(path)
    texts = ["", "Hello, World's 42 it'll'd --- ''s", "Ünïcode ÄÖÜ ß Straße", "tab\tnew\nline\x0b\x0c\r", "ΑΣ σς İstanbul é", "中文 emoji 😀!", "<|endoftext|> x", "a\x1cb\x85c\xa0d", "x" * 3000, "'" * 9 + "s ' s"]
    for _ in range(2):
        for t, ids in zip(texts, ours.encode(texts), strict=True):
            assert np.frombuffer(ids, "<u4").tolist() == library.encode(t, add_special_tokens=False).ids, t


def test_tokenizer_keeps_words_that_come_again(monkeypatch):
    """A full memo isn't emptied: words of every batch are learnt once, and ids stay those of the library."""
    from tokenizers import Tokenizer

    monkeypatch.setattr(packing, "_MEMO", 40)
    path, rng, asked = tokenizer_path(), random.Random(2), []
    library, ours = Tokenizer.from_file(path), packing.WordTokenizer(path)
    learn = ours._learn_pieces
    monkeypatch.setattr(ours, "_learn_pieces", lambda order: (asked.extend(order), learn(order))[1])
    for _ in range(30):
        fresh = ["".join(rng.choices("aeiouklmnrst", k=9)) for _ in range(6)]
        texts = ["again and again, it's again", " ".join(f"{w}. '{w} {w}#" for w in fresh), "''' # ' again\x1c"]
        for t, ids in zip(texts, ours.encode(texts), strict=True):
            assert np.frombuffer(ids, "<u4").tolist() == library.encode(t, add_special_tokens=False).ids, t
    assert asked.count("again") == 1


@pytest.mark.parametrize("window", [16, 4096])
def test_packing_round_trip(corpus, empty, window):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(tokenizer_path())
    rows = packing.pack(corpus.repartition(3), tokenizer_path(), window).collect()
    sequences: dict = {}
    for r in rows:
        sequences.setdefault(r["sequence_id"], []).append((r["offset"], bytes(r["ids"])))
        assert len(r["ids"]) == 4 * r["length"] > 0
    stream = b""
    for s in range(len(sequences)):
        for offset, ids in sorted(sequences[s]):
            assert offset * 4 == len(stream) - s * window * 4
            stream += ids
        assert len(stream) == (s + 1) * window * 4 or s == len(sequences) - 1
    want = Counter(tuple([*library.encode(r["text"] or "", add_special_tokens=False).ids, 2]) for r in corpus.collect())
    ids, got, now = np.frombuffer(stream, "<u4").tolist(), Counter(), []
    for i in ids:
        now.append(i)
        if i == 2:
            got[tuple(now)] += 1
            now = []
    assert got == want
    assert packing.pack(empty, tokenizer_path()).collect() == []


# -- language model --------------------------------------------------------------------------------------------------
def test_class_model(spark, corpus):
    rng = random.Random(3)
    nouns, verbs = [f"n{i}" for i in range(30)], [f"v{i}" for i in range(30)]
    rows = [(i, " ".join(f"The {rng.choice(nouns)} {rng.choice(verbs)} a {rng.choice(nouns)}." for _ in range(20))) for i in range(120)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string").unionByName(corpus.select("doc_id", "text"))
    got = class_lm.score(docs, classes=6, passes=3).collect()
    tokens = [(r["doc_id"], [*W.findall(lower(r["text"])), None]) for r in docs.collect()]
    fold = lambda i: zlib.crc32(("" if i is None else str(i)).encode()) % 10 == 0
    c = Counter(w for i, t in tokens if not fold(i) for w in t)
    n, v = sum(c.values()), len(c)
    want = sorted((repr(i), fold(i), len(t), sum(c[w] > 0 for w in t), n, round(sum(math.log10((c[w] + 0.1) / (n + 0.1 * (v + 1))) for w in t), 4)) for i, t in tokens)
    assert sorted((repr(r["doc_id"]), r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"], round(r["base_score"], 4)) for r in got) == want
    held = {r["held_out"]: r for r in class_lm.perplexity(spark.createDataFrame(got)).collect()}
    assert held[True]["perplexity"] < 0.7 * held[True]["base_perplexity"]


def test_class_probabilities_sum_to_one(spark):
    rows = [(i, "a b c a b d e f g h " * 3) for i in range(30)]
    model, words = class_lm.train(class_lm.bodies_of(spark.createDataFrame(rows, "doc_id bigint, text string")), classes=3, passes=2, limit=0.05)
    assert np.allclose((10.0**model.step).sum(1), 1)
    f, total = len(model.frequent.words), 0.0
    for r in words.collect():
        known = np.flatnonzero(model.frequent.words == np.int64(r["word"]).astype(np.uint64))
        if not len(known):
            total += r["c"] / (model.form_total[r["form"]] + model.form_once[r["form"]])
    by_class = np.bincount(model.of[:f], weights=model.frequent.counts / model.class_total[model.of[:f]])
    assert np.allclose(by_class[by_class > 0], 1)
    forms = model.form_total > 0
    assert np.isclose(total, (model.form_total[forms] / (model.form_total + model.form_once)[forms]).sum())


def test_exchange_raises_likelihood():
    rng = np.random.default_rng(1)
    words, k = 40, 4
    hidden = rng.integers(0, 4, words)
    pairs = rng.poisson(np.where((hidden[:, None] + 1) % 4 == hidden[None, :], 8.0, 0.3)).astype(float)

    def counts(of):
        after, before = np.zeros((words, k)), np.zeros((words, k))
        for c in range(k):
            after[:, c], before[:, c] = pairs[:, of == c].sum(1), pairs[of == c].sum(0)
        return before, after

    def value(of):
        m = np.zeros((k, k))
        np.add.at(m, of, counts(of)[1])
        return class_lm.likelihood(m)

    of = np.arange(words) % k
    start = value(of)
    for _ in range(6):
        of = class_lm.exchange(*counts(of), of, np.arange(words), k)
    assert value(of) > start


def test_language_model_on_nothing(empty):
    assert class_lm.score(empty).collect() == []


# -- decontamination -------------------------------------------------------------------------------------------------
def test_leaks(spark, corpus, empty):
    rng = random.Random(6)
    words = [f"t{i}" for i in range(3000)]
    text = lambda n: " ".join(rng.choice(words) for _ in range(n))
    items = [(i, f"{text(rng.randrange(15, 50))}. {text(6)}.") for i in range(25)] + [(98, None), (99, "")]
    clean = [(1000 + i, text(300)) for i in range(150)]
    planted = []
    for i in range(25):
        w = items[i][1].split()
        if i % 3 == 1:  # reworded: some words left out, some put in
            w = [x for j, x in enumerate(w) if j % 9 != 4]
            w.insert(5, "extra")
        planted.append((i, f"{text(rng.randrange(0, 120))} {' '.join(w)} {text(rng.randrange(0, 120))}"))
    docs = spark.createDataFrame(clean + planted, "doc_id bigint, text string").unionByName(corpus.select("doc_id", "text"))
    bench = spark.createDataFrame(items, "item_id bigint, text string")
    got = {(r["doc_id"], r["item_id"]) for r in decontamination.find_leaks(docs, bench).collect()}
    want = {(i, i) for i in range(25)}
    assert got == want or (len(got & want) / len(want) >= 0.9 and got <= want)
    assert decontamination.clean(docs, bench).count() == docs.count() - len(got)
    assert decontamination.find_leaks(empty, bench).collect() == [] and decontamination.find_leaks(docs, bench.limit(0)).collect() == []


def test_widespread_leak(spark):
    rng = random.Random(8)
    words = [f"t{i}" for i in range(3000)]
    text = lambda n: " ".join(rng.choice(words) for _ in range(n))
    items = [(1, "which of the old rivers runs north past seven mills. the grey one does."), (2, "name a metal that stays liquid in a cold cellar. quicksilver stays.")]
    bench = spark.createDataFrame(items, "item_id bigint, text string")

    def leaks(rows):
        return sorted((r["doc_id"], r["item_id"]) for r in decontamination.find_leaks(spark.createDataFrame(rows, "doc_id bigint, text string"), bench).collect())

    rows = [(i, f"{text(60)} {items[0][1]} {text(60)}" if i % 3 == 0 else text(150)) for i in range(90)]
    assert leaks(rows) == [(i, 1) for i in range(0, 90, 3)]
    for n in range(1, 5):
        assert leaks([(0, f"{text(30)} {items[1][1]}"), *[(i, text(50)) for i in range(1, n)]]) == [(0, 2)]
    assert leaks([(i, items[i // 4][1]) for i in range(8)]) == [(i, i // 4 + 1) for i in range(8)]


def test_latent_space(spark):
    rng = random.Random(3)
    sides = [[f"{c}{i}" for i in range(40)] for c in "pqr"]
    rows = [(i, " ".join(rng.choice(sides[i % 3]) for _ in range(100))) for i in range(120)]
    bodies = decontamination.bodies_of(spark.createDataFrame(rows, "doc_id bigint, text string"))
    items = [decontamination._tokens(" ".join(side[:20])) for side in sides]
    others = [decontamination._tokens(" ".join(side[20:])) for side in sides]
    slots = decontamination.Slots(np.unique(np.concatenate(items)))
    n, df, sketch = decontamination.gathered(bodies, slots)
    weight = decontamination.weights_of(n, df)
    v = decontamination.basis(sketch, weight, 3)
    assert n == 120 and v.shape == (len(slots), 3) and np.allclose(v.T @ v, np.eye(3), atol=1e-3)
    a, b = (np.stack([(v * weight[:, None])[slots.of(x)].sum(0) for x in xs]) for xs in (items, others))
    like = (a / np.linalg.norm(a, axis=1, keepdims=True)) @ (b / np.linalg.norm(b, axis=1, keepdims=True)).T
    assert (like.diagonal() > 0.9).all() and (like[~np.eye(3, dtype=bool)] < 0.5).all()  # no word is shared
    # the TF-IDF way out of reach: what is found comes from the latent space
    docs = spark.createDataFrame([*rows, (500, " ".join(sides[1][:20]))], "doc_id bigint, text string")
    bench = spark.createDataFrame([(7, " ".join(sides[1][:20]))], "item_id bigint, text string")
    got = decontamination.find_leaks(docs, bench, cosine=1e6)
    assert [(r["doc_id"], r["item_id"]) for r in got.collect()] == [(500, 7)]


def test_common_subsequence():
    rng = random.Random(0)
    for _ in range(60):
        a, b = ([rng.randrange(5) for _ in range(rng.randrange(1, 30))] for _ in range(2))
        row = [0] * (len(b) + 1)
        for x in a:
            new = [0]
            for j, y in enumerate(b):
                new.append(row[j] + 1 if x == y else max(row[j + 1], new[j]))
            row = new
        assert decontamination.common_length(a, b) == row[-1]


# -- shards ----------------------------------------------------------------------------------------------------------
def test_shards(corpus, empty):
    out = sharding.assign(corpus.select("doc_id", "text"), F.col("doc_id"), shards=5, nodes=8, cells=64).collect()
    by: dict = {}
    for r in out:
        by.setdefault(r["shard"], []).append(r["slot"])
    sizes = [len(v) for v in by.values()]
    assert sum(sizes) == corpus.count() and max(sizes) - min(sizes) <= 1 and all(sorted(v) == list(range(len(v))) for v in by.values())
    assert sharding.assign(empty.select("doc_id", "text"), F.col("doc_id")).collect() == []


def test_ring_moves_little(spark):
    rows = spark.range(4000).withColumnRenamed("id", "doc_id")
    a = {r["doc_id"]: r["shard"] for r in sharding.assign(rows, F.col("doc_id"), shards=8).collect()}
    b = {r["doc_id"]: r["shard"] for r in sharding.assign(rows.where("doc_id < 3960"), F.col("doc_id"), shards=8).collect()}
    assert sum(a[i] != s for i, s in b.items()) < 0.1 * len(b)


def test_ring_grows(spark):
    rows = spark.range(6000).withColumnRenamed("id", "doc_id")
    a = {r["doc_id"]: r["shard"] for r in sharding.assign(rows, F.col("doc_id"), shards=8).collect()}
    b = {r["doc_id"]: r["shard"] for r in sharding.assign(rows, F.col("doc_id"), shards=9).collect()}
    assert sum(a[i] != s for i, s in b.items()) < 0.25 * len(b)  # a ninth has to move
    assert sum(a[i] != s and s != 8 for i, s in b.items()) < 0.1 * len(b)


def test_shards_of_a_hot_key(spark):
    rows = spark.range(900).select(F.when(F.col("id") >= 300, F.col("id")).alias("doc_id"), F.lit("same").alias("a"), (F.col("id") % 2).alias("slot"))
    for piece in (40, 1 << 20):
        out = sharding.assign(rows, F.col("doc_id"), shards=7, nodes=8, cells=64, piece_rows=piece).collect()
        by: dict = {}
        for r in out:
            by.setdefault(r["shard"], []).append(r["slot"])
        assert len(out) == 900 and sum(r["doc_id"] is None for r in out) == 300
        assert max(map(len, by.values())) - min(map(len, by.values())) <= 1 and all(sorted(v) == list(range(len(v))) for v in by.values())


# -- licences --------------------------------------------------------------------------------------------------------
def test_matching_statistics():
    rng = random.Random(5)
    for _ in range(30):
        texts = [[rng.randrange(4) for _ in range(rng.randrange(1, 20))] for _ in range(3)]
        automaton = license_scan.SuffixAutomaton()
        for n, t in enumerate(texts):
            automaton.add(n, t)
        automaton.finish()
        query = [rng.randrange(5) for _ in range(40)]
        parts = {tuple(t[i:j]) for t in texts for i in range(len(t)) for j in range(i + 1, len(t) + 1)}
        for e, (n, state) in enumerate(automaton.statistics(query)):
            assert n == max((m for m in range(1, e + 2) if tuple(query[e + 1 - m : e + 1]) in parts), default=0)
            for number, end in automaton.ends[state] if n else ():
                assert texts[number][end + 1 - n : end + 1] == query[e + 1 - n : e + 1]


def test_license_scan(spark, corpus, empty):
    mit = license_scan.TEMPLATES["mit"]
    cut = mit.split()
    rows = [(1, f"x y {mit} z"), (2, " ".join([*cut[:9], "odd", *cut[9:]])), (3, "the MIT-License and the mit license; General public LICENSE"), (4, "permission is not free of this software"), (5, None), (6, "")]
    out = {r["doc_id"]: r for r in license_scan.scan(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    share = lambda i, t: next((c["share"] for c in out[i]["covers"] if c["template"] == t), 0.0)
    assert share(1, "mit") == 1.0 and share(2, "mit") > 0.8 and share(4, "mit") < 0.5
    assert [(c["a"], c["b"]) for c in next(c for c in out[1]["covers"] if c["template"] == "mit")["spans"]] == [(2, 22)]
    assert [(p["label"], p["word"]) for p in out[3]["base_places"]] == [("mit", 1), ("mit", 5), ("gpl", 7)]
    assert out[5]["n_words"] == out[6]["n_words"] == 0
    assert license_scan.scan(corpus).count() == corpus.count() and license_scan.scan(empty).collect() == []


def test_long_template_with_repeated_clauses(spark):
    rng = random.Random(2)
    words = [f"w{i}" for i in range(12)]
    clause = " ".join(rng.choice(words) for _ in range(9))
    template = " ".join(f"{clause} " + " ".join(rng.choice(words) for _ in range(6)) for _ in range(60))
    cut = template.split()
    broken = [w for i, w in enumerate(cut) if i % 37 != 20]
    rows = [(1, f"zz {template} zz"), (2, " ".join(broken)), (3, f"{clause} zz " * 400), (4, f"zz {' '.join(cut[: len(cut) // 3])}")]
    out = {r["doc_id"]: {c["template"]: c["share"] for c in r["covers"]} for r in license_scan.scan(spark.createDataFrame(rows, "doc_id bigint, text string"), {"own": template}).collect()}
    assert out[1]["own"] == 1.0 and out[2]["own"] > 0.85 and abs(out[4]["own"] - 1 / 3) < 0.1
    assert out[3]["own"] <= 60 * 9.5 / len(cut) + 0.05


# -- hosts -----------------------------------------------------------------------------------------------------------
def test_registered_domains(spark):
    hosts = ["a.b.example.org", "example.org", "shop.x.co.uk", "x.co.uk", "co.uk", "me.github.io", "10.0.0.1", "10.0.0.1:80", "h.net:8080", "single", ""]
    df = spark.createDataFrame([(h,) for h in hosts], "host string")
    got = [tuple(r) for r in df.select(*[c.alias(n) for n, c in host_reputation.levels(F.col("host")).items()]).collect()]
    assert got == [("org", "example.org"), ("org", "example.org"), ("co.uk", "x.co.uk"), ("co.uk", "x.co.uk"), ("co.uk", "co.uk"), ("github.io", "me.github.io"), ("", "10.0.0.1"), ("", "10.0.0.1:80"), ("net", "h.net"), ("single", "single"), ("", "")]
    own = host_reputation.levels(F.col("host"), ("b.example.org",))
    assert df.where("host = 'a.b.example.org'").select(own["domain"]).first()[0] == "a.b.example.org"


def test_url_parts_and_rules(spark):
    urls = ["http://A.Example.com/en/x?y", "https://www.example.com/en/", "ftp://m.net/es/1#f", "http://net", "x", None, "http://h.org?q=/en/", "http://sub.com/", "http://notcom/", "http://a.net/fr", "http://EXAMPLE.com/enx", "a://b://c/d"]
    df = spark.createDataFrame([(i, u) for i, u in enumerate(urls)], "page_id bigint, url string")
    labels = spark.createDataFrame([], "doc_id bigint, quality int, toxic int")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in host_reputation.judge(df, labels).collect()}

    def brute(u):
        host = path = ""
        if u and "://" in u:
            rest = u.split("://", 1)[1]
            host = lower(re.match(r"[^/?#]*", rest)[0])
            path = re.match(r"[^?#]*", rest[len(host) :])[0]
        fits = [(h + p, v) for v, h, p in host_reputation.RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
        return host, path, *(max(fits, key=lambda x: len(x[0])) if fits else (None, "allow"))

    assert got == {i: brute(u) for i, u in enumerate(urls)}


def test_reputation_shrinks(spark):
    pages = [(n, f"http://bad.example.org/{n}/") for n in range(60)] + [(n, f"http://good.example.org/{n}/") for n in range(60, 160)] + [(n, f"http://new.bad.example.org/{n}/") for n in range(160, 162)]
    labels = [(n, 0, 1) for n in range(60)] + [(n, 1, 0) for n in range(60, 160)] + [(160, 0, 0)]
    out = host_reputation.judge(spark.createDataFrame(pages, "page_id bigint, url string"), spark.createDataFrame(labels, "doc_id bigint, quality int, toxic int"))
    got = {r["host"]: r for r in out.select("host", "mean", "bound", "verdict").distinct().collect()}
    assert got["bad.example.org"]["verdict"] == "block" and got["good.example.org"]["verdict"] == "allow"
    assert got["good.example.org"]["mean"] < got["new.bad.example.org"]["mean"] and got["new.bad.example.org"]["bound"] < got["bad.example.org"]["bound"]
    none = host_reputation.judge(spark.createDataFrame([], "page_id bigint, url string"), spark.createDataFrame(labels, "doc_id bigint, quality int, toxic int"))
    assert none.collect() == []


def test_clashing_columns(corpus):
    names = ["ord", "rid", "body", "row", "had", "key", "n", "sid", "shard", "slot", "_spot", "rank", "kept", "words", "host", "bound"]
    odd = corpus.withColumns({c: F.lit(c) for c in names})
    assert quality_rules.passing(odd).columns == odd.columns
    assert sharding.assign(odd, F.col("doc_id")).count() == odd.count()
    assert license_scan.scan(odd).count() == odd.count() and class_lm.score(odd).count() == odd.count()
    bench = odd.limit(3).select(F.lit(1).alias("item_id"), "text", "ord")
    out = decontamination.clean(odd, bench)
    assert out.columns == odd.columns and 0 < out.count() <= odd.count() and out.where("text is null").count() == corpus.where("text is null").count()
    pages = odd.select(F.col("doc_id").alias("page_id"), F.lit("http://a.org/1").alias("url"), "host", "bound")
    assert host_reputation.judge(pages, odd.select("doc_id", F.lit(1).alias("quality"), F.lit(0).alias("toxic"))).count() == odd.count()


def test_rare_words_join_learnt_classes(spark):
    rng = random.Random(31)
    nouns, verbs = [f"n{i}" for i in range(12)], [f"v{i}" for i in range(12)]
    rare_nouns, rare_verbs = [f"xr{i}q" for i in range(30)], [f"yr{i}q" for i in range(30)]  # all forms end alike
    pick = lambda often, rare: rng.choice(rare) if rng.random() < 0.06 else rng.choice(often)
    rows = [(i, " ".join(f"{pick(nouns, rare_nouns)} {pick(verbs, rare_verbs)} a {pick(nouns, rare_nouns)} ." for _ in range(30))) for i in range(100)]
    model, _ = class_lm.train(class_lm.bodies_of(spark.createDataFrame(rows, "doc_id bigint, text string")), classes=5, passes=6, limit=0.01)
    assert len(model.frequent.words) > 60 and np.allclose((10.0**model.step).sum(1), 1)

    def class_of(words):
        raw = np.frombuffer(" ".join(words).encode(), np.uint8)
        hashes, forms, _ = class_lm.encoded(raw, np.array([0, len(raw)]))
        return Counter(model.of[model.frequent.ids(hashes, forms)][:-1].tolist())

    for often, rare in ((nouns, rare_nouns), (verbs, rare_verbs)):
        seen = class_of(often)
        assert sum(n for c, n in class_of(rare).items() if c in seen) >= 0.8 * len(rare)
    assert not set(class_of(rare_nouns)) & set(class_of(verbs))
