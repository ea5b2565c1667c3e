"""The registered queries against SQL over the smallest tables, and their columns that SQL doesn't give against plain Python."""

from __future__ import annotations

import hashlib
import math
import os
import re
import zlib
from collections import Counter

import duckdb
import numpy as np
import pyarrow.parquet as pq
import pytest

from ordjoin.llm import decontamination
from ordjoin.llm.host_reputation import RULES
from ordjoin.llm.license_scan import PHRASES
from ordjoin.llm.queries import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"
W = re.compile("[^\x20\x09-\x0d]+")
L = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")

pytestmark = pytest.mark.skipif(not os.path.isdir(SF), reason="no tables here")


def lower(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


@pytest.fixture(scope="module")
def texts():
    return {r["doc_id"]: r["text"] for r in pq.read_table(f"{SF}/documents.parquet").to_pylist()}


def run(spark, number):
    name = next(n for n in QUERIES if n.startswith(f"op{number}_"))
    return QUERIES[name](spark, SF).collect()


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_against_sql(spark, name):
    con = duckdb.connect()
    for f in os.listdir(SF):
        con.sql(f"create view {f.split('.')[0]} as select * from '{SF}/{f}'")
    df, want = QUERIES[name](spark, SF), con.sql(ORACLES[name])
    columns = sorted(df.columns)
    assert columns == sorted(want.columns)
    order = [want.columns.index(c) for c in columns]
    assert sorted((tuple(r[c] for c in columns) for r in df.collect()), key=repr) == sorted((tuple(r[i] for i in order) for r in want.fetchall()), key=repr)


def test_pieces(spark, texts):
    tokenizers = pytest.importorskip("tokenizers")
    path = pytest.importorskip("public_tokenizers").path("word_bpe_49k.json")
    library = tokenizers.Tokenizer.from_file(path)
    whole = {i: np.array([*library.encode(t or "", add_special_tokens=False).ids, 2], "<u4") for i, t in texts.items()}
    rows = run(spark, 4)
    by_doc, by_sequence = {}, {}
    for r in rows:
        ids = whole[r["doc_id"]]
        assert r["doc_tokens"] == len(ids) and r["length"] > 0
        assert r["ids_crc32"] == zlib.crc32(ids[r["start"] : r["start"] + r["length"]].tobytes())
        by_doc.setdefault(r["doc_id"], []).append((r["start"], r["length"]))
        by_sequence.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for i, ids in whole.items():
        at = 0
        for start, length in sorted(by_doc[i]):
            assert start == at
            at += length
        assert at == len(ids)
    for pieces in by_sequence.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= 4096
    assert len(by_sequence) == -(-sum(map(len, whole.values())) // 4096)


def test_scores(spark, texts):
    tokens = {i: [*W.findall(lower(t)), None] for i, t in texts.items()}
    held = {i: zlib.crc32(str(i).encode()) % 10 == 0 for i in texts}
    c = Counter(w for i, t in tokens.items() if not held[i] for w in t)
    n, v = sum(c.values()), len(c)
    rows = run(spark, 5)
    assert len(rows) == len(texts)
    for r in rows:
        t = tokens[r["doc_id"]]
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (held[r["doc_id"]], len(t), sum(c[w] > 0 for w in t), n)
        assert math.isclose(r["base_score"], sum(math.log10((c[w] + 0.1) / (n + 0.1 * (v + 1))) for w in t), rel_tol=1e-9)
        assert r["score"] < 0
    both = [(sum(r[k] for r in rows if r["held_out"]), sum(r["n_tokens"] for r in rows if r["held_out"])) for k in ("score", "base_score")]
    assert both[0][0] > both[1][0]  # the class model is the better one on held-out texts


def test_leaks_against_every_passage(spark):
    docs, bench = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/benchmark.parquet")
    every = {(r["doc_id"], r["item_id"]) for r in decontamination.find_leaks(docs, bench, cosine=-1.0, topic=-1.0).collect()}
    got = {(r["doc_id"], r["item_id"]) for r in run(spark, 6)}
    assert got <= every and len(got) >= 0.9 * len(every) > 0


def test_shards_of_documents(spark, texts):
    rows = run(spark, 7)
    assert len(rows) == len(texts)
    by = {}
    for r in rows:
        body = (texts[r["doc_id"]] or "").encode()
        assert (r["size"], r["text_crc32"], r["law"], r["grown_shard"]) == (len(body) + 1, zlib.crc32(body), "rows", None)
        by.setdefault(r["shard"], []).append(r["slot"])
    assert set(by) == set(range(8)) and max(map(len, by.values())) - min(map(len, by.values())) <= 1
    assert all(sorted(s) == list(range(len(s))) for s in by.values())


def test_licences(spark, texts):
    for r in run(spark, 8):
        w = L.findall(lower(texts[r["doc_id"]]))
        places = [(i, label) for label, phrase in PHRASES.items() for i in range(len(w)) if w[i : i + len(phrase.split())] == phrase.split()]
        assert (r["n_words"], r["n_base"]) == (len(w), len(places))
        assert (r["first_word"], r["last_word"]) == ((min(places)[0], max(places)[0]) if places else (None, None))
        base = sorted({label for _, label in places})
        assert r["base_labels"] == ",".join(base) and set(base) <= set(r["labels"].split(",")) | {""} and 0 <= r["score"] <= 1
        assert r["labels"] == ",".join(sorted(set(r["labels"].split(","))))


def test_hosts(spark):
    urls = {r["page_id"]: r["url"] for r in pq.read_table(f"{SF}/pages.parquet").to_pylist()}
    rows = run(spark, 9)
    assert len(rows) == len(urls)
    for r in rows:
        host = path = ""
        if urls[r["page_id"]] and "://" in urls[r["page_id"]]:
            rest = urls[r["page_id"]].split("://", 1)[1]
            host = re.match(r"[^/?#]*", rest)[0]
            path, host = re.match(r"[^?#]*", rest[len(host) :])[0], lower(host)
        fits = [(h + p, v) for v, h, p in RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
        rule, verdict = max(fits, key=lambda x: len(x[0])) if fits else (None, r["verdict"])
        assert (r["host"], r["path"], r["rule"], r["verdict"]) == (host, path, rule, verdict) and r["verdict"] in ("allow", "block")


def test_rows_of_one_missing_id(spark):
    """Texts without an id whose 32-bit hashes agree are still told apart."""
    from ordjoin.llm import class_lm, near_duplicates, substring_dedup, suffix_dedup

    made = spark.range(160_000).selectExpr("concat_ws(' ', transform(sequence(1, 60), i -> concat('w', xxhash64(id, i)))) as text")
    clash = made.selectExpr("text", "hash(text, 9223372036854775807L) as h").groupBy("h").agg({"text": "collect_list"}).toDF("h", "both").where("size(both) > 1").limit(1).collect()
    a, b = clash[0]["both"][:2]
    docs = spark.createDataFrame([(None, a), (None, b), (None, b), *[(i, f"word{i}") for i in range(5)]], "doc_id bigint, text string")
    missing = lambda df: df.where("doc_id is null").collect()
    sha = lambda t: hashlib.sha256(t.encode()).hexdigest()
    size = len(b.encode())
    assert sorted((r["n_removed"], r["kept_sha256"]) for r in missing(suffix_dedup.remove_repeats(docs))) == [(0, sha(a)), (size, sha("")), (size, sha(""))]
    known = docs.unionByName(spark.createDataFrame([(7, b)], docs.schema))
    assert sorted((r["n_removed"], r["kept_sha256"]) for r in missing(substring_dedup.deduplicate(known))) == [(0, sha(a)), (60, sha("")), (60, sha(""))]
    assert len(missing(near_duplicates.classes(docs))) == 3
    assert sorted(r["text"] for r in missing(near_duplicates.one_of_each(docs))) == sorted([a, b])
    assert [r["n_tokens"] for r in missing(class_lm.score(docs))] == [61] * 3
