from __future__ import annotations

import os
import random
import re
import zlib

import pytest

import __spark_entry__
import corpus_pipeline

SF = "/root/testdata/sf0.001"
W = re.compile("[^\x20\x09-\x0d]+")


def test_registered():
    names = set(__spark_entry__.queries())
    assert "pipeline" in names and all(any(n.startswith(f"op{i}_") for n in names) for i in range(1, 11))
    assert [name for name, _ in corpus_pipeline.STAGES] == ["quality_rules", "near_duplicates", "substring_dedup", "decontamination", "packing"]


@pytest.mark.skipif(not os.path.isdir(SF), reason="no tables here")
def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    before, columns = docs.count(), docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, SF)
        assert docs.columns == columns
        docs = spark.createDataFrame(docs.toArrow(), docs.schema)
        assert 0 < docs.count() <= before, name
        before = docs.count()
    out = corpus_pipeline.STAGES[-1][1](spark, docs, SF)
    assert out.select("doc_id").distinct().count() == before


def test_against_brute_force(spark, corpus, tmp_path):
    """All stages over small texts, each against a plain version of it on what its predecessor kept."""
    import numpy as np

    from ordjoin.llm import quality_rules
    from tests.llm.test_dedup import brute_classes

    tokenizers = pytest.importorskip("tokenizers")
    library = tokenizers.Tokenizer.from_file(pytest.importorskip("public_tokenizers").path("word_bpe_49k.json"))
    rng = random.Random(21)
    words = [f"{a}{b}{c}el" for a in "bdfgkl" for b in "aeiou" for c in "mnprst"]
    text = lambda n: " ".join(rng.choice(words) for _ in range(n))
    items = [(i, f"{text(22)}. {text(7)}.") for i in range(4)]
    passage, page = text(70), text(150)
    extra = [(600 + i, f"{text(80)} {items[i][1]} {text(80)}") for i in range(4)]
    extra += [(700 + i, f"{text(60)} {passage} {text(60)}") for i in range(4)]
    extra += [(800, page), (801, page + " odd"), (802, page.upper()), (803, None), (804, "")]
    rows = extra + [(r["doc_id"], r["text"]) for r in corpus.collect() if r["doc_id"] is None or r["doc_id"] < 300]
    made = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    sf = str(tmp_path)
    made.coalesce(1).write.parquet(f"{sf}/documents.parquet")
    spark.createDataFrame(items, "item_id bigint, text string").coalesce(1).write.parquet(f"{sf}/benchmark.parquet")

    judged = {(r["doc_id"], r["text"]) for r in quality_rules.judge(made).where("kept").select("doc_id", "text").collect()}
    now = [r for r in rows if r in judged]
    want, find = brute_classes(now, 5, 80)
    best: dict = {}
    for i, (d, _) in enumerate(now):
        key = (2**63 if d is None else d, i)
        best[find(i)] = min(best.get(find(i), key), key)
    now = [now[i] for _, i in sorted(best.values())]
    first: dict = {}
    split = [W.findall(t) for _, t in now]
    for (d, _), w in zip(now, split, strict=True):
        for j in range(len(w) - 49):
            first[tuple(w[j : j + 50])] = min(first.get(tuple(w[j : j + 50]), 2**63), 2**63 if d is None else d)
    cleaned = []
    for (d, t), w in zip(now, split, strict=True):
        gone = {x for j in range(len(w) - 49) if first[tuple(w[j : j + 50])] < (2**63 if d is None else d) for x in range(j, j + 50)}
        cleaned.append((d, " ".join(x for j, x in enumerate(w) if j not in gone) if gone else t))
    assert any(a[1] != b[1] for a, b in zip(now, cleaned, strict=True))
    now = [(d, t) for d, t in cleaned if not any(" ".join(W.findall(i)) in " ".join(W.findall(t)) for _, i in items)]
    assert len(now) == len(cleaned) - 4
    want = sorted((repr(d), len(ids := library.encode(t, add_special_tokens=False).ids) + 1, zlib.crc32(np.array([*ids, 2], "<u4").tobytes())) for d, t in now)
    got: dict = {}
    for r in corpus_pipeline.run(spark, sf).orderBy("sequence_id", "offset").collect():
        got.setdefault((repr(r["doc_id"]), r["doc_tokens"]), []).append((r["start"], bytes(r["ids"])))
    assert sorted((d, n, zlib.crc32(b"".join(ids for _, ids in sorted(pieces)))) for (d, n), pieces in got.items()) == want
