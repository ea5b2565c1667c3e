from __future__ import annotations

import pytest

WORDS = [f"{chr(97 + i % 26)}{chr(97 + i // 26)}or" for i in range(400)]


@pytest.fixture
def corpus(spark):
    """Small texts with copies, near copies, shared passages, empty, null, long and repeated rows."""
    import random

    rng = random.Random(4)

    def text(n):
        return " ".join(rng.choice(WORDS) for _ in range(n))

    passage, page = text(70), text(120)
    near = page.split()
    near[60] = "changed"
    rows = [(i, text(rng.randrange(12, 90)), "en", "src0", 5) for i in range(30)]
    rows += [(100, page, "en", "s", 1), (101, page, "en", "s", 1), (102, " ".join(near), "de", "s", 1), (103, page.upper(), "en", None, None)]
    rows += [(200 + i, f"{text(25)} {passage} {text(20)}", "en", "s", 1) for i in range(4)]
    rows += [(300, None, None, None, None), (301, "", "en", "s", 0), (302, " \n\t ", "en", "s", 0), (303, "one two three", "en", "s", 0), (304, "One two\nthree", "en", "s", 0)]
    rows += [(400, "again " * 900, "en", "s", 1), (401, ("abcdefghij" * 60) + "\n" + "Ünïcode tëxt ", "fr", "s", 1), (402, text(6000), "en", "s", 1)]
    rows += [rows[0], (None, text(60), "en", "s", 1), (None, None, "en", "s", 1)]
    return spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")


@pytest.fixture
def empty(corpus):
    return corpus.limit(0)
