"""Quality rules as a short-circuit cascade, in DataFrame functions only.

Each rule is a Boolean column that is true for a text to reject. A bounded sample gives every rule's cost and how much
it rejects; rules are then tried in the order of rejections per cost, and a CASE chain stops at the first that fires.
The order changes the work, never the verdict, since a text is kept if no rule fires.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ordjoin.llm.common import table

SPACES = r"[\x20\x09-\x0D]+"
NON_SPACE = r"[^\x20\x09-\x0D]"
SYMBOLS = r"[#*$%&|<>]"
GRAM = 5
MIN_WORDS, MAX_REPEAT_PERCENT = 10, 20
SAMPLE_ROWS = 256


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is computed once, also where ``body`` uses it inside lambdas."""
    return F.transform(F.array(value), body)[0]


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(text, SPACES), "")


def duplicate_lines(text: Column) -> Column:
    """Lines with a word that equal an earlier line."""
    return let(F.filter(F.split(text, "\n"), lambda line: line.rlike(NON_SPACE)), lambda lines: (F.size(lines) - F.size(F.array_distinct(lines))).cast("long"))


def repeated_words(words: Column, gram: int = GRAM) -> Column:
    """Words covered by windows of ``gram`` words that stand twice or more in the text.

    Hashes of all windows settle most texts: no two alike. Where some are, the windows themselves are sorted with
    their places; neighbours that agree are the repeated ones.
    """

    def windows(make: Callable[[Column], Column]) -> Callable[[Column], Column]:
        return lambda w: F.transform(F.sequence(F.lit(0), F.size(w) - gram), make_at(w, make))

    def make_at(w: Column, make: Callable[[Column], Column]) -> Callable[[Column], Column]:
        return lambda i: make(w, i)

    hashed = windows(lambda w, i: F.xxhash64(*[F.get(w, i + j) for j in range(gram)]))
    placed = windows(lambda w, i: F.struct(F.array_join(F.slice(w, i + 1, gram), " ").alias("k"), i.alias("i")))

    def covered(w: Column) -> Column:
        same = let(
            F.array_sort(placed(w)),
            lambda s: F.filter(s, lambda x, i: F.coalesce(x["k"] == F.get(s, i + 1)["k"], F.lit(False)) | (F.when(i > 0, F.coalesce(x["k"] == F.get(s, i - 1)["k"], F.lit(False))).otherwise(False))),
        )
        return let(
            F.array_sort(F.transform(same, lambda x: x["i"])),
            lambda at: F.aggregate(F.transform(at, lambda p, i: F.least(F.lit(gram), F.coalesce(F.get(at, i + 1) - p, F.lit(gram)))), F.lit(0), lambda a, x: a + x),
        )

    return let(words, lambda w: F.when(F.size(w) < gram, 0).otherwise(let(hashed(w), lambda h: F.when(F.size(h) == F.size(F.array_distinct(h)), 0).otherwise(covered(w))))).cast("long")


def expressions(words: Column, text: Column) -> dict[str, Column]:
    return {
        "n_words": F.size(words).cast("long"),
        "word_chars": F.length(F.array_join(words, "")).cast("long"),
        "n_symbols": F.regexp_count(text, F.lit(SYMBOLS)).cast("long"),
        "n_dup_lines": duplicate_lines(text),
        "n_repeat_words": repeated_words(words),
    }


def measures(docs: DataFrame) -> DataFrame:
    """Add n_words, word_chars, n_symbols, n_dup_lines and n_repeat_words; a null text counts as empty."""
    text = F.coalesce(F.col("text"), F.lit(""))
    found = expressions(F.col("_quality_words"), text)
    return docs.withColumn("_quality_words", words_of(text)).select(*[c for c in docs.columns if c not in found], *[v.alias(k) for k, v in found.items()])


@dataclass(frozen=True)
class Rule:
    """``rejects`` is true for a text to reject, null counts as false."""

    name: str
    rejects: Column


def default_rules(of: Callable[[str], Column] = F.col) -> list[Rule]:
    """``of`` gives a measure's column: by its name where it is computed, or its expression over the text."""
    text = F.coalesce(F.col("text"), F.lit(""))
    lines = F.size(F.filter(F.split(text, "\n"), lambda x: x.rlike(NON_SPACE)))
    return [
        Rule("few_words", of("n_words") < MIN_WORDS),
        Rule("repeats", 100 * of("n_repeat_words") > MAX_REPEAT_PERCENT * of("n_words")),
        Rule("symbols", 10 * of("n_symbols") > of("n_words")),
        Rule("word_length", (of("word_chars") < 2 * of("n_words")) | (of("word_chars") > 15 * of("n_words"))),
        Rule("lines_again", 10 * of("n_dup_lines") > 5 * lines),
        Rule("letters", 2 * F.length(F.regexp_replace(text, r"[\P{L}]+", "")) < of("word_chars")),
    ]


def rules_on_text() -> list[Rule]:
    text = F.coalesce(F.col("text"), F.lit(""))
    return default_rules(expressions(words_of(text), text).__getitem__)


def ordered(docs: DataFrame, rules: Sequence[Rule], rows: int = SAMPLE_ROWS) -> list[tuple[Rule, float, float]]:
    """(rule, rejected share, seconds) by rejections per second on at most ``rows`` rows, best first.

    Each rule (over the text) runs on the sample in a job of its own, so its cost holds all that it needs. An empty
    sample keeps the order given.
    """
    sample = docs.limit(rows).cache()
    try:
        n = sample.count()
        if not n:
            return [(r, 0.0, 0.0) for r in rules]
        found = []
        for rule in rules:
            began = time.perf_counter()
            hits = sample.where(rule.rejects).select(F.count(F.lit(1))).first()[0]
            found.append((rule, hits / n, time.perf_counter() - began))
        return sorted(found, key=lambda x: -(x[1] + 1e-6) / max(x[2], 1e-6))
    finally:
        sample.unpersist()


def cascade(rules: Sequence[Rule]) -> Column:
    """Name of the first rule in this order that rejects, or null; later rules aren't evaluated then."""
    out = F.when(F.coalesce(rules[0].rejects, F.lit(False)), F.lit(rules[0].name))
    for r in rules[1:]:
        out = out.when(F.coalesce(r.rejects, F.lit(False)), F.lit(r.name))
    return out


def judge(docs: DataFrame) -> DataFrame:
    """Add the measures, ``rejected_by`` (null: kept) and ``kept``.

    Null and empty texts have no words and go by ``few_words``; repeated rows get equal verdicts; ids may be null;
    columns of the measures' names are replaced, others stay.
    """
    rank = {r.name: i for i, (r, _, _) in enumerate(ordered(docs, rules_on_text()))}
    best = sorted(default_rules(), key=lambda r: rank[r.name])
    return measures(docs).withColumn("rejected_by", cascade(best)).withColumn("kept", F.col("rejected_by").isNull())


def passing(docs: DataFrame) -> DataFrame:
    """The documents that no rule rejects, with their own columns; a rule's measures are computed only where the
    cascade comes to it."""
    out = docs
    for rule, _, _ in ordered(docs, rules_on_text()):
        out = out.where(~F.coalesce(rule.rejects, F.lit(False)))
    return out


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))
    return judge(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"), "kept")


ORACLE = r"""
WITH d AS (
  SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t,
         regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w,
         list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l
  FROM documents
), g AS (
  SELECT r, i, array_to_string(w[i:i + 4], ' ') AS k
  FROM (SELECT r, w, unnest(generate_series(1, len(w) - 4)) AS i FROM d WHERE len(w) >= 5)
), p AS (
  SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, k) AS n FROM g) WHERE n > 1
), c AS (
  SELECT r, sum(least(5, coalesce(nxt - i, 5)))::BIGINT AS n
  FROM (SELECT r, i, lead(i) OVER (PARTITION BY r ORDER BY i) AS nxt FROM p) GROUP BY r
), m AS (
  SELECT doc_id, t, l, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars,
         (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
         (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines, coalesce(c.n, 0)::BIGINT AS n_repeat_words
  FROM d LEFT JOIN c ON d.r = c.r
), b AS (
  SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM m
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT (base_failed OR 10 * n_symbols > n_words OR word_chars < 2 * n_words OR word_chars > 15 * n_words
            OR 10 * n_dup_lines > 5 * len(l) OR 2 * length(regexp_replace(t, '\P{L}+', '', 'g')) < word_chars) AS kept
FROM b
"""
