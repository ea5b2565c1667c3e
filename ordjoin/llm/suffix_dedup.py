"""Removal of repeated byte strings by a prefix-free parse of the corpus.

Triggers (the 32-byte string with the least rolling hash in some window) cut each text into phrases. The dictionary is
the set of distinct phrases with what surrounds them up to one window; the parse is the sequence of its entries.
Entries that stand twice repeat as a whole. Entries that share a trigger are ordered by suffix arrays of the dictionary
(backwards from the trigger) and of the parse (forwards from it), and the two orders together name each 200-byte string
at stake (see ``windows``). Entries that share nothing can't repeat and are not ordered.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ordjoin.llm.common import bodies_of, discard, lay_out, settle, table
from ordjoin.llm.windows import Unit, contested, contexts_of, find_runs, kept, removed_spans

WINDOW, TRIGGER = 200, 32


def remove_repeats(docs: DataFrame, window: int = WINDOW, trigger: int = TRIGGER, text: bool = False) -> DataFrame:
    """Remove each byte covered by a ``window``-byte string that also starts anywhere else in ``docs``.

    Rows of the result: doc_id, n, n_removed, n_spans, kept_sha256 (with ``text`` also rest and kept_text). Null and empty
    texts have no bytes and stay as they are; a null doc_id is an id like any other here; equal rows are two places and
    lose their text. Other columns are ignored, whatever their names. A long text is hashed in stretches; it needs a few
    times its own size in a task's memory.
    """
    unit = Unit(words=False, window=window, gram=min(trigger, window))
    layout = lay_out(bodies_of(docs))
    runs = settle(find_runs(layout.frame, unit), "phrases")
    # entries that may repeat, by their hashes alone; then only their own occurrences, with places
    entries = runs.groupBy("key", "ctx").agg(F.count(F.lit(1)).alias("times"))
    entries = settle(contested(entries, F.lit(True)), "entries")
    parse = settle(runs.join(entries, ["key", "ctx"]), "parse")
    discard(runs, entries)
    marked = settle(contexts_of(parse, F.first("shared").alias("shared")), "dictionary")
    spans = removed_spans(parse, marked, [layout], unit, first_stays=False)
    return kept(layout, spans, unit, text)


def op3_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = remove_repeats(table(spark, sf_dir, "documents"))
    return out.select("doc_id", F.col("n").alias("n_bytes"), "n_removed", "n_spans", "kept_sha256")
