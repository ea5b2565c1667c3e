"""Corpus cleaning: quality rules, near-duplicate join, substring dedup, decontamination, packing."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ordjoin.llm import decontamination, near_duplicates, packing, quality_rules, substring_dedup
from ordjoin.llm.common import alive, discard, settle, sweep, table

_LEFT: set[str] = set()  # tables that the last stage's result read


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that no quality rule rejects. Null and empty texts have too few words and go; rows that stand twice are
    judged alike; other columns, whatever their names, stay as they are."""
    return quality_rules.passing(docs)


def near_duplicate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of five-word shingle sets that a similarity of 0.8 or more links: the least id, of equal
    ids the first row. A null id stands behind all others; texts without words all stay; columns stay as they are."""
    return near_duplicates.one_of_each(docs, width=5, percent=80)


def substrings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document, without the words that a 50-word window of a document with a smaller id covers.

    A null id stands behind all others and rows of one id leave each other alone; null texts stay null, and a text that
    loses nothing keeps its spaces. n_chars is counted anew; other columns stay as they are."""
    return substring_dedup.cleaned(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no benchmark item stands. Null and empty texts stay, items without words match nothing, and equal
    rows are judged alike; columns stay as they are."""
    return decontamination.clean(docs, table(spark, sf_dir, "benchmark"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of token sequences: ids, their checksum and their place. Null and empty texts are one end id; ids may be null
    or repeat; no other column is read. An empty table gives no piece."""
    import public_tokenizers

    return packing.pack(docs, public_tokenizers.path("word_bpe_49k.json")).withColumn("ids_crc32", F.crc32("ids"))


def _in_turn(stage: Callable[[SparkSession, DataFrame, str], DataFrame], first: bool = False) -> Callable[[SparkSession, DataFrame, str], DataFrame]:
    """A stage that first deletes the intermediate tables of the stage before it, whose result has been written by then.
    The first stage deletes nothing, as the last one's result may still be read."""

    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        if not first:
            sweep(_LEFT)
        _LEFT.clear()
        before = alive()
        out = stage(spark, docs, sf_dir)
        _LEFT.update(alive() - before)
        return out

    return run_stage


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality_rules", _in_turn(quality, first=True)),
    ("near_duplicates", _in_turn(near_duplicate)),
    ("substring_dedup", _in_turn(substrings)),
    ("decontamination", _in_turn(decontaminate)),
    ("packing", _in_turn(pack)),
]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in turn; each one's result is written and read again as the next one's documents, and deleted once the
    next one has been written."""
    docs, before = table(spark, sf_dir, "documents"), []
    for name, stage in STAGES[:-1]:
        docs = settle(stage(spark, docs, sf_dir), f"after-{name}")
        discard(*before)
        before = [docs]
    return STAGES[-1][1](spark, docs, sf_dir)
