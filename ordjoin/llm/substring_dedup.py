"""Incremental removal of word windows that earlier documents hold, by a log-structured fingerprint index."""

from __future__ import annotations

import json
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ordjoin.llm.common import LAST, Layout, bodies_of, delete, documents_of, first_row, lay_out, lean, settle, shared_folder, table
from ordjoin.llm.windows import PLACE, Unit, contested, contexts_of, find_runs, kept, removed_spans

WINDOW, GRAM, BATCHES = 50, 12, 3
CONTEXT = ["key", "ctx"]


class FingerprintIndex:
    """Sorted immutable runs of the fingerprints of all windows seen so far, and the texts that they stand in.

    A run is a bucketed table sorted by (trigger, context): a new batch is merge-joined with it without shuffling the
    run. ``fanout`` runs are merged to one, which the next batch reads. A fingerprint keeps its first document, so the
    index never loses a smaller id, whichever batch brings it. ``describe`` gives what ``reopen`` needs in a later
    session whose catalog still has the tables.
    """

    def __init__(self, spark: SparkSession, buckets: int = 0, fanout: int = 2) -> None:
        self.spark, self.fanout = spark, fanout
        self.buckets = buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))
        self.runs: list[DataFrame] = []
        self.names: list[str] = []
        self.layouts: list[Layout] = []

    def describe(self) -> str:
        return json.dumps({"buckets": self.buckets, "fanout": self.fanout, "runs": self.names, "layouts": [[x.buckets, x.name, x.path] for x in self.layouts]})

    @classmethod
    def reopen(cls, spark: SparkSession, described: str) -> FingerprintIndex:
        kept_as = json.loads(described)
        index = cls(spark, kept_as["buckets"], kept_as["fanout"])
        index.names = kept_as["runs"]
        index.runs = [spark.table(name) for name in index.names]
        index.layouts = [Layout(spark.table(name), buckets, name, path) for buckets, name, path in kept_as["layouts"]]
        return index

    def write(self, contexts: DataFrame) -> tuple[str, DataFrame]:
        name = f"fingerprints_{uuid.uuid4().hex}"
        rows = contexts.repartition(self.buckets, *CONTEXT).write.format("parquet").option("compression", "zstd")
        with lean(self.spark):
            rows.option("path", f"{shared_folder(self.spark)}/{name}").bucketBy(self.buckets, *CONTEXT).sortBy(*CONTEXT).saveAsTable(name)
        return name, self.spark.table(name)

    def merged(self, fresh: DataFrame) -> DataFrame:
        """All fingerprints, with a mark on those of the new batch: a merge join with each run."""
        out = fresh.withColumn("fresh", F.lit(True))
        for run in self.runs:
            old = run.select(*CONTEXT, *[F.col(c).alias(f"old_{c}") for c in (*PLACE, "least", "times")])
            out = out.hint("merge").join(old, CONTEXT, "full").select(
                *CONTEXT,
                *[F.when(F.col("old_times").isNotNull(), F.col(f"old_{c}")).otherwise(F.col(c)).alias(c) for c in PLACE],
                F.least("least", "old_least").alias("least"),
                (F.coalesce("times", F.lit(0)) + F.coalesce("old_times", F.lit(0))).alias("times"),
                F.coalesce("fresh", F.lit(False)).alias("fresh"),
            )
        return out

    def add(self, name: str, run: DataFrame) -> None:
        self.names.append(name)
        self.runs.append(run)
        if len(self.runs) >= self.fanout:
            self.compact()

    def compact(self) -> None:
        """Merge all runs into one new run and drop the old ones."""
        if len(self.runs) < 2:
            return
        first, *self.runs = self.runs
        name, whole = self.write(self.merged(first).drop("fresh"))
        for old in self.names:
            self._drop(old)
        self.names, self.runs = [name], [whole]

    def _drop(self, name: str) -> None:
        self.spark.sql(f"drop table if exists {name}")
        delete(self.spark, f"{shared_folder(self.spark)}/{name}")

    def drop(self, texts: bool = True) -> None:
        """Delete the runs, and with ``texts`` the layouts, which results that are not yet read still need."""
        for name in self.names:
            self._drop(name)
        for layout in self.layouts if texts else ():
            layout.drop()
        self.runs, self.names, self.layouts = [], [], []


def remove_known(batch: DataFrame, index: FingerprintIndex, window: int = WINDOW, gram: int = GRAM, text: bool = False, more: bool = True) -> DataFrame:
    """Remove from each document of ``batch`` the words that a window of a document with a smaller id covers, of this batch
    or of any that ``index`` holds.

    The batch is then added to the index, unless no ``more`` batches follow. Rows: doc_id, n, n_removed, n_spans,
    kept_sha256 (and with ``text`` rest, kept_text). Null or empty texts and texts under one window stay whole; a null
    id stands behind all others; rows with one id don't remove each other's words; other columns are ignored.
    """
    unit = Unit(words=True, window=window, gram=min(gram, window))
    layout = lay_out(bodies_of(batch))
    index.layouts.append(layout)
    runs = settle(find_runs(layout.frame, unit, len(index.layouts) - 1), "runs")
    name, fresh = index.write(contexts_of(runs))
    marked = settle(contested(index.merged(fresh), F.col("fresh")), "marked")
    spans = removed_spans(runs, marked, index.layouts, unit, first_stays=True)
    if more:
        index.add(name, fresh)
    else:
        index._drop(name)
    return kept(layout, spans, unit, text)


def deduplicate(docs: DataFrame, batches: int = BATCHES, window: int = WINDOW, gram: int = GRAM, text: bool = False) -> DataFrame:
    """``remove_known`` over all documents, dealt into batches by ranges of doc_id."""
    spark = docs.sparkSession
    place = F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST))
    bounds = first_row(docs.select(F.percentile_approx("doc_id", [i / batches for i in range(1, batches)], 1000).alias("b")))["b"] if batches > 1 else []
    index, out, low = FingerprintIndex(spark), None, None
    for high in [*sorted(set(bounds or [])), None]:
        now = docs.where(place > low) if low is not None else docs
        now = now.where(place <= high) if high is not None else now
        part = remove_known(now, index, window, gram, text, more=high is not None)
        out, low = part if out is None else out.unionByName(part), high
    index.drop(texts=False)
    return out


def cleaned(docs: DataFrame, batches: int = BATCHES) -> DataFrame:
    """``docs`` with what ``deduplicate`` leaves of each text; n_chars, where there is one, is counted anew.

    Null texts stay null, texts without a word stay as they are, rows that stand twice stay twice; all columns keep
    their names and values.
    """
    return documents_of(deduplicate(docs, batches, text=True), docs, F.col("kept_text"))


def op2_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = deduplicate(table(spark, sf_dir, "documents"))
    return out.select("doc_id", F.col("n").alias("n_words"), "n_removed", "kept_sha256")
