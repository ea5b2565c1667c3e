"""Shared folder, lineage cuts, row layouts and Arrow helpers used by the text operators."""

from __future__ import annotations

import tempfile
import uuid
import zipfile
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from dataclasses import dataclass
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Row, SparkSession
from pyspark.sql import functions as F

_OWN: dict[str, str] = {}
_SENT: dict[str, str] = {}
_ALIVE: dict[str, Callable[[], None]] = {}  # intermediate tables that have not been deleted: path -> how to
BATCH_ROWS = 512
LAST = 2**63 - 1  # where a null id stands in the order
MAX_BUCKETS = 100_000  # Spark's own limit for a bucketed table
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_SUBSET_KEYS = "spark.sql.requireAllClusterKeysForCoPartition"


def shared_folder(spark: SparkSession) -> str:
    """Folder that driver and executors share: ``spark.checkpoint.dir``. Where it is unset, one of our own on a single
    machine; on a cluster that is an error, as each executor would write to its own disk."""
    set_to = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not set_to:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        app = spark.sparkContext.applicationId
        if app not in _OWN:
            _OWN[app] = "file://" + tempfile.mkdtemp(prefix="ordjoin-")
        set_to = _OWN[app]
    return set_to.rstrip("/")


@contextmanager
def lean(spark: SparkSession) -> Iterator[None]:
    """Spark deletes the shuffle files of what is run in here as soon as it has ended, not at some later collection."""
    before = spark.conf.get(_CLEANUP, None)
    spark.conf.set(_CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.set(_CLEANUP, before) if before is not None else spark.conf.unset(_CLEANUP)


def first_row(df: DataFrame) -> Row:
    """The first row of a small result; its shuffle files go at once."""
    with lean(df.sparkSession):
        return df.first()


def settle(df: DataFrame, name: str, codec: str = "zstd") -> DataFrame:
    """Write a frame to the shared folder and read it back: a lineage cut that survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    with lean(spark):
        df.write.option("compression", codec).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._settled_at = path
    _ALIVE[path] = lambda: delete(spark, path)
    return out


def delete(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
    _ALIVE.pop(path, None)


def discard(*frames: DataFrame) -> None:
    """Delete settled tables that no unfinished plan reads any more."""
    for df in frames:
        delete(df.sparkSession, df._settled_at)


def alive() -> set[str]:
    """Paths of intermediate tables that still exist. A result that an operator has returned may read some of them."""
    return set(_ALIVE)


def sweep(paths: set[str]) -> None:
    """Delete these tables, once all results that read them have been written or dropped."""
    for path in paths & set(_ALIVE):
        _ALIVE[path]()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _int_hashes(x: np.ndarray) -> np.ndarray:
    """Spark's hash of 32-bit integers (Murmur3, seed 42)."""
    with np.errstate(over="ignore"):
        k = x.astype(np.uint32) * np.uint32(0xCC9E2D51)
        k = (k << np.uint32(15) | k >> np.uint32(17)) * np.uint32(0x1B873593)
        h = np.uint32(42) ^ k
        h = (h << np.uint32(13) | h >> np.uint32(19)) * np.uint32(5) + np.uint32(0xE6546B64)
        h ^= np.uint32(4)
        h = (h ^ h >> np.uint32(16)) * np.uint32(0x85EBCA6B)
        h = (h ^ h >> np.uint32(13)) * np.uint32(0xC2B2AE35)
        return (h ^ h >> np.uint32(16)).astype(np.int32)


def bucket_keys(buckets: int) -> np.ndarray:
    """For each bucket the least non-negative integer that Spark puts into it."""
    keys, at = np.full(buckets, -1, np.int64), 0
    while (keys < 0).any():
        x = np.arange(at, at + 4 * buckets + 64)
        b = _int_hashes(x).astype(np.int64) % buckets
        found, first = np.unique(b, return_index=True)
        new = keys[found] < 0
        keys[found[new]] = x[first[new]]
        at += len(x)
    return keys


@dataclass(frozen=True)
class Layout:
    """Rows written once with a number of their own, so that small tables of row numbers meet them without moving a text.

    ``frame``: slot, row and the columns given. ``row`` is unique whatever ids and texts repeat. Each task of the write
    fills one bucket (``slot`` is chosen so that Spark's hash of it says which), hence nothing is shuffled, and a bucket
    is as large as the input splits that fill it.
    """

    frame: DataFrame
    buckets: int
    name: str
    path: str

    def slot(self, row: Column) -> Column:
        return _slot(F.shiftright(row, 33), self.buckets)

    def meet(self, small: DataFrame, columns: list[str], how: str = "inner") -> DataFrame:
        """``columns`` of the rows, joined on ``row`` with a table of row numbers, which alone is moved (and not even that
        where it has been dealt by a ``slot`` of its own)."""
        numbered = small if "slot" in small.columns else small.withColumn("slot", self.slot(F.col("row")))
        return self.frame.select("slot", "row", *columns).join(numbered.hint("shuffle_hash"), ["slot", "row"], how).drop("slot")

    def gathered(self, small: DataFrame, *lists: Column) -> DataFrame:
        """``small`` grouped by row, dealt as the rows lie."""
        dealt = small.withColumn("slot", self.slot(F.col("row"))).repartition(self.buckets, "slot")
        return dealt.groupBy("slot", "row").agg(*lists).drop("slot")

    def beside(self, rows: DataFrame) -> Layout:
        """Rows made from this layout's (with ``slot`` and ``row``), written to lie as these do."""
        return _written(rows, self.buckets)

    def drop(self) -> None:
        spark = self.frame.sparkSession
        spark.sql(f"drop table if exists {self.name}")
        delete(spark, self.path)


def _slot(task: Column, buckets: int) -> Column:
    keys = F.split(F.lit(",".join(map(str, bucket_keys(buckets).tolist()))), ",").cast("array<int>")
    return F.element_at(keys, (task % buckets).cast("int") + 1)


def lay_out(df: DataFrame) -> Layout:
    """Write ``df`` once, row by row as it lies, with ``slot`` and ``row``.

    Joins with it need ``spark.sql.requireAllClusterKeysForCoPartition`` off in the session: rows are spread by slot, and
    row numbers are compared inside.
    """
    spark = df.sparkSession
    spark.conf.set(_SUBSET_KEYS, "false")
    buckets = max(1, min(df.rdd.getNumPartitions(), MAX_BUCKETS))
    return _written(df.select(_slot(F.spark_partition_id(), buckets).alias("slot"), F.monotonically_increasing_id().alias("row"), "*"), buckets)


def _written(rows: DataFrame, buckets: int) -> Layout:
    spark = rows.sparkSession
    name = f"layout_{uuid.uuid4().hex}"
    path = f"{shared_folder(spark)}/{name}"
    with lean(spark):
        rows.write.format("parquet").option("compression", "zstd").option("path", path).bucketBy(buckets, "slot").saveAsTable(name)
    out = Layout(spark.table(name), buckets, name, path)
    _ALIVE[path] = out.drop
    return out


def bodies_of(docs: DataFrame) -> DataFrame:
    """(doc_id, ord, body, had, rest): the id's place in the order, the text's bytes, whether there is a text, and the
    other columns."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rest = [F.col(f"`{c}`") for c in docs.columns if c not in ("doc_id", "text")] or [F.lit(0).alias("none")]
    doc_id = F.col("doc_id").cast("long")
    return docs.select(doc_id.alias("doc_id"), F.coalesce(doc_id, F.lit(LAST)).alias("ord"), text.cast("binary").alias("body"), F.col("text").isNotNull().alias("had"), F.struct(*rest).alias("rest"))


def documents_of(bodies: DataFrame, like: DataFrame, text: Column | None = None) -> DataFrame:
    """Rows of ``bodies_of`` as rows of ``like``, with another text where one is given; n_chars is counted anew then."""
    types = dict(like.dtypes)
    made = {"doc_id": F.col("doc_id").cast(types["doc_id"]), "text": F.when(F.col("had"), F.col("body").cast("string")) if text is None else text}
    if text is not None and "n_chars" in types:
        made["n_chars"] = F.length(text).cast(types["n_chars"])
    return bodies.select(*[(made[c] if c in made else F.col(f"rest.`{c}`")).alias(c) for c in like.columns])


def column_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a binary Arrow column without nulls, and the offsets of its values in them."""
    if pa.types.is_large_binary(column.type) or pa.types.is_string(column.type):
        column = column.cast(pa.binary())
    _, offsets, data = column.buffers()
    ends = np.frombuffer(offsets, dtype=np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None else np.empty(0, np.uint8)
    return raw, ends


def slices(column: pa.Array, budget: int) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets) for consecutive rows of about ``budget`` bytes; a longer value stands alone."""
    raw, ends = column_bytes(column)
    a, n = 0, len(column)
    while a < n:
        b = max(a + 1, int(np.searchsorted(ends, ends[a] + budget, side="right")) - 1)
        b = min(b, n)
        yield a, b, raw[ends[a] : ends[b]], ends[a : b + 1] - ends[a]
        a = b


def whole_groups(batches: Iterator[pa.RecordBatch], keys: int, least: int = 1) -> Iterator[pa.Table]:
    """Rows that are sorted by their first ``keys`` columns as tables of whole groups, of ``least`` rows or more each (but
    for the last)."""
    held: list[pa.RecordBatch] = []
    rows = 0
    for batch in batches:
        if not batch.num_rows:
            continue
        columns = [batch.column(k).to_numpy() for k in range(keys)]
        edge = np.flatnonzero(np.any([np.diff(c) != 0 for c in columns], axis=0)) + 1
        if held and any(held[-1].column(k)[held[-1].num_rows - 1].as_py() != columns[k][0] for k in range(keys)):
            edge = np.concatenate([[0], edge])
        start = 0
        for x in edge.tolist():
            if rows + x - start >= least:
                if x > start:
                    held.append(batch.slice(start, x - start))
                yield pa.Table.from_batches(held).combine_chunks()
                held, rows, start = [], 0, x
        held.append(batch.slice(start))
        rows += batch.num_rows - start
    if rows:
        yield pa.Table.from_batches(held).combine_chunks()


def ship(spark: SparkSession) -> None:
    """Send this package to the executors once per application, so that their Python workers can import it."""
    app = spark.sparkContext.applicationId
    if _SENT.get("app") == app:
        return
    package = Path(__file__).resolve().parents[1]
    archive = Path(tempfile.mkdtemp(prefix="ordjoin-code-")) / f"{package.name}.zip"
    with zipfile.ZipFile(archive, "w") as z:
        for f in sorted(package.rglob("*.py")):
            z.write(f, f.relative_to(package.parent))
    spark.sparkContext.addPyFile(str(archive))
    _SENT["app"] = app


def map_arrow(df: DataFrame, each: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """``mapInArrow`` with small batches, so that a worker holds few texts at once, however long they are."""
    ship(df.sparkSession)
    df.sparkSession.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS)
    return df.mapInArrow(each, schema)
