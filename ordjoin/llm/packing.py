"""Packing by concatenation and cutting: global token offsets from two passes, then fixed windows.

Pass one tokenises, with a running total inside each partition, and writes ids to the shared folder. The totals of the
partitions (one number each) give every partition's global offset by a prefix sum; pass two adds it and cuts each
document at window borders, into one record per piece.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ordjoin.llm.common import map_arrow, settle, table

WINDOW, END_ID = 4096, 2
#: fixed values: how the public word-end vocabulary splits normalised text
PIECES = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
_PLAIN = re.compile("[^\x00-\x1b\x20-ɏ]|<\\|")
_MEMO = 1_000_000
MAX_LISTED_PARTITIONS = 2_000_000


def _is_plain(t: str) -> bool:
    if t.isascii():
        return not ("<|" in t or "\x1c" in t or "\x1d" in t or "\x1e" in t or "\x1f" in t)
    return _PLAIN.search(t) is None


class _Memo(dict):
    """Ids by word, in two generations. A word that neither has gets an empty bytearray, noted in ``new``, which is filled
    after the look-up: so a word is looked up once, also where it is met first."""

    __slots__ = ("new", "old")

    def __init__(self, old: dict[str, bytes] | None = None) -> None:
        super().__init__()
        self.old, self.new = old or {}, {}

    def __missing__(self, w: str) -> bytes | bytearray:
        found = self.old.get(w)
        if found is None:
            found = self.new[w] = bytearray()
        self[w] = found
        return found


class WordTokenizer:
    """The tokenizers file's ids, with a memo by word.

    The memo is used where normalisation and splitting are the same in Python: texts of characters below U+0250 without
    control separators or special-token strings. Any other text goes through the library as a whole. Nothing crosses
    white space, so a text's ids are those of its words in turn. A new word is split into pieces (most are letters
    alone, or with a mark behind), and pieces that are new are encoded together, parted by spaces. A memo that is half
    full becomes the old generation, from which words are taken over when they are met again.
    """

    def __init__(self, path: str) -> None:
        import os

        import regex
        from tokenizers import Tokenizer

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        self.model, self.split = Tokenizer.from_file(path), regex.compile(PIECES).findall
        self.memo = _Memo()

    def _learn_pieces(self, order: list[str]) -> None:
        found = self.model.encode(" ".join(order), add_special_tokens=False)
        ids, at = np.array(found.ids, "<u4"), np.array([-1 if w is None else w for w in found.word_ids], np.int64)
        bounds = np.searchsorted(at, np.arange(len(order) + 1))
        if not len(at) or at[-1] != len(order) - 1 or (np.diff(bounds) == 0).any():
            for w in order:
                self.memo[w] = np.array(self.model.encode(w, add_special_tokens=False).ids, "<u4").tobytes()
            return
        raw = ids.tobytes()
        cuts = (bounds * 4).tolist()
        self.memo.update((w, raw[x:y]) for w, x, y in zip(order, cuts, cuts[1:], strict=False))

    def _learn(self) -> None:
        """Fill in the words that the last look-up has noted."""
        memo, new, unknown, composed = self.memo, self.memo.new, set(), []
        have = memo.get
        for w in new:
            if w.isalpha():
                unknown.add(w)
                continue
            if w[-1] in ".,;:!?" and w[:-1].isalpha():
                parts = (w[:-1], w[-1])
            else:
                parts = self.split(w)
            composed.append((w, parts))
            unknown.update(p for p in parts if type(have(p)) is not bytes)
        if unknown:
            self._learn_pieces(list(unknown))
        get = memo.__getitem__
        whole = [b"".join(map(get, parts)) for _, parts in composed]
        memo.update(zip((w for w, _ in composed), whole, strict=True))
        for w, slot in new.items():
            slot += memo[w]
        memo.new = {}

    def encode(self, texts: list[str]) -> list[bytes]:
        """Little-endian 32-bit ids of each text."""
        if len(self.memo) > _MEMO // 2:
            self.memo = _Memo(dict(self.memo))
        get = self.memo.__getitem__
        try:
            found = [list(map(get, t.lower().split())) if _is_plain(t) else None for t in texts]
            if self.memo.new:
                self._learn()
        except BaseException:
            self.memo = _Memo()  # no half-filled word may stay
            raise
        join = b"".join
        return [join(ids) if ids is not None else np.array(self.model.encode(t, add_special_tokens=False).ids, "<u4").tobytes() for t, ids in zip(texts, found, strict=True)]


_TOKENIZERS: dict[str, WordTokenizer] = {}


def tokenizer_of(path: str) -> WordTokenizer:
    """One tokenizer a process: its memos serve all tasks of a worker."""
    if path not in _TOKENIZERS:
        _TOKENIZERS[path] = WordTokenizer(path)
    return _TOKENIZERS[path]


def tokenized(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, part, at, n, ids): ids with the end id as bytes; ``at``: tokens before it in its partition. Settled."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        end = END_ID.to_bytes(4, "little")
        encoder, part, at = tokenizer_of(path), TaskContext.get().partitionId(), 0
        for batch in batches:
            for x in range(0, batch.num_rows, 512):
                rows = batch.slice(x, 512)
                ids = [i + end for i in encoder.encode(["" if t is None else t for t in rows.column(1).to_pylist()])]
                sizes = [len(i) // 4 for i in ids]
                starts = [at, *accumulate(sizes, initial=at)][1:-1] if sizes else []
                at += sum(sizes)
                yield pa.RecordBatch.from_arrays(
                    [rows.column(0), pa.array([part] * len(ids), pa.int64()), pa.array(starts, pa.int64()), pa.array(sizes, pa.int64()), pa.array(ids, pa.binary())], names=["doc_id", "part", "at", "n", "ids"]
                )

    return settle(map_arrow(docs.select(F.col("doc_id").cast("long"), "text"), each, "doc_id long, part long, at long, n long, ids binary"), "tokens")


def pack(docs: DataFrame, tokenizer_path: str, window: int = WINDOW) -> DataFrame:
    """One row per piece: doc_id, start, length, ids (binary), doc_tokens, sequence_id, offset.

    Sequences are full windows, but for the last. Null and empty texts hold the end id alone; repeated rows and null
    ids are packed like others; an empty table gives no piece.
    """
    ids = tokenized(docs, tokenizer_path)
    totals = ids.groupBy("part").agg(F.sum("n").alias("total"))
    if ids.select("part").distinct().count() > MAX_LISTED_PARTITIONS:
        raise ValueError("too many partitions for one list of totals; coalesce the input")
    before = totals.select("part", F.coalesce(F.sum("total").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))  # one row a partition
    rows = ids.join(F.broadcast(before), "part").withColumn("first", F.col("before") + F.col("at"))
    pieces = rows.withColumn("sequence_id", F.explode(F.expr(f"sequence(first div {window}, (first + n - 1) div {window})")))
    begin = F.greatest(F.col("first"), F.col("sequence_id") * window)
    stop = F.least(F.col("first") + F.col("n"), (F.col("sequence_id") + 1) * window)
    return pieces.select(
        "doc_id",
        (begin - F.col("first")).alias("start"),
        (stop - begin).alias("length"),
        F.substring("ids", ((begin - F.col("first")) * 4 + 1).cast("int"), ((stop - begin) * 4).cast("int")).alias("ids"),
        F.col("n").alias("doc_tokens"),
        F.col("sequence_id").cast("long").alias("sequence_id"),
        (begin - F.col("sequence_id") * window).alias("offset"),
    )


def op4_concat_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    out = pack(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
    return out.withColumn("ids_crc32", F.crc32("ids")).drop("ids")
