"""Benchmark decontamination by latent semantic retrieval, checked by common subsequences.

Documents are cut into overlapping passages. Words of the benchmark's items are counted and weighted each on its own;
no word has weight 0, however common. One pass over all documents counts words and adds every block into a small
random sketch, whose leading singular vectors, once weighted, span the latent space of a randomised SVD; items have no
part in it and are projected like passages. Every passage of every document is compared with every item by cosine in
that space and by the product of TF-IDF vectors (passages whose words, each at its best item, can't reach the limit are
skipped there, which loses nothing); candidates of either are checked on the words around the passage: the heaviest
common subsequence with the item, and how much of the item's answer (its last sentence) is there in order.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ordjoin.llm import kernels as K
from ordjoin.llm.common import bodies_of, documents_of, lean, map_arrow, slices, table
from ordjoin.llm.license_scan import tokens_of

DIMS, BLOCK = 1 << 15, 20
TOPICS, SKETCH = 32, 48
COSINE, TOPIC, LCS, ANSWER = 0.3, 0.9, 0.6, 0.5
ITEMS_AT_ONCE = 512
_SENTENCE = re.compile(r"(?<=[.!?])\s+")


@dataclass
class Slots:
    """Place of each word among the dimensions: words of the items have one of their own, all others share DIMS by hash."""

    words: np.ndarray  # sorted hashes of the items' words

    def __len__(self) -> int:
        return DIMS + len(self.words)

    def of(self, tokens: np.ndarray) -> np.ndarray:
        shared = (tokens >> np.uint64(20)).astype(np.int64) % DIMS
        if not len(self.words):
            return shared
        at = np.minimum(np.searchsorted(self.words, tokens), len(self.words) - 1)
        return np.where(self.words[at] == tokens, DIMS + at, shared)


def gathered(bodies: DataFrame, slots: Slots) -> tuple[int, np.ndarray, np.ndarray]:
    """Number of documents with a word; for each slot in how many of them it stands, and its row of the sketch.

    The sketch is of all blocks of all documents: each block, at unit length in word counts, is added to one of SKETCH
    columns with a sign, both drawn by its task and its number there. It is linear, so weights can follow once they are
    known.
    """
    size = len(slots)

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, sketch = np.zeros(size + 1, np.int64), np.zeros((size + 1) * SKETCH, np.float32)
        number = TaskContext.get().partitionId() << 40
        for batch in batches:
            for _, _, raw, ends in slices(batch.column(0), 1 << 18):
                tokens, first = tokens_of(raw, ends)
                doc = np.repeat(np.arange(len(first) - 1), np.diff(first))
                slot = slots.of(tokens)
                total[:size] += np.bincount(np.unique(doc * size + slot) % size, minlength=size)
                total[size] += int((np.diff(first) > 0).sum())
                block, owner, _ = blocks_of(first)
                drawn = K.mixed(np.arange(number, number + len(owner)).astype(np.uint64))
                number += len(owner)
                value = np.where(drawn >> np.uint64(63), 1, -1) / np.sqrt(np.maximum(np.bincount(block, minlength=len(owner)), 1))
                np.add.at(sketch, slot * SKETCH + (drawn % np.uint64(SKETCH)).astype(np.int64)[block], value.astype(np.float32)[block])
        at = np.flatnonzero(total)
        yield _rows_of(at, total, sketch.reshape(-1, SKETCH).astype(np.float16))

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, sketch = np.zeros(size + 1, np.int64), np.zeros((size + 1, SKETCH), np.float32)
        for batch in batches:
            dim = batch.column(0).to_numpy()
            np.add.at(total, dim, batch.column(1).to_numpy())
            np.add.at(sketch, dim, _matrix(batch.column(2), np.float16))
        yield _rows_of(np.flatnonzero(total), total, sketch)

    parts = map_arrow(bodies.select("body"), each, "dim long, n long, row binary")
    with lean(bodies.sparkSession):
        got = map_arrow(parts.repartition("dim"), add, "dim long, n long, row binary").toArrow()  # at most a row of SKETCH numbers a slot
    out, sketch = np.zeros(size + 1, np.int64), np.zeros((size + 1, SKETCH), np.float32)
    dim = got.column("dim").to_numpy()
    out[dim] = got.column("n").to_numpy()
    sketch[dim] = _matrix(got.column("row"), np.float32)
    return int(out[size]), out[:size], sketch[:size]


def _rows_of(at: np.ndarray, total: np.ndarray, rows: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at]), pa.array([rows[i].tobytes() for i in at.tolist()], pa.binary())], names=["dim", "n", "row"])


def _matrix(rows: pa.Array, kind: type) -> np.ndarray:
    return np.frombuffer(b"".join(rows.to_pylist()), kind).reshape(-1, SKETCH)


def basis(sketch: np.ndarray, weight: np.ndarray, topics: int = TOPICS) -> np.ndarray:
    """slots x (at most ``topics``): leading right singular vectors of the documents' weighted blocks, from their sketch
    of more columns. Items have no part in it."""
    rows = sketch * weight[:, None]
    values, vectors = np.linalg.eigh((rows.T @ rows).astype(np.float64))
    keep = np.argsort(-values)[:topics]
    keep = keep[values[keep] > 1e-6 * max(values.max(), 1e-9)]
    return (rows @ (vectors[:, keep] / np.sqrt(values[keep]))).astype(np.float32)


def weights_of(n: int, df: np.ndarray) -> np.ndarray:
    """Smoothed inverse document frequencies: at least log 2, also for a word of every document."""
    return np.log(1 + max(n, 1) / np.maximum(df, 1)).astype(np.float32)


def blocks_of(first: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(block of each word; document of each block; its place there): blocks of BLOCK words."""
    per = -(-np.diff(first) // BLOCK)
    base = np.cumsum(per) - per
    doc = np.repeat(np.arange(len(first) - 1), np.diff(first))
    owner = np.repeat(np.arange(len(first) - 1), per)
    return base[doc] + (np.arange(int(first[-1])) - first[doc]) // BLOCK, owner, np.arange(len(owner)) - base[owner]


def stretches(owner: np.ndarray, place: np.ndarray, wide: int) -> tuple[np.ndarray, np.ndarray]:
    """(stretch of each block; document of each stretch): stretches of ``wide`` blocks."""
    head = place % wide == 0
    return np.cumsum(head) - 1, owner[head]


def _pairs_of_blocks(sums: np.ndarray, squares: np.ndarray, owner: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Passages of two blocks each (the last block of a document stands alone)."""
    out, norm = sums.copy(), squares.copy()
    joined = np.flatnonzero(owner[1:] == owner[:-1])
    out[joined] += sums[joined + 1]
    norm[joined] += squares[joined + 1]
    return out, norm


def _block_sums(values: np.ndarray, block: np.ndarray, n: int) -> np.ndarray:
    out = np.zeros((n, values.shape[1]), np.float32)
    if len(block):
        cuts = np.flatnonzero(np.diff(block, prepend=-1))
        out[block[cuts]] = np.add.reduceat(values, cuts, axis=0)
    return out


def common_length(a: list[int], b: list[int]) -> int:
    """Length of the longest common subsequence, in bit-parallel steps over ``b``."""
    where: dict[int, int] = {}
    for i, x in enumerate(a):
        where[x] = where.get(x, 0) | 1 << i
    full = (1 << len(a)) - 1
    row = full
    for x in b:
        hit = row & where.get(x, 0)
        row = ((row + hit) | (row - hit)) & full
    return len(a) - row.bit_count()


class Sequence:
    """An item's words (or its answer's) in order, for weighted common subsequences."""

    def __init__(self, slot: np.ndarray, weight: np.ndarray) -> None:
        self.slot = slot
        self.distinct, place = np.unique(slot, return_inverse=True)
        self.of_word = np.zeros((len(self.distinct), len(slot)), np.float32)
        self.of_word[place, np.arange(len(slot))] = weight[slot]
        self.by_word = self.of_word.sum(1)
        self.total = float(self.by_word.sum())

    def share(self, around: np.ndarray, least: float) -> float:
        """Weight of the heaviest common subsequence with ``around`` by the own weight; 0 where it can't reach ``least``."""
        at = np.minimum(np.searchsorted(self.distinct, around), len(self.distinct) - 1)
        at = at[self.distinct[at] == around]
        if self.by_word[np.unique(at)].sum() < 0.999 * least * self.total:
            return 0.0
        row = np.zeros(len(self.slot) + 1, np.float32)
        for x in at.tolist():
            row[1:] = np.maximum.accumulate(np.maximum(row[1:], row[:-1] + self.of_word[x]))
        return min(1.0, float(row[-1]) / self.total)


def _tokens(text: str) -> np.ndarray:
    raw = np.frombuffer(text.encode(), np.uint8)
    return tokens_of(raw, np.array([0, len(raw)]))[0]


def _item_rows(words: list[np.ndarray], slots: Slots, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """TF-IDF rows of unit length over the items' own slots, and the length of each before."""
    rows = np.zeros((len(words), len(slots.words)), np.float32)
    for i, own in enumerate(words):
        np.add.at(rows[i], slots.of(own) - DIMS, weight[slots.of(own)])
    length = np.linalg.norm(rows, axis=1)
    return rows / length[:, None], length


LIMITS = (COSINE, TOPIC, LCS, ANSWER)
_LEAK = "doc_id long, item_id long, cosine double, lcs double, answer double"


def _searches(bodies: DataFrame, benchmark: DataFrame, limits: tuple) -> Iterator[Callable]:
    """A search over batches of texts for each block of items: it gives (place in the batch, item, cosine, lcs, answer)."""
    total = benchmark.count()
    blocks = max(1, -(-total // ITEMS_AT_ONCE))
    for k in range(blocks):
        some = benchmark.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == k).select(F.col("item_id").cast("long"), F.coalesce("text", F.lit("")).alias("text")).orderBy("item_id", "text")
        with lean(bodies.sparkSession):
            some = some.toArrow()
        texts = [(i, t, w) for i, t in zip(some.column("item_id").to_pylist(), some.column("text").to_pylist(), strict=True) if len(w := _tokens(t))]
        if not texts:
            continue
        words = [w for _, _, w in texts]
        slots = Slots(np.unique(np.concatenate(words)))
        n, df, sketch = gathered(bodies, slots)
        weight = weights_of(n, df)
        answers = [[p for p in map(_tokens, _SENTENCE.split(t)) if len(p)][-1] for _, t, _ in texts]
        yield _search(slots, weight, basis(sketch, weight), [i for i, _, _ in texts], words, answers, limits)


def find_leaks(docs: DataFrame, benchmark: DataFrame, cosine: float = COSINE, lcs: float = LCS, answer: float = ANSWER, topic: float = TOPIC) -> DataFrame:
    """(doc_id, item_id, cosine, lcs, answer): benchmark items that stand in a document, also reworded in part.

    A passage is a candidate by its TF-IDF product (``cosine``) or its cosine in the latent space (``topic``).
    ``lcs`` and ``answer`` are shares of the weight of the item's words found in order near the passage; a pair is a
    leak if both reach their limits. Items without a word, null or empty texts on either side give nothing; repeated
    rows give their rows again; a null doc_id stays null. A large benchmark is searched in blocks of items.
    """
    bodies = bodies_of(docs).select("doc_id", "body")
    out = docs.sparkSession.createDataFrame([], _LEAK)
    for search in _searches(bodies, benchmark, (cosine, topic, lcs, answer)):
        out = out.unionByName(map_arrow(bodies, _reporting(search), _LEAK))
    return out


def _reporting(search: Callable) -> Callable:
    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        find = search()
        for batch in batches:
            doc_ids = batch.column(0).to_pylist()
            hits = [(doc_ids[p], *hit) for p, *hit in find(batch.column(1))]
            columns = list(zip(*hits, strict=True)) if hits else [()] * 5
            types = (pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.float64())
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(columns, types, strict=True)], names=[x.split()[0] for x in _LEAK.split(", ")])

    return each


def _sparing(search: Callable) -> Callable:
    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        find = search()
        for batch in batches:
            clean = np.ones(batch.num_rows, bool)
            clean[[p for p, *_ in find(batch.column(1))]] = False
            yield batch.filter(pa.array(clean))

    return each


def _search(slots: Slots, weight: np.ndarray, v: np.ndarray, ids: list, words: list, answers: list, limits: tuple) -> Callable:
    rows, heavy = _item_rows(words, slots, weight)
    gain = rows.T * weight[DIMS:, None]  # what a word adds to the product with each item
    best, best_share = gain.max(axis=1), (gain / heavy).max(axis=1)
    latent = rows @ v[DIMS:]
    latent = (latent / np.maximum(np.linalg.norm(latent, axis=1, keepdims=True), 1e-9)).T
    turn = np.concatenate([v * weight[:, None], np.zeros((1, v.shape[1]), np.float32)])  # what a word adds to a passage's place in the latent space
    part_of = np.ascontiguousarray((rows / rows.sum(axis=1, keepdims=True)).T)  # what a word is of each item's weight
    wide = -(-(2 * max(map(len, words)) + 3 * BLOCK) // BLOCK)  # blocks: what is read around a passage reaches no further
    del rows, v

    def search() -> Callable:
        cosine, topic, lcs, answer = limits
        items, said_by = [Sequence(slots.of(w), weight) for w in words], [Sequence(slots.of(w), weight) for w in answers]

        def find(texts: pa.Array) -> list[tuple]:
            hits: list[tuple] = []
            for a, _, raw, ends in slices(texts, 1 << 18):
                tokens, first = tokens_of(raw, ends)
                if not len(tokens):
                    continue
                slot = slots.of(tokens)
                w = weight[slot]
                block, owner, place = blocks_of(first)
                n = len(owner)
                at = np.flatnonzero(slot >= DIMS)
                own = slot[at] - DIMS
                most, share = (np.bincount(block[at], weights=x[own], minlength=n) for x in (best, best_share))
                squares = np.bincount(block, weights=w * w, minlength=n)
                share, _ = _pairs_of_blocks(share, squares, owner)
                most, squares = _pairs_of_blocks(most, squares, owner)
                length = np.sqrt(np.maximum(squares, 1e-9))
                hope = (most >= 0.999 * cosine * length) | (share >= 0.999 * cosine)
                wanted = hope.copy()
                wanted[1:] |= hope[:-1]
                use = wanted[block[at]]
                sums, _ = _pairs_of_blocks(_block_sums(gain[own[use]], block[at][use], n), squares, owner)
                rows_at = np.flatnonzero(hope)
                # the product by the lighter length: a whole item counts among heavier words, a part of it alone as well
                near = sums[rows_at]
                grid = np.full((n, BLOCK), len(slots))  # a row of slots a block; short ones end in a slot of no weight
                grid[block, (np.arange(len(slot)) - np.repeat(first[:-1], np.diff(first))) % BLOCK] = slot
                flat = np.zeros((n, turn.shape[1]), np.float32)
                for column in grid.T:
                    flat += np.take(turn, column, axis=0)
                flat, _ = _pairs_of_blocks(flat, squares, owner)
                close = flat @ latent >= topic * np.maximum(np.linalg.norm(flat, axis=1, keepdims=True), 1e-9)
                close[rows_at] |= near >= cosine * np.minimum(length[rows_at, None], heavy)
                passages, wanted_items = np.nonzero(close)
                if not len(passages):
                    continue
                # words that don't stand in the stretches around can't be in a common subsequence
                stretch, of_doc = stretches(owner, place, wide)
                near_by = np.unique(stretch[passages])
                read = np.unique(np.clip(np.concatenate([near_by - 1, near_by, near_by + 1]), 0, len(of_doc) - 1))
                spot = np.full(len(of_doc), -1)
                spot[read] = np.arange(len(read))
                row = spot[stretch[block[at]]]
                there = np.zeros((len(read), len(best)), np.float32)
                there[row[row >= 0], own[row >= 0]] = 1
                words_near = there[spot[near_by]]
                for step in (-1, 1):
                    beside = np.clip(near_by + step, 0, len(of_doc) - 1)
                    same = of_doc[beside] == of_doc[near_by]
                    words_near[same] = np.maximum(words_near[same], there[spot[beside[same]]])
                enough = words_near @ part_of >= 0.999 * lcs
                use = enough[np.searchsorted(near_by, stretch[passages]), wanted_items]
                found: dict[tuple[int, int], tuple] = {}
                for p, i in zip(passages[use].tolist(), wanted_items[use].tolist(), strict=True):
                    d = int(owner[p])
                    lo = int(first[d]) + int(place[p]) * BLOCK
                    reach = 2 * len(words[i]) + BLOCK
                    around = slot[max(int(first[d]), lo - reach) : min(int(first[d + 1]), lo + 2 * BLOCK + reach)]
                    part = items[i].share(around, lcs)
                    if part < lcs:
                        continue
                    said = said_by[i].share(around, answer)
                    if said >= answer:
                        passage = slot[lo : min(int(first[d + 1]), lo + 2 * BLOCK)]
                        c = float(gain[passage[passage >= DIMS] - DIMS, i].sum() / length[p])
                        found[d, i] = max(found.get((d, i), (0.0, 0.0, 0.0)), (part, said, min(1.0, c)))
                hits += [(a + d, ids[i], c, part, said) for (d, i), (part, said, c) in sorted(found.items())]
            return hits

        return find

    return search


def clean(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """``docs`` without those that hold a benchmark item: rows are read and dropped where they lie, nothing is joined.

    Null and empty texts stay; each of several equal rows is judged alike; an empty benchmark drops nothing; all columns
    keep their names and values.
    """
    bodies = bodies_of(docs).select("doc_id", "body", "had", "rest")
    schema = f"doc_id long, body binary, had boolean, rest {dict(bodies.dtypes)['rest']}"
    rest = bodies
    for search in _searches(bodies, benchmark, LIMITS):
        rest = map_arrow(rest, _sparing(search), schema)
    return documents_of(rest, docs)


def op6_latent_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
