"""Brown-style class bigram model: exchange clustering, class transitions and word emissions, smoothed perplexity.

Words are lower-cased and known by a 64-bit hash. Words over a relative frequency (so at most 1 / that many) are the core:
they are clustered by exchange, where each pass counts, in parallel, how often every core word stands before and after
every class, and moves words one by one to the class that raises the likelihood of the class bigrams most. All other
words seen twice or more, up to a bounded list of the most frequent, join the learnt class under which their neighbours
are most likely, in one distributed pass. Words beyond the list, seen once or never, belong to a class by their form (the
last byte), which is known without a lookup.

P(w | v) = P(class(w) | class(v)) * P(w | class(w)). Transitions are counted over all training texts with the final
classes and smoothed by class frequencies; a form class keeps a share for unseen words as large as its words seen once
would have it (one unknown word a class, as the base model has one for all). Counts cover every training text; the
vocabulary stays distributed, and what the list doesn't hold is joined, never broadcast.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ordjoin.llm import kernels as K
from ordjoin.llm.common import LAST, bodies_of, discard, first_row, lean, map_arrow, settle, slices, table, whole_groups

CLASSES, FORMS, PASSES = 48, 32, 4
FREQUENT = 5e-5  # relative frequency from which words are clustered by exchange
LISTED = 500_000  # words, the most frequent first, that have a learnt class
END = 0x1F3D5B79A2C4E6F8  # the end's place among word hashes
ALPHA = 0.1


def encoded(raw: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word hashes with an end after each text, form of each (end: -1), and offsets of texts."""
    low = K.LOWER[raw]
    starts, stops, first = K.word_spans(low, ends)
    n = len(ends) - 1
    words = K.word_hashes(low, starts, stops)
    hashes, forms = np.full(len(words) + n, END, np.uint64), np.full(len(words) + n, -1, np.int64)
    at = np.arange(len(words)) + np.repeat(np.arange(n), np.diff(first))
    hashes[at] = words
    forms[at] = low[stops - 1] % FORMS if len(words) else 0
    return hashes, forms, first + np.arange(n + 1)


def vocabulary(bodies: DataFrame) -> DataFrame:
    """(word, form, c): counts of all training tokens."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, _, raw, ends in slices(batch.column(0), 1 << 22):
                hashes, forms, _ = encoded(raw, ends)
                words, at, c = np.unique(hashes, return_index=True, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(K.signed(words)), pa.array(forms[at].astype(np.int32)), pa.array(c)], names=["word", "form", "c"])

    return map_arrow(bodies.select("body"), each, "word long, form int, c long").groupBy("word").agg(F.min("form").alias("form"), F.sum("c").alias("c"))


@dataclass
class Known:
    """Listed words, sorted by hash, and their counts; ids of other words are len + form."""

    words: np.ndarray
    counts: np.ndarray

    def ids(self, hashes: np.ndarray, forms: np.ndarray) -> np.ndarray:
        at = pc.index_in(pa.array(hashes), value_set=pa.array(self.words)).fill_null(-1).to_numpy().astype(np.int64)
        return np.where(at >= 0, at, len(self.words) + forms)


def _pairs(raw: np.ndarray, ends: np.ndarray, known: Known) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ids before, ids, and forms of all tokens; the end also stands before each text."""
    hashes, forms, first = encoded(raw, ends)
    ids = known.ids(hashes, forms)
    before = np.empty_like(ids)
    before[1:] = ids[:-1]
    before[first[:-1]] = int(np.searchsorted(known.words, np.uint64(END)))
    return before, ids, forms


def neighbours(bodies: DataFrame, core: Known) -> DataFrame:
    """(u, v, c): counts of neighbouring ids."""
    size = len(core.words) + FORMS

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, _, raw, ends in slices(batch.column(0), 1 << 22):
                before, ids, _ = _pairs(raw, ends, core)
                pairs, c = np.unique(before * size + ids, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(pairs // size), pa.array(pairs % size), pa.array(c)], names=["u", "v", "c"])

    return map_arrow(bodies.select("body"), each, "u long, v long, c long").groupBy("u", "v").agg(F.sum("c").alias("c"))


def joined_classes(bodies: DataFrame, known: Known, core: np.ndarray, of: np.ndarray, step: np.ndarray, free: int) -> DataFrame:
    """(spot, class) for each known word that isn't ``core``, by its place: the class of the first ``free`` under which the
    classes that stand before and after it are most likely. ``of``: classes of core words and forms, by id; what stands
    for other words there isn't read."""
    k, size = len(step), len(known.words)
    fixed = np.append(core, np.ones(FORMS, bool))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, _, raw, ends in slices(batch.column(0), 1 << 22):
                before, ids, forms = _pairs(raw, ends, known)
                at = np.flatnonzero(~fixed[ids])
                classes = of[ids]
                classes[at] = of[size + forms[at]]  # a neighbour whose class isn't known yet counts by its form
                last = np.empty_like(classes)
                last[1:] = classes[:-1]
                start = np.flatnonzero(before != np.append(-1, ids[:-1]))  # heads of texts, where the end stands before
                last[start] = of[before[start]]
                ahead = at[at + 1 < len(ids)]
                cells = np.concatenate([ids[at] * 2 * k + last[at], ids[ahead] * 2 * k + k + classes[ahead + 1]])
                cells, c = np.unique(cells, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(cells // (2 * k)), pa.array((cells % (2 * k)).astype(np.int32)), pa.array(c)], names=["spot", "cell", "c"])

    def choose(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weight = np.concatenate([step[:, :free], step[:free].T])  # a class before the word, a class after it
        for t in whole_groups(batches, 1, 1 << 16):
            spot, cell, c = (t.column(i).to_numpy() for i in range(3))
            words, row = np.unique(spot, return_inverse=True)
            seen = np.zeros((len(words), 2 * k))
            np.add.at(seen, (row, cell), c)
            yield pa.RecordBatch.from_arrays([pa.array(words), pa.array((seen @ weight).argmax(axis=1).astype(np.int32))], names=["spot", "class"])

    cells = map_arrow(bodies.select("body"), count, "spot long, cell int, c long").groupBy("spot", "cell").agg(F.sum("c").alias("c"))
    return map_arrow(cells.repartition("spot").sortWithinPartitions("spot"), choose, "spot long, class int")


def transitions(bodies: DataFrame, known: Known, of: np.ndarray, k: int) -> np.ndarray:
    """How often each class stands before each class in all texts: k * k numbers."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(k * k, np.int64)
        for batch in batches:
            for _, _, raw, ends in slices(batch.column(0), 1 << 22):
                before, ids, _ = _pairs(raw, ends, known)
                total += np.bincount(of[before] * k + of[ids], minlength=k * k)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], names=["cell", "c"])

    with lean(bodies.sparkSession):
        got = map_arrow(bodies.select("body"), each, "cell long, c long").groupBy("cell").agg(F.sum("c").alias("c")).toArrow()
    out = np.zeros(k * k)
    out[got.column("cell").to_numpy()] = got.column("c").to_numpy()
    return out.reshape(k, k)


def smoothed(m: np.ndarray) -> np.ndarray:
    """log10 of transition probabilities from counts; every class may follow every class."""
    share = (m.sum(0) + 1) / (m.sum() + len(m))
    return np.log10((m + share) / (m.sum(1, keepdims=True) + 1))


def _by_class(pairs: DataFrame, of: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """before[w, c], after[w, c]: how often class c stands before and after id w (bounded by ids times classes)."""
    size = len(of)

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(2 * size * k)
        for batch in batches:
            u, v, c = (batch.column(i).to_numpy() for i in range(3))
            total += np.bincount(v * k + of[u], weights=c, minlength=len(total))
            total += np.bincount(size * k + u * k + of[v], weights=c, minlength=len(total))
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at].astype(np.int64))], names=["cell", "c"])

    with lean(pairs.sparkSession):
        got = map_arrow(pairs, each, "cell long, c long").groupBy("cell").agg(F.sum("c").alias("c")).toArrow()
    flat = np.zeros(2 * size * k)
    flat[got.column("cell").to_numpy()] = got.column("c").to_numpy()
    return flat[: size * k].reshape(size, k), flat[size * k :].reshape(size, k)


def _gain(x: np.ndarray) -> np.ndarray:
    return np.where(x > 0, x * np.log(np.maximum(x, 1e-300)), 0.0)


def likelihood(m: np.ndarray) -> float:
    """The part of the log-likelihood of class bigrams that classes change."""
    return float(_gain(m).sum() - _gain(m.sum(0)).sum() - _gain(m.sum(1)).sum())


def exchange(before: np.ndarray, after: np.ndarray, of: np.ndarray, movable: np.ndarray, free: int) -> np.ndarray:
    """One pass: each movable word in turn to the best of the first ``free`` classes, neighbours' classes as counted."""
    of, k = of.copy(), before.shape[1]
    m = np.zeros((k, k))
    np.add.at(m, of, after)
    for w in movable.tolist():
        a, row, col = of[w], after[w], before[w]
        own = m.copy()
        own[a] -= row
        own[:, a] -= col
        own = np.maximum(own, 0)
        rows, cols = own.sum(1), own.sum(0)
        # after joining class b: row b gains ``row``, column b gains ``col``; the cell (b, b) gains both
        gr = _gain(own[:free] + row) - _gain(own[:free])
        gc = _gain(own[:, :free].T + col) - _gain(own[:, :free].T)
        d = np.arange(free)
        both = _gain(own[d, d] + row[:free] + col[:free]) - _gain(own[d, d]) - gr[d, d] - gc[d, d]
        n = row.sum()
        score = gr.sum(1) + gc.sum(1) + both - (_gain(rows[:free] + n) - _gain(rows[:free])) - (_gain(cols[:free] + n) - _gain(cols[:free]))
        b = int(score.argmax())
        if score[b] > score[a] + 1e-9 if a < free else True:
            of[w] = b
            own[b] += row
            own[:, b] += col
            m = own
    return of


@dataclass
class Model:
    """All that doesn't grow with the corpus: classes of ids, log10 transitions, form totals, and totals of the base."""

    frequent: Known
    of: np.ndarray
    step: np.ndarray
    class_total: np.ndarray
    form_total: np.ndarray
    form_once: np.ndarray
    tokens: int
    types: int


def train(bodies: DataFrame, classes: int = CLASSES, passes: int = PASSES, limit: float = FREQUENT, most: int = LISTED) -> tuple[Model, DataFrame]:
    """The model and the settled vocabulary (word, form, c) of training texts."""
    words = settle(vocabulary(bodies), "vocabulary")
    total = first_row(words.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n"), F.count(F.lit(1)).alias("v")))
    end = F.lit(END).cast("long")
    with lean(words.sparkSession):
        top = words.where((F.col("c") >= 2) | (F.col("word") == end)).orderBy((F.col("word") == end).desc(), F.desc("c"), "word").limit(most + 1).select("word", "c").toArrow()
    hashes, counts = top.column("word").to_numpy().astype(np.int64).view(np.uint64), top.column("c").to_numpy().astype(np.int64)
    if not total["n"]:
        hashes, counts = np.array([END], np.uint64), np.zeros(1, np.int64)
    order = np.argsort(hashes)
    known = Known(hashes[order], counts[order])
    often = (known.counts >= limit * total["n"]) | (known.words == np.uint64(END))  # at most 1 / limit + 1 words
    core = Known(known.words[often], known.counts[often])
    # classes: 0 .. classes-1 are learnt, then the end, then one for each form
    f, k = len(core.words), classes + 1 + FORMS
    by_count = np.argsort(-core.counts, kind="stable")
    of = np.empty(f + FORMS, np.int64)
    of[by_count] = np.arange(f) % classes
    at_end = int(np.searchsorted(core.words, np.uint64(END)))
    of[at_end] = classes
    of[f:] = classes + 1 + np.arange(FORMS)
    pairs = settle(neighbours(bodies, core), "neighbours")
    movable = by_count[by_count != at_end]
    for _ in range(passes):
        before, after = _by_class(pairs, of, k)
        new = exchange(before, after, of, movable, classes)
        if (new == of).all():
            break
        of = new
    _, after = _by_class(pairs, of, k)
    discard(pairs)
    m = np.zeros((k, k))
    np.add.at(m, of, after)
    final = np.zeros(len(known.words) + FORMS, np.int64)
    final[: len(known.words)][often] = of[:f]
    final[len(known.words) :] = of[f:]
    if not often.all():
        with lean(words.sparkSession):
            got = joined_classes(bodies, known, often, final, smoothed(m), classes).toArrow()  # at most ``most`` rows
        final[got.column("spot").to_numpy()] = got.column("class").to_numpy()
        m = transitions(bodies, known, final, k)
    rest = words.where(~((F.col("c") >= 2) | (F.col("word") == end))) if len(known.words) <= most else words.join(F.broadcast(words.sparkSession.createDataFrame(pa.table({"word": pa.array(K.signed(known.words))}))), "word", "left_anti")
    with lean(words.sparkSession):
        forms = rest.groupBy("form").agg(F.sum("c").alias("c"), F.count_if(F.col("c") == 1).alias("once")).collect()  # at most FORMS rows
    form_total, form_once = np.zeros(FORMS), np.zeros(FORMS)
    for r in forms:
        form_total[r["form"]], form_once[r["form"]] = r["c"], r["once"]
    class_total = np.bincount(final[: len(known.words)], weights=known.counts, minlength=k)
    return Model(known, final, smoothed(m), class_total, form_total, np.maximum(form_once, 0.5), total["n"], total["v"]), words


def scored(docs: DataFrame, model: Model, words: DataFrame) -> DataFrame:
    """(doc_id, n_tokens, n_known, base_score, score) per row of ``docs``."""
    f = len(model.frequent.words)

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        with np.errstate(divide="ignore"):
            emit = np.log10(model.frequent.counts / np.maximum(model.class_total[model.of[:f]], 1))
        emit = np.where(np.isfinite(emit), emit, 0.0)
        scale = np.log10(model.tokens + ALPHA * (model.types + 1))
        base = np.log10(model.frequent.counts + ALPHA) - scale
        end = int(np.searchsorted(model.frequent.words, np.uint64(END)))
        for batch in batches:
            ords, numbers = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            for a, b, raw, ends in slices(batch.column(2), 1 << 21):
                hashes, forms, first = encoded(raw, ends)
                ids = model.frequent.ids(hashes, forms)
                before = np.empty_like(ids)
                before[1:] = ids[:-1]
                before[first[:-1]] = end
                value = model.step[model.of[before], model.of[ids]]
                often = ids < f
                value = value + np.where(often, emit[np.minimum(ids, f - 1)], 0.0)
                own = np.where(often, base[np.minimum(ids, f - 1)], 0.0)
                known = often & (model.frequent.counts[np.minimum(ids, f - 1)] > 0)
                doc = np.repeat(np.arange(b - a), np.diff(first))
                rare = np.flatnonzero(~often)
                order = rare[np.lexsort((hashes[rare], doc[rare]))]
                head = np.ones(len(order), bool)
                head[1:] = (hashes[order][1:] != hashes[order][:-1]) | (doc[order][1:] != doc[order][:-1])
                starts = np.flatnonzero(head)
                times = np.diff(np.append(starts, len(order)))
                rows = order[starts]
                n = b - a
                sums = [np.bincount(doc, weights=x, minlength=n) for x in (value, own, known)]
                nan = np.zeros(len(rows))
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(np.concatenate([ords[a:b], ords[a + doc[rows]]])),
                        pa.array(np.concatenate([numbers[a:b], numbers[a + doc[rows]]])),
                        pa.array(np.concatenate([numbers[a:b], K.signed(hashes[rows])])),
                        pa.array(np.concatenate([np.full(n, -1), forms[rows]]).astype(np.int32)),
                        pa.array(np.concatenate([np.diff(first), times])),
                        pa.array(np.concatenate([sums[0], nan])),
                        pa.array(np.concatenate([sums[1], nan])),
                        pa.array(np.concatenate([sums[2], nan]).astype(np.int64)),
                    ],
                    names=["ord", "row", "word", "form", "times", "score", "base_score", "n_known"],
                )

    # one row a text (form -1: its sums) and one for each of its rare words; texts are numbered as they lie
    rows = map_arrow(docs.select("ord", F.monotonically_increasing_id().alias("row"), "body"), each, "ord long, row long, word long, form int, times long, score double, base_score double, n_known long")
    joined = rows.join(words.select("word", "c"), "word", "left")
    text, c = F.col("form") < 0, F.coalesce("c", F.lit(0))
    form_total, form_once = (F.array(*[F.lit(float(x)) for x in xs]) for xs in (model.form_total, model.form_once))
    mass = F.get(form_total, F.col("form")) + F.get(form_once, F.col("form"))
    emission = F.log10(F.when(c > 0, c.cast("double")).otherwise(F.get(form_once, F.col("form"))) / mass)
    base = F.log10((c + ALPHA) / F.lit(float(model.tokens + ALPHA * (model.types + 1))))
    sums = joined.groupBy("row").agg(
        F.min("ord").alias("ord"),
        F.sum(F.when(text, F.col("times")).otherwise(0)).alias("n_tokens"),
        F.sum(F.when(text, F.col("n_known")).when(c > 0, F.col("times")).otherwise(0)).alias("n_known"),
        F.sum(F.when(text, F.col("base_score")).otherwise(base * F.col("times"))).alias("base_score"),
        F.sum(F.when(text, F.col("score")).otherwise(emission * F.col("times"))).alias("score"),
    )
    return sums.select(F.when(F.col("ord") < F.lit(LAST), F.col("ord")).alias("doc_id"), "n_tokens", "n_known", "base_score", "score")


def held_out(doc_id: Column) -> Column:
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(10)) == 0


def score(docs: DataFrame, classes: int = CLASSES, passes: int = PASSES) -> DataFrame:
    """Train on the texts whose id falls outside the held-out tenth and score all of them.

    Null and empty texts are one end token. A null id counts as the empty string for the fold; repeated rows train and
    are scored as often as they stand; without training texts every token is unknown. Other columns are ignored.
    Besides the scores: held_out and train_tokens.
    """
    bodies = bodies_of(docs)
    training = bodies.where(~held_out(F.col("doc_id")))
    model, words = train(training, classes, passes)
    out = scored(bodies, model, words)
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "n_tokens", "n_known", F.lit(int(model.tokens)).cast("long").alias("train_tokens"), "base_score", "score")


def perplexity(scores: DataFrame) -> DataFrame:
    """(held_out, tokens, base_perplexity, perplexity) from scores."""
    return scores.groupBy("held_out").agg(
        F.sum("n_tokens").alias("tokens"), F.pow(F.lit(10.0), -F.sum("base_score") / F.sum("n_tokens")).alias("base_perplexity"), F.pow(F.lit(10.0), -F.sum("score") / F.sum("n_tokens")).alias("perplexity")
    )


def op5_brown_class_bigrams(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(table(spark, sf_dir, "documents"))
