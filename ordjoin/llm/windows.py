"""Repeated windows of a fixed length by prefix-free parsing.

Every window chooses a trigger from its own content (the gram with the least rolling hash in it; a modulus, as in the
usual parse, leaves windows without one). Triggers cut texts into phrases: consecutive windows with one trigger form a
run (about one in twenty words, one in eighty bytes), and only runs are shuffled. A run's whole content has one hash
(its context); the dictionary is the set of distinct contexts, each with a place, and the parse says where each stands:

* runs with equal contexts hold equal windows, so one row per context says where it stands first and how often;
* a trigger that has one context needs nothing more;
* contexts that share a trigger are cut out of the texts, one copy each, and ordered twice: by what stands before the
  trigger, read backwards (the suffixes of the dictionary, a phrase's suffixes being those of one backward string), and
  by what follows it up to a window's end (the order of the parse behind the trigger). Both are suffix arrays with the
  common lengths of neighbours. A window that starts p symbols before its trigger is named by the interval of the first
  order that agrees on p symbols and the interval of the second that agrees on the rest; windows of one pair of
  intervals are equal, and these pairs in order are the corpus order of all windows at stake;
* a trigger with very many contexts is one group that no task should get. Its contexts are cut into blocks of up to 16
  windows instead, which are dealt by a hash of what their windows have in common, and where several blocks share that,
  single windows are matched by hash.

Counting is by hash with map-side partial aggregates, so a passage that stands in a third of all documents costs a row
per task. Work and rows grow with the input, never with the pairs in a group. Rows are told apart by the numbers of
their layout, so equal texts, equal and missing ids are as good as others, and texts are never shuffled: places, cuts
and spans are sent to where the texts lie.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ordjoin.llm import kernels as K
from ordjoin.llm.common import Layout, column_bytes, discard, map_arrow, settle, slices, whole_groups

PLACE = ["ord", "part", "row", "start", "n"]
LONG = 1 << 22  # symbols that are hashed at once; a longer text is taken in overlapping stretches
HOT = 50_000  # contexts of one trigger that one task orders; triggers with more go by blocks
ORDERED_ROWS = 1 << 14  # contexts whose orders are made at once, and whole groups beyond


@dataclass(frozen=True)
class Unit:
    """What a window is made of: ``words`` between ASCII spaces, or ``bytes``."""

    words: bool
    window: int
    gram: int
    slice_bytes: int = 1 << 18

    @property
    def block(self) -> int:
        return max(1, min(16, self.window // 4))

    def symbols(self, raw: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not self.words:
            return K.BYTE_CODES[raw], ends
        starts, stops, first = K.word_spans(raw, ends)
        return K.word_hashes(raw, starts, stops), first


def runs_in(raw: np.ndarray, ends: np.ndarray, unit: Unit) -> dict[str, np.ndarray]:
    """Runs of window starts of some texts; windows of a long text are taken stretch by stretch."""
    if unit.words:
        symbols, first = unit.symbols(raw, ends)
        if len(symbols) <= LONG or len(first) > 2:
            return K.trigger_runs(symbols, first, unit.window, unit.gram)
        stretch = lambda a: symbols[a : a + LONG + unit.window - 1]
        size = len(symbols)
    else:
        if len(raw) <= LONG or len(ends) > 2:
            return K.trigger_runs(*unit.symbols(raw, ends), unit.window, unit.gram)
        stretch = lambda a: K.BYTE_CODES[raw[a : a + LONG + unit.window - 1]]
        size = len(raw)
    parts = []
    for a in range(0, size - unit.window + 1, LONG):
        some = stretch(a)
        found = K.trigger_runs(some, np.array([0, len(some)]), unit.window, unit.gram)
        parts.append(found | {"start": found["start"] + a})
    return {k: np.concatenate([p[k] for p in parts]) for k in parts[0]}


def find_runs(bodies: DataFrame, unit: Unit, part: int = 0) -> DataFrame:
    """Runs of the rows (ord, row, body) of a layout, which is number ``part`` of those whose runs are brought together."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ords, rows = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
            for a, _, raw, ends in slices(batch.column(2), unit.slice_bytes):
                found = runs_in(raw, ends, unit)
                at = found["doc"] + a
                yield pa.RecordBatch.from_arrays(
                    [pa.array(ords[at]), pa.array(np.full(len(at), part, np.int32)), pa.array(rows[at]), pa.array(found["start"].astype(np.int32)), pa.array(found["n"].astype(np.int32)), pa.array(K.signed(found["key"])), pa.array(K.signed(found["ctx"]))],
                    names=["ord", "part", "row", "start", "n", "key", "ctx"],
                )

    return map_arrow(bodies.select("ord", "row", "body"), each, "ord long, part int, row long, start int, n int, key long, ctx long")


def contexts_of(runs: DataFrame, *more: Column) -> DataFrame:
    """One row per distinct context: a place of it, the least document that has it, and how often it stands.

    The columns of the place come from one row, as all of them take the first; only fixed-width buffers are used,
    so the aggregate hashes.
    """
    place = [F.first(c).alias(c) for c in PLACE]
    return runs.groupBy("key", "ctx").agg(*place, F.min("ord").alias("least"), F.count(F.lit(1)).alias("times"), *more)


def contested(contexts: DataFrame, fresh: Column, key: str = "key") -> DataFrame:
    """Contexts that share their trigger with another one where a fresh one takes part, and fresh ones that repeat.

    ``shared``: how many contexts the trigger has, 0 where it has one.
    """
    keys = contexts.groupBy(key).agg(F.count(F.lit(1)).alias("shared"), F.max(fresh).alias("any_fresh")).where("shared > 1 and any_fresh").select(key, "shared")
    return contexts.join(keys, key, "left").withColumn("shared", F.coalesce("shared", F.lit(0))).where((F.col("shared") > 0) | (F.col("times") > 1) & fresh)


def pieces_of(contexts: DataFrame, layouts: list[Layout], unit: Unit) -> DataFrame:
    """One copy of each context: (key, ctx, lead, n, least, times, shared, piece); ``lead``: where its trigger stands."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reach = unit.window - unit.gram + 1
        for batch in batches:
            cuts = batch.column(1)
            places = np.asarray(cuts.offsets)
            fields = [np.asarray(cuts.values.field(i)) for i in range(7)]
            for a, b, raw, ends in slices(batch.column(0), unit.slice_bytes):
                lo, hi = places[a], places[b]
                start, n, key, ctx, times, least, shared = (f[lo:hi] for f in fields)
                doc = np.repeat(np.arange(b - a), np.diff(places[a : b + 1]))
                if unit.words:
                    starts, stops, first = K.word_spans(raw, ends)
                    at = first[doc] + start
                    low, high = starts[at], stops[at + n + unit.window - 2]
                else:
                    low = ends[doc] + start
                    high = low + n + unit.window - 1
                whole = raw.tobytes()
                texts = [whole[x:y] for x, y in zip(low.tolist(), high.tolist(), strict=True)]
                some = pa.array(texts, pa.binary())
                lead = np.zeros(len(texts), np.int32)
                for x, y, piece, cut in slices(some, unit.slice_bytes):
                    symbols, first = unit.symbols(piece, cut)
                    grams = K.rolling(K.prefix_sums(symbols), unit.gram)
                    wanted = key[x:y].view(np.uint64)
                    lead[x:y] = [int(np.flatnonzero(grams[p : p + reach] == k)[-1]) for p, k in zip(first[:-1].tolist(), wanted, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(ctx), pa.array(lead), pa.array(n), pa.array(least), pa.array(times), pa.array(shared), some], names=["key", "ctx", "lead", "n", "least", "times", "shared", "piece"])

    out = None
    for part, layout in enumerate(layouts):
        fields = ["start", "n", "key", "ctx", "times", "least", "shared"]
        wanted = layout.gathered(contexts.where(F.col("part") == part).select("row", *fields), F.collect_list(F.struct(*fields)).alias("cuts"))
        some = map_arrow(layout.meet(wanted, ["body"]).select("body", "cuts"), each, "key long, ctx long, lead int, n int, least long, times long, shared long, piece binary")
        out = some if out is None else out.unionByName(some)
    return out


def _order(rows: np.ndarray, group: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Suffix array of the rows of a symbol matrix inside their groups, and the common length of each with the one before
    (-1 at the head of a group)."""
    head = group.astype(">u4").view(np.uint8).reshape(-1, 4)
    flat = np.concatenate([head, np.ascontiguousarray(rows).view(np.uint8).reshape(len(rows), -1)], axis=1)
    order = np.argsort(np.ascontiguousarray(flat).view(f"V{flat.shape[1]}").ravel(), kind="stable")
    differs = rows[order[1:]] != rows[order[:-1]]
    common = np.where(differs.any(axis=1), differs.argmax(axis=1), rows.shape[1])
    common[group[order[1:]] != group[order[:-1]]] = -1
    return order, np.concatenate([[-1], common])


def _interval(order: np.ndarray, common: np.ndarray, depth: int) -> np.ndarray:
    """For each row the number of the interval of its order that agrees on ``depth`` symbols."""
    out = np.empty(len(order), np.int64)
    out[order] = np.cumsum(common < depth)
    return out


def repeated_windows(t: pa.Table, unit: Unit, first_stays: bool) -> tuple[np.ndarray, np.ndarray]:
    """(row, offset) of each window of whole trigger groups (key, ctx, lead, n, least, times, shared, piece) that goes: one
    that also stands in a context with an earlier document, or without ``first_stays`` in any other."""
    key, _, lead, n, least, times, _ = (t.column(i).to_numpy() for i in range(7))
    raw, ends = column_bytes(t.column(7).combine_chunks() if t.column(7).num_chunks != 1 else t.column(7).chunk(0))
    raw, ends = raw[ends[0] : ends[-1]], ends - ends[0]
    symbols, first = unit.symbols(raw, ends) if unit.words else (raw, ends)
    wide, at = unit.window - unit.gram, np.arange(unit.window - unit.gram)
    group = np.cumsum(np.concatenate([[0], key[1:] != key[:-1]]))
    low, high = first[:-1], first[1:]
    spots = (low + lead - 1)[:, None] - at[None]
    before = np.where(spots >= low[:, None], symbols[np.maximum(spots, 0)], symbols.dtype.type(0))
    spots = (low + lead + unit.gram)[:, None] + at[None]
    after = np.where(spots < high[:, None], symbols[np.minimum(spots, len(symbols) - 1)], symbols.dtype.type(0))
    back, ahead = _order(before, group), _order(after, group)
    rows, offs = [], []
    for p in range(wide + 1):
        here = np.flatnonzero((p <= lead) & (p > lead - n))
        if len(here) < 2:
            continue
        pair = _interval(*back, p)[here] * (len(key) + 1) + _interval(*ahead, wide - p)[here]
        _, which = np.unique(pair, return_inverse=True)
        if first_stays:
            earliest = np.full(len(here), np.iinfo(np.int64).max)
            np.minimum.at(earliest, which, least[here])
            gone = here[earliest[which] < least[here]]
        else:
            gone = here[np.bincount(which, weights=times[here])[which] > times[here]]
        rows.append(gone), offs.append(lead[gone] - p)
    return (np.concatenate([np.empty(0, np.int64), *rows]), np.concatenate([np.empty(0, np.int64), *offs]))


def ordered_ranges(pieces: DataFrame, unit: Unit, first_stays: bool) -> DataFrame:
    """(key, ctx, ranges): runs [x, y) of windows of each context that go, for triggers that one task can order."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in whole_groups(batches, 1, ORDERED_ROWS):
            row, off = repeated_windows(t, unit, first_stays)
            if not len(row):
                continue
            order = np.lexsort((off, row))
            row, off = row[order], off[order]
            head = np.flatnonzero(np.concatenate([[True], (row[1:] != row[:-1]) | (off[1:] != off[:-1] + 1)]))
            tail = np.append(head[1:], len(row)) - 1
            owner = row[head]
            cuts = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]]))
            ranges = pa.StructArray.from_arrays([pa.array(off[head].astype(np.int32)), pa.array((off[tail] + 1).astype(np.int32))], names=["x", "y"])
            lists = pa.ListArray.from_arrays(pa.array(np.append(cuts, len(owner)).astype(np.int32)), ranges)
            which = pa.array(owner[cuts])
            yield pa.RecordBatch.from_arrays([t.column(0).combine_chunks().take(which), t.column(1).combine_chunks().take(which), lists], names=["key", "ctx", "ranges"])

    rows = pieces.repartition("key").sortWithinPartitions("key")
    return map_arrow(rows, each, "key long, ctx long, ranges array<struct<x:int,y:int>>")


def blocks_of(pieces: DataFrame, unit: Unit) -> DataFrame:
    """Cut each context's windows into blocks of ``unit.block`` places before the trigger.

    Per block: a hash of what all its windows have in common (``key2``), a hash of all that they cover (``ctx2``), its
    first window in the run and how many it has. Blocks with equal ctx2 hold equal windows; blocks with different key2
    hold none.
    """
    size = unit.block

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for x, y, raw, ends in slices(batch.column(7), unit.slice_bytes):
                key, ctx, lead, n, ords, times = (batch.column(i).to_numpy()[x:y] for i in range(6))
                symbols, first = unit.symbols(raw, ends)
                prefix = K.prefix_sums(symbols)
                least, most = (lead - n + 1) // size, lead // size
                count = (most - least + 1).astype(np.int64)
                row = np.repeat(np.arange(y - x), count)
                m = np.arange(len(row)) - np.repeat(np.cumsum(count) - count, count) + least[row]
                high = np.minimum(m * size + size - 1, lead[row])
                low = np.maximum(m * size, (lead - n + 1)[row])
                base = first[:-1][row] + lead[row]
                core = K.spans_hash(prefix, base - m * size, base - m * size - size + 1 + unit.window)
                full = K.spans_hash(prefix, base - high, base - low + unit.window)
                key2 = K.mixed(core ^ K.mixed(key[row].view(np.uint64) + m.astype(np.uint64)))
                ctx2 = K.mixed(full ^ (high * 1024 + low).astype(np.uint64))
                yield pa.RecordBatch.from_arrays(
                    [pa.array(key[row]), pa.array(ctx[row]), pa.array(ords[row]), pa.array(times[row]), pa.array(K.signed(key2)), pa.array(K.signed(ctx2)), pa.array((lead[row] - high).astype(np.int32)), pa.array((high - low + 1).astype(np.int32))],
                    names=["key", "ctx", "least", "times", "key2", "ctx2", "first", "width"],
                )

    return map_arrow(pieces, each, "key long, ctx long, least long, times long, key2 long, ctx2 long, first int, width int")


def windows_of(blocks: DataFrame, pieces: DataFrame, unit: Unit) -> DataFrame:
    """Windows of one copy of each block: (key2, ctx2, off, win, least, times)."""
    wanted = blocks.groupBy("key", "ctx").agg(F.collect_list(F.struct("first", "width", "key2", "ctx2", "times", "least")).alias("cuts"))
    one = pieces.select("key", "ctx", "piece").join(wanted, ["key", "ctx"]).select("piece", "cuts")

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cuts = batch.column(1)
            places = np.asarray(cuts.offsets)
            fields = [np.asarray(cuts.values.field(i)) for i in range(6)]
            for a, b, raw, ends in slices(batch.column(0), unit.slice_bytes):
                symbols, first = unit.symbols(raw, ends)
                wins = K.rolling(K.prefix_sums(symbols), unit.window)
                start, n, key2, ctx2, times, least = (f[places[a] : places[b]] for f in fields)
                doc = np.repeat(np.arange(a, b), np.diff(places[a : b + 1]))
                off = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                at = np.repeat(first[doc - a] + start, n) + off
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.repeat(key2, n)), pa.array(np.repeat(ctx2, n)), pa.array(off.astype(np.int32)), pa.array(K.signed(wins[at])), pa.array(np.repeat(least, n)), pa.array(np.repeat(times, n))],
                    names=["key2", "ctx2", "off", "win", "least", "times"],
                )

    return map_arrow(one, each, "key2 long, ctx2 long, off int, win long, least long, times long")


def _whole(first_stays: bool, before: str, own: str, times: str) -> Column:
    return F.col(before) < F.col(own) if first_stays else F.col(times) > 1


def block_ranges(pieces: DataFrame, unit: Unit, first_stays: bool) -> tuple[DataFrame, list[DataFrame]]:
    """The same ranges for triggers with many contexts, by blocks and hashes; and the settled tables that they read."""
    blocks = settle(blocks_of(pieces, unit), "blocks")
    same = blocks.groupBy("key2", "ctx2").agg(*[F.first(c).alias(c) for c in ("key", "ctx", "first", "width")], F.min("least").alias("least"), F.sum("times").alias("times"))
    marked = settle(contested(same, F.lit(True), "key2"), "shared-blocks")
    windows = settle(windows_of(marked.where("shared > 0"), pieces, unit), "windows")
    where = windows.groupBy("key2", "win").agg(F.min("least").alias("before"), F.sum("times").alias("total")).where("total > 1")
    gone = F.col("before") < F.col("least") if first_stays else F.col("total") > F.col("times")
    offs = windows.join(where, ["key2", "win"]).where(gone).groupBy("key2", "ctx2").agg(F.collect_list("off").alias("offs"))
    known = marked.select("key2", "ctx2", F.col("least").alias("before"), F.col("times").alias("total")).join(offs, ["key2", "ctx2"], "left")
    known = settle(known.where((F.col("total") > 1) | F.col("offs").isNotNull()), "block-verdicts")
    all_of_it = _whole(first_stays, "before", "least", "total")
    ranges = F.when(all_of_it, F.array(F.struct(F.col("first").alias("x"), (F.col("first") + F.col("width")).alias("y")))).otherwise(
        F.transform("offs", lambda o: F.struct((F.col("first") + o).alias("x"), (F.col("first") + o + 1).alias("y")))
    )
    parts = blocks.join(known, ["key2", "ctx2"]).where(all_of_it | F.col("offs").isNotNull())
    discard(marked, windows)
    return parts.groupBy("key", "ctx").agg(F.flatten(F.collect_list(ranges)).alias("ranges")), [blocks, known]


def removed_spans(runs: DataFrame, marked: DataFrame, layouts: list[Layout], unit: Unit, first_stays: bool) -> DataFrame:
    """(row, spans): the removed [a, b) of each row of the last of ``layouts``, settled.

    ``first_stays``: a window goes if it also starts in a document before this one; otherwise if it starts anywhere else.
    """
    pieces = settle(pieces_of(marked.where("shared > 0"), layouts, unit), "pieces")
    parts, read = ordered_ranges(pieces.where(F.col("shared") <= HOT), unit, first_stays), []
    hot = pieces.where(F.col("shared") > HOT)
    if not hot.isEmpty():
        more, read = block_ranges(hot, unit, first_stays)
        parts = parts.unionByName(more)
    known = marked.select("key", "ctx", F.col("least").alias("before"), "times").join(parts, ["key", "ctx"], "left")
    known = settle(known.where((F.col("times") > 1) | F.col("ranges").isNotNull()), "verdicts")
    discard(pieces, marked, *read)
    width = F.lit(unit.window - 1)
    all_of_it = _whole(first_stays, "before", "ord", "times")
    spans = F.when(all_of_it, F.array(F.struct(F.col("start").alias("a"), (F.col("start") + F.col("n") + width).alias("b")))).otherwise(
        F.transform("ranges", lambda r: F.struct((F.col("start") + r["x"]).alias("a"), (F.col("start") + r["y"] + width).alias("b")))
    )
    hits = runs.select("ord", "row", "start", "n", "key", "ctx").join(known, ["key", "ctx"]).where(all_of_it | F.col("ranges").isNotNull())
    hits = hits.select("row", F.explode(spans).alias("span"))
    out = settle(layouts[-1].gathered(hits, F.collect_list("span").alias("spans")), "spans")
    discard(runs, known)
    return out


def kept(layout: Layout, spans: DataFrame, unit: Unit, text: bool = False) -> DataFrame:
    """What is left of each body: (doc_id, n, n_removed, n_spans, kept_sha256), or with ``text`` the row's other columns
    (``rest``) and ``kept_text``, which is the text as it was where nothing goes."""
    names = ["doc_id", "n", "n_removed", "n_spans", "kept_sha256", *["rest", "kept_text"] * text]

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column, lists = batch.column(1), batch.column(2)
            places = np.concatenate([[0], np.cumsum(np.asarray(lists.value_lengths().fill_null(0)))])
            flat = lists.flatten()
            begin, stop = (np.asarray(flat.field(i)).astype(np.int64) for i in (0, 1))
            raw, ends = column_bytes(column)
            had = batch.column(4) if text else ()
            ns, removed, n_spans, shas, texts = [], [], [], [], []
            for i in range(len(column)):
                body = raw[ends[i] : ends[i + 1]].tobytes()
                lo, hi = places[i], places[i + 1]
                parts = body.split() if unit.words else body
                n = len(parts)
                if lo == hi:
                    left, gone, count = b" ".join(parts) if unit.words else body, 0, 0
                else:
                    steps = np.bincount(begin[lo:hi], minlength=n + 1) - np.bincount(stop[lo:hi], minlength=n + 1)
                    stay = np.cumsum(steps)[:n] == 0
                    gone = n - int(stay.sum())
                    count = int((np.diff(stay.astype(np.int8), prepend=1) == -1).sum())
                    left = b" ".join(w for w, s in zip(parts, stay.tolist(), strict=True) if s) if unit.words else np.frombuffer(body, np.uint8)[stay].tobytes()
                ns.append(n), removed.append(gone), n_spans.append(count), shas.append(hashlib.sha256(left).hexdigest())
                if text:
                    texts.append((left if gone else body).decode("utf-8", "ignore") if had[i].as_py() else None)
            arrays = [batch.column(0), pa.array(ns, pa.int64()), pa.array(removed, pa.int64()), pa.array(n_spans, pa.int64()), pa.array(shas, pa.string())]
            yield pa.RecordBatch.from_arrays([*arrays, *([batch.column(3), pa.array(texts, pa.string())] if text else [])], names=names)

    joined = layout.meet(spans, ["doc_id", "body", *["rest", "had"] * text], "left").select("doc_id", "body", "spans", *["rest", "had"] * text)
    schema = "doc_id long, n long, n_removed long, n_spans long, kept_sha256 string"
    if text:
        schema += f", rest {dict(layout.frame.dtypes)['rest']}, kept_text string"
    return map_arrow(joined, each, schema)
