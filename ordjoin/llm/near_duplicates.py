"""Shingle-set Jaccard join with count-vector R-trees.

A document's distinct shingles are hashed into groups; the counts per group are its point. Two points bound the overlap
of their sets by the sum of coordinate minima, and so do the upper corners of two R-tree nodes, so a tree is joined with
itself by descending into node pairs that the bound admits; surviving pairs are verified on whole texts.

In so many dimensions boxes of unrelated texts overlap, so one tree over a corpus prunes too little. The corpus is
therefore dealt into a forest without loss: under any total order of shingles, two sets that are similar enough share
one of their first n - ceil(t n) + 1 shingles, and each of these is a block. The order puts the most frequent shingles
(by a count over a sixteenth of the texts; a list of bounded length) last; it changes the work, not the result. Then:

* equal sets are one node, named by the number of the first row that has it;
* blocks of the same nodes are one block;
* in each block, nodes of about one size are paired with the first and the last of them, and these pairs are bounded and
  verified first: a group of copies is joined by a few pairs for each of its nodes;
* blocks that still hold several components are dealt by size class, and what still does in a class is joined: the nodes
  outside its largest component with all of it, by R-trees of chunks, for pairs of different components only. Rows and
  tasks follow the nodes that are not yet joined, not the square of the block. Each pair is made in one place alone;
* where the number of links is asked for, it is counted inside components, where all links are: each set is reduced to
  how it differs from its component's first set, chunks of these differences are compared by products of incidence
  matrices, and only counts leave a task, never pairs.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ordjoin.llm import kernels as K
from ordjoin.llm.common import LAST, Layout, bodies_of, discard, documents_of, lay_out, map_arrow, settle, slices, table, whole_groups
from ordjoin.llm.components import components

WIDTH, PERCENT, GROUPS = 4, 85, 128
SAMPLE_SHARE, COMMON_IN, MAX_COMMON = 16, 2, 1_000_000
CHUNK, LEAF, PAIRS_A_TASK, LEAST_CELLS = 512, 8, 64, 8
COUNT_CHUNK, COUNT_SHINGLES, COUNT_ROWS, COLUMNS, LIGHT = 8192, 1 << 21, 1024, 1024, 64


def shingle_sets(raw: np.ndarray, ends: np.ndarray, width: int) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text, A-Z lower-cased."""
    low = K.LOWER[raw]
    starts, stops, first = K.word_spans(low, ends)
    prefix = K.prefix_sums(K.word_hashes(low, starts, stops))
    grams = K.rolling(prefix, width)
    out = []
    for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
        if b - a >= width:
            out.append(np.unique(grams[a : b - width + 1]))
        elif b > a:
            out.append(K.spans_hash(prefix, np.array([a]), np.array([b])))
        else:
            out.append(np.empty(0, np.uint64))
    return out


def count_vector(s: np.ndarray) -> bytes:
    """Counts of shingles by the leading bits of their hash: 128 groups, or more for large sets, so that a group holds
    few shingles and the bound stays sharp. Neighbouring groups add up to coarser ones. The first byte says how they are
    kept: half a byte each, or one or four bytes where a group holds more."""
    bits = min(max(7, (len(s) // 4).bit_length()), 14)
    counts = np.bincount((s >> np.uint64(64 - bits)).astype(np.int64), minlength=1 << bits)
    if (most := counts.max()) < 16:
        return b"\0" + (counts[0::2] | counts[1::2] << 4).astype(np.uint8).tobytes()
    return b"\1" + counts.astype(np.uint8).tobytes() if most < 256 else b"\2" + counts.astype("<u4").tobytes()


def counts_of(point: bytes) -> np.ndarray:
    """The counts in a vector."""
    if point[0]:
        return np.frombuffer(point, np.uint8 if point[0] == 1 else "<u4", offset=1)
    pairs = np.frombuffer(point, np.uint8, offset=1)
    return np.stack([pairs & 15, pairs >> 4], 1).ravel()


def coarse(points: list[np.ndarray]) -> np.ndarray:
    """Vectors of 128 groups, a row each (sums over four bytes, as a group may hold many)."""
    out = np.empty((len(points), GROUPS), np.int32)
    for i, p in enumerate(points):
        out[i] = p.reshape(GROUPS, -1).sum(axis=1)
    return out


def bound(a: np.ndarray, b: np.ndarray) -> int:
    """Largest overlap that two vectors admit, on the finer groups that both have."""
    if len(a) > len(b):
        a, b = b, a
    return int(np.minimum(a, b.reshape(len(a), -1).sum(axis=1)).sum())


def _sets(bodies: DataFrame, width: int, percent: int, common: np.ndarray) -> DataFrame:
    """(slot, row, ord, n, sid, check, point, keys): sid and check are hashes of the set, keys its first shingles under the order."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, raw, ends in slices(batch.column(3), 1 << 18):
                ns, sids, checks, points, keys = [], [], [], [], []
                for s in shingle_sets(raw, ends, width):
                    n = len(s)
                    total = s.sum(dtype=np.uint64)
                    sid, check = K.mixed(np.array([total ^ np.uint64(n), K.mixed(s ^ np.uint64(0x5851F42D4C957F2D)).sum(dtype=np.uint64)], np.uint64)).view(np.int64).tolist()
                    ns.append(n), sids.append(sid), checks.append(check)
                    points.append(count_vector(s) if n else None)
                    if n:
                        if len(common):
                            spot = np.minimum(np.searchsorted(common, s), len(common) - 1)
                            s = np.concatenate([s[(last := common[spot] == s) ^ True], s[last]])
                        keys.append(s[: n - -(-percent * n // 100) + 1].view(np.int64))
                    else:
                        keys.append(np.empty(0, np.int64))
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum([len(k) for k in keys])]).astype(np.int32)), pa.array(np.concatenate(keys)))
                yield pa.RecordBatch.from_arrays(
                    [*(batch.column(i).slice(a, b - a) for i in range(3)), pa.array(ns, pa.int64()), pa.array(sids, pa.int64()), pa.array(checks, pa.int64()), pa.array(points, pa.binary()), lists],
                    names=["slot", "row", "ord", "n", "sid", "check", "point", "keys"],
                )

    return map_arrow(bodies.select("slot", "row", "ord", "body"), each, "slot int, row long, ord long, n long, sid long, check long, point binary, keys array<long>")


def _common(bodies: DataFrame, width: int) -> np.ndarray:
    """The most frequent shingles of a share of the texts, sorted: those in ``COMMON_IN`` of them, ``MAX_COMMON`` at most."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, _, raw, ends in slices(batch.column(0), 1 << 18):
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([np.empty(0, np.uint64), *shingle_sets(raw, ends, width)]).view(np.int64))], names=["h"])

    sample = bodies.where(F.pmod(F.xxhash64("row"), F.lit(SAMPLE_SHARE)) == 0).select("body")
    found = map_arrow(sample, each, "h long").groupBy("h").count().where(F.col("count") >= COMMON_IN).orderBy(F.desc("count")).limit(MAX_COMMON).select("h")
    found = settle(found, "common")  # a plain write leaves no shuffle files behind
    out = np.sort(found.toArrow().column("h").to_numpy().astype(np.int64).view(np.uint64))
    discard(found)
    return out


def needed(n: np.ndarray, m: np.ndarray, percent: int) -> np.ndarray:
    """Least overlap of sets of n and m shingles that are similar enough."""
    return -(-(n + m) * percent // (100 + percent))


class CountTree:
    """R-tree of two levels over count vectors: leaves of points near in size and leading counts, with upper corners."""

    def __init__(self, points: np.ndarray, sizes: np.ndarray) -> None:
        self.order = np.lexsort((points[:, 0], points[:, 1], sizes)) if points.shape[1] > 1 else np.argsort(sizes)
        self.points, self.sizes = points[self.order], sizes[self.order]
        cuts = np.arange(0, len(sizes), LEAF)
        self.corner = np.maximum.reduceat(self.points, cuts, axis=0)
        self.least, self.most = np.minimum.reduceat(self.sizes, cuts), np.maximum.reduceat(self.sizes, cuts)
        self.cuts = np.append(cuts, len(sizes))

    def join(self, other: CountTree, percent: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Index pairs (into the points given) whose bound admits enough overlap."""
        for i in range(len(self.corner)):
            roof = np.minimum(self.corner[i], other.corner).sum(axis=1, dtype=np.int64)
            near = (roof >= needed(self.least[i], other.least, percent)) & (100 * self.most[i] >= percent * other.least) & (100 * other.most >= percent * self.least[i])
            mine = slice(self.cuts[i], self.cuts[i + 1])
            for j in np.flatnonzero(near).tolist():
                theirs = slice(other.cuts[j], other.cuts[j + 1])
                roof = np.minimum(self.points[mine, None], other.points[None, theirs]).sum(axis=2, dtype=np.int64)
                x, y = np.nonzero(roof >= needed(self.sizes[mine][:, None], other.sizes[theirs][None], percent))
                if len(x):
                    yield self.order[mine][x], other.order[theirs][y]


def _facing(pairs: DataFrame, layout: Layout, columns: list[str]) -> tuple[DataFrame, DataFrame]:
    """Rows (a, salt, role, row, columns) of a layout that bring each of the settled ``pairs`` (a, b) together, and the
    settled table that they read.

    Pairs of one ``a`` are dealt into tasks of bounded size; ``a``'s own row (role 0) goes to each of them, and every
    other one streams by. What is moved follows the pairs, never the layout.
    """
    per = pairs.groupBy("a").agg(F.count(F.lit(1)).alias("many"))
    dealt = pairs.join(per, "a").select("a", "b", F.pmod(F.xxhash64("b"), F.ceil(F.col("many") / PAIRS_A_TASK)).cast("int").alias("salt"))
    dealt = settle(dealt, "candidates")
    wanted = dealt.select("a", "salt", F.lit(1).alias("role"), F.col("b").alias("row")).unionByName(dealt.select("a", "salt", F.lit(0).alias("role"), F.col("a").alias("row")).distinct())
    rows = layout.meet(wanted, columns).select("a", "salt", "role", "row", *columns)
    return rows.repartition("a", "salt").sortWithinPartitions("a", "salt", "role"), dealt


def _admitted(pairs: DataFrame, sets: Layout, percent: int) -> DataFrame:
    """Those of the settled ``pairs`` (a, b) whose summed coordinate minima admit enough overlap; settled."""
    rows, dealt = _facing(pairs, sets, ["n", "point"])

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, size, own = None, 0, np.empty(0, np.uint8)
        for batch in batches:
            a, role, node, n = (batch.column(k).to_numpy() for k in (0, 2, 3, 4))
            roof = np.full(len(a), -1, np.int64)
            least = np.zeros(len(a), np.int64)
            for k, p in enumerate(batch.column(5).to_pylist()):
                if role[k] == 0:
                    now, size, own = a[k], n[k], counts_of(p)
                elif a[k] == now:
                    least[k] = needed(n[k], size, percent)
                    roof[k] = bound(own, counts_of(p))
            keep = roof >= least
            yield pa.RecordBatch.from_arrays([pa.array(a[keep]), pa.array(node[keep])], names=["a", "b"])

    out = settle(map_arrow(rows, each, "a long, b long"), "pairs")
    discard(dealt)
    return out


def _tree_pairs(rows: DataFrame, percent: int) -> DataFrame:
    """Candidate pairs (a, b) of different components, from rows (block, i, j, side, node, root, n, point, blocks) sorted
    by chunk pair; ``side`` 0 or 2 holds nodes outside the block's largest component, side 1 or 2 any node of the block.

    ``blocks``: a node's least mixed blocks; a pair is left to a lesser block where these tell that both have one. The
    least block that both have always gives it, so none is lost, and some are given more than once.
    """

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in whole_groups(batches, 3):
            block, side, node, root, n = int(t.column(0)[0].as_py()), *(t.column(k).to_numpy() for k in (3, 4, 5, 6))
            left, right = np.flatnonzero(side != 1), np.flatnonzero(side != 0)
            if not len(left) or not len(right):
                continue
            exact = list(map(counts_of, t.column(7).to_pylist()))
            points = coarse(exact)
            found = [np.stack([left[x], right[y]], 1) for x, y in CountTree(points[left], n[left]).join(CountTree(points[right], n[right]), percent)]
            if not found:
                continue
            at = np.concatenate(found)
            at = at[root[at[:, 0]] != root[at[:, 1]]]
            least = needed(n[at[:, 0]], n[at[:, 1]], percent)
            at = at[[len(exact[x]) == len(exact[y]) == GROUPS or bound(exact[x], exact[y]) >= m for (x, y), m in zip(at.tolist(), least.tolist(), strict=True)]] if len(at) else at
            if len(at):
                lesser = [frozenset(k for k in b if k < block) for b in t.column(8).to_pylist()]
                at = at[[lesser[x].isdisjoint(lesser[y]) for x, y in at.tolist()]]
            if len(at):
                p = np.unique(np.sort(node[at], axis=1), axis=0)
                yield pa.RecordBatch.from_arrays([pa.array(p[:, 0]), pa.array(p[:, 1])], names=["a", "b"])

    return map_arrow(rows, each, "a long, b long")


def _verified(pairs: DataFrame, layout: Layout, width: int, percent: int) -> DataFrame:
    """Those of the settled ``pairs`` (a, b: nodes) whose sets are similar enough, by whole texts; settled."""
    rows, dealt = _facing(pairs, layout, ["body"])

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, own = None, np.empty(0, np.uint64)
        for batch in batches:
            a, role, node = (batch.column(k).to_numpy() for k in (0, 2, 3))
            out: list[tuple[int, int]] = []
            for x, y, raw, ends in slices(batch.column(4), 1 << 18):
                for k, s in zip(range(x, y), shingle_sets(raw, ends, width), strict=True):
                    if role[k] == 0:
                        now, own = a[k], s
                    elif a[k] == now:
                        both = len(np.intersect1d(own, s, assume_unique=True))
                        if 100 * both >= percent * (len(own) + len(s) - both):
                            out.append((int(a[k]), int(node[k])))
            yield pa.RecordBatch.from_arrays([pa.array([p[0] for p in out], pa.int64()), pa.array([p[1] for p in out], pa.int64())], names=["a", "b"])

    links = settle(map_arrow(rows, each, "a long, b long"), "links")
    discard(dealt)
    return links


def _classes(percent: int, finer: bool = False) -> Column:
    """Size classes of ``n``: two grids that lie half a step apart, with a step of twice the largest admissible ratio of
    sizes, so that sizes of an admissible ratio share a class; and a finer grid where it is asked for."""
    ratio = 1.001 * math.log(100 / percent) or 1.0  # a little more, for rounding
    size = F.log("n")
    wide = [3 * F.floor(size / F.lit(2 * ratio) + F.lit(shift)) + F.lit(odd) for odd, shift in ((0, 0.0), (1, 0.5))]
    return F.array(*wide, *([3 * F.floor(size / F.lit(ratio / 4)) + F.lit(2)] if finer else []))


def _stars(members: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b): blocks of two, and each larger block's nodes with the first and the last of their size class in it."""
    two = members.where("many = 2").groupBy("block").agg(F.min(F.struct("node", "n")).alias("x"), F.max(F.struct("node", "n")).alias("y"))
    two = two.where(100 * F.least("x.n", "y.n") >= percent * F.greatest("x.n", "y.n")).select(F.col("x.node").alias("a"), F.col("y.node").alias("b"))
    rows = members.where("many > 2").withColumn("class", F.explode(_classes(percent, finer=True)))
    ends = [(F.min("node"), F.min_by("n", "node")), (F.max("node"), F.max_by("n", "node"))]
    heads = rows.groupBy("block", "class").agg(*[c.alias(f"{what}{k}") for k, end in enumerate(ends) for what, c in zip(("x", "n"), end, strict=True)]).where("x0 <> x1")
    both = F.explode(F.array(*[F.struct(F.col(f"x{k}").alias("x"), F.col(f"n{k}").alias("n")) for k in (0, 1)])).alias("h")
    near = 100 * F.least("n", "h.n") >= percent * F.greatest("n", "h.n")
    pairs = rows.join(heads, ["block", "class"]).select("node", "n", both).where(near & (F.col("node") != F.col("h.x"))).select("node", F.col("h.x").alias("head"))
    return two.unionByName(pairs.select(F.least("node", "head").alias("a"), F.greatest("node", "head").alias("b"))).distinct()


def _blocks(nodes: DataFrame) -> DataFrame:
    """(block, node, n, many) of all blocks of two nodes or more; of blocks of the same nodes only one. Settled."""
    keys = nodes.select(F.explode("keys").alias("block"), "node", F.col("n").cast("int").alias("n"))
    many = F.count(F.lit(1)).over(Window.partitionBy("block")).cast("int")  # counted where they lie, so that keys move once
    all_of_them = settle(keys.withColumn("many", many).where("many > 1"), "all-blocks")
    who = [F.bit_xor(F.xxhash64("node", F.lit(i))).alias(f"who{i}") for i in (0, 1)]
    held = all_of_them.groupBy("block", "many").agg(*who)
    chosen = held.groupBy("many", "who0", "who1").agg(F.min("block").alias("block")).select("block")
    members = settle(all_of_them.join(chosen, "block"), "blocks")
    discard(all_of_them)
    return members


def _unjoined(members: DataFrame, root: DataFrame, sets: Layout, percent: int) -> tuple[DataFrame, list[DataFrame]]:
    """Rows for ``_tree_pairs``, and the settled tables that they read.

    A block's size class that holds several components is a cell. Chunks of the nodes outside a cell's largest component
    meet chunks of all its nodes; a cell of one chunk is one group, in which each node stands once (side 2). A node's
    cells go to where its set lies and leave from there with its vector.
    """
    rooted = members.where("many > 2").join(root, "node", "left").select("block", "node", "n", F.coalesce("root", "node").alias("root"))
    rooted = rooted.withColumn("class", F.explode(_classes(percent))).select(F.xxhash64("block", "class").alias("block"), "node", "root")
    rooted = settle(rooted, "rooted")
    per = rooted.groupBy("block", "root").agg(F.count(F.lit(1)).alias("c"))
    mixed = per.groupBy("block").agg(F.max(F.struct("c", "root")).alias("top"), F.sum("c").alias("many"), F.count(F.lit(1)).alias("roots")).where("roots > 1")
    cuts = mixed.select("block", F.col("top.root").alias("top"), F.ceil((F.col("many") - F.col("top.c")) / CHUNK).cast("int").alias("some"), F.ceil(F.col("many") / CHUNK).cast("int").alias("all"))
    cell = F.struct("block", (F.col("root") != F.col("top")).alias("apart"), "some", "all")
    mine = rooted.join(cuts, "block").select(F.col("node").alias("row"), "root", cell.alias("cell"))
    dealt = mine.withColumn("slot", sets.slot(F.col("row"))).repartition(sets.buckets, "slot")
    own = dealt.groupBy("slot", "row").agg(F.first("root").alias("root"), F.sort_array(F.collect_list("cell")).alias("cells"))  # two for each of its shingles at most
    about = sets.meet(own, ["n", "point"]).withColumn("blocks", F.slice("cells.block", 1, LEAST_CELLS)).withColumn("cell", F.explode("cells"))

    def at(i: Column, j: Column, side: Column) -> Column:
        return F.struct(i.cast("int").alias("i"), j.cast("int").alias("j"), side.cast("int").alias("side"))

    spread, some, every, apart = F.xxhash64("row"), F.col("cell.some"), F.col("cell.all"), F.col("cell.apart")
    whole = F.transform(F.sequence(F.lit(0), some - 1), lambda i: at(i, F.pmod(spread, every), F.lit(1)))
    rest = F.when(apart, F.transform(F.sequence(F.lit(0), every - 1), lambda j: at(F.pmod(spread, some), j, F.lit(0))))
    places = F.when(every == 1, F.array(at(F.lit(0), F.lit(0), F.when(apart, 2).otherwise(1)))).when(apart, F.concat(whole, rest)).otherwise(whole)
    rows = about.withColumn("at", F.explode(places)).select("cell.block", "at.i", "at.j", "at.side", F.col("row").alias("node"), "root", "n", "point", "blocks")
    return rows.repartition("block", "i", "j").sortWithinPartitions("block", "i", "j"), [rooted]


def linked_sets(layout: Layout, width: int, percent: int) -> tuple[DataFrame, DataFrame]:
    """(ord, row, n, node) of each text, node null where it has no shingle, and (node, ord, n, root) of each distinct set; settled."""
    sets = layout.beside(_sets(layout.frame, width, percent, _common(layout.frame, width)))
    first = F.min(F.struct("ord", "row")).alias("f")
    same = settle(sets.frame.where("n > 0").groupBy("sid", "check").agg(first).select("sid", "check", F.col("f.row").alias("node")), "same")
    texts = sets.frame.select("sid", "check", "ord", "row", "n").join(same, ["sid", "check"], "left")
    texts = settle(texts.select("ord", "row", "n", F.when(F.col("n") > 0, F.col("node")).alias("node")), "texts")
    nodes = texts.where("row = node").select("node", "ord", "n")
    members = _blocks(sets.meet(same.select(F.col("node").alias("row")), ["n", "keys"]).withColumnRenamed("row", "node"))
    discard(same)
    star = settle(_stars(members, percent), "star")
    pairs = _admitted(star, sets, percent)
    links = _verified(pairs, layout, width, percent)
    root = components(links)
    discard(pairs, links)
    rows, read = _unjoined(members, root, sets, percent)
    more = settle(_tree_pairs(rows, percent).distinct().join(star, ["a", "b"], "left_anti"), "more")
    discard(members, star, *read)
    sets.drop()
    extra = _verified(more, layout, width, percent)
    joined = components(root.select(F.col("node").alias("a"), F.col("root").alias("b")).unionByName(extra))
    named = settle(nodes.select("node", "ord", "n").join(joined, "node", "left").select("node", "ord", "n", F.coalesce("root", "node").alias("root")), "named")
    discard(root, more, extra, joined)
    return texts, named


def overlaps(left: list[np.ndarray], right: list[np.ndarray]) -> np.ndarray:
    """Sizes of the intersections of all sets of two lists: rare members pair by pair, others by incidence matrices."""
    out = np.zeros((len(left), len(right)), np.float32)
    sides = []
    for sets in (left, right):
        owner = np.repeat(np.arange(len(sets)), list(map(len, sets)))
        members = np.concatenate([np.empty(0, np.int64), *sets])
        order = np.argsort(members, kind="stable")
        sides.append((members[order], owner[order]))
    (here, mine), (there, theirs) = sides
    shared = np.intersect1d(here, there)  # a member of one side alone adds nothing
    low, high = np.searchsorted(here, shared), np.searchsorted(here, shared, side="right")
    least, most = np.searchsorted(there, shared), np.searchsorted(there, shared, side="right")
    rare = (high - low) * (most - least) <= LIGHT
    if rare.any():
        n = (high - low)[rare]
        entry = np.repeat(low[rare] - np.cumsum(n) + n, n) + np.arange(n.sum())
        each = np.repeat((most - least)[rare], n)
        other = np.repeat(np.repeat(least[rare], n) - np.cumsum(each) + each, each) + np.arange(each.sum())
        np.add.at(out, (np.repeat(mine[entry], each), theirs[other]), 1)
    often = np.flatnonzero(~rare)
    for x in range(0, len(often), COLUMNS):
        columns = often[x : x + COLUMNS]
        marks = [np.zeros((len(rows), len(columns)), np.float32) for rows in (left, right)]
        for j, c in enumerate(columns.tolist()):
            marks[0][mine[low[c] : high[c]], j] = 1
            marks[1][theirs[least[c] : most[c]], j] = 1
        out += marks[0] @ marks[1].T
    return out


def _differences(named: DataFrame, layout: Layout, width: int) -> DataFrame:
    """(root, node, n, missing, extra) of each set in a component of several: what it lacks of the root's set and has
    beyond it; settled. The root's text goes to each task that has some of its members."""
    many = named.groupBy("root").agg(F.count(F.lit(1)).alias("many")).where("many > 1")
    dealt = named.join(many, "root").select("node", "root", F.pmod(F.xxhash64("node"), F.ceil(F.col("many") / PAIRS_A_TASK)).cast("int").alias("salt"))
    wanted = dealt.select("root", "salt", F.lit(1).alias("role"), F.col("node").alias("row")).unionByName(dealt.select("root", "salt", F.lit(0).alias("role"), F.col("root").alias("row")).distinct())
    rows = layout.meet(wanted, ["body"]).select("root", "salt", "role", "row", "body").repartition("root", "salt").sortWithinPartitions("root", "salt", "role")

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = np.empty(0, np.uint64)
        for batch in batches:
            root, role, node = (batch.column(k).to_numpy() for k in (0, 2, 3))
            out: list[tuple] = []
            for x, y, raw, ends in slices(batch.column(4), 1 << 18):
                for k, s in zip(range(x, y), shingle_sets(raw, ends, width), strict=True):
                    if role[k] == 0:
                        own = s
                    else:
                        out.append((root[k], node[k], len(s), np.setdiff1d(own, s, assume_unique=True).view(np.int64), np.setdiff1d(s, own, assume_unique=True).view(np.int64)))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64()))
            columns = list(zip(*out, strict=True)) if out else [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=["root", "node", "n", "missing", "extra"])

    return settle(map_arrow(rows, each, "root long, node long, n long, missing array<long>, extra array<long>"), "differences")


def _lists(column: pa.Array) -> list[np.ndarray]:
    values, cuts = column.flatten().to_numpy(zero_copy_only=False), np.concatenate([[0], np.cumsum(column.value_lengths().to_numpy(zero_copy_only=False))])
    return [values[a:b] for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)]


def link_counts(named: DataFrame, layout: Layout, width: int, percent: int) -> DataFrame:
    """(node, n_links): the number of other distinct sets that are similar enough, for nodes that have any.

    Linked sets share a component, so each component is compared with itself, in pairs of chunks of bounded size: c sets
    cost c * c / 8192 rows of differences, more where these are long, and c * c comparisons.
    """
    apart = _differences(named, layout, width)
    sums = apart.groupBy("root").agg(F.count(F.lit(1)).alias("many"), F.sum(F.size("missing") + F.size("extra")).alias("size"))
    chunks = sums.select("root", F.greatest(F.ceil(F.col("many") / COUNT_CHUNK), F.ceil(F.col("size") / COUNT_SHINGLES)).cast("int").alias("chunks"))
    own = apart.join(chunks, "root").withColumn("c", F.pmod(F.xxhash64("node"), F.col("chunks")).cast("int"))
    dealt = own.withColumn("o", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    dealt = dealt.select("root", F.least("c", "o").alias("i"), F.greatest("c", "o").alias("j"), F.when(F.col("c") <= F.col("o"), 0).otherwise(1).alias("side"), "node", "n", "missing", "extra")
    rows = dealt.repartition("root", "i", "j").sortWithinPartitions("root", "i", "j", "side")

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in whole_groups(batches, 3):
            alone = t.column(1)[0] == t.column(2)[0]
            side, node, n = (t.column(k).to_numpy() for k in (3, 4, 5))
            lacks, adds = (_lists(t.column(k).chunk(0)) for k in (6, 7))
            left, right = np.flatnonzero(side == 0), np.flatnonzero(side == (0 if alone else 1))
            if not len(left) or not len(right):
                continue
            lack, add = np.array(list(map(len, lacks))), np.array(list(map(len, adds)))
            whole = int(n[0] - add[0] + lack[0])  # the root's set
            many = np.zeros(len(node), np.int64)
            for x in range(0, len(left), COUNT_ROWS):
                some = left[x : x + COUNT_ROWS]
                both = overlaps([lacks[k] for k in some], [lacks[k] for k in right]) + overlaps([adds[k] for k in some], [adds[k] for k in right])
                both = both.astype(np.int64) + whole - lack[some][:, None] - lack[right][None]
                linked = 100 * both >= percent * (n[some][:, None] + n[right][None] - both)
                if alone:
                    linked[np.arange(len(some)), x + np.arange(len(some))] = False
                many[some] += linked.sum(axis=1)
                if not alone:
                    many[right] += linked.sum(axis=0)
            yield pa.RecordBatch.from_arrays([pa.array(node), pa.array(many)], names=["node", "n_links"])

    counts = map_arrow(rows, each, "node long, n_links long").groupBy("node").agg(F.sum("n_links").alias("n_links"))
    out = settle(counts, "degrees")
    discard(apart)
    return out


def classes(docs: DataFrame, width: int = WIDTH, percent: int = PERCENT) -> DataFrame:
    """(doc_id, n_shingles, component_id, n_links) per row of ``docs``.

    component_id is the least doc_id that links reach; n_links is the number of other sets that are similar enough to
    this row's set. Null and empty texts have no shingles and stand alone; rows of equal sets are one class; a null
    doc_id counts as larger than others, and a class of nulls alone has a null component. Other columns are ignored.
    """
    layout = lay_out(bodies_of(docs))
    texts, named = linked_sets(layout, width, percent)
    links = link_counts(named, layout, width, percent)
    least = named.groupBy("root").agg(F.min("ord").alias("least"))
    verdict = settle(named.join(least, "root").join(links, "node", "left").select("node", "least", F.coalesce("n_links", F.lit(0)).alias("n_links")), "verdict")
    discard(named, links)
    layout.drop()
    # a text without shingles meets no verdict; its row number spreads such texts over the tasks
    rows = texts.withColumn("node", F.coalesce("node", -1 - F.col("row"))).join(verdict, "node", "left")

    def known(x: Column) -> Column:
        return F.when(x < F.lit(LAST), x)

    return rows.select(known(F.col("ord")).alias("doc_id"), F.col("n").alias("n_shingles"), known(F.coalesce("least", "ord")).alias("component_id"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"))


def one_of_each(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """``docs`` with one row of each class: the least id, of repeated rows the first as they lie. Texts without words all
    stay, whatever they hold else; null ids stand behind all others; all columns keep their names and values."""
    layout = lay_out(bodies_of(docs))
    texts, named = linked_sets(layout, width, percent)
    stays = named.groupBy("root").agg(F.min(F.struct("ord", "node")).alias("p")).select(F.col("p.node").alias("row"))
    stays = settle(stays.unionByName(texts.where("n = 0").select("row")), "stays")
    discard(texts, named)
    return documents_of(layout.meet(stays, ["doc_id", "body", "had", "rest"]), docs)


def op10_count_vector_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classes(table(spark, sf_dir, "documents"))
