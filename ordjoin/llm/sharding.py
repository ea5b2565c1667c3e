"""Sharding on a consistent-hash ring with virtual nodes and bounded loads, in DataFrame functions only.

Keys and virtual nodes lie on a ring of hashes. A key goes to the shard of the next virtual node clockwise; when that
shard is full, keys behind its share continue clockwise to the next shard with room. A shard's bound is its share of
the rows, so counts differ by one at most (law ``rows``), and only overflow leaves its home.

The ring has a fixed number of cells. A first pass counts the rows of each cell (bounded by the ring, not by the data);
the driver walks these counts round the ring and gives each cell one or a few ranges of ranks with their shard and
first slot; a second pass ranks rows inside their cells and looks its range up. A cell that holds many rows (a key that
stands often, nulls, or a large table) is ranked in pieces of bounded size, whose counts give their first ranks. Rows are
written once with the number that deals them into pieces, so both passes see the same; hand over ids, sizes and
checksums, not texts.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ordjoin.llm.common import lean, settle, table

SHARDS, NODES, CELLS = 8, 64, 1 << 13
PIECE_ROWS = 1 << 20  # rows of a cell that one task ranks


def _hash(text: str) -> int:
    import hashlib

    return int.from_bytes(hashlib.blake2b(text.encode(), digest_size=8).digest(), "big")


@dataclass(frozen=True)
class Ring:
    """``owner[c]``: the shard of cell c; ``walk(c)``: the other shards in clockwise order from it."""

    shards: int
    nodes: int = NODES
    cells: int = CELLS

    def owners(self) -> list[int]:
        """Virtual nodes stand on cells; a cell belongs to the first node at or after it."""
        marks: dict[int, int] = {}
        for shard in range(self.shards):
            for v in range(self.nodes):
                marks.setdefault(_hash(f"{shard}/{v}") % self.cells, shard)
        out, now = [0] * self.cells, marks[min(marks)]
        for c in range(self.cells - 1, -1, -1):
            now = marks.get(c, now)
            out[c] = now
        return out

    def place(self, counts: dict[int, int], bounds: list[int]) -> list[tuple[int, int, int, int, int]]:
        """(cell, first rank, end rank, shard, first slot): home shares first, then overflow, clockwise.

        Overflow of a cell enters the next cells' shards in ring order until one has room.
        """
        owner, used, out = self.owners(), [0] * self.shards, []
        spill: list[tuple[int, int, int]] = []
        for c in range(self.cells):
            n, s = counts.get(c, 0), owner[c]
            here = min(n, bounds[s] - used[s])
            if here:
                out.append((c, 0, here, s, used[s]))
                used[s] += here
            if here < n:
                spill.append((c, here, n))
        for c, a, n in spill:
            step = c
            while a < n:
                step += 1
                s = owner[step % self.cells]
                room = min(n - a, bounds[s] - used[s])
                if room:
                    out.append((c, a, a + room, s, used[s]))
                    used[s] += room
                    a += room
                elif step > c + self.cells:  # a shard that owns no cell after this one
                    s = max(range(self.shards), key=lambda x: bounds[x] - used[x])
                    room = min(n - a, bounds[s] - used[s])
                    out.append((c, a, a + room, s, used[s]))
                    used[s] += room
                    a += room
        return out


def assign(docs: DataFrame, key: Column, shards: int = SHARDS, nodes: int = NODES, cells: int = CELLS, piece_rows: int = PIECE_ROWS) -> DataFrame:
    """Add ``shard`` and ``slot`` to ``docs`` (columns of these names are replaced); counts of shards differ by one at most.

    ``key``: any column (an id). Equal keys, nulls among them, share a cell and are dealt in pieces if they are many; rows
    of one key may swap places. Empty tables give no rows.
    """
    ring = Ring(shards, nodes, cells)
    docs = docs.drop("shard", "slot")
    spot = F.xxhash64(key)
    rows = docs.withColumns({"_ring_spot": spot, "_ring_cell": F.pmod(spot, F.lit(cells)).cast("int"), "_ring_row": F.monotonically_increasing_id()})
    rows = settle(rows, "ring")
    spark = docs.sparkSession
    with lean(spark):
        counts = {r["_ring_cell"]: r["count"] for r in rows.groupBy("_ring_cell").count().collect()}  # at most ``cells`` rows
    total = sum(counts.values())
    bounds = [total // shards + (s < total % shards) for s in range(shards)]
    ranges = spark.createDataFrame(ring.place(counts, bounds), "_ring_cell int, _ring_from long, _ring_to long, shard int, _ring_slot long")
    cuts = {c: -(-n // piece_rows) for c, n in counts.items() if n > piece_rows}  # about a piece for every ``piece_rows`` rows
    first = [(c, 0, 0) for c in counts if c not in cuts]
    if cuts:
        dealt = F.broadcast(spark.createDataFrame(list(cuts.items()), "_ring_cell int, _ring_cuts long"))
        rows = rows.join(dealt, "_ring_cell", "left").withColumn("_ring_piece", F.coalesce(F.pmod(F.xxhash64("_ring_row"), F.col("_ring_cuts")), F.lit(0)).cast("int")).drop("_ring_cuts")
        with lean(spark):
            sizes = rows.where(F.col("_ring_cell").isin(list(cuts))).groupBy("_ring_cell", "_ring_piece").count().collect()
        before = dict.fromkeys(cuts, 0)
        for r in sorted(sizes, key=lambda r: (r["_ring_cell"], r["_ring_piece"])):
            first.append((r["_ring_cell"], r["_ring_piece"], before[r["_ring_cell"]]))
            before[r["_ring_cell"]] += r["count"]
    else:
        rows = rows.withColumn("_ring_piece", F.lit(0))
    starts = spark.createDataFrame(first, "_ring_cell int, _ring_piece int, _ring_first long")
    kinds = dict(docs.dtypes)
    place = Window.partitionBy("_ring_cell", "_ring_piece").orderBy("_ring_spot", *[f"`{c}`" for c in docs.columns if kinds[c] in _SORTABLE], "_ring_row")
    ranked = rows.withColumn("_ring_at", F.row_number().over(place) - 1).join(F.broadcast(starts), ["_ring_cell", "_ring_piece"])
    rank = (F.col("_ring_at") + F.col("_ring_first")).cast("long")
    placed = ranked.withColumn("_ring_rank", rank).join(F.broadcast(ranges), "_ring_cell").where("_ring_rank >= _ring_from and _ring_rank < _ring_to")
    made = (F.col("_ring_slot") + F.col("_ring_rank") - F.col("_ring_from")).alias("slot")
    return placed.select(*[f"`{c}`" for c in docs.columns], "shard", made)


_SORTABLE = {"bigint", "int", "smallint", "tinyint", "string", "double", "float", "boolean", "date", "timestamp", "timestamp_ntz", "binary"}


def op7_consistent_hash_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Law ``rows``: equal texts are rows of their own and may lie in different shards (only the law ``key`` would hold
    groups together). Null texts have size 1 and the checksum of nothing; null ids are one key, dealt in pieces."""
    text = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    docs = table(spark, sf_dir, "documents").select("doc_id", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text).alias("text_crc32"))
    out = assign(docs, F.col("doc_id"))
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
