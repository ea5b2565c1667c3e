"""Connected components of a link table by alternating star contractions; nothing is collected."""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ordjoin.llm.common import discard, settle

MAX_ROUNDS = 60


def _settled(edges: DataFrame, name: str) -> tuple[DataFrame, tuple]:
    """The edges, written, and a mark of what they are, observed while they were written."""
    seen = Observation()
    marks = [F.bit_xor(F.xxhash64("u", "v", F.lit(i))).alias(f"x{i}") for i in (0, 1)]
    out = settle(edges.observe(seen, F.count(F.lit(1)).alias("n"), *marks), name)
    got = seen.get
    return out, (got["n"], got["x0"], got["x1"])


def components(links: DataFrame) -> DataFrame:
    """(node, root) for each node of ``links`` (a, b: long); root is the least node of its component. Settled.

    Rounds grow with the logarithm of a component's diameter; each is two joins on the links and is settled.
    """
    edges, mark = _settled(links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "links")
    for _ in range(MAX_ROUNDS):
        if not mark[0]:
            break
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("e")).select("e.u", "e.v").where("u <> v").distinct()
        before = edges
        edges, new = _settled(small, "stars")
        discard(before)
        if new == mark:
            break
        mark = new
    else:
        raise RuntimeError("components did not settle")
    roots = edges.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("root"))
    out = settle(roots.unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()), "roots")
    discard(edges)
    return out
