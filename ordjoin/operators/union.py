"""Ordered union of ranked branches, with or without repeats between them."""

from __future__ import annotations

import heapq
from collections.abc import Iterable, Iterator, Sequence
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def ordered_union(branches: Sequence[DataFrame], head: Sequence[str], k: int, dedup: bool = False) -> DataFrame:
    """The k best of branches that hold their own k best each (head columns and ``weight``).

    With ``dedup``, answers that several branches give count once; if an answer can stand in at most c branches or
    repeat c times in one, ask each branch for c * k.
    """
    rows = reduce(DataFrame.unionByName, [b.select(*head, "weight") for b in branches])
    rows = rows.dropDuplicates([*head]) if dedup else rows
    top = rows.orderBy("weight", *head).limit(k)
    return top.withColumn("rnk", F.row_number().over(Window.orderBy("weight", *head)).cast("long"))  # at most k rows


def merge_cursors(cursors: Iterable[Iterable], dedup: bool = True) -> Iterator:
    """Merge cursors' rows by weight on the driver; repeats are dropped as they come."""
    seen: set = set()
    for row in heapq.merge(*[((r["weight"], tuple(v for n, v in r.asDict().items() if n not in ("weight", "rnk")), n, r) for r in c) for n, c in enumerate(cursors)], key=lambda x: x[:3]):
        if dedup and row[1] in seen:
            continue
        if dedup:
            seen.add(row[1])
        yield row[3]
