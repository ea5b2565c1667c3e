"""Ranked answers over streams (insert-only)."""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import DataStreamWriter

from ordjoin.operators.levels import sum_topk
from ordjoin.plans.model import ConjunctiveQuery
from ordjoin.plans.ranking import Rank


def ranked_batches(stream: DataFrame, build: Callable[[DataFrame], ConjunctiveQuery], rank: Rank, k: int, sink: Callable[[DataFrame, int], None]) -> DataStreamWriter:
    """The k best answers of each micro-batch against static relations: ``build`` makes the query of a batch."""

    def each(batch: DataFrame, number: int) -> None:
        batch.persist()
        try:
            sink(sum_topk(build(batch), rank, k), number)
        finally:
            batch.unpersist()

    return stream.writeStream.foreachBatch(each)


def running_messages(stream: DataFrame, keys: Sequence[str], weight: Column) -> DataFrame:
    """Min messages kept up to date under inserts: one state row a key (use output mode update or complete)."""
    return stream.groupBy(*keys).agg(F.min(weight).alias("opt"), F.count(F.lit(1)).alias("rows"))


def windowed_best(stream: DataFrame, time: str, late: str, length: str, slide: str | None, keys: Sequence[str], weight: Column) -> DataFrame:
    """The least weight per window and key, with a watermark: one state row a group."""
    window = F.window(time, length, slide) if slide else F.window(time, length)
    return stream.withWatermark(time, late).groupBy(window.alias("w"), *keys).agg(F.min(weight).alias("best"), F.count(F.lit(1)).alias("rows"))


def session_best(stream: DataFrame, time: str, late: str, gap: str, keys: Sequence[str], weight: Column) -> DataFrame:
    return stream.withWatermark(time, late).groupBy(F.session_window(time, gap).alias("w"), *keys).agg(F.min(weight).alias("best"), F.count(F.lit(1)).alias("rows"))


def interval_join(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, within: str, late: str) -> DataFrame:
    """Stream-stream join of left rows with right rows of the same key that follow within an interval. Rows behind the
    watermark are dropped and counted by the engine."""
    a = left.withWatermark(left_time, late)
    b = right.withWatermark(right_time, late)
    on = (a[key] == b[key]) & (b[right_time] > a[left_time]) & (b[right_time] <= a[left_time] + F.expr(f"interval {within}"))
    return a.join(b, on).drop(b[key])


def best_k_so_far(stream: DataFrame, key: str, weight: str, identity: str, k: int) -> DataFrame:
    """The k least (weight, identity) pairs of each key over all batches so far, as rows (key, weight, identity, rnk) that
    are sent again whenever a batch changes them. State: at most k pairs of integers a key; rows behind the k-th go."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def each(name: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        weights, ids = (list(x) for x in state.get) if state.exists else ([], [])
        held = list(zip(weights, ids, strict=True))
        best = held
        for f in frames:
            best = sorted([*best, *zip(f[weight].tolist(), f[identity].tolist(), strict=True)])[:k]
        if best != held:
            state.update(([w for w, _ in best], [i for _, i in best]))
            yield pd.DataFrame({key: [name[0]] * len(best), weight: [w for w, _ in best], identity: [i for _, i in best], "rnk": range(1, len(best) + 1)})

    kinds = dict(stream.dtypes)
    rows = stream.select(F.col(key), F.col(weight).cast("long").alias(weight), F.col(identity).cast("long").alias(identity))
    out = f"{key} {kinds[key]}, {weight} long, {identity} long, rnk long"
    return rows.groupBy(key).applyInPandasWithState(each, out, "weights array<long>, ids array<long>", "update", GroupStateTimeout.NoTimeout)
