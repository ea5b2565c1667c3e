"""As-of join: for each left row the latest earlier right row of the same key, through the dyadic inequality rewrite."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ordjoin.operators.levels import full_join
from ordjoin.operators.predicates import lt_rewrite
from ordjoin.plans.model import Atom, ConjunctiveQuery


def as_of(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, left_id: Sequence[str]) -> DataFrame:
    """Left rows with an earlier right row: ``left_id`` columns and all of the latest right row's columns.

    Equal times of one key are broken by the right row's other columns. An equi-join on (key, bit, bits above) and a
    map-side aggregate; no nested loop, and a hot key is spread over its time prefixes.
    """
    others = [c for c in right.columns if c != key]
    a, b = Atom("left", left, tuple(left.columns)), Atom("right", right, tuple(right.columns))
    q = lt_rewrite(ConjunctiveQuery((a, b), (*left_id,), ("left", "right")), right_time, left_time)
    pairs = full_join(q)
    best = pairs.groupBy(*left_id).agg(F.max(F.struct(right_time, *[c for c in others if c != right_time])).alias("r"))
    return best.select(*left_id, *[F.col(f"r.{c}").alias(c) for c in others])
