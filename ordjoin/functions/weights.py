"""Weight functions of single values, as columns that stay inside code generation."""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F


def cents(x: Column | str) -> Column:
    """Money with two decimals as an exact integer."""
    return F.round((F.col(x) if isinstance(x, str) else x) * 100).cast("long")


def scaled(x: Column | str, digits: int) -> Column:
    return F.round((F.col(x) if isinstance(x, str) else x) * 10**digits).cast("long")


def micros(ts: Column | str) -> Column:
    """A timestamp without time zone as microseconds since 1970, independent of the session's zone."""
    name = ts if isinstance(ts, str) else ts._jc.toString()
    return F.expr(f"timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', `{name}`)")


def age_days(ts: Column, now: Column) -> Column:
    """Older is heavier."""
    return F.datediff(now, ts).cast("long")


def json_number(props: Column, path: str) -> Column:
    return F.get_json_object(props, path).cast("double")


def squared_distance(vector: Column, to: Sequence[float], scale: int = 10**6) -> Column:
    """Squared Euclidean distance to a fixed vector, scaled to an integer so that sums are exact."""
    other = F.array(*[F.lit(float(v)) for v in to])
    return F.round(F.aggregate(F.zip_with(vector, other, lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x) * scale).cast("long")


def user_weight(function: Callable, kind: str = "bigint") -> Callable[..., Column]:
    """A weight of one's own: a function of pandas series, run on Arrow batches. It is charged to the atom that holds its
    variables, so it sees each row once, before any join. Integers or decimals keep sums exact."""
    from pyspark.sql.functions import pandas_udf

    udf = pandas_udf(function, kind)
    return lambda *columns: udf(*[F.col(c) if isinstance(c, str) else c for c in columns])
