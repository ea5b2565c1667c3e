"""Table functions for SQL."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf
from pyspark.sql.types import LongType, Row, StructType
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult


class FirstOfEach:
    """``first_of_each(TABLE(t) PARTITION BY g ORDER BY (w, id), k)``: the first k rows of each partition, with their place.

    Rows stream by in the order that the call gives; nothing is kept. A partition that holds many rows is one task's, so
    a hot one is better cut before (``sort_groups`` uses the engine's group limit).
    """

    def __init__(self) -> None:
        self.seen = 0

    @staticmethod
    def analyze(rows: AnalyzeArgument, k: AnalyzeArgument) -> AnalyzeResult:
        if not rows.isTable:
            raise ValueError("the first argument is a table")
        return AnalyzeResult(schema=StructType([*rows.dataType.fields]).add("rnk", LongType()))

    def eval(self, row: Row, k: int) -> Iterator[tuple]:
        self.seen += 1
        if self.seen <= k:
            yield (*row, self.seen)


def register(spark: SparkSession) -> None:
    """Make the table functions known to SQL of this session."""
    spark.udtf.register("first_of_each", udtf(FirstOfEach))
