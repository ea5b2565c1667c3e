"""Time to the k-th answer and the other measures of an enumeration."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


@dataclass
class Curve:
    """(k, seconds to the k-th answer) points in the order of k."""

    points: list[tuple[int, float]]

    def at(self, k: int) -> float | None:
        return next((s for n, s in self.points if n >= k), None)

    @property
    def first(self) -> float | None:
        return self.points[0][1] if self.points else None

    @property
    def last(self) -> float | None:
        return self.points[-1][1] if self.points else None

    def answers_before(self, seconds: float) -> int:
        """Answers delivered within a time (such as a baseline's first answer)."""
        return max((n for n, s in self.points if s <= seconds), default=0)


def tt_curve(run: Callable[[], Iterator], marks: Sequence[int]) -> Curve:
    """Time from the start to each mark, and to the last answer, of one enumeration."""
    began, points, n = time.perf_counter(), [], 0
    wanted = iter(sorted(marks))
    nxt = next(wanted, None)
    for _ in run():
        n += 1
        if n == nxt:
            points.append((n, time.perf_counter() - began))
            nxt = next(wanted, None)
    if not points or points[-1][0] != n:
        points.append((n, time.perf_counter() - began))
    return Curve(points)


def tt_bulk(run: Callable[[int], DataFrame], marks: Sequence[int]) -> Curve:
    """Time to have the first k answers, each k by a run of its own."""
    points = []
    for k in marks:
        began = time.perf_counter()
        run(k).write.format("noop").mode("overwrite").save()
        points.append((k, time.perf_counter() - began))
    return Curve(points)


def max_delay(run: Callable[[], Iterator]) -> tuple[float, float]:
    """(seconds to the first answer, longest time between two)."""
    last, first, worst = time.perf_counter(), 0.0, 0.0
    for n, _ in enumerate(run()):
        now = time.perf_counter()
        if n:
            worst = max(worst, now - last)
        else:
            first = now - last
        last = now
    return first, worst


def last_ratio(ours: Curve, other: Curve) -> float:
    return ours.last / other.last


def is_ranked(df: DataFrame, weight: str = "weight") -> bool:
    """Whether weights never fall along ``rnk`` (of a top-k result)."""
    w = Window.orderBy("rnk")
    return df.withColumn("_was", F.lag(weight).over(w)).where(F.col("_was") > F.col(weight)).isEmpty()


def input_size(frames: Sequence[DataFrame]) -> int:
    """Tuples over all relations."""
    return sum(f.count() for f in frames)


def spark_metrics(spark, since: int = 0) -> dict[str, int]:
    """What Spark's status store still knows from a job id on: jobs, stages, tasks, bytes shuffled and spilled, rows read."""
    tracker, store = spark.sparkContext.statusTracker(), spark.sparkContext._jsc.sc().statusStore()
    jobs = [j for j in tracker.getJobIdsForGroup(None) if j >= since]
    stages = {s for j in jobs for s in (tracker.getJobInfo(j).stageIds if tracker.getJobInfo(j) else [])}
    out = {"jobs": len(jobs), "stages": 0, "tasks": 0, "shuffle_bytes": 0, "spilled_bytes": 0, "input_rows": 0}
    for s in stages:
        info = tracker.getStageInfo(s)
        if info is None:
            continue
        data = store.lastStageAttempt(s)
        out["stages"] += 1
        out["tasks"] += info.numTasks
        out["shuffle_bytes"] += data.shuffleWriteBytes()
        out["spilled_bytes"] += data.diskBytesSpilled()
        out["input_rows"] += data.inputRecords()
    return out


def last_job(spark) -> int:
    """The number of the newest job, as a start for ``spark_metrics``; -1 if there was none."""
    return max(spark.sparkContext.statusTracker().getJobIdsForGroup(None), default=-1)
