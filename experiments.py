"""Time to the k-th answer of ordered enumeration, batch and engine plans; prints one JSON line a point.

``python experiments.py SF_DIR LENGTH [BATCH_UP_TO]``: paths of ``LENGTH`` edges (the experiment's self-join chain), from
the first answer to the last; the complete batch runs where it has at most ``BATCH_UP_TO`` answers.
``python experiments.py SF_DIR walk``: the lightest of a number of walks that can't be built.
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ordjoin import workloads as W
from ordjoin.operators import baselines, cursor, dp, levels
from ordjoin.operators import sequential as S


def session() -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{os.environ.get('BENCH_CPUS', '8')}]")
        .config("spark.sql.shuffle.partitions", "16")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "12g")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def clock(f) -> float:
    began = time.perf_counter()
    f()
    return round(time.perf_counter() - began, 3)


def into_nothing(df) -> None:
    df.write.format("noop").mode("overwrite").save()


def walks(sf: str) -> None:
    spark = session()
    q, rank = W.walk(spark, sf), W.chain_sum(4)
    answers = int(dp.count_answers(q).first()["answers"])
    into_nothing(levels.sum_topk(q, rank, 1))
    for k in (1, 1000, 100_000):
        print(json.dumps({"sf": sf, "workload": "walk", "answers": answers, "method": "level-wise top-k", "k": k, "seconds": clock(lambda k=k: into_nothing(levels.sum_topk(q, rank, k)))}), flush=True)
    spark.stop()


def main(sf: str, length: int, batch_up_to: int) -> None:
    spark = session()
    edge = spark.createDataFrame(W.T.edges(spark, sf).toArrow()).repartition(16).cache()
    n = edge.count()
    W.T.edges = lambda *_: edge  # every method starts from the same cached relation
    q, rank = W.chain(spark, sf, length), W.chain_sum(length)
    answers = int(dp.count_answers(q).first()["answers"])
    say = lambda **x: print(json.dumps({"sf": sf, "length": length, "n": n * length, "answers": answers} | x), flush=True)

    into_nothing(levels.sum_topk(q, rank, 10))
    into_nothing(baselines.engine_topk(W.chain(spark, sf, 2), W.chain_sum(2), 10))
    ours = []
    for k in (1, 10, 1000, 100_000, 1_000_000, 4_000_000):
        if k <= answers:
            ours.append((k, clock(lambda k=k: into_nothing(levels.sum_topk(q, rank, k)))))
            say(method="level-wise top-k", k=k, seconds=ours[-1][1])
            levels.release()
    first, p = time.perf_counter(), dp.ranked(q, rank)
    cut = dp.prune(p, dp.tau_from_root(p, 1000))
    stats = S.EnumStats()
    run = iter(S.SumHeap(S.collect_groups(cut), stats=stats))
    next(run)
    say(method="pruned, queue on the driver", k=1, seconds=round(time.perf_counter() - first, 3))
    for _ in range(999):
        if next(run, None) is None:
            break
    say(method="pruned, queue on the driver", k=1000, seconds=round(time.perf_counter() - first, 3), most_open=stats.most_open, pushes=stats.pushes, most_pushes_a_step=stats.most_pushes_a_step)
    for k in (1, 1000):
        say(method="engine join, sort, limit", k=k, seconds=clock(lambda k=k: into_nothing(baselines.engine_topk(q, rank, k))))
    if answers <= batch_up_to:
        batch = baselines.batch_reduce_join_sort(q, rank)
        whole = clock(lambda: into_nothing(batch.select("weight")))
        start = clock(lambda: next(batch.toLocalIterator()))
        say(method="reduce, join, sort: first answer", k=1, seconds=start, ours_before_it=max((k for k, s in ours if s <= start), default=0), first_ratio=round(start / ours[0][1], 1))
        say(method="reduce, join, sort: last answer", k=answers, seconds=whole)
        began, given, tau, step = time.perf_counter(), 0, None, 2
        with cursor.RisingBound(q, rank) as rounds:
            tau = int(rounds.p.frames[rounds.p.root].agg(F.min("_opt")).first()[0]) + 1
            while given < answers:
                out = rounds.up_to(tau).orderBy("weight", *q.head)
                into_nothing(out)
                given += rounds.kept[-1][-1][1]
                say(method="rising bound, each round sorted", k=given, seconds=round(time.perf_counter() - began, 3), bound=tau)
                tau, step = tau + step, step * 2
        say(method="last answer: rising bound by batch", ratio=round((time.perf_counter() - began) / whole, 2))
    spark.stop()


if __name__ == "__main__":
    where = sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.01"
    if sys.argv[2:3] == ["walk"]:
        walks(where)
    else:
        main(where, int(sys.argv[2]) if len(sys.argv) > 2 else 4, int(sys.argv[3]) if len(sys.argv) > 3 else 10_000_000)
