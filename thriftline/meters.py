"""Measures of a run: wall times and their blend, CPU, shuffled bytes, the share of communication, modelled bits."""

from __future__ import annotations

import statistics
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from thriftline.sources.io import discard


def blend(mean: float, peak: float) -> float:
    """The plotted time: six tenths of the mean and four tenths of the peak."""
    return 0.6 * mean + 0.4 * peak


def barrier(spark: SparkSession) -> None:
    """Waits until no job runs and all events of earlier ones are in."""
    while spark.sparkContext.statusTracker().getActiveJobsIds():
        time.sleep(0.01)
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(30_000)


def totals(spark: SparkSession) -> dict[str, int]:
    """Sums over all stages that the application's status store keeps."""
    store = spark.sparkContext._jsc.sc().statusStore()
    jvm = spark.sparkContext._jvm
    stages = store.stageList(jvm.java.util.ArrayList(), False, False, jvm.scala.Array.emptyDoubleArray(), jvm.java.util.ArrayList())
    out = {"shuffle_bytes": 0, "cpu_ns": 0, "run_ms": 0, "wait_ms": 0}
    for n in range(stages.size()):
        stage = stages.apply(n)
        out["shuffle_bytes"] += stage.shuffleWriteBytes()
        out["cpu_ns"] += stage.executorCpuTime()
        out["run_ms"] += stage.executorRunTime()
        out["wait_ms"] += stage.shuffleFetchWaitTime() + stage.shuffleWriteTime() // 1_000_000
    return out


def timed(spark: SparkSession, make: Callable[[], DataFrame], repeats: int = 3) -> dict[str, float]:
    """Runs a query to its end several times, after a barrier each, and gives its measures; those of the stages are of the last run.

    ``comm_share`` is the time of tasks spent writing and awaiting shuffled data; broadcasts are not in it.
    """
    walls, counted = [], {}
    for _ in range(repeats):
        barrier(spark)
        before = totals(spark)
        begin = time.perf_counter()
        discard(make())
        walls.append(time.perf_counter() - begin)
        barrier(spark)
        after = totals(spark)
        counted = {k: after[k] - before[k] for k in after}
    mean, peak = statistics.fmean(walls), max(walls)
    out = {"wall_mean": mean, "wall_max": peak, "wall_median": statistics.median(walls), "blend": blend(mean, peak)}
    return out | {"shuffle_bytes": counted["shuffle_bytes"], "cpu_s": counted["cpu_ns"] / 1e9, "comm_share": counted["wait_ms"] / max(1, counted["run_ms"])}
