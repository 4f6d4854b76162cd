"""What runs cost: stage times of Spark's own status store, split into communication and computation."""

from __future__ import annotations

from collections.abc import Callable
from time import perf_counter, sleep

from pyspark.sql import DataFrame, SparkSession


def _stages(spark: SparkSession) -> dict[tuple[int, int], tuple[float, float, float, int]]:
    """Finished stages: seconds of their tasks, of these waiting for and writing shuffles, and bytes that went through shuffles."""
    sc = spark.sparkContext
    no_quantiles = sc._gateway.new_array(sc._jvm.double, 0)
    found = sc._jsc.sc().statusStore().stageList(None, False, False, no_quantiles, sc._jvm.java.util.ArrayList())
    out = {}
    for i in range(found.size()):
        s = found.apply(i)
        if s.status().toString() == "COMPLETE":
            moving = s.shuffleFetchWaitTime() / 1e3 + s.shuffleWriteTime() / 1e9
            out[s.stageId(), s.attemptId()] = (s.executorRunTime() / 1e3, moving, s.executorCpuTime() / 1e9, s.shuffleReadBytes() + s.shuffleWriteBytes())
    return out


def measured(spark: SparkSession, work: Callable[[], object]) -> dict[str, float]:
    """Seconds of `work`, task seconds of its stages, of these communication (shuffle waits and writes) and computation, and MB shuffled."""
    before = _stages(spark)
    t = perf_counter()
    work()
    seconds = perf_counter() - t
    sleep(0.2)  # the store hears of stages a little later
    new = [v for k, v in _stages(spark).items() if k not in before]
    tasks, moving, cpu, size = (sum(x[i] for x in new) for i in range(4))
    return {
        "seconds": round(seconds, 3), "task_seconds": round(tasks, 3), "communication": round(moving, 3), "computation": round(max(0.0, tasks - moving), 3),
        "cpu_seconds": round(cpu, 3), "shuffle_mb": round(size / 1e6, 3),
    }


def run(df: DataFrame) -> None:
    """All rows, kept nowhere."""
    df.write.format("noop").mode("overwrite").save()
