"""Run-time and memory of a step: forced without a result, measured from the session's own counters."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession


@dataclass(frozen=True)
class Cost:
    """seconds until all rows were made; shuffle and spill in bytes; heap: largest use of an executor's heap so far, in bytes."""

    seconds: float
    shuffle_bytes: int
    spill_bytes: int
    task_bytes: int
    heap_bytes: int


def _stages(spark: SparkSession) -> dict[int, tuple[int, int, int]]:
    """(bytes shuffled, spilled, most execution memory) of each stage that the session still knows of."""
    gateway, store = spark.sparkContext._gateway, spark._jsparkSession.sparkContext().statusStore()
    none = gateway.jvm.java.util.ArrayList()
    listed = store.stageList(none, False, False, gateway.new_array(gateway.jvm.double, 0), none)
    rows = (listed.apply(i) for i in range(listed.size()))
    return {s.stageId(): (s.shuffleWriteBytes(), s.diskBytesSpilled(), s.peakExecutionMemory()) for s in rows}


def _heap(spark: SparkSession) -> int:
    found = spark._jsparkSession.sparkContext().statusStore().executorList(False)
    peaks = [found.apply(i).peakMemoryMetrics() for i in range(found.size())]
    used = [p.get().getMetricValue("JVMHeapMemory") for p in peaks if p.isDefined()]
    return max([0, *used])


def timed(df: DataFrame) -> float:
    """Seconds until all rows of df are made; nothing is kept."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def memory_probe(spark: SparkSession, step: Callable[[], object]) -> Cost:
    """Runs a step that forces its own work and tells what it cost. Stages of other threads count too."""
    before = _stages(spark)
    began = time.perf_counter()
    step()
    seconds = time.perf_counter() - began
    spark._jsparkSession.sparkContext().listenerBus().waitUntilEmpty(30_000)
    new = [v for k, v in _stages(spark).items() if k not in before]
    return Cost(seconds, sum(v[0] for v in new), sum(v[1] for v in new), max([0, *(v[2] for v in new)]), _heap(spark))
