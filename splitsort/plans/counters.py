"""What Spark itself counted while something ran: shuffle, spill, input and output bytes, and seconds."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession


@dataclass(frozen=True)
class Counted:
    seconds: float
    shuffle_bytes: int
    spill_bytes: int
    output_bytes: int
    input_bytes: int
    cpu_seconds: float


def counted(spark: SparkSession, work: Callable[[], object]) -> Counted:
    """Run ``work`` and add up the stages that ran meanwhile, from the driver's own status store."""
    sc = spark.sparkContext._jsc.sc()
    store, first = sc.statusStore(), sc.dagScheduler().nextStageId()
    began = time.perf_counter()
    work()
    took = time.perf_counter() - began
    sc.listenerBus().waitUntilEmpty()
    totals = [0, 0, 0, 0, 0]
    for k in range(first, sc.dagScheduler().nextStageId()):
        try:
            s = store.lastStageAttempt(k)
        except Py4JJavaError:  # a stage that was planned and never submitted
            continue
        for i, v in enumerate((s.shuffleWriteBytes(), s.diskBytesSpilled(), s.outputBytes(), s.inputBytes(), s.executorCpuTime())):
            totals[i] += v
    return Counted(took, *totals[:4], totals[4] / 1e9)


def written(df: DataFrame) -> Callable[[], None]:
    """An action that evaluates all of ``df`` and keeps nothing."""
    return lambda: df.write.format("noop").mode("overwrite").save()
