"""Memory, spill and shuffle of each stage that an action runs, from the session's own status store."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

SHAPE = "stage int, name string, tasks int, run_ms bigint, cpu_ms bigint, gc_ms bigint, peak_memory bigint, memory_spilled bigint, disk_spilled bigint, input_bytes bigint, shuffle_read bigint, shuffle_written bigint"


def _stages(spark: SparkSession) -> list:
    sc = spark.sparkContext
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    found = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), sc._jvm.java.util.ArrayList())
    return [found.apply(i) for i in range(found.size())]


def stage_metrics(spark: SparkSession, action: Callable[[], object]) -> DataFrame:
    """One row for each stage that action has run; peak_memory is the sum over its tasks of what they held at most.

    The store keeps as many stages as spark.ui.retainedStages says; stages that were skipped are left out.
    """
    before = {(x.stageId(), x.attemptId()) for x in _stages(spark)}
    action()
    rows = []
    for x in _stages(spark):
        if (x.stageId(), x.attemptId()) not in before and x.numCompleteTasks():
            rows.append((x.stageId(), x.name(), x.numCompleteTasks(), x.executorRunTime(), x.executorCpuTime() // 10**6, x.jvmGcTime(), x.peakExecutionMemory(), x.memoryBytesSpilled(), x.diskBytesSpilled(), x.inputBytes(), x.shuffleReadBytes(), x.shuffleWriteBytes()))
    return spark.createDataFrame(sorted(rows), SHAPE)
