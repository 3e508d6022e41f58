"""Physical measures of what a block of code ran: task time, JVM CPU, shuffled bytes and waits, read from Spark's own status store.

The JVM's CPU time leaves out the Python workers: what is neither CPU of the JVM nor a wait for a
shuffle is the share of the Python kernels and of reading.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass

from pyspark.sql import SparkSession


@dataclass
class TaskReport:
    seconds: float = 0.0
    tasks: int = 0
    run_s: float = 0.0
    jvm_cpu_s: float = 0.0
    shuffle_wait_s: float = 0.0
    shuffle_written: int = 0
    shuffle_read: int = 0
    spilled: int = 0

    @property
    def jvm_share(self) -> float:
        """CPU time of the JVM in the tasks' run time."""
        return self.jvm_cpu_s / self.run_s if self.run_s else 0.0

    @property
    def dominant(self) -> str:
        """C20: where most of the tasks' time went."""
        rest = max(0.0, self.run_s - self.jvm_cpu_s - self.shuffle_wait_s)
        return max((("jvm", self.jvm_cpu_s), ("python and reading", rest), ("shuffle", self.shuffle_wait_s)), key=lambda x: x[1])[0]


def _stages(spark: SparkSession) -> dict[tuple[int, int], object]:
    """The attempts that the status store holds (the last ``spark.ui.retainedStages``), by id."""
    sc = spark.sparkContext
    jsc, gateway = sc._jsc.sc(), sc._gateway
    jsc.listenerBus().waitUntilEmpty()
    held = jsc.statusStore().stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), gateway.jvm.java.util.ArrayList())
    stages = (held.apply(i) for i in range(held.size()))
    return {(x.stageId(), x.attemptId()): x for x in stages}


@contextmanager
def measured(spark: SparkSession) -> Iterator[TaskReport]:
    """Fills its report when the block ends, with all stages that began in it, of whatever thread of the application."""
    before, report, at = set(_stages(spark)), TaskReport(), time.perf_counter()
    try:
        yield report
    finally:
        report.seconds = time.perf_counter() - at
        for key, x in _stages(spark).items():
            if key in before:
                continue
            report.tasks += x.numCompleteTasks()
            report.run_s += x.executorRunTime() / 1e3
            report.jvm_cpu_s += x.executorCpuTime() / 1e9
            report.shuffle_wait_s += x.shuffleFetchWaitTime() / 1e3 + x.shuffleWriteTime() / 1e9
            report.shuffle_written += x.shuffleWriteBytes()
            report.shuffle_read += x.shuffleReadBytes()
            report.spilled += x.diskBytesSpilled()
