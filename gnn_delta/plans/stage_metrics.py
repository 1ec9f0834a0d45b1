"""What the stages of a piece of work cost: task time, and the part of it that moves data between tasks."""

from __future__ import annotations

from contextlib import contextmanager
from dataclasses import dataclass

from pyspark.sql import SparkSession


@dataclass
class StageCost:
    stages: int = 0
    run_s: float = 0.0  # task time
    shuffle_s: float = 0.0  # of it waiting for and writing shuffle blocks
    shuffle_read_bytes: int = 0
    shuffle_write_bytes: int = 0

    @property
    def compute_s(self) -> float:
        return max(0.0, self.run_s - self.shuffle_s)


def _totals(spark: SparkSession) -> dict[tuple[int, int], tuple]:
    gateway = spark.sparkContext._gateway
    store = spark._jsc.sc().statusStore()
    spark._jsc.sc().listenerBus().waitUntilEmpty()
    every = store.stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), gateway.jvm.java.util.ArrayList())
    out = {}
    for i in range(every.size()):
        x = every.apply(i)
        out[x.stageId(), x.attemptId()] = (x.executorRunTime(), x.shuffleFetchWaitTime(), x.shuffleWriteTime(), x.shuffleReadBytes(), x.shuffleWriteBytes())
    return out


@contextmanager
def measured(spark: SparkSession):
    """``with measured(spark) as cost``: filled in at the end from the status store of the driver."""
    cost, before = StageCost(), _totals(spark)
    yield cost
    for key, (run, wait, write, read, wrote) in _totals(spark).items():
        if key not in before:
            cost.stages += 1
            cost.run_s += run / 1e3
            cost.shuffle_s += wait / 1e3 + write / 1e9
            cost.shuffle_read_bytes += read
            cost.shuffle_write_bytes += wrote
