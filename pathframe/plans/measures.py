"""What running something cost: wall time, bytes shuffled and spilled, processor time, as Spark's own status store has them."""

from __future__ import annotations

import time
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass

from pyspark.sql import SparkSession


@dataclass
class Measures:
    wall_s: float = 0.0
    cpu_s: float = 0.0
    shuffle_written: int = 0
    shuffle_read: int = 0
    spilled: int = 0
    stages: int = 0


def _stages(spark: SparkSession) -> list:
    sc, gateway = spark.sparkContext, spark.sparkContext._gateway
    none = gateway.jvm.java.util.ArrayList
    found = sc._jsc.sc().statusStore().stageList(none(), False, False, gateway.new_array(gateway.jvm.double, 0), none())
    return [found.apply(i) for i in range(found.size())]


@contextmanager
def measured(spark: SparkSession) -> Iterator[Measures]:
    """Measures of the jobs that the session runs inside; filled in at the end. Stages that the store has dropped by then
    (it keeps the last thousand) don't count."""
    before = max((s.stageId() for s in _stages(spark)), default=-1)
    out, began = Measures(), time.perf_counter()
    yield out
    out.wall_s = time.perf_counter() - began
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
    for s in _stages(spark):
        if s.stageId() > before and s.numCompleteTasks():
            out.stages += 1
            out.cpu_s += s.executorCpuTime() / 1e9
            out.shuffle_written += s.shuffleWriteBytes()
            out.shuffle_read += s.shuffleReadBytes()
            out.spilled += s.diskBytesSpilled()
