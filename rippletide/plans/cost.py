"""What a run costs, from Spark's own stage metrics."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession


class Meter:
    """Seconds, and over the stages that ended inside: the largest execution memory of a stage, MB
    shuffled, and rows read from shuffles, which is the work that moves."""

    def __init__(self, spark: SparkSession) -> None:
        self.spark = spark
        self.seconds = self.peak_mb = self.shuffle_mb = 0.0
        self.stages = self.rows = 0

    def _all(self) -> list:
        sc = self.spark.sparkContext
        sc._jsc.sc().listenerBus().waitUntilEmpty()
        none = sc._gateway.new_array(sc._jvm.double, 0)
        found = sc._jsc.sc().statusStore().stageList(None, False, False, none, sc._jvm.java.util.ArrayList())
        return [found.apply(k) for k in range(found.size())]

    def __enter__(self) -> Meter:
        self._before = max((s.stageId() for s in self._all()), default=-1)
        self._began = time.perf_counter()
        return self

    def __exit__(self, *_) -> None:
        self.seconds = time.perf_counter() - self._began
        new = [s for s in self._all() if s.stageId() > self._before]
        self.stages = len(new)
        self.peak_mb = max((s.peakExecutionMemory() for s in new), default=0) / 2**20
        self.shuffle_mb = sum(s.shuffleWriteBytes() for s in new) / 2**20
        self.rows = sum(s.shuffleReadRecords() for s in new)


def plan_mb(df: DataFrame) -> float:
    """Size of a table as the optimizer knows it, for the memory that a graph itself takes."""
    return float(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) / 2**20
