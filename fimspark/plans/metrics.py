"""Task metrics of the stages that a piece of work ran: seconds of computing and of moving data apart, and what was spilled.

Spilled bytes stand where the published runs would page: a stage that gets more than its memory holds writes the rest to disk, and it shows here.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession


@dataclass
class TaskMetrics:
    """Use as a context: `with TaskMetrics(spark) as m: ...`, then read m.total."""

    spark: SparkSession
    total: dict[str, float] = field(default_factory=dict)

    def _stages(self) -> dict[tuple[int, int], object]:
        sc = self.spark.sparkContext
        jvm = sc._jvm
        empty = jvm.java.util.ArrayList()
        quantiles = sc._gateway.new_array(jvm.double, 0)
        stages = sc._jsc.sc().statusStore().stageList(empty, False, False, quantiles, empty)
        return {(s.stageId(), s.attemptId()): s for s in (stages.apply(i) for i in range(stages.size()))}

    def __enter__(self) -> TaskMetrics:
        self._before = {k: s.executorRunTime() for k, s in self._stages().items()}
        self._began = time.perf_counter()
        return self

    def __exit__(self, *_) -> None:
        self.total = dict.fromkeys(("compute_s", "move_s", "gc_s", "read_mb", "shuffle_mb", "spill_mb"), 0.0)
        self.total["wall_s"] = time.perf_counter() - self._began
        for key, s in self._stages().items():
            if key in self._before:
                continue
            move = s.shuffleWriteTime() / 1e9 + s.shuffleFetchWaitTime() / 1e3
            gc = s.jvmGcTime() / 1e3
            self.total["move_s"] += move
            self.total["gc_s"] += gc
            self.total["compute_s"] += max(0.0, s.executorRunTime() / 1e3 - move - gc)
            self.total["read_mb"] += s.inputBytes() / 1e6
            self.total["shuffle_mb"] += s.shuffleWriteBytes() / 1e6
            self.total["spill_mb"] += s.diskBytesSpilled() / 1e6


def to_frame(spark: SparkSession, rows: list[tuple[str, dict[str, float]]]) -> DataFrame:
    names = ["wall_s", "compute_s", "move_s", "gc_s", "read_mb", "shuffle_mb", "spill_mb"]
    return spark.createDataFrame([(k, *(float(m[n]) for n in names)) for k, m in rows], "method string, " + ", ".join(f"{n} double" for n in names))
