"""What a run cost: wall seconds, executor CPU and bytes, read from the status store of the application."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession


@dataclass(frozen=True)
class Cost:
    """cpu_seconds is the CPU time of executor threads; Python workers aren't in it, so compare methods that stay in the JVM."""

    wall_seconds: float
    cpu_seconds: float
    input_bytes: int
    output_bytes: int
    shuffle_bytes: int
    spill_bytes: int
    stages: int

    @property
    def io_bytes(self) -> int:
        """Bytes that moved through files: tables and intermediates read and written, and shuffled."""
        return self.input_bytes + self.output_bytes + self.shuffle_bytes

    def as_dict(self) -> dict:
        return asdict(self) | {"io_bytes": self.io_bytes}


def _stages(spark: SparkSession) -> dict:
    """(stage id, attempt) -> stage data, of the stages that the application still holds (spark.ui.retainedStages)."""
    gateway, context = spark.sparkContext._gateway, spark.sparkContext._jsc.sc()
    context.listenerBus().waitUntilEmpty()
    listed = context.statusStore().stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), gateway.jvm.java.util.ArrayList())
    found = (listed.apply(i) for i in range(listed.size()))
    return {(s.stageId(), s.attemptId()): s for s in found}


def measure(spark: SparkSession, action: Callable[[], object]) -> Cost:
    """Runs the action and adds up the stages that it ran; other jobs at the same time would be counted too."""
    before = set(_stages(spark))
    start = time.perf_counter()
    action()
    wall = time.perf_counter() - start
    ran = [s for key, s in _stages(spark).items() if key not in before]
    total = lambda field: sum(getattr(s, field)() for s in ran)
    return Cost(
        round(wall, 3), round(total("executorCpuTime") / 1e9, 3), total("inputBytes"), total("outputBytes"), total("shuffleReadBytes"),
        total("memoryBytesSpilled") + total("diskBytesSpilled"), sum(s.status().toString() == "COMPLETE" for s in ran),
    )


def measure_query(spark: SparkSession, make: Callable[[], DataFrame]) -> Cost:
    """The cost of building a frame, with what it runs on the way, and of all its rows."""
    return measure(spark, lambda: make().write.format("noop").mode("overwrite").save())


def speed_up(slow: Cost, fast: Cost) -> float:
    """How many times the CPU time of the faster one the slower one takes."""
    return slow.cpu_seconds / fast.cpu_seconds if fast.cpu_seconds else float("inf")


def percent_better(base: Cost, other: Cost) -> float:
    """By how many per cent the other's CPU time lies below that of the base; negative if above."""
    return 100 * (1 - other.cpu_seconds / base.cpu_seconds) if base.cpu_seconds else 0.0
