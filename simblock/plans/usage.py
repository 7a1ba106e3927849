"""Time and memory of a piece of work, from what Spark records of its stages."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import SparkSession


@dataclass
class Usage:
    """``seconds`` is a mean over runs; ``peak_bytes`` the most of any stage of any run."""

    result: object
    seconds: float
    peak_bytes: int
    runs: int


def _stages(spark: SparkSession) -> dict:
    """(stage, attempt) -> execution memory in bytes, each task's peak summed, of the stages still on record."""
    sc = spark.sparkContext._jsc.sc()
    sc.listenerBus().waitUntilEmpty(30_000)
    gateway = spark.sparkContext._gateway
    quantiles = gateway.new_array(gateway.jvm.double, 0)
    found = sc.statusStore().stageList(None, False, False, quantiles, gateway.jvm.java.util.ArrayList())
    return {(s.stageId(), s.attemptId()): s.peakExecutionMemory() for s in (found.apply(i) for i in range(found.size()))}


def measured(spark: SparkSession, work: Callable[[], object], runs: int = 1) -> Usage:
    """Run ``work`` and record what it took.

    Peak memory is the execution memory (hash maps, sorts, shuffles) of the stage that
    held most, its tasks' peaks summed, as if all ran at once: an upper bound for the cluster. Memory
    of Python workers and cached tables isn't in it. Other work of the same session counts too.
    """
    before = max(_stages(spark), default=(-1, 0))[0]
    took, result = [], None
    for _ in range(max(1, runs)):
        start = time.perf_counter()
        result = work()
        took.append(time.perf_counter() - start)
    peak = max([0, *(m for (stage, _), m in _stages(spark).items() if stage > before)])
    return Usage(result, sum(took) / len(took), int(peak), len(took))
