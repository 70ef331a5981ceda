"""Costs of a run, measured: driver rounds, and what Spark's status store holds of their jobs
(stages, shuffled records and bytes, executor time, memory, bytes sent to the driver)."""

from __future__ import annotations

import itertools
import math
import time
from contextlib import contextmanager
from dataclasses import dataclass, field

from py4j.protocol import Py4JJavaError
from pyspark.accumulators import AccumulatorParam
from pyspark.sql import DataFrame, SparkSession

_runs = itertools.count()
# Two-sided 95 % quantiles of Student's t for 1 to 30 degrees of freedom.
T95 = [12.706, 4.303, 3.182, 2.776, 2.571, 2.447, 2.365, 2.306, 2.262, 2.228, 2.201, 2.179, 2.160, 2.145, 2.131,
       2.120, 2.110, 2.101, 2.093, 2.086, 2.080, 2.074, 2.069, 2.064, 2.060, 2.056, 2.052, 2.048, 2.045, 2.042]


class MaxParam(AccumulatorParam):
    """An accumulator that keeps the greatest number."""

    def zero(self, value):
        return 0

    def addInPlace(self, a, b):
        return max(a, b)


@dataclass
class RunLedger:
    """One run's costs. A round is one wait of the driver for all executors.

    ``persists`` counts calls of persist; ``buffer_peak`` is the most values that one task's buffer
    held; ``exact`` is unknown until ``verify`` has counted around the answers.
    """

    method: str = ""
    n: int = 0
    partitions: int = 0
    eps: float | None = None
    rounds: int = 0
    jobs: int = 0
    stages: int = 0
    persists: int = 0
    candidates: int = 0
    rank_err: int = 0
    exact: bool | None = None
    seconds: float = 0.0
    driver_seconds: float = 0.0
    executor_seconds: float = 0.0
    executor_memory: int = 0
    buffer_peak: int = 0
    driver_bytes: int = 0
    shuffle_bytes: int = 0
    shuffled: list = field(default_factory=list)
    steps: list = field(default_factory=list)
    notes: dict = field(default_factory=dict)

    @property
    def net_rows(self) -> int:
        return sum(self.shuffled)

    @property
    def net_bytes(self) -> int:
        return self.shuffle_bytes + self.driver_bytes

    @property
    def full_shuffles(self) -> int:
        """Stages that wrote most of the values to an exchange."""
        return sum(r >= max(1, self.n / 2) for r in self.shuffled)

    @contextmanager
    def round(self, spark: SparkSession, name: str):
        sc, group = spark.sparkContext, f"rank-run-{next(_runs)}"
        before = sc.getLocalProperty("spark.jobGroup.id")
        sc.setJobGroup(group, name)
        began = time.perf_counter()
        try:
            yield self
        finally:
            took = time.perf_counter() - began
            sc.setLocalProperty("spark.jobGroup.id", before)
            self.rounds += 1
            self.seconds += took
            self.steps.append((name, took))
            self._measure(sc, group, took)

    def _measure(self, sc, group: str, took: float) -> None:
        jsc = sc._jsc.sc()
        jsc.listenerBus().waitUntilEmpty()
        store, busy = jsc.statusStore(), 0.0
        for number in sc.statusTracker().getJobIdsForGroup(group):
            self.jobs += 1
            job = store.job(number)
            if job.completionTime().isDefined() and job.submissionTime().isDefined():
                busy += (job.completionTime().get().getTime() - job.submissionTime().get().getTime()) / 1000
            ids = job.stageIds()
            for i in range(ids.size()):
                try:
                    stage = store.lastStageAttempt(ids.apply(i))
                except Py4JJavaError:  # a stage that never ran is the first that the store forgets
                    continue
                if stage.status().toString() != "COMPLETE":
                    continue  # skipped: another job of this run has made it
                self.stages += 1
                self.executor_seconds += stage.executorRunTime() / 1000
                self.executor_memory = max(self.executor_memory, stage.peakExecutionMemory())
                if stage.shuffleWriteRecords():
                    self.shuffled.append(stage.shuffleWriteRecords())
                    self.shuffle_bytes += stage.shuffleWriteBytes()
                else:
                    self.driver_bytes += stage.resultSize()
        self.driver_seconds += max(0.0, took - busy)

    def as_row(self, run_id: str = "") -> tuple:
        return (run_id, *(getattr(self, c.split()[0]) for c in LEDGER_SCHEMA.split(", ")[1:]))


LEDGER_SCHEMA = (
    "run_id string, method string, n long, partitions int, eps double, rounds int, jobs int, stages int, full_shuffles int, persists int, net_rows long, net_bytes long, "
    "driver_bytes long, candidates long, rank_err long, exact boolean, buffer_peak long, executor_memory long, executor_seconds double, driver_seconds double, seconds double"
)


def ledger_table(spark: SparkSession, ledgers: dict[str, RunLedger]) -> DataFrame:
    return spark.createDataFrame([x.as_row(k) for k, x in ledgers.items()], LEDGER_SCHEMA)


def ci95(samples: list[float]) -> tuple[float, float, float]:
    """Mean and its two-sided 95 % t-interval."""
    n = len(samples)
    mean = sum(samples) / n
    if n < 2:
        return mean, mean, mean
    t = T95[n - 2] if n - 2 < len(T95) else 1.96 + 2.5 / (n - 1)
    half = t * math.sqrt(sum((x - mean) ** 2 for x in samples) / (n - 1) / n)
    return mean, mean - half, mean + half
