"""Cost of a piece of work: processor time over all tasks, reserved time, elapsed time, shuffled bytes, scans."""

from __future__ import annotations

import inspect
import time
from dataclasses import asdict, dataclass

import pandas as pd
from pyspark.sql import DataFrame, SparkSession


_worker_cpu: dict[str, object] = {}


def worker_cpu(spark: SparkSession):
    """The session's accumulator of processor seconds in Python workers."""
    sc = spark.sparkContext
    if sc.applicationId not in _worker_cpu:
        _worker_cpu[sc.applicationId] = sc.accumulator(0.0)
    return _worker_cpu[sc.applicationId]


def timed(spark: SparkSession, kernel):
    """``kernel``, a generator over batches or a function of a group or of a pair of cogroups, with the processor time of its worker added up."""
    spent = worker_cpu(spark)
    if inspect.isgeneratorfunction(kernel):

        def generator(batches):
            begin = time.process_time()
            try:
                yield from kernel(batches)
            finally:
                spent.add(time.process_time() - begin)

        return generator

    def measured(*frames):
        begin = time.process_time()
        try:
            return kernel(*frames)
        finally:
            spent.add(time.process_time() - begin)

    # Spark counts the parameters of a function
    return (lambda frame: measured(frame)) if len(inspect.signature(kernel).parameters) == 1 else (lambda left, right: measured(left, right))


@dataclass
class CostReport:
    """cpu_s: processor seconds over all cores and executors, JVM and Python workers; task_s: seconds that tasks ran, waiting included.

    reserved_s: seconds for which executors were held, each counted from when it came to when it went or the work ended.
    """

    name: str
    cpu_s: float
    jvm_cpu_s: float
    python_cpu_s: float
    task_s: float
    reserved_s: float
    elapsed_s: float
    shuffle_bytes: int
    stages: int

    def df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(pd.DataFrame([asdict(self)]))


class CostMeter:
    """``with CostMeter(spark, "svd") as m: ...`` then m.report; work inside ``with m.pause():`` doesn't count."""

    def __init__(self, spark: SparkSession, name: str = "work"):
        self.spark, self.name = spark, name
        self.report: CostReport | None = None
        self._off = [0.0] * 6
        self._seen: dict[tuple[int, int], tuple[float, float, float]] = {}

    def _totals(self) -> list[float]:
        sc = self.spark.sparkContext
        sc._jsc.sc().listenerBus().waitUntilEmpty()
        store = sc._jsc.sc().statusStore()
        empty = sc._gateway.new_array(sc._jvm.double, 0)
        stages = store.stageList(None, False, False, empty, None)
        for k in range(stages.size()):  # the store forgets old stages; what was seen once is kept here
            s = stages.apply(k)
            self._seen[(s.stageId(), s.attemptId())] = (s.executorRunTime() / 1e3, s.executorCpuTime() / 1e9, float(s.shuffleWriteBytes()))
        totals = [sum(x[i] for x in self._seen.values()) for i in range(3)]
        return [*totals, float(len(self._seen)), float(worker_cpu(self.spark).value), time.perf_counter()]

    def _held(self, begin: float, end: float) -> float:
        """Seconds between two moments (of the epoch) in which executors were held, summed over executors."""
        sc = self.spark.sparkContext
        found = sc._jsc.sc().statusStore().executorList(False)
        held = 0.0
        for k in range(found.size()):
            e = found.apply(k)
            if e.id() == "driver" and found.size() > 1:
                continue
            gone = e.removeTime()
            to = min(end, gone.get().getTime() / 1e3) if gone.isDefined() else end
            held += max(0.0, to - max(begin, e.addTime().getTime() / 1e3))
        return held

    def __enter__(self) -> CostMeter:
        self._begin = self._totals()
        self._since = time.time()
        return self

    def pause(self) -> _Pause:
        return _Pause(self)

    def __exit__(self, *_):
        ends = self._totals()
        run, cpu, shuffle, n, python, now = (b - a - o for a, b, o in zip(self._begin, ends, self._off, strict=True))
        until = time.time()
        share = now / max(ends[-1] - self._begin[-1], 1e-9)  # without pauses
        self.report = CostReport(self.name, cpu + python, cpu, python, run, self._held(self._since, until) * share, now, int(shuffle), int(n))


class _Pause:
    def __init__(self, meter: CostMeter):
        self.meter = meter

    def __enter__(self):
        self.begin = self.meter._totals()

    def __exit__(self, *_):
        self.meter._off = [o + b - a for o, a, b in zip(self.meter._off, self.begin, self.meter._totals(), strict=True)]
