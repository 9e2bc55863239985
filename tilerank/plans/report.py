"""What a run has cost: passes, jobs, stages, bytes read, shuffled and spilled, from the session's own status store."""

from __future__ import annotations

import time
from dataclasses import asdict, dataclass

from pyspark.sql import SparkSession


@dataclass
class Report:
    """``passes`` and ``written`` as the factorization counted them, the rest as Spark did."""

    seconds: float
    stages: int = 0
    tasks: int = 0
    bytes_read: int = 0
    bytes_written: int = 0
    shuffle_read: int = 0
    shuffle_written: int = 0
    spilled: int = 0
    passes: int | None = None
    written: int | None = None


def finished_stages(spark: SparkSession) -> dict[tuple[int, int], object]:
    """Stage data by (stage, attempt)."""
    sc = spark.sparkContext
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    store = sc._jsc.sc().statusStore()
    none = sc._gateway.new_array(sc._jvm.double, 0)
    found = store.stageList(sc._jvm.java.util.ArrayList(), False, False, none, sc._jvm.java.util.ArrayList())
    stages = [found.apply(i) for i in range(found.size())]
    return {(x.stageId(), x.attemptId()): x for x in stages if x.numCompleteTasks()}


def run_report(spark: SparkSession, run) -> tuple[object, Report]:
    """``run()``'s result, and what it cost. Other jobs of the session at the same time are counted too."""
    before = set(finished_stages(spark))
    start = time.time()
    out = run()
    report = Report(time.time() - start)
    for key, x in finished_stages(spark).items():
        if key not in before:
            report.stages += 1
            report.tasks += x.numCompleteTasks()
            report.bytes_read += x.inputBytes()
            report.bytes_written += x.outputBytes()
            report.shuffle_read += x.shuffleReadBytes()
            report.shuffle_written += x.shuffleWriteBytes()
            report.spilled += x.diskBytesSpilled()
    for name in ("passes", "written"):
        if isinstance(getattr(out, name, None), int):
            setattr(report, name, getattr(out, name))
    return out, report


def as_row(report: Report) -> dict:
    return asdict(report)
