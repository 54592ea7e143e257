"""Timings and counters of experiments."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass

from pyspark import InheritableThread
from pyspark.sql import SparkSession


@dataclass
class Timing:
    """Mean seconds of the runs; None if they were cut off."""

    name: str
    seconds: float | None
    runs: int
    result: object = None

    def __str__(self) -> str:
        return f"{self.name}: {'TIMEOUT' if self.seconds is None else f'{self.seconds:.2f} s'}"


def timed(name: str, run: Callable[[], object], runs: int = 1, timeout_s: float = 600.0, spark: SparkSession | None = None) -> Timing:
    """Mean wall seconds of ``runs`` runs.  With a session, a run beyond the cut-off is cancelled; without one, it is found
    out when the run ends.  In both cases the mean is not recorded."""
    total, result = 0.0, None
    for k in range(runs):
        start = time.perf_counter()
        if spark is None:
            result = run()
        else:
            done, result = _limited(spark, run, timeout_s)
            if not done:
                return Timing(name, None, k + 1)
        total += time.perf_counter() - start
        if total / (k + 1) > timeout_s:
            return Timing(name, None, k + 1, result)
    return Timing(name, total / runs, runs, result)


def _limited(spark: SparkSession, run: Callable[[], object], timeout_s: float) -> tuple[bool, object]:
    """Run in a thread whose jobs are a group; cancel the group when time is up."""
    group, out = f"limited-{uuid.uuid4().hex}", {}

    def work() -> None:
        spark.sparkContext.setJobGroup(group, "a run with a cut-off", True)
        try:
            out["result"] = run()
        except Exception as e:
            out["error"] = e

    thread = InheritableThread(target=work, session=spark)
    thread.start()
    thread.join(timeout_s)
    if thread.is_alive():
        while thread.is_alive():  # the driver may be between two jobs
            spark.sparkContext.cancelJobGroup(group)
            thread.join(1)
        return False, None
    if "error" in out:
        raise out["error"]
    return True, out["result"]
