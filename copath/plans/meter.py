"""What a run costs: time limits, tasks at a time, peak memory."""

from __future__ import annotations

import threading
import time
import uuid
from contextlib import contextmanager

from pyspark import InheritableThread
from pyspark.sql import SparkSession

from copath.plans.store import one_process


def together(*jobs) -> list:
    """Results of functions that each wait for Spark, run at the same time."""
    out: list = [None] * len(jobs)
    failed: list[Exception] = []

    def one(i: int) -> None:
        try:
            out[i] = jobs[i]()
        except Exception as e:  # raised again below
            failed.append(e)

    threads = [InheritableThread(target=one, args=(i,)) for i in range(len(jobs))]
    for t in threads:
        t.start()
    for t in threads:
        t.join()
    if failed:
        raise failed[0]
    return out


@contextmanager
def deadline(spark: SparkSession, seconds: float | None):
    """Jobs inside are cancelled once the time is up; gives a function that says whether it is."""
    if seconds is None:
        yield lambda: False
        return
    context, group, end = spark.sparkContext, f"copath-{uuid.uuid4().hex}", time.monotonic() + seconds
    context.setJobGroup(group, "mining run with a deadline", True)

    def stop() -> None:
        # Again and again, as the driver may start one more job before it notices.
        while not done.wait(0.5):
            if time.monotonic() > end:
                context.cancelJobGroup(group)

    done = threading.Event()
    watcher = threading.Thread(target=stop, daemon=True)
    watcher.start()
    try:
        yield lambda: time.monotonic() > end
    finally:
        done.set()
        watcher.join()
        context.setLocalProperty("spark.jobGroup.id", None)


@contextmanager
def parallelism(spark: SparkSession, n: int | None):
    """At most ``n`` partitions, and so tasks at a time, in every shuffle and scan inside."""
    if n is None:
        yield
        return
    names = ("spark.sql.shuffle.partitions", "spark.sql.files.maxPartitionNum")
    before = {k: spark.conf.get(k, None) for k in names}
    for k in names:
        spark.conf.set(k, str(n))
    try:
        yield
    finally:
        for k, x in before.items():
            if x is None:
                spark.conf.unset(k)
            else:
                spark.conf.set(k, x)


def _pools(spark: SparkSession):
    beans = spark.sparkContext._jvm.java.lang.management.ManagementFactory
    return [p for p in beans.getMemoryPoolMXBeans() if p.getType().toString().lower().startswith("heap")]


def reset_peak(spark: SparkSession) -> None:
    """Starts a new measurement of the peak in this process; executors elsewhere report theirs since they started."""
    if one_process(spark):
        spark.sparkContext._jvm.java.lang.System.gc()
        for p in _pools(spark):
            p.resetPeakUsage()


def peak_mb(spark: SparkSession) -> float:
    """Peak heap: of this process since ``reset_peak``, or the sum over executors."""
    if one_process(spark):
        return sum(p.getPeakUsage().getUsed() for p in _pools(spark)) / (1 << 20)
    found = spark.sparkContext._jsc.sc().statusStore().executorList(True)
    total = 0
    for i in range(found.size()):
        peak = found.apply(i).peakMemoryMetrics()
        if peak.isDefined():
            total += peak.get().getMetricValue("JVMHeapMemory")
    return total / (1 << 20)
