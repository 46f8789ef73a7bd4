"""Cost measures from the status store of the running application."""

from __future__ import annotations

import os
import resource
import threading
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

SCHEMA = "run string, seconds double, stages long, input_bytes long, output_bytes long, shuffle_read_bytes long, shuffle_write_bytes long, spill_bytes long, peak_task_memory long, driver_rss long"


def measured(spark: SparkSession, name: str, run: Callable, repeats: int = 1, cold: bool = True) -> DataFrame:
    """A row for each repeat of ``run``: seconds, and the bytes of the stages it ran where the status store tells them.

    ``cold`` drops cached tables before each repeat; the operating system's file cache is left alone. The store is a private
    interface, so figures it does not give are null.
    """
    rows = []
    for k in range(repeats):
        if cold:
            spark.catalog.clearCache()
        group = f"{name}-{time.time_ns()}"
        spark.sparkContext.setJobGroup(group, name)
        began = time.time()
        run()
        seconds = time.time() - began
        rows.append((f"{name}#{k}", seconds, *_figures(spark, group), resource.getrusage(resource.RUSAGE_SELF).ru_maxrss * 1024))
    return spark.createDataFrame(rows, SCHEMA)


def _figures(spark: SparkSession, group: str) -> tuple:
    try:
        tracker = spark.sparkContext.statusTracker()
        store = spark.sparkContext._jsc.sc().statusStore()
        ids = {s for j in tracker.getJobIdsForGroup(group) for s in (tracker.getJobInfo(j).stageIds if tracker.getJobInfo(j) else ())}
        sums = [0] * 6
        for s in ids:
            try:
                x = store.lastStageAttempt(s)
            except Exception:
                continue
            for i, v in enumerate((x.inputBytes(), x.outputBytes(), x.shuffleReadBytes(), x.shuffleWriteBytes(), x.diskBytesSpilled())):
                sums[i] += v
            sums[5] = max(sums[5], x.peakExecutionMemory())
        return (len(ids), *sums)
    except Exception:
        return (None,) * 7


def round_figures(spark: SparkSession, engine: str, report) -> DataFrame:
    """A row for each round of a report whose jobs were named after their rounds: seconds, and the bytes of its stages."""
    rows = [(engine, r["round"], float(r["seconds"]), *_figures(spark, group)) for r, group in zip(report.rounds, report.groups)]
    return spark.createDataFrame(rows, "engine string, round long, seconds double, stages long, input_bytes long, output_bytes long, shuffle_read_bytes long, shuffle_write_bytes long, spill_bytes long, peak_task_memory long")


def tree_memory() -> int:
    """Bytes that this process and all below it hold, the Java process and Python workers among them, from /proc."""
    parents: dict[int, list[int]] = {}
    for name in os.listdir("/proc"):
        if name.isdigit():
            try:
                with open(f"/proc/{name}/stat") as f:
                    parents.setdefault(int(f.read().rsplit(")", 1)[1].split()[1]), []).append(int(name))
            except OSError:
                continue
    total, todo = 0, [os.getpid()]
    while todo:
        pid = todo.pop()
        todo += parents.get(pid, [])
        try:
            with open(f"/proc/{pid}/statm") as f:
                total += int(f.read().split()[1]) * resource.getpagesize()
        except OSError:
            continue
    return total


def with_memory(spark: SparkSession, runs: dict[str, Callable], every: float = 0.2) -> DataFrame:
    """A row for each run: seconds, the peak of the process tree below the driver, and how far that is above the start.

    In local mode the tree has the executor's threads and Python workers; on a cluster it is the driver's side only.
    """
    rows = []
    for name, run in runs.items():
        spark.catalog.clearCache()
        before = peak = tree_memory()
        over = threading.Event()

        def sample():
            nonlocal peak
            while not over.wait(every):
                peak = max(peak, tree_memory())

        watcher = threading.Thread(target=sample, daemon=True)
        watcher.start()
        began = time.time()
        try:
            run()
        finally:
            over.set()
            watcher.join()
        rows.append((name, time.time() - began, peak, peak - before))
    return spark.createDataFrame(rows, "engine string, seconds double, peak_bytes long, grown_bytes long")
