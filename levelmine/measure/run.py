"""Measured runs: wall time, memory of the JVM and of the Python workers, bytes read, written and shuffled, CPU use and
I/O rates over time, failures as values."""

from __future__ import annotations

import os
import statistics
import threading
import time
from collections.abc import Callable
from dataclasses import dataclass, field
from pathlib import Path

from pyspark.sql import SparkSession


@dataclass
class Run:
    name: str
    seconds: float | None
    failure: str | None = None
    peak_bytes: int = 0
    cached_bytes: int = 0
    process_bytes: int = 0
    detail: dict = field(default_factory=dict)


@dataclass(frozen=True)
class Stage:
    """One ended stage: seconds since the epoch, bytes, and seconds of its tasks."""

    number: int
    began: float
    ended: float
    read: int
    written: int
    shuffled: int
    spilled: int
    cpu: float
    run: float


def timed(fn: Callable[[], object], repeats: int = 3, warm: int = 1) -> float:
    """Median wall time after warm-up."""
    for _ in range(warm):
        fn()
    taken = []
    for _ in range(repeats):
        began = time.perf_counter()
        fn()
        taken.append(time.perf_counter() - began)
    return statistics.median(taken)


def peak_memory(spark: SparkSession) -> int:
    """Heap bytes that the driver's JVM has had at most; in local mode that is all of Spark's JVM side."""
    beans = spark.sparkContext._jvm.java.lang.management.ManagementFactory.getMemoryPoolMXBeans()
    return sum(b.getPeakUsage().getUsed() for b in beans if str(b.getType().toString()) == "Heap memory")


def reset_peak(spark: SparkSession) -> None:
    for b in spark.sparkContext._jvm.java.lang.management.ManagementFactory.getMemoryPoolMXBeans():
        b.resetPeakUsage()


def cached_bytes(spark: SparkSession) -> int:
    """Memory and disk that cached levels take."""
    return sum(i.memSize() + i.diskSize() for i in spark.sparkContext._jsc.sc().getRDDStorageInfo())


def process_bytes(root: int | None = None) -> int:
    """Resident bytes of this process and all below it (the JVM in local mode, and the Python workers), where /proc is;
    pages that several of them share count for each."""
    parents, resident = {}, {}
    for p in Path("/proc").glob("[0-9]*"):
        try:
            after = (p / "stat").read_text().rpartition(")")[2].split()
            parents[int(p.name)] = int(after[1])
            resident[int(p.name)] = int(after[21]) * os.sysconf("SC_PAGE_SIZE")
        except (OSError, ValueError, IndexError):
            continue
    own, grown = {root or os.getpid()}, True
    while grown:
        more = {p for p, up in parents.items() if up in own} - own
        grown = bool(more)
        own |= more
    return sum(resident.get(p, 0) for p in own)


class MemoryWatch:
    """Samples the process tree while a block runs; `peak` is the most it saw."""

    def __init__(self, every: float = 0.2):
        self.every, self.peak, self._stop = every, 0, threading.Event()

    def __enter__(self) -> MemoryWatch:
        def watch() -> None:
            while not self._stop.is_set():
                self.peak = max(self.peak, process_bytes())
                self._stop.wait(self.every)

        self._thread = threading.Thread(target=watch, daemon=True)
        self._thread.start()
        return self

    def __exit__(self, *_) -> None:
        self._stop.set()
        self._thread.join()


def stages(spark: SparkSession, after: int = -1) -> list[Stage]:
    """Ended stages with a number above `after`, as Spark's own status store has them."""
    sc = spark.sparkContext._jsc.sc()
    sc.listenerBus().waitUntilEmpty(10_000)
    jvm, gateway = spark.sparkContext._jvm, spark.sparkContext._gateway
    held, out = sc.statusStore().stageList(None, False, False, gateway.new_array(jvm.double, 0), jvm.java.util.ArrayList()), []
    for i in range(held.size()):
        s = held.apply(i)
        if s.stageId() <= after or not s.submissionTime().isDefined() or not s.completionTime().isDefined():
            continue
        began, ended = s.submissionTime().get().getTime() / 1000, s.completionTime().get().getTime() / 1000
        out.append(Stage(s.stageId(), began, ended, s.inputBytes(), s.outputBytes(), s.shuffleWriteBytes(), s.diskBytesSpilled(), s.executorCpuTime() / 1e9, s.executorRunTime() / 1e3))
    return sorted(out, key=lambda s: s.number)


def last_stage(spark: SparkSession) -> int:
    return max((s.number for s in stages(spark)), default=-1)


def over_time(found: list[Stage], cores: int, step: float = 1.0) -> list[dict]:
    """For each interval: CPU use of the cores in percent, and MB a second read, written and shuffled; a stage's work is
    spread evenly over its time."""
    if not found:
        return []
    first, last = min(s.began for s in found), max(s.ended for s in found)
    out, at = [], first
    while at < last or not out:
        row = {"second": round(at - first, 3), "cpu_percent": 0.0, "read_mb_s": 0.0, "written_mb_s": 0.0, "shuffled_mb_s": 0.0}
        for s in found:
            share = max(0.0, min(at + step, s.ended) - max(at, s.began)) / max(s.ended - s.began, 1e-3)
            row["cpu_percent"] += 100 * s.cpu * share / step / cores
            for key, size in (("read_mb_s", s.read), ("written_mb_s", s.written), ("shuffled_mb_s", s.shuffled)):
                row[key] += size * share / step / 1e6
        out.append({k: round(v, 3) for k, v in row.items()})
        at += step
    return out


def measured(spark: SparkSession, name: str, fn: Callable[[], object]) -> Run:
    """One run; a failure such as a lack of memory or disk is a value, not an exception. detail: bytes read, written,
    shuffled and spilled, CPU seconds of its tasks, CPU use in percent, and the same by interval (`over_time`)."""
    reset_peak(spark)
    before, began, failure = last_stage(spark), time.perf_counter(), None
    with MemoryWatch() as watch:
        try:
            fn()
        except Exception as e:
            failure = f"{type(e).__name__}: {str(e).splitlines()[0][:200]}"
    seconds, found = time.perf_counter() - began, stages(spark, before)
    cores = spark.sparkContext.defaultParallelism
    detail = {key: sum(getattr(s, key) for s in found) for key in ("read", "written", "shuffled", "spilled", "cpu", "run")}
    detail |= {"cpu_percent": 100 * detail["cpu"] / max(seconds, 1e-3) / cores, "over_time": over_time(found, cores)}
    return Run(name, None if failure else seconds, failure, peak_memory(spark), cached_bytes(spark), watch.peak, detail)
