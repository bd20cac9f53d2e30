"""Cost measures: timing, speedups, memory and spill, search space."""

from __future__ import annotations

import math
import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession


@dataclass
class Timing:
    seconds: float
    runs: list[float]
    rows: int


def time_app(fn: Callable[[], DataFrame], repeats: int = 3, warm: bool = True) -> Timing:
    """Mean seconds of materialising fn() without keeping it; building the input is the
    caller's business and not counted."""
    if warm:
        fn().write.format("noop").mode("overwrite").save()
    runs = []
    for _ in range(repeats):
        began = time.perf_counter()
        fn().write.format("noop").mode("overwrite").save()
        runs.append(time.perf_counter() - began)
    return Timing(sum(runs) / len(runs), runs, fn().count())


def geo_speedup(ours: dict[str, float], theirs: dict[str, float]) -> float:
    """Geometric mean of theirs / ours over the cells that both have."""
    both = [k for k in ours if theirs.get(k)]
    return math.exp(sum(math.log(theirs[k] / ours[k]) for k in both) / len(both)) if both else float("nan")


def ablate(variants: dict[str, Callable[[], DataFrame]], repeats: int = 1) -> dict[str, Timing]:
    """Times of variants that must agree; raises if their rows differ."""
    answers = {k: sorted(map(tuple, f().collect()), key=str) for k, f in variants.items()}
    first = next(iter(answers.values()))
    if any(a != first for a in answers.values()):
        raise AssertionError("variants disagree")
    return {k: time_app(f, repeats, warm=False) for k, f in variants.items()}


def assert_same(a: DataFrame, b: DataFrame) -> None:
    x, y = (sorted(map(tuple, df.collect()), key=str) for df in (a, b))
    if x != y:
        raise AssertionError(f"{len(x)} and {len(y)} rows differ")


def relative_error(estimate: float, exact: float) -> float:
    return abs(estimate - exact) / exact if exact else float(estimate != exact)


def memory(spark: SparkSession) -> dict[str, int]:
    """Bytes of storage memory in use and available over all executors."""
    status = spark.sparkContext._jsc.sc().getExecutorMemoryStatus()
    it, used, total = status.iterator(), 0, 0
    while it.hasNext():
        pair = it.next()._2()
        total += int(pair._1())
        used += int(pair._1()) - int(pair._2())
    return {"used": used, "total": total}


def peak_resident_mb() -> float:
    """Peak resident memory of this machine's JVM and Python driver processes (Linux)."""
    import os

    total, me = 0.0, os.getpid()
    for pid in [me, *_children(me)]:
        try:
            with open(f"/proc/{pid}/status") as f:
                total += next(int(line.split()[1]) for line in f if line.startswith("VmHWM")) / 1024
        except (OSError, StopIteration):
            continue
    return total


def _children(pid: int) -> list[int]:
    try:
        with open(f"/proc/{pid}/task/{pid}/children") as f:
            own = [int(x) for x in f.read().split()]
    except OSError:
        return []
    return own + [y for x in own for y in _children(x)]


IO = {"read_bytes": "inputBytes", "shuffle_write_bytes": "shuffleWriteBytes", "shuffle_read_bytes": "shuffleReadBytes", "memory_spill_bytes": "memoryBytesSpilled", "disk_spill_bytes": "diskBytesSpilled"}


def io_of(spark: SparkSession, fn: Callable[[], DataFrame]) -> dict[str, int]:
    """Bytes that all stages of materialising fn() read, shuffled and spilled, from Spark's own stage records."""
    sc = spark.sparkContext
    group = f"io-{uuid.uuid4().hex}"
    sc.setJobGroup(group, "io")
    try:
        fn().write.format("noop").mode("overwrite").save()
    finally:
        sc.setLocalProperty("spark.jobGroup.id", None)
    jsc = sc._jsc.sc()
    jsc.listenerBus().waitUntilEmpty()
    tracker, store = sc.statusTracker(), jsc.statusStore()
    stages = {s for job in tracker.getJobIdsForGroup(group) for s in tracker.getJobInfo(job).stageIds}
    out = dict.fromkeys(IO, 0)
    for s in stages:
        try:
            last = store.lastStageAttempt(s)
        except Exception:  # a stage that was skipped has no record
            continue
        for name, field in IO.items():
            out[name] += int(getattr(last, field)())
    return out
