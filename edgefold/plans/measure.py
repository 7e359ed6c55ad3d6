"""Measures that need runs: kernel time, speedup, achieved rate, bytes that Spark moved, memory, scaling, sweeps, epochs.

Inputs are read, packed and shipped before a kernel is timed, and what is timed ends in a sink without output; timing
starts from Python. Compared kernels take turns, so that neither has the warmer machine.
"""

from __future__ import annotations

import json
import os
import statistics
import subprocess
import sys
import time
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession

from edgefold.plans import cost


def run(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def time_kernels(makes: dict[str, Callable[[], DataFrame]], n: int = 10, warm: int = 1, budget_s: float | None = None) -> dict[str, float | None]:
    """Mean seconds of n runs of each, in turns after `warm` runs; None for what fails (out of memory, say).

    With a budget, no further turn begins beyond it, but each has one timed run.
    """
    times: dict[str, list[float]] = {name: [] for name in makes}
    failed, began = set(), time.time()
    for turn in range(warm + n):
        if turn > warm and budget_s is not None and time.time() - began > budget_s:
            break
        # every other turn goes backwards, so that no kernel always follows the same one
        for name, make in list(makes.items())[:: -1 if turn % 2 else 1]:
            if name in failed:
                continue
            t = time.time()
            try:
                run(make())
            except Exception:  # noqa: BLE001 - a kernel that cannot run has no time
                failed.add(name)
            if turn >= warm:
                times[name].append(time.time() - t)
    return {name: None if name in failed or not t else statistics.fmean(t) for name, t in times.items()}


def time_kernel(make: Callable[[], DataFrame], n: int = 10, warm: int = 1) -> float | None:
    return time_kernels({"it": make}, n, warm)["it"]


def rates(nnz: int, d: int, m: int, seconds: float, bandwidth: float) -> dict[str, float]:
    """Achieved and attainable rate in 1e9 operations a second; bandwidth in 1e9 bytes a second."""
    ai = cost.intensity(nnz / m, d)
    return {"intensity": ai, "achieved": cost.achieved(nnz, d, seconds), "attainable": cost.roofline(ai, bandwidth)}


def bandwidth(megabytes: int = 256, rounds: int = 5) -> float:
    """Of one core, in 1e9 bytes a second: a scaled sum of two arrays into a third, the best of some rounds."""
    import numpy as np

    n = (megabytes << 20) // 24
    a, b, c = np.ones(n), np.ones(n), np.empty(n)
    best = float("inf")
    for _ in range(rounds):
        t = time.perf_counter()
        np.multiply(b, 3.0, out=c)
        np.add(c, a, out=c)
        best = min(best, time.perf_counter() - t)
    return 5 * 8 * n / best / 1e9  # three arrays are read or written by the sum, two by the product


class Moved:
    """Bytes that Spark's stages wrote and read in shuffles, spilled, and read and wrote, between enter and exit.

    From the status store of the driver, which works without a web interface. peak: the most memory that a stage's tasks
    held for execution.
    """

    FIELDS = ("shuffleWriteBytes", "shuffleReadBytes", "memoryBytesSpilled", "diskBytesSpilled", "inputBytes", "outputBytes")

    def __init__(self, spark: SparkSession):
        self.spark, self.bytes, self.peak = spark, {}, 0

    def _stages(self):
        context = self.spark.sparkContext
        gateway = context._gateway
        none, percentiles = gateway.jvm.java.util.ArrayList(), gateway.new_array(gateway.jvm.double, 0)
        stages = context._jsc.sc().statusStore().stageList(none, False, False, percentiles, none)
        return [stages.apply(i) for i in range(stages.size())]

    def __enter__(self):
        self.known = {(s.stageId(), s.attemptId()) for s in self._stages()}
        return self

    def __exit__(self, *_):
        time.sleep(0.2)  # the store is written by listeners
        new = [s for s in self._stages() if (s.stageId(), s.attemptId()) not in self.known]
        self.bytes = {f: sum(getattr(s, f)() for s in new) for f in self.FIELDS}
        self.peak = max((s.peakExecutionMemory() for s in new), default=0)


def peak_memory(spark: SparkSession, make: Callable[[], DataFrame]) -> dict[str, float]:
    """MB: between the phases on disk and in shuffles, and the most that a stage's tasks held."""
    with Moved(spark) as moved:
        run(make())
    stored = moved.bytes["outputBytes"] + moved.bytes["shuffleWriteBytes"]
    return {"stored_mb": stored / 1e6, "execution_mb": moved.peak / 1e6, "spilled_mb": moved.bytes["diskBytesSpilled"] / 1e6}


def sweep(values: Iterable, makes_of: Callable[[object], dict[str, Callable[[], DataFrame]]], n: int = 3, budget_s: float | None = None) -> dict:
    """Seconds of each kernel for each value of a parameter (dimension, degree), and the speedup of `fused` over `two_phase`."""
    out = {}
    for value in values:
        times = time_kernels(makes_of(value), n, budget_s=budget_s)
        out[value] = times | {"speedup": cost.speedup(times.get("two_phase"), times.get("fused"))}
    return out


def scaling(code: str, cores: Iterable[int], env: dict[str, str] | None = None, timeout_s: float = 600) -> dict[int, dict]:
    """What a program prints as its last line of JSON when it is run with CORES set to each number, in a process of its own."""
    out = {}
    for p in cores:
        got = subprocess.run([sys.executable, "-c", code], env=os.environ | (env or {}) | {"CORES": str(p)}, capture_output=True, text=True, timeout=timeout_s)
        if got.returncode:
            raise RuntimeError(got.stderr[-2000:])
        out[p] = json.loads(got.stdout.strip().splitlines()[-1])
    return out


def time_epochs(edges: DataFrame, ids: DataFrame, methods: Iterable[str] = ("fused", "two_phase", "tensor"), epochs: int = 2, **options) -> dict[str, float]:
    """Mean seconds of an epoch for each method, the first one left out."""
    from edgefold.operators.training import train_embedding

    out = {}
    for method in methods:
        _, seconds = train_embedding(edges, ids, epochs=epochs + 1, method=method, **options)
        out[method] = statistics.fmean(seconds[1:])
    return out
