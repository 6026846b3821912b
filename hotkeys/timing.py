"""Throughput and latency of methods and kernels: the experiments that are timed."""

from __future__ import annotations

import time
from collections.abc import Callable, Hashable
from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame

from hotkeys.frames import keep, release
from hotkeys.kernels.minmax import MinMaxSummary
from hotkeys.kernels.others import MinHeapSummary
from hotkeys.operators import baselines
from hotkeys.operators import owner_split as engine
from hotkeys.spec import SupportSpec


def seconds(frame: DataFrame) -> float:
    """Time of computing every row of frame, which no one reads."""
    start = time.perf_counter()
    frame.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start


def zipf_list(n: int, a: float, seed: int = 42) -> list[int]:
    """n draws of ranks 1..n in the driver, for kernels alone."""
    sums = np.cumsum(np.arange(1, n + 1, dtype=np.float64) ** -a)
    return (np.searchsorted(sums, np.random.default_rng(seed).random(n) * sums[-1]) + 1).tolist()


def inner_timing(arrivals: list[Hashable], m: int, phi: str, every: int = 10_000, times: int = 3, owners: int = 1) -> dict[str, dict[str, float]]:
    """Per kernel: updates and operations a second of CPU, mean microseconds and comparisons of a query each `every` updates.

    With several owners the kernel is one of theirs, and a query's threshold is that of all their arrivals.

    The kernels take turns, and the fastest of `times` runs counts.
    """
    out: dict[str, dict[str, float]] = {}
    for _ in range(times):
        for name, kernel in (("minmax", MinMaxSummary), ("minheap", MinHeapSummary)):
            own, spent, asked, compared, answers = kernel(m), 0.0, 0, 0, 0
            start = time.process_time()
            for k, e in enumerate(arrivals, 1):
                own.update(e)
                if k % every == 0:
                    before = time.process_time()
                    answers = len(own.query(phi, owners * own.n))
                    spent += time.process_time() - before
                    asked += 1
                    compared += own.stats.comparisons
            total = time.process_time() - start
            made = {"updates_per_s": len(arrivals) / (total - spent), "operations_per_s": (len(arrivals) + asked) / total, "query_us": 1e6 * spent / max(1, asked), "comparisons": compared / max(1, asked), "answers": answers}
            if name not in out or made["operations_per_s"] > out[name]["operations_per_s"]:
                out[name] = made
    return out


METHODS: dict[str, Callable[[DataFrame, SupportSpec], DataFrame]] = {
    "owner_split": lambda s, p: engine.frequent(s, p),
    "owner_split_minheap": lambda s, p: engine.frequent(s, p, inner="minheap"),
    "single_summary": lambda s, p: engine.query(baselines.single_summary(s, p), p.phi),
    "local_merge": lambda s, p: baselines.local_merge(s, p),
    "merge_collector": lambda s, p: baselines.merge_collector(s, p),
    "cell_majority": lambda s, p: baselines.cell_majority(s, p),
}


def throughput(stream: DataFrame, spec: SupportSpec, methods: list[str] | None = None, times: int = 2) -> dict[str, float]:
    """Seconds of each method from stream to answer, the best of some runs."""
    out = {}
    for name, make in METHODS.items():
        if methods is None or name in methods:
            spent = []
            for _ in range(times):
                spent.append(seconds(make(stream, spec)))
                release()
            out[name] = min(spent)
    return out


def scaling(stream: DataFrame, spec: SupportSpec, owners: tuple[int, ...] = (1, 2, 4, 8)) -> dict[int, float]:
    """Seconds of the engine with so many owners, and as many tasks before them; the speed-up is the first over each."""
    out = {}
    for t in owners:
        given = keep(stream.coalesce(t))
        given.count()
        out[t] = seconds(engine.frequent(given, replace(spec, owners=t)))
        release()
    return out


def query_seconds(summary: DataFrame, phi: str, times: int = 3) -> float:
    """Mean time of a query of a summary that is already there."""
    summary.count()
    return sum(seconds(engine.query(summary, phi)) for _ in range(times)) / times


def looped(stream: DataFrame, spec: SupportSpec, limit_s: float = 10.0) -> float:
    """Arrivals a second while the stream is gone through again and again for limit_s."""
    n = stream.count()
    start, rounds = time.perf_counter(), 0
    while time.perf_counter() - start < limit_s:
        seconds(engine.frequent(stream, spec))
        release()
        rounds += 1
    return rounds * n / (time.perf_counter() - start)
