"""Measures of the experiments: times, speedups, growth, cardinalities, program summaries."""

from __future__ import annotations

import math
import statistics
import time
import uuid
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor, wait
from concurrent.futures import TimeoutError as Late
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from ruleweave.lang.graph import components


@dataclass(frozen=True)
class Timing:
    """Seconds of each repeat with median and standard deviation; dnf if it did not finish."""

    seconds: tuple[float, ...]
    dnf: bool = False

    @property
    def median(self) -> float:
        return statistics.median(self.seconds) if self.seconds else math.inf

    @property
    def deviation(self) -> float:
        return statistics.stdev(self.seconds) if len(self.seconds) > 1 else 0.0


def timed(run: Callable[[], object], repeats: int = 5) -> Timing:
    """Evaluation only: loading, compilation and key building belong outside of `run`."""
    out = []
    for _ in range(repeats):
        start = time.perf_counter()
        run()
        out.append(time.perf_counter() - start)
    return Timing(tuple(out))


def run_with_timeout(run: Callable[[], object], seconds: float = 900, repeats: int = 1, spark: SparkSession | None = None) -> Timing:
    """As timed(); being late makes the configuration a DNF, anything else that goes wrong is raised. With spark, the jobs of a late run are
    cancelled and its thread is waited for, so that it does not disturb the next cell."""
    group = f"cell-{uuid.uuid4().hex}"

    def cell() -> Timing:
        if spark is not None:
            spark.sparkContext.setJobGroup(group, "timed cell", interruptOnCancel=True)
        return timed(run, repeats)

    pool = ThreadPoolExecutor(1)
    done = pool.submit(cell)
    try:
        return done.result(timeout=seconds)
    except Late:
        if done.done():  # the run's own
            raise
        while spark is not None and not done.done():
            spark.sparkContext.cancelJobGroup(group)
            wait([done], timeout=1)
        return Timing((), True)
    finally:
        pool.shutdown(wait=False, cancel_futures=True)


def speedup(base: Timing, other: Timing) -> float:
    """How many times faster the other is, by medians."""
    return base.median / other.median


def geomean(values: list[float]) -> float:
    return math.exp(sum(map(math.log, values)) / len(values))


def ratio(a: Timing, b: Timing) -> float:
    return a.median / b.median


def growth(sizes: list[float], seconds: list[float | None]) -> list[tuple[float, float]]:
    """(size ratio, time ratio) of each completed cell against the first."""
    return [(s / sizes[0], t / seconds[0]) for s, t in zip(sizes, seconds, strict=True) if t is not None and seconds[0]]


def cardinality_match(found: DataFrame, expected: int) -> bool:
    return found.count() == expected


def program_summary(compiled) -> tuple[int, int, int, int]:
    """Input relations, derived relations, components, rules."""
    p = compiled.program
    return len(p.edb), len(p.idb), len(components(p)), len(p.rules)


def per_component(evaluation) -> dict[str, tuple[int, int, float]]:
    """For each recursive definition: rounds, rows of its largest delta, seconds in rounds."""
    return {n: (r.rounds, max(r.delta_sizes, default=0), sum(r.seconds)) for n, r in evaluation.fixpoints.items()}
