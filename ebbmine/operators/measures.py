"""Measures of runs: time, speedup, efficiency, gain, and what the trace of a miner tells."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .mining import MiningResult


def timed(f: Callable):
    """(value, seconds)."""
    began = time.perf_counter()
    value = f()
    return value, time.perf_counter() - began


def speedup(t1: float, tk: float) -> float:
    return t1 / tk


def efficiency(t1: float, tk: float, k: int) -> float:
    return speedup(t1, tk) / k


def gain(off: float, on: float) -> float:
    """What a feature brings: time without over time with it."""
    return off / on


def summary(spark: SparkSession, runs: dict[str, MiningResult]) -> DataFrame:
    """One row a run: passes, stops, peak of watched sets, containment tests, pruned sets (and those of them pruned as supersets), results."""
    rows = [
        (name, float(r.passes), sum(t[0] > 0 for t in r.trace), int(r.peak), int(r.tests), int(sum(t[6] for t in r.trace)), int(sum(t[8] for t in r.trace)), len(r.sets), max((len(x) for x, _ in r.sets), default=0))
        for name, r in runs.items()
    ]
    return spark.createDataFrame(rows, "run string, passes double, stops int, peak_watched bigint, tests bigint, pruned bigint, pruned_above bigint, n_sets int, k_max int")
