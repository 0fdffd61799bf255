"""The experiments, each as a frame of measurements.

Times include Spark's job latency, so small sizes scale badly here as they do in the published runs.
"""

from __future__ import annotations

from contextlib import nullcontext

from pyspark.sql import DataFrame, SparkSession

from .functions.bits import n_words
from .operators import interval, layout, measures
from .operators.counting import BY_NUMBER, count
from .operators.lattice import joined
from .operators.mining import mine, one_task
from .sources import workloads
from .sources.shared import discard, kept

#: Transactions of the generated tables in these runs; bench.py uses the published 20 million.
ROWS = 1_000_000
NAMES = [f"i{p:02d}" for p in range(64)]


#: The two generated shapes: short baskets of the log, and long ones of correlated patterns with thousands of sets.
SHAPES = {"log": workloads.synthetic_masks, "market": workloads.market_masks}


def resident(spark: SparkSession, n: int = ROWS, chunks: int = 2, partitions: int | None = None, shape: str = "log"):
    """A generated table of a published shape, encoded and kept in memory as bit columns."""
    table = SHAPES[shape](spark, n, partitions=partitions or spark.sparkContext.defaultParallelism)
    return layout.sliced(layout.from_masks(table, NAMES, chunks, resident=True), resident=True)


def _drop(e: layout.Encoded) -> None:
    e.enc.unpersist()
    e.slices.unpersist()


#: The methods that are compared, with their options.
METHODS = {"IC-B": ("ic_b", {"chunks": 2}), "IC-4": ("ic_4", {"chunks": 2}), "LEVEL": ("level", {}), "VERT": ("vert", {}), "FPT": ("fpt", {})}
RUNS = "workload string, method string, tasks string, n_sets int, seconds double"


def _race(spark: SparkSession, sf_dir: str, w: str, minsup: str, serial: bool) -> list[tuple]:
    """Every method on a workload, its baskets written beforehand; serial: all but IC-B in one task, as the rivals were run."""
    tx, rows = kept(workloads.BASKETS[w](spark, sf_dir), "race"), []
    for name, (method, options) in METHODS.items():
        alone = serial and name != "IC-B"
        with one_task(spark) if alone else nullcontext():
            found, took = measures.timed(lambda method=method, options=options, alone=alone: mine(tx.coalesce(1) if alone else tx, minsup, method, **options))
        rows.append((w, name, "one" if alone else "all", len(found.sets), took))
    discard(tx)
    return rows


def e1_methods(spark: SparkSession, sf_dir: str, on: tuple = (("w2", "0.1"), ("w4", "0.05"), ("w5", "0.4"), ("w1", "0.01"))) -> DataFrame:
    """Run time of every method on four workloads, all of them with all tasks."""
    return spark.createDataFrame([r for w, minsup in on for r in _race(spark, sf_dir, w, minsup, False)], RUNS)


def e1_serial(spark: SparkSession, sf_dir: str, on: tuple = (("w2", "0.1"), ("w5", "0.4"))) -> DataFrame:
    """The same against rivals in one task each."""
    return spark.createDataFrame([r for w, minsup in on for r in _race(spark, sf_dir, w, minsup, True)], RUNS)


def e2_vectorised(spark: SparkSession, sf_dir: str, on: tuple = (("w2", "0.1"), ("w4", "0.05")), some: int = 60) -> DataFrame:
    """Counting with the vector kernels and with scalar loops, on the same sets and all transactions of a workload.
    The first `some` pairs of items: scalar loops need minutes for all."""
    out = []
    for w, minsup in on:
        e, _ = layout.prepare(workloads.BASKETS[w](spark, sf_dir), minsup, folded=False)
        masks, rows = sorted(joined([1 << p for p in range(len(e.items))]))[:some], []
        for strategy in ("scalar", "vector", "sliced"):
            count(e.enc, masks[:2], e.words, strategy)
            rows.append((strategy, measures.timed(lambda strategy=strategy, e=e, masks=masks: count(e.enc, masks, e.words, strategy))[1]))
        out += [(w, s, t, measures.gain(rows[0][1], t)) for s, t in rows]
        e.release()
    return spark.createDataFrame(out, "workload string, kernel string, seconds double, gain double")


def e3_speedup(spark: SparkSession, sf_dir: str, n: int = 4 * ROWS) -> DataFrame:
    """One counting pass in 1, 2, 4, ... tasks, up to what runs at once."""
    e = resident(spark, n, 1)
    masks = sorted(joined([1 << p for p in range(64)]))
    rows, k = [], 1
    while k <= spark.sparkContext.defaultParallelism:
        part = e.slices.repartition(k).persist()
        part.count()
        count(e.enc, masks[:2], 1, "sliced", False, part, 64)
        rows.append((k, measures.timed(lambda part=part: count(e.enc, masks, 1, "sliced", False, part, 64))[1]))
        part.unpersist()
        k *= 2
    _drop(e)
    return spark.createDataFrame([(k, t, measures.speedup(rows[0][1], t), measures.efficiency(rows[0][1], t, k)) for k, t in rows], "tasks int, seconds double, speedup double, efficiency double")


def speedup(spark: SparkSession, sf_dir: str, n: int = ROWS, minsup: str = "0.1") -> DataFrame:
    """Whole mining runs, all passes and stops, with the table dealt over 1, 2, 4, ... tasks."""
    rows, k = [], 1
    while k <= spark.sparkContext.defaultParallelism:
        e = resident(spark, n, 2, k)
        found, took = measures.timed(lambda e=e: interval.mine_encoded(e, minsup))
        rows.append((k, len(found.sets), took))
        _drop(e)
        k *= 2
    first = rows[0][2]
    return spark.createDataFrame([(k, m, t, measures.speedup(first, t), measures.efficiency(first, t, k)) for k, m, t in rows], "tasks int, n_sets int, seconds double, speedup double, efficiency double")


def e4_minsup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Run time as the threshold falls, in one task and in all, on both generated shapes (the long one is smaller)."""
    rows = []
    for shape, n, levels in (("log", ROWS, ("0.2", "0.1", "0.05", "0.03")), ("market", ROWS // 20, ("0.3", "0.2", "0.15"))):
        for tasks in (1, spark.sparkContext.defaultParallelism):
            e = resident(spark, n, 2, tasks, shape)
            for minsup in levels:
                found, took = measures.timed(lambda e=e, minsup=minsup: interval.mine_encoded(e, minsup))
                rows.append((shape, tasks, float(minsup), len(found.sets), took))
            _drop(e)
    return spark.createDataFrame(rows, "shape string, tasks int, minsup double, n_sets int, seconds double")


def e4_tables(spark: SparkSession, sf_dir: str, on: tuple = (("w2", ("0.2", "0.1", "0.05")), ("w4", ("0.1", "0.05")))) -> DataFrame:
    """The same on the node log and the line attributes, encoding included. The baskets of a workload are
    written once for all its runs, beside their times: seconds hold folding, item counts, encoding, chunks and mining."""
    rows = []
    for w, levels in on:
        tx = workloads.BASKETS[w](spark, sf_dir)
        baskets = layout.gathered(tx)
        for alone in (True, False):
            for minsup in levels:
                with one_task(spark) if alone else nullcontext():
                    found, took = measures.timed(lambda tx=tx, minsup=minsup, held=layout.in_one_task(baskets) if alone else baskets: mine(tx, minsup, "ic_b", baskets=held))
                rows.append((w, "one" if alone else "all", float(minsup), len(found.sets), took))
        discard(baskets)
    return spark.createDataFrame(rows, "workload string, tasks string, minsup double, n_sets int, seconds double")


def e5_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Transactions a second by the size of the table: small tables pay for the jobs only."""
    rows = []
    for shape, n, minsup in [("log", n, "0.1") for n in (10_000, 100_000, 1_000_000)] + [("market", n, "0.2") for n in (10_000, 100_000)]:
        e = resident(spark, n, shape=shape)
        found, took = measures.timed(lambda e=e, minsup=minsup: interval.mine_encoded(e, minsup))
        rows.append((shape, n, len(found.sets), took, n / took))
        _drop(e)
    return spark.createDataFrame(rows, "shape string, n bigint, n_sets int, seconds double, per_second double")


def e6_stops(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The interval between stops: passes, stops, peak and time for 1, 2, 4, 10 and 20 stops a pass."""
    rows = []
    for chunks in (1, 2, 4, 10, 20):
        found, took = measures.timed(lambda chunks=chunks: mine(workloads.w2(spark, sf_dir), "0.1", "ic_b", chunks=chunks, bound="uniform"))
        rows.append((chunks, float(found.passes), int(found.peak), int(found.tests), took))
    return spark.createDataFrame(rows, "stops_a_pass int, passes double, peak_watched bigint, tests bigint, seconds double")


def e8_layout(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes of the masks against (tid, item) rows of two LONGs, and time to count sets on bits and on item arrays."""
    rows = []
    for w, minsup in (("w2", "0.1"), ("w6", "0.25"), ("w8", "0.01")):
        tx = workloads.BASKETS[w](spark, sf_dir)
        e, _ = layout.prepare(tx, minsup, folded=False)
        masks = sorted(joined([1 << p for p in range(min(20, len(e.items)))]))
        times = [measures.timed(lambda e=e, masks=masks, s=s: count(e.enc, masks, e.words, s))[1] for s in ("set", "sliced")]
        rows.append((w, layout.size_bytes(e.n, len(e.items)), sum(e.counts) * 16, n_words(len(e.items)), *times))
        e.release()
    return spark.createDataFrame(rows, "workload string, mask_bytes bigint, row_bytes bigint, words int, set_s double, bits_s double")


def e9_loops(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Which loop is outside: every counting strategy for few and for many sets."""
    e, _ = layout.prepare(workloads.w2(spark, sf_dir), "0.1", folded=False)
    every = sorted(joined([1 << p for p in range(len(e.items))]))
    rows = []
    for sets in (every[:4], every[:200]):
        for number, strategy in BY_NUMBER.items():
            if strategy not in ("set", "scalar"):
                rows.append((number, strategy, len(sets), measures.timed(lambda sets=sets, strategy=strategy: count(e.enc, sets, e.words, strategy))[1]))
    e.release()
    return spark.createDataFrame(rows, "number string, strategy string, sets int, seconds double")


ALL = {f.__name__: f for f in (e1_methods, e1_serial, e2_vectorised, e3_speedup, speedup, e4_minsup, e4_tables, e5_size, e6_stops, e8_layout, e9_loops)}
