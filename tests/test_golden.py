"""Passes, peaks and tests of the trajectories fixed in the survey, and what this round added to the miners."""

import pytest
from pyspark.sql import functions as F

from ebbmine import registry
from ebbmine.operators import counting, interval, layout, result
from ebbmine.operators.mining import mine
from ebbmine.sources import workloads

SF = "/root/testdata/sf0.01"
#: workload, minsup, stops a pass, passes, peak of watched sets, containment tests, of interval counting with the uniform bound.
GOLDEN = [
    ("w2", "0.1", 2, 3.5, 2036, 4_362_444),
    ("w2", "0.1", 10, 3.5, 2445, 4_362_444),
    ("w2", "0.1", 20, 3.4, 2445, 4_259_244),
    ("w1", "0.01", 2, 3.0, 2300, 38_700_375),
    ("w3", "0.1", 4, 2.75, 20, 100_150),
    ("w5", "0.4", 2, 7.0, 231, 891_000),
    ("w6", "0.25", 10, 3.0, 8734, 4_978_850),
    ("w7", "0.6", 10, 3.0, 587, 1_274_250),
]


@pytest.mark.parametrize(("w", "minsup", "stops", "passes", "peak", "tests"), GOLDEN)
def test_trajectory(spark, w, minsup, stops, passes, peak, tests):
    run = registry.run(spark, SF, w, "icb_m2", minsup, chunks=stops, bound="uniform", mode="rank", folded=False)
    assert (round(run.passes, 2), run.peak, run.tests) == (passes, peak, tests)


def test_classic_and_level_trajectories(spark):
    level = registry.run(spark, SF, "w2", "level")
    assert (level.passes, [t[3] for t in level.trace], level.tests) == (4.0, [64, 2016, 511, 15], 4_362_444)
    classic = registry.run(spark, SF, "w2", "ic4_m4", chunks=2, mode="rank")
    assert (classic.passes, classic.peak) == (3.0, 2036)


def test_pruning_bound_saves_tests(spark):
    off, on = (registry.run(spark, SF, "w7", "icb_m10", chunks=10, bound="uniform", mode="rank", prune=p, folded=False) for p in ("none", "bound"))
    assert off.sets == on.sets and (off.tests, on.tests) == (1_368_000, 1_274_250)
    assert sum(t[6] for t in off.trace) == 0 < sum(t[6] for t in on.trace) and all(t[8] <= t[6] for t in on.trace)


def test_must_and_never(spark):
    tx = workloads.w3(spark, "/root/testdata/sf0.001")
    every = mine(tx, "0.05", "level")
    for method in ("ic_b", "vert", "fpt"):
        got = mine(tx, "0.05", method, must=["click"], never=["view"])
        assert got.n == every.n and got.sets == [(x, s) for x, s in every.sets if "click" in x and "view" not in x]
    assert mine(tx, "0.05", "ic_b", must=["no such item"]).sets == []


def test_one_task_leaves_the_settings(spark):
    before = spark.conf.get("spark.sql.shuffle.partitions")
    tx = workloads.w3(spark, "/root/testdata/sf0.001")
    assert mine(tx, "0.1", "ic_4", parallelism=1).sets == mine(tx, "0.1", "level").sets
    assert spark.conf.get("spark.sql.shuffle.partitions") == before


def test_choice_of_strategy():
    assert counting.choose(4, 8) == "wide" and counting.choose(500, 8) == "sliced" and counting.choose(500, 8, folded=True) == "vector"
    assert counting.choose(500, 8, n_chunk=100) == "itemset" and counting.choose(6, 8, n_chunk=5_000) == "grid"
    assert counting.choose(500, 8, n_chunk=1 << 30, distinct=0.1) == "vector"
    assert counting.choose(500, 8, n_chunk=1 << 30, words=100) == "anchor" and counting.choose(500, 8, n_chunk=1 << 30, words=100, mean_size=5) == "vertical"


def test_stored_table_and_snapshots(spark, tmp_path):
    tx = workloads.w3(spark, "/root/testdata/sf0.001")
    e, _ = layout.prepare(tx, "0.1", chunks=3, folded=False)
    layout.store(e, str(tmp_path / "t"))
    back = layout.load(spark, str(tmp_path / "t"))
    assert (back.items, back.counts, back.n, back.sizes) == (e.items, e.counts, e.n, e.sizes)
    want = interval.mine_encoded(back, "0.1")
    folder = str(tmp_path / "s")
    calls, plain = [], interval.count

    def failing(*a, **k):  # lost while a pass runs
        calls.append(1)
        if len(calls) > 6:
            raise OSError("lost")
        return plain(*a, **k)

    interval.count = failing
    try:
        with pytest.raises(OSError):
            interval.mine_encoded(back, "0.1", snapshot=folder)
    finally:
        interval.count = plain
    again = interval.mine_encoded(back, "0.1", snapshot=folder)
    assert again.sets == want.sets and again.trace == want.trace and again.passes == want.passes


def test_encode_arrays_and_common_items(spark):
    df = spark.createDataFrame([(1, ["a", "b", "a"]), (2, ["b", None, "z"]), (3, None), (4, [])], "t int, x array<string>")
    for items in (["b", "a"], ["b", "a"] + [f"q{k}" for k in range(300)]):
        got = {r["tid"]: r["w0"] for r in layout.encode_arrays(df, "t", "x", items).collect()}
        assert got == {1: 3, 2: 1, 3: 0, 4: 0}
    tx = spark.createDataFrame([(1, "a"), (1, "b"), (2, "b"), (2, "c")], "tid int, item string")
    assert [r["item"] for r in result.common_items(layout.prepare(tx, "0.1", folded=False)[0]).collect()] == ["b"]
    got = result.bucketed(spark.range(1, 101).select(F.when(F.col("id") < 101, F.col("id")).alias("v")), "v", [0.25, 0.5, 0.75])
    assert {r[0]: r[1] for r in got.groupBy("v_bucket").count().collect()} == {0: 24, 1: 25, 2: 25, 3: 26}


def test_long_baskets_are_drawn(spark):
    masks = workloads.market_masks(spark, 20_000)
    lengths = masks.select(F.bit_count("w0").alias("l")).agg(F.avg("l"), F.min("l"), F.max("l"), F.stddev("l")).first()
    assert 12 < lengths[0] < 22 and lengths[1] < 6 and lengths[2] > 25 and lengths[3] > 3
    assert masks.exceptAll(workloads.market_masks(spark, 20_000, partitions=3)).count() == 0
