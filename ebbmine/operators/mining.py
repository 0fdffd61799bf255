"""The result of a mining run, and the entry point that dispatches on the method."""

from __future__ import annotations

from contextlib import contextmanager
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.bits import bits_of

RESULT = "items string, k int, supp bigint"
TRACE = "stop int, chunk int, n_chunk bigint, n_watched bigint, n_likely bigint, n_new bigint, n_pruned bigint, n_settled bigint, n_above bigint, tests bigint"


@dataclass
class MiningResult:
    spark: SparkSession
    sets: list[tuple[tuple[str, ...], int]]  # sorted item names, support count
    n: int
    need: int
    trace: list[tuple] = field(default_factory=list)
    passes: float = 0.0

    def itemsets(self, as_array: bool = False) -> DataFrame:
        """items ('|'-joined, ascending), k, supp; or items as an array with the fraction."""
        if as_array:
            rows = [(list(x), len(x), s, s / self.n) for x, s in self.sets]
            return self.spark.createDataFrame(rows, "items array<string>, k int, supp bigint, support double")
        return self.spark.createDataFrame([("|".join(x), len(x), s) for x, s in self.sets], RESULT)

    def trace_frame(self) -> DataFrame:
        return self.spark.createDataFrame(self.trace, TRACE)

    @property
    def tests(self) -> int:
        return sum(t[-1] for t in self.trace)

    @property
    def peak(self) -> int:
        return max((t[3] for t in self.trace), default=0)


def decoded(masks: dict[int, int], items: list[str]) -> list[tuple[tuple[str, ...], int]]:
    return sorted((tuple(sorted(items[p] for p in bits_of(x))), s) for x, s in masks.items())


#: What keeps every stage of a run in one task, for runs of a serial miner.
ONE_TASK = {"spark.sql.shuffle.partitions": "1", "spark.sql.files.maxPartitionBytes": "1099511627776", "spark.sql.leafNodeDefaultParallelism": "1", "spark.sql.files.minPartitionNum": "1"}


@contextmanager
def one_task(spark: SparkSession):
    """Within it scans, shuffles and local frames have one partition each, so that one task runs at a time;
    the session's settings come back afterwards."""
    before = {k: spark.conf.get(k, None) for k in ONE_TASK}
    for k, v in ONE_TASK.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def holding(tx: DataFrame, must: list[str]) -> DataFrame:
    """The baskets that hold every item of `must`: a set with these items has its whole support there."""
    wanted = sorted(set(must))
    full = tx.where(F.col("item").isin(wanted)).groupBy("tid").agg(F.count("*").alias("c")).where(F.col("c") == len(wanted))
    return tx.join(full, "tid", "left_semi")


def mine(
    tx: DataFrame, minsup: str | float, method: str = "ic_b", tids: DataFrame | None = None, only_items: list[str] | None = None, must: list[str] | None = None, never: list[str] | None = None, **options
) -> MiningResult:
    """Frequent itemsets of (tid, item) baskets, by ic_b, ic_4, level, vert, fpt or mllib. `must`: only sets that
    hold all these items; `never`: only sets without any of these; n stays the number of all baskets."""
    from . import interval, levelwise, treegrowth, vertical

    if must or never:
        tids = tids if tids is not None else tx.select("tid").distinct()
        if never:
            tx = tx.where(~F.col("item").isin(sorted(set(never))))
        found = mine(holding(tx, must) if must else tx, minsup, method, tids, only_items, **options)
        found.sets = [(x, s) for x, s in found.sets if set(must or ()) <= set(x)]
        return found

    methods = {
        "ic_b": interval.mine, "ic_4": interval.mine_classic, "level": levelwise.mine, "level_distributed": levelwise.mine_distributed,
        "vert": vertical.mine, "fpt": treegrowth.mine, "mllib": treegrowth.mine_mllib,
    }
    return methods[method](tx, minsup, tids=tids, only_items=only_items, **options)
