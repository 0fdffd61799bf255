"""Level-wise mining: a whole pass for the candidates of each size."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.shared import discard, kept
from . import layout
from .counting import count
from .lattice import joined, passes_subset_test
from .mining import MiningResult, decoded


def mine(tx: DataFrame, minsup: str | float, counter: str = "auto", folded: str | bool = "auto", tids: DataFrame | None = None, only_items: list[str] | None = None, max_len: int | None = None, group_of: dict | None = None) -> MiningResult:
    """One job a level over the whole encoded table; candidates on the driver."""
    e, need = layout.prepare(tx, minsup, 1, "rank", True, folded, tids, only_items)
    groups = [group_of.get(x) for x in e.items] if group_of else None
    found = {1 << p: c for p, c in enumerate(e.counts) if c >= need}
    trace = [(1, 0, e.n, e.counted, len(found), 0, 0, e.counted, 0, e.counted * e.n)]
    level, k = list(found), 1
    try:
        while level and (max_len is None or k < max_len):
            likely = set(level)
            wanted = sorted(x for x in joined(sorted(level)) if passes_subset_test(x, likely))
            if groups is not None:
                from .lattice import _crowded

                wanted = [x for x in wanted if not _crowded(x, groups)]
            if not wanted:
                break
            got = count(e.enc, wanted, e.words, counter, e.folded, e.slices, len(e.items))
            level = [x for x in wanted if got[x] >= need]
            found |= {x: got[x] for x in level}
            k += 1
            trace.append((k, 0, e.n, len(wanted), len(found), len(wanted), 0, len(wanted), 0, len(wanted) * e.n))
    finally:
        e.release()
    return MiningResult(e.spark, decoded(found, e.items), e.n, need, trace, float(len(trace)))


def mine_distributed(tx: DataFrame, minsup: str | float, tids: DataFrame | None = None, only_items: list[str] | None = None, max_len: int | None = None, **_) -> MiningResult:
    """For candidate sets beyond the driver: each level is a table, joined and tested by equi-joins,
    counted by anchoring each candidate at its rarest item. The result is collected at the end."""
    found, n, need, spark = frequent_tables(tx, minsup, tids, only_items, max_len)
    rows = found.collect()
    return MiningResult(spark, sorted((tuple(sorted(r["names"])), r["supp"]) for r in rows), n, need)


def frequent_tables(tx: DataFrame, minsup: str | float, tids: DataFrame | None = None, only_items: list[str] | None = None, max_len: int | None = None):
    """(names, supp) as a DataFrame, with n, need and the session."""
    spark = tx.sparkSession
    if only_items is not None:
        tids = tids if tids is not None else tx.select("tid").distinct()
        tx = tx.where(F.col("item").isin(only_items))
    n = (tids if tids is not None else tx).select("tid").distinct().count()
    need = layout.need_count(minsup, n) if n else 1
    known = layout.dictionary(tx, need)
    numbers = spark.createDataFrame([(x, k) for k, (x, _) in enumerate(known)], "item string, id int")
    baskets = kept(tx.join(F.broadcast(numbers) if len(known) <= layout.LISTED_ITEMS else numbers, "item").groupBy("tid").agg(F.array_sort(F.collect_list("id")).alias("held")).groupBy("held").agg(F.count("*").alias("weight")), "baskets")
    level = spark.createDataFrame([([k], c) for k, (_, c) in enumerate(known)], "ids array<int>, supp bigint")
    levels, k = [level], 1
    while max_len is None or k < max_len:
        left = level.select("ids", F.slice("ids", 1, k - 1).alias("prefix") if k > 1 else F.lit(0).alias("prefix"), F.element_at("ids", -1).alias("a"))
        right = level.select(F.slice("ids", 1, k - 1).alias("prefix") if k > 1 else F.lit(0).alias("prefix"), F.element_at("ids", -1).alias("b"))
        made = left.join(right, "prefix").where("a < b").select(F.concat("ids", F.array("b")).alias("ids"))
        if k > 1:  # all subsets with one item less are frequent
            below = made.select("ids", F.explode(F.transform(F.sequence(F.lit(0), F.lit(k)), lambda i: F.filter("ids", lambda x, j: j != i))).alias("sub"))
            made = below.join(level.select(F.col("ids").alias("sub")), "sub", "left_semi").groupBy("ids").agg(F.count("*").alias("c")).where(F.col("c") == k + 1).select("ids")
        made = made.withColumn("anchor", F.element_at("ids", -1))
        held = baskets.where(F.size("held") > k).select("held", "weight", F.explode("held").alias("anchor"))
        hits = held.join(made, "anchor").where(F.size(F.array_except("ids", "held")) == 0)
        level = kept(hits.groupBy("ids").agg(F.sum("weight").alias("supp")).where(F.col("supp") >= need), "level")
        if level.isEmpty():
            discard(level)
            break
        levels.append(level)
        k += 1
    every = levels[0]
    for x in levels[1:]:
        every = every.unionAll(x)
    names = F.transform("ids", lambda i: F.get(F.array(*[F.lit(x) for x, _ in known]), i)) if known else F.array().cast("array<string>")
    return every.select(names.alias("names"), "supp"), n, need, spark
