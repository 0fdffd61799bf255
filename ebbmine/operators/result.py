"""Operations on results (items '|'-joined, k, supp): profiles, top lists, borders, comparisons."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.bits import bits_of, item_ids, word_names
from .counting import count
from .layout import Encoded


def parts(items: Column) -> Column:
    return F.split(items, r"\|")


def immediate_subsets(items: Column) -> Column:
    """The sets with one item less, joined again; none for single items."""
    p = parts(items)
    less = F.transform(p, lambda x: F.array_join(F.filter(p, lambda y: y != x), "|"))
    return F.when(F.size(p) > 1, less).otherwise(F.array().cast("array<string>"))


def profile(freq: DataFrame) -> DataFrame:
    return freq.groupBy("k").agg(F.count("*").alias("n_sets"), F.min("supp").alias("min_supp"), F.max("supp").alias("max_supp"))


def longest(freq: DataFrame) -> DataFrame:
    return freq.agg(F.max("k").alias("k_max"), F.count("*").alias("n_sets"))


def maximal(freq: DataFrame) -> DataFrame:
    """Frequent sets without a frequent superset."""
    below = freq.select(F.explode(immediate_subsets(F.col("items"))).alias("items")).distinct()
    return freq.join(below, "items", "left_anti").select("items", "k", "supp")


def closed(freq: DataFrame) -> DataFrame:
    """Frequent sets without a superset of equal support."""
    below = freq.select(F.explode(immediate_subsets(F.col("items"))).alias("items"), "supp").groupBy("items").agg(F.max("supp").alias("above"))
    return freq.join(below, "items", "left").where(F.col("above").isNull() | (F.col("above") < F.col("supp"))).select("items", "k", "supp")


def top_k(freq: DataFrame, k: int, per_size: bool = True) -> DataFrame:
    """The k sets of greatest support (of each size), ties by name; with their rank."""
    order = [F.desc("supp"), F.asc("items")]
    if per_size:
        return freq.withColumn("rank", F.row_number().over(Window.partitionBy("k").orderBy(*order))).where(F.col("rank") <= k)
    best = freq.orderBy(*order).limit(k)
    return best.withColumn("rank", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(*order)))  # k rows


def contrast(a: DataFrame, b: DataFrame) -> DataFrame:
    """Sets frequent in a and not in b."""
    return a.join(b.select("items"), "items", "left_anti").select("items", "k", "supp")


def compare(a: DataFrame, b: DataFrame) -> DataFrame:
    """Sets that two results do not agree on; empty if they are equal."""
    left, right = a.select("items", F.col("supp").alias("supp_a")), b.select("items", F.col("supp").alias("supp_b"))
    return left.join(right, "items", "full_outer").where(~F.col("supp_a").eqNullSafe(F.col("supp_b")))


def support_of(e: Encoded, itemsets: list[list[str]], strategy: str = "auto") -> DataFrame:
    """Supports of given item sets; sets with an item outside the dictionary have support 0."""
    number = {x: p for p, x in enumerate(e.items)}
    masks = [sum(1 << number[i] for i in set(s)) if all(i in number for i in s) else None for s in itemsets]
    got: dict[int, int] = {}
    for chunk in range(len(e.sizes)):
        for x, c in count(e.chunk(chunk), sorted({m for m in masks if m}), e.words, strategy).items():
            got[x] = got.get(x, 0) + c
    rows = [("|".join(sorted(set(s))), len(set(s)), got.get(m, e.n if m == 0 else 0) if m is not None else 0) for s, m in zip(itemsets, masks)]
    return e.spark.createDataFrame(rows, "items string, k int, supp bigint")


def names_of(mask: int, items: list[str]) -> list[str]:
    return sorted(items[p] for p in bits_of(mask))


def support_by_group(tx: DataFrame, groups: DataFrame, columns: list[str], kind: str = "rollup") -> DataFrame:
    """Item supports by groups of transactions (groups: tid and the columns), with subtotals (rollup, cube, grouping_sets)."""
    rows = tx.join(groups.select("tid", *columns), "tid")
    if kind == "grouping_sets":  # each column alone and all columns together, by item
        sets = [[F.col(c), F.col("item")] for c in columns] + [[*map(F.col, columns), F.col("item")]]
        grouped = rows.groupingSets(sets, *[F.col(c) for c in (*columns, "item")])
    else:
        grouped = getattr(rows, kind)(*columns, "item")
    return grouped.agg(F.count("*").alias("supp"), F.grouping_id().cast("int").alias("level")).where("item is not null")


def support_pivot(tx: DataFrame, groups: DataFrame, column: str, values: list[str]) -> DataFrame:
    """item and a column a group: the item's support there, 0 where it has none. The groups are named by the caller,
    so that no job looks for them first."""
    rows = tx.join(groups.select("tid", column), "tid")
    return rows.groupBy("item").pivot(column, values).agg(F.count("item")).na.fill(0, values)


def common_items(e: Encoded) -> DataFrame:
    """chunk, item: the items that every transaction of a chunk holds (the bit-and of its masks)."""
    held = e.enc.groupBy("chunk").agg(*[F.bit_and(w).alias(w) for w in word_names(e.words)])
    names = F.array(*[F.lit(x) for x in e.items]) if e.items else F.array().cast("array<string>")
    return held.select("chunk", F.explode(F.transform(item_ids(e.words), lambda p: F.get(names, p.cast("int")))).alias("item"))


def ranked(freq: DataFrame, buckets: int = 4) -> DataFrame:
    """Places of a set among those of its size: rank, dense_rank, percent_rank by support, and its bucket of `buckets`."""
    by_support = Window.partitionBy("k").orderBy(F.desc("supp"))
    return freq.select(
        "items", "k", "supp", F.rank().over(by_support).alias("rank"), F.dense_rank().over(by_support).alias("dense_rank"),
        F.round(F.percent_rank().over(by_support), 9).alias("percent_rank"), F.ntile(buckets).over(Window.partitionBy("k").orderBy(F.desc("supp"), "items")).alias("bucket"),
    )


def near_support(freq: DataFrame, reach: int) -> DataFrame:
    """How many sets of the same size lie within `reach` transactions of a set's support (itself included)."""
    frame = Window.partitionBy("k").orderBy("supp").rangeBetween(-reach, reach)
    return freq.select("items", "k", "supp", F.count("*").over(frame).alias("near"))


def bucketed(df: DataFrame, column: str, shares: list[float], accuracy: int = 10_000) -> DataFrame:
    """df with `<column>_bucket`: how many of the column's percentile edges a value reaches (null stays null).
    The edges are one aggregate, joined back as a single row."""
    edges = df.agg(F.percentile_approx(column, shares, accuracy).alias("_edges"))
    reached = F.size(F.filter("_edges", lambda x: F.col(column) >= x))
    return df.join(F.broadcast(edges)).withColumn(f"{column}_bucket", F.when(F.col(column).isNotNull(), reached)).drop("_edges")


def trace_steps(trace: DataFrame) -> DataFrame:
    """The trace with its neighbours: sets watched at the stop before and after, tests so far, share of all tests.
    One row a stop, so that a single window is bounded by the number of stops."""
    order = Window.partitionBy(F.lit(0)).orderBy("stop")
    whole = Window.partitionBy(F.lit(0))
    return trace.select(
        "stop", "chunk", "n_watched", F.lag("n_watched").over(order).alias("before"), F.lead("n_watched").over(order).alias("after"),
        F.sum("tests").over(order.rowsBetween(Window.unboundedPreceding, 0)).alias("tests_so_far"), (F.sum("tests").over(order) / F.sum("tests").over(whole)).alias("share"),
    )
