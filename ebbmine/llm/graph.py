"""Distributed connected components by alternating stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import dropped, written


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """edges(a, b) of any ordered type -> node, component: the least node it reaches. Nodes without
    an edge to another node are absent; nulls and loops are ignored.

    A large star links every greater neighbour of a node to the node's least neighbour, a small
    star every lesser one; repeated until nothing moves, each component is a star around its least
    node. The number of edges never grows, a node's neighbours are only ever aggregated to a
    minimum (summed before the shuffle), and each round is a table in the shared folder.
    """
    a, b = F.col("a"), F.col("b")
    now = written(edges.where(a.isNotNull() & b.isNotNull() & (a != b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct(), "stars")
    mark = None
    for _ in range(rounds):
        state = now.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("u", "v")).alias("x"), F.bit_xor(F.xxhash64("v", "u")).alias("y")).first()
        if state == mark or not state["n"]:
            break
        mark = state
        both = now.unionAll(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        large = written(large, "stars")
        root = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(root, "u").where(F.col("v") > F.col("m")).select(F.col("v").alias("u"), F.col("m").alias("v"))
        after = written(small.unionAll(root.select("u", F.col("m").alias("v"))).distinct(), "stars")
        dropped(now)
        dropped(large)
        now = after
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionAll(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
