"""Conditional baskets: for each item the weighted sets of more frequent items it occurs with.

Item p's conditional table is searched by one task. It holds distinct masks of the items below p:
at most min(2^p, transactions with p) rows, for frequent items few masks, for rare ones few
transactions; equal masks are summed before the shuffle. This is the common ground of the vertical
and the tree miner: each frequent set is found in the table of its rarest item only.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bits import WORD_BITS, item_ids, signed, word_names
from .layout import Encoded


def conditional(e: Encoded) -> DataFrame:
    """p, w0.., weight."""
    names = word_names(e.words)
    parts = e.enc.select(F.explode(item_ids(e.words)).alias("p"), *names, "weight")
    cut = []
    for j, w in enumerate(names):
        here = F.bitwise_not(F.call_function("shiftleft", F.lit(-1).cast("bigint"), (F.col("p") % WORD_BITS).cast("int")))
        cut.append(F.when(F.floor(F.col("p") / WORD_BITS) > j, F.col(w)).when(F.floor(F.col("p") / WORD_BITS) == j, F.col(w).bitwiseAND(here)).otherwise(F.lit(0).cast("bigint")).alias(w))
    return parts.select("p", *cut, "weight").groupBy("p", *names).agg(F.sum("weight").alias("weight"))


def search(e: Encoded, local: Callable[[np.ndarray, np.ndarray], dict[int, int]]) -> dict[int, int]:
    """Runs local(bits (rows x items below p) as booleans, weights) -> {mask below p: support} on each item's table."""
    words, names = e.words, word_names(e.words)

    def run(key, table):
        p = key[0].as_py()
        rows = np.stack([table[w].to_numpy() for w in names], 1).astype(np.int64).view(np.uint64)
        weight = table["weight"].to_numpy().astype(np.int64)
        held = np.unpackbits(np.ascontiguousarray(rows).view(np.uint8), axis=1, bitorder="little")[:, : max(p, 0)].astype(bool)
        found = local(held, weight) | {0: int(weight.sum())}
        masks = [x | 1 << p for x in found]
        cols = {f"w{j}": pa.array([signed((x >> (64 * j)) & ((1 << 64) - 1)) for x in masks], pa.int64()) for j in range(words)}
        return pa.table(cols | {"supp": pa.array(list(found.values()), pa.int64())})

    shape = ", ".join(f"{w} bigint" for w in names) + ", supp bigint"
    rows = conditional(e).groupBy("p").applyInArrow(run, shape).collect()  # the frequent sets
    return {sum((r[w] & ((1 << 64) - 1)) << (64 * j) for j, w in enumerate(names)): r["supp"] for r in rows}
