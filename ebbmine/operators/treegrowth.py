"""Pattern growth: conditional baskets grown into prefix trees, each mined by one task.
mine_mllib runs Spark's own implementation for cross-checks."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bits import item_ids
from ..sources.shared import discard, kept
from . import layout
from .conditional import search
from .mining import MiningResult, decoded


class _Tree:
    """A prefix tree in arrays: item, parent and count of each node, and the nodes of each item."""

    def __init__(self):
        self.item, self.up, self.count, self.down, self.of = [-1], [-1], [0], [{}], {}

    def add(self, path, count: int) -> None:
        at = 0
        for p in path:
            nxt = self.down[at].get(p)
            if nxt is None:
                nxt = self.down[at][p] = len(self.item)
                self.item.append(p)
                self.up.append(at)
                self.count.append(0)
                self.down.append({})
                self.of.setdefault(p, []).append(nxt)
            self.count[nxt] += count
            at = nxt

    def single_path(self):
        """The only path as [(item, count)], or None if the tree branches."""
        out, at = [], 0
        while self.down[at]:
            if len(self.down[at]) > 1:
                return None
            at = next(iter(self.down[at].values()))
            out.append((self.item[at], self.count[at]))
        return out

    def above(self, p: int):
        for node in self.of[p]:
            path, at = [], self.up[node]
            while at:
                path.append(self.item[at])
                at = self.up[at]
            yield path[::-1], self.count[node]


def _grow(rows, need: int, prefix: int, left: int, found: dict[int, int]) -> None:
    """rows: (items in falling frequency, count) pairs of one conditional base."""
    if left <= 0:
        return
    total: dict[int, int] = {}
    rows = list(rows)
    for path, c in rows:
        for p in path:
            total[p] = total.get(p, 0) + c
    total = {p: c for p, c in total.items() if c >= need}
    tree = _Tree()
    for path, c in rows:
        tree.add([p for p in path if p in total], c)
    path = tree.single_path()
    if path is not None:  # every subset of a single path is frequent; its count is that of its deepest item
        sets = [(prefix, 0)]
        for p, c in path:
            sets += [(m | 1 << p, k + 1) for m, k in sets if k < left]
            for m, k in sets:
                if m >> p & 1 and k:
                    found.setdefault(m, c)
        return
    for p in sorted(total, key=lambda p: (total[p], -p)):
        mask = prefix | 1 << p
        found[mask] = total[p]
        _grow(tree.above(p), need, mask, left - 1, found)


def mine(tx: DataFrame, minsup: str | float, tids: DataFrame | None = None, only_items: list[str] | None = None, max_len: int | None = None, **_) -> MiningResult:
    e, need = layout.prepare(tx, minsup, 1, "rank", True, False, tids, only_items)
    left = (max_len or 1 << 30) - 1

    def local(held: np.ndarray, weight: np.ndarray) -> dict[int, int]:
        found: dict[int, int] = {}
        _grow(((np.flatnonzero(row).tolist(), int(w)) for row, w in zip(held, weight)), need, 0, left, found)
        found.pop(0, None)
        return found

    found = search(e, local)
    e.release()
    return MiningResult(e.spark, decoded(found, e.items), e.n, need)


#: At most so many equal baskets are one row of what is dealt to the tasks of Spark's miner.
COPIES = 64


def dealt_by_path(e: layout.Encoded, tasks: int) -> DataFrame:
    """A folded table as arrays of item numbers (ids) with up to COPIES copies a row, written once in ranges of such
    arrays: those that share a path of a prefix tree, equal ones above all, meet in one task, not in the trees of all."""
    ids = e.enc.select(item_ids(e.words).alias("ids"), "weight")
    blocks = ids.select("ids", "weight", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("weight") - 1, F.lit(COPIES).cast("bigint"))).alias("at"))
    return kept(blocks.repartitionByRange(tasks, "ids", "at").select("ids", F.least(F.lit(COPIES), F.col("weight") - F.col("at")).cast("int").alias("copies")), "paths")


def mine_mllib(tx: DataFrame, minsup: str | float, tids: DataFrame | None = None, only_items: list[str] | None = None, **_) -> MiningResult:
    from pyspark.ml.fpm import FPGrowth

    e, need = layout.prepare(tx, minsup, 1, "rank", True, True, tids, only_items)
    rows = []
    if e.items:
        tasks = max(e.spark.sparkContext.defaultParallelism, int(e.spark.conf.get("spark.sql.shuffle.partitions")))
        paths = dealt_by_path(e, tasks)
        every = paths.select("ids", F.explode(F.sequence(F.lit(1), F.col("copies")))).select("ids")  # a row a transaction
        miner = FPGrowth(itemsCol="ids", minSupport=(need - 0.5) / e.n, numPartitions=min(len(e.items), tasks))
        rows = miner.fit(every).freqItemsets.where(F.col("freq") >= need).collect()
        discard(paths)
    e.release()
    return MiningResult(e.spark, sorted((tuple(sorted(e.items[p] for p in r["items"])), r["freq"]) for r in rows), e.n, need)
