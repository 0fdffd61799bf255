"""All subsets of every basket, counted: the definition itself, for small inputs and tests."""

from __future__ import annotations

from itertools import combinations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .layout import need_count
from .mining import MiningResult


def mine(tx: DataFrame, minsup: str | float, max_len: int = 20, tids: DataFrame | None = None, **_) -> MiningResult:
    n = (tids if tids is not None else tx).select("tid").distinct().count()
    need = need_count(minsup, n) if n else 1

    def run(batches):
        for batch in batches:
            sets = ["|".join(c) for held in batch.column(0).to_pylist() for k in range(1, min(max_len, len(held)) + 1) for c in combinations(held, k)]
            yield pa.RecordBatch.from_arrays([pa.array(sets, pa.string())], ["items"])

    baskets = tx.distinct().groupBy("tid").agg(F.array_sort(F.collect_list("item")).alias("held")).select("held")
    rows = baskets.mapInArrow(run, "items string").groupBy("items").agg(F.count("*").alias("supp")).where(F.col("supp") >= need).collect()
    return MiningResult(tx.sparkSession, sorted((tuple(r["items"].split("|")), r["supp"]) for r in rows), n, need)
