"""Names for SQL users: views of results and table functions on item sets."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="subset string")
class ImmediateSubsets:
    """The sets with one item less."""

    def eval(self, items: str):
        held = items.split("|") if items else []
        for i in range(len(held)) if len(held) > 1 else ():
            yield ("|".join(held[:i] + held[i + 1 :]),)


@udtf(returnType="antecedent string, consequent string")
class AllSplits:
    """All ways to part a set into two non-empty sets."""

    def eval(self, items: str):
        held = items.split("|") if items else []
        for k in range(1, len(held)):
            for left in combinations(held, k):
                yield "|".join(left), "|".join(x for x in held if x not in left)


def register(spark: SparkSession, **views: DataFrame) -> None:
    """Table functions immediate_subsets and all_splits, and the given frames as temporary views."""
    spark.udtf.register("immediate_subsets", ImmediateSubsets)
    spark.udtf.register("all_splits", AllSplits)
    for name, df in views.items():
        df.createOrReplaceTempView(name)
