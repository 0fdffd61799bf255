"""Association rules from frequent sets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .result import parts


def derive(freq: DataFrame, n: int, min_conf: float, min_lift: float | None = None, max_consequent: int | None = None) -> DataFrame:
    """X => Z \\ X for every frequent Z of two items or more and non-empty X below it:
    antecedent, consequent, supp, confidence = supp(Z) / supp(X), lift = confidence * n / supp(Z \\ X).
    Splits are made inside a row; both supports come by equi-joins, so nothing is paired at large."""
    z = freq.where("k > 1").withColumn("p", parts(F.col("items")))
    masks = F.sequence(F.lit(1).cast("bigint"), F.call_function("shiftleft", F.lit(1).cast("bigint"), F.size("p")) - 2)
    split = z.select("p", "supp", F.explode(masks).alias("m"))
    side = lambda bit: F.array_join(F.filter("p", lambda x, i: F.call_function("getbit", F.col("m"), i) == bit), "|")
    split = split.select(side(1).alias("antecedent"), side(0).alias("consequent"), "supp", (F.size("p") - F.bit_count("m")).alias("right"))
    if max_consequent:
        split = split.where(F.col("right") <= max_consequent)
    of = lambda name, to: freq.select(F.col("items").alias(name), F.col("supp").alias(to))
    rules = split.join(of("antecedent", "sa"), "antecedent").withColumn("confidence", F.col("supp") / F.col("sa")).where(F.col("confidence") >= min_conf)
    rules = rules.join(of("consequent", "sc"), "consequent").withColumn("lift", F.col("supp") * F.lit(float(n)) / F.col("sa") / F.col("sc"))
    if min_lift is not None:
        rules = rules.where(F.col("lift") >= min_lift)
    return rules.select("antecedent", "consequent", "supp", "confidence", "lift")


def about(rules: DataFrame, antecedent_has: str | None = None, consequent_has: str | None = None, max_len: int | None = None) -> DataFrame:
    if antecedent_has is not None:
        rules = rules.where(F.array_contains(parts(F.col("antecedent")), antecedent_has))
    if consequent_has is not None:
        rules = rules.where(F.array_contains(parts(F.col("consequent")), consequent_has))
    if max_len is not None:
        rules = rules.where(F.size(parts(F.col("antecedent"))) + F.size(parts(F.col("consequent"))) <= max_len)
    return rules


def fired(rules: DataFrame, tx: DataFrame) -> DataFrame:
    """(tid, antecedent, consequent) of the rules whose antecedent a basket holds: baskets meet rules
    by the antecedent's items in an equi-join, counted per basket and rule."""
    listed = rules.select("antecedent", "consequent", F.size(parts(F.col("antecedent"))).alias("k"), F.explode(parts(F.col("antecedent"))).alias("item"))
    met = tx.join(listed, "item").groupBy("tid", "antecedent", "consequent", "k").agg(F.count("*").alias("have"))
    return met.where("have = k").select("tid", "antecedent", "consequent")
