"""Readers: the star-schema tables, basket files and frames of other shapes as (tid, item)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "labels": "doc_id bigint, quality int, toxic int",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "pages": "page_id bigint, url string, html string",
    "benchmark": "item_id bigint, text string",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table with its declared columns; Parquet scans prune the columns and take the filters."""
    want = [x.strip().split(" ")[0] for x in SCHEMAS[name].split(", ")]
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet").select(*want)


def from_long(df: DataFrame, tid: str, item: str) -> DataFrame:
    """(tid, item) from a long frame: nulls dropped, an item once a basket."""
    return df.select(F.col(tid).alias("tid"), F.col(item).cast("string").alias("item")).where("tid is not null and item is not null").distinct()


def from_arrays(df: DataFrame, tid: str, items: str) -> DataFrame:
    return from_long(df.select(F.col(tid).alias("tid"), F.explode(items).alias("item")), "tid", "item")


def from_wide(df: DataFrame, tid: str, columns: list[str] | None = None) -> DataFrame:
    """From one boolean (or 0/1) column an item."""
    columns = columns or [c for c in df.columns if c != tid]
    long = df.select(tid, *[F.col(c).cast("boolean").alias(c) for c in columns]).unpivot([tid], columns, "item", "held")
    return from_long(long.where("held"), tid, "item")


def attributes(df: DataFrame, tid: str, columns: list[str], buckets: dict[str, float | list[float]] | None = None) -> DataFrame:
    """Records as baskets of 'column=value' items; numbers in buckets of a width or between edges. Null values give no item."""
    parts = []
    for c in columns:
        value = F.col(c)
        rule = (buckets or {}).get(c)
        if isinstance(rule, list):
            value = sum((F.when(F.col(c) >= edge, 1).otherwise(0) for edge in rule), F.when(F.col(c).isNotNull(), 0))
        elif rule is not None:
            value = F.floor(F.col(c) / rule)
        parts.append(F.when(value.isNotNull(), F.concat(F.lit(f"{c}="), value.cast("string"))))
    return from_long(df.select(F.col(tid).alias("tid"), F.explode(F.array(*parts)).alias("item")), "tid", "item")


def read_baskets(spark: SparkSession, path: str, fmt: str = "lines", tid: str = "tid", item: str = "item") -> DataFrame:
    """Basket files: 'lines' holds a basket a line, items parted by spaces (a line's tid is its place
    in the files); 'csv', 'json' and 'parquet' hold long rows, or an array column of items."""
    if fmt == "lines":
        rows = spark.read.text(path).select(F.monotonically_increasing_id().alias("tid"), F.split(F.trim("value"), r"\s+").alias("items"))
        return from_arrays(rows, "tid", "items").where("item <> ''")
    reader = spark.read.option("header", True) if fmt == "csv" else spark.read
    df = reader.format(fmt).load(path)
    if dict(df.dtypes)[item].startswith("array"):
        return from_arrays(df, tid, item)
    return from_long(df, tid, item)


def write_itemsets(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists") -> None:
    """Sink for results, rules and traces; arrays are joined by '|' where the format has no arrays."""
    if fmt == "csv":
        df = df.select(*[F.array_join(c, "|").alias(c) if kind.startswith("array") else F.col(c) for c, kind in df.dtypes])
    df.write.mode(mode).format(fmt).options(header=True).save(path)
