"""Shared folders, table readers and span expressions used by the corpus operators."""

from __future__ import annotations

import atexit
import ctypes
import functools
import shutil
import tempfile
import uuid

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def shared_root(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir; where it is unset, the
    warehouse on a cluster and a temporary folder in local mode (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    master = spark.sparkContext.master
    if master.startswith("local[") or master == "local":
        kept = getattr(shared_root, "local", None)
        if kept is None:
            kept = shared_root.local = tempfile.mkdtemp(prefix="ebbmine-")
            atexit.register(shutil.rmtree, kept, ignore_errors=True)
        return f"file://{kept}"
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_ebbmine"


def shared_path(spark: SparkSession, label: str) -> str:
    return f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"


def written(df: DataFrame, label: str, partition_by: str | None = None) -> DataFrame:
    """df as a Parquet table in the shared folder: cuts the lineage and survives lost executors."""
    spark, path = df.sparkSession, shared_path(df.sparkSession, label)
    writer = df.write.partitionBy(partition_by) if partition_by else df.write
    writer.parquet(path)
    back = spark.read.schema(df.schema).parquet(path)
    back.shared_path = path
    return back


def dropped(df: DataFrame) -> None:
    """Removes the files of a table made by written(); nothing may read it afterwards."""
    spark = df.sparkSession
    path = spark._jvm.org.apache.hadoop.fs.Path(df.shared_path)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def only(df: DataFrame, **columns: str) -> DataFrame:
    """The named columns under fixed names, whatever else the table carries:
    only(df, doc_id="bigint", text="string"). Extra columns with clashing names cannot disturb."""
    return df.select(*[F.col(f"`{name}`").cast(kind).alias(name) for name, kind in columns.items()])


def found_spans(text: Column, pattern: str) -> Column:
    """array<struct<start,end,value>> of the leftmost non-overlapping matches of a Java pattern
    that never matches the empty string; offsets in code points, end exclusive. Built from the
    gaps (split) and the matches (regexp_extract_all), which run the same matcher."""
    gaps = F.split(text, pattern, -1)
    hits = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    steps = F.zip_with(F.slice(gaps, 1, F.size(hits)), hits, lambda g, h: F.struct(F.length(g).alias("gap"), h.alias("value")))
    none = F.array().cast("array<struct<start:int,end:int,value:string>>")
    laid = F.aggregate(
        steps,
        F.struct(F.lit(0).alias("at"), none.alias("spans")),
        lambda acc, s: F.struct(
            (acc["at"] + s["gap"] + F.length(s["value"])).alias("at"),
            F.concat(
                acc["spans"],
                F.array(F.struct((acc["at"] + s["gap"]).alias("start"), (acc["at"] + s["gap"] + F.length(s["value"])).alias("end"), s["value"].alias("value"))),
            ).alias("spans"),
        ),
        lambda acc: acc["spans"],
    )
    return F.when(F.size(hits) > 0, laid).otherwise(none)


def tidy(run):
    """For a function on batches: hands freed memory back to the system when a task ends, so that the
    Python workers that Spark keeps for later tasks stay small."""

    @functools.wraps(run)
    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except (AttributeError, OSError):  # not glibc
                pass

    return wrapped
