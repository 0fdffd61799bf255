"""Tables kept between jobs in the folder that all executors share."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where it is unset, the warehouse on a cluster and a temporary folder in local mode."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    if spark.sparkContext.master.split("[")[0] == "local":
        if not hasattr(shared_root, "local"):
            shared_root.local = tempfile.mkdtemp(prefix="ebbmine-")
            atexit.register(shutil.rmtree, shared_root.local, ignore_errors=True)
        return f"file://{shared_root.local}"
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_ebbmine"


def kept(df: DataFrame, label: str, by: str | None = None) -> DataFrame:
    """df written as Parquet (partitioned by one column, if named) and read again."""
    spark = df.sparkSession
    path = f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"
    (df.write.partitionBy(by) if by else df.write).parquet(path)
    back = spark.read.schema(df.schema).parquet(path)
    back.shared_path = path
    return back


def discard(df: DataFrame) -> None:
    """Removes the files of a table made by kept()."""
    spark = df.sparkSession
    path = spark._jvm.org.apache.hadoop.fs.Path(df.shared_path)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
