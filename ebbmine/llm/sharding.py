"""Global shuffle into shards by a two-pass external shuffle.

Pass 1 scatters the records uniformly, by seeded hashes, over buckets that fit in memory; pass 2
permutes each bucket by Fisher-Yates and writes it. The law is `key`: doc_id and the number of
shards alone decide the shard (jump consistent hashing), so one more shard only takes rows into
itself. A bucket belongs to one shard; its slots follow those of the shard's earlier buckets.

A row's bucket in its shard is the seeded hash of doc_id, text checksum, size and occurrence; each shard
has as many buckets as its own bytes fill, so a hot doc_id spreads over many. Rows that are alike in all
columns are counted, travel once, and are numbered by occurrence when they are laid out again, a
thousand at a time, so that a row repeated by a third of the table spreads, too. Nothing depends on how the input
is partitioned: the same rows give the same buckets, places and slots.

Null doc_id: hashed like a value of its own. Null or empty text: size 16. Rows are never dropped or
merged; ties (equal rows) keep a place each. Empty table: empty result. Extra columns travel along;
those with one of the operator's own names (OWN) are dropped in favour of the operator's.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import only, shared_path, table, written

OWN = ("bucket", "shard", "grown_shard", "size", "text_crc32", "occurrence", "mark1", "mark2", "place", "before", "slot")
#: Copies that are laid out by one step.
STEP = 1000
#: Partitions of a shuffle at most; beyond, a task takes several buckets, one after the other.
MOST_PARTITIONS = 20_000


def jump_shard(key: Column, shards: int, seed: int) -> Column:
    """Jump consistent hashing: shard s is taken at step s with probability 1/(s+1), decided by a
    hash of (key, s); the last step taken is the shard, so a step more moves rows only into the new one."""
    steps = F.sequence(F.lit(1), F.lit(shards - 1)) if shards > 1 else F.array().cast("array<int>")
    return F.aggregate(
        steps,
        F.lit(0),
        lambda at, s: F.when(F.pmod(F.xxhash64(key, s, F.lit(seed)), s.cast("bigint") + 1) == 0, s).otherwise(at),
    )


def _with_shards(docs: DataFrame, shards: int, seed: int) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit(""))
    grown = F.when(F.pmod(F.xxhash64(F.col("doc_id"), F.lit(shards), F.lit(seed)), F.lit(shards + 1)) == 0, F.lit(shards)).otherwise(F.col("shard"))
    rows = docs.select(*[F.col(f"`{c}`") for c in docs.columns if c.lower() not in OWN])
    every = [F.col(f"`{c}`") for c in rows.columns]
    return (
        rows.withColumn("mark1", F.xxhash64(F.lit(seed), *every))
        .withColumn("mark2", F.xxhash64(*every, F.lit(seed)))
        .withColumn("size", F.octet_length(text).cast("bigint") + 16)
        .withColumn("text_crc32", F.crc32(F.encode(text, "UTF-8")))
        .withColumn("shard", jump_shard(F.col("doc_id"), shards, seed))
        .withColumn("grown_shard", grown)
    )


def _numbered(rows: DataFrame, listed: int) -> DataFrame:
    """rows with `occurrence`: 0 for a row that is like no other, 0, 1, 2, ... for rows that are alike."""
    alike = written(rows.groupBy("mark1", "mark2").agg(F.count("*").alias("copies")).where("copies > 1"), "shard-copies")
    many = alike.count()
    if not many:
        return rows.withColumn("occurrence", F.lit(0).cast("bigint"))
    side = F.broadcast(alike) if many <= listed else alike  # three numbers a row, of checked size
    plain = rows.join(side.drop("copies"), ["mark1", "mark2"], "left_anti").withColumn("occurrence", F.lit(0).cast("bigint"))
    names = [c for c in rows.columns if c not in ("mark1", "mark2")]
    once = rows.join(side, ["mark1", "mark2"]).groupBy("mark1", "mark2", "copies").agg(F.first(F.struct(*[F.col(f"`{c}`") for c in names])).alias("row"))
    steps = once.withColumn("step", F.explode(F.sequence(F.lit(0).cast("bigint"), F.floor((F.col("copies") - 1) / STEP))))
    dealt = steps.repartition(F.col("mark1"), F.col("mark2"), F.col("step"))
    laid = dealt.withColumn("occurrence", F.explode(F.sequence(F.col("step") * STEP, F.least(F.col("copies"), (F.col("step") + 1) * STEP) - 1)))
    return plain.unionByName(laid.select("mark1", "mark2", *[F.col(f"row.`{c}`").alias(c) for c in names], "occurrence"))


def scatter(docs: DataFrame, shards: int, bucket_bytes: int, seed: int, listed: int = 1_000_000) -> DataFrame:
    """docs with size, text_crc32, shard, grown_shard, occurrence and bucket; buckets are numbered through the shards."""
    rows = _with_shards(docs, shards, seed)
    filled = {r["shard"]: r["bytes"] for r in rows.groupBy("shard").agg(F.sum("size").alias("bytes")).collect()}  # a number a shard
    parts = [max(1, -(-filled.get(s, 0) // bucket_bytes)) for s in range(shards)]
    first = np.concatenate([[0], np.cumsum(parts)]).tolist()
    per_shard, begin = F.get(F.array(*[F.lit(x).cast("bigint") for x in parts]), F.col("shard")), F.get(F.array(*[F.lit(x).cast("bigint") for x in first[:-1]]), F.col("shard"))
    part = F.pmod(F.xxhash64("doc_id", "text_crc32", "size", "occurrence", F.lit(seed + 1)), per_shard)
    # as many partitions as buckets: a task holds one or a few
    return _numbered(rows, listed).withColumn("bucket", begin + part).repartition(min(first[-1], MOST_PARTITIONS), "bucket")


def fisher_yates(rows: int, seed: int, bucket: int) -> np.ndarray:
    """A seeded permutation of 0 .. rows - 1, by swaps from the end."""
    order = np.arange(rows)
    draw = np.random.default_rng([seed, bucket]).random(rows)
    for i in range(rows - 1, 0, -1):
        j = int(draw[i] * (i + 1))
        order[i], order[j] = order[j], order[i]
    return order


def _permuted(seed: int):
    def run(bucket: pa.Table) -> pa.Table:
        """One bucket, put in a fixed order first, so a retry gives the same, then permuted."""
        keys = ["doc_id", "text_crc32", "size", "mark1", "mark2", "occurrence"]
        at = bucket.select(keys).append_column("at", pa.array(np.arange(bucket.num_rows))).sort_by([(k, "ascending") for k in keys])["at"].to_numpy()
        order = at[fisher_yates(bucket.num_rows, seed, bucket["bucket"][0].as_py())]
        return bucket.drop_columns(["mark1", "mark2", "occurrence"]).take(pa.array(order)).append_column("place", pa.array(np.arange(bucket.num_rows, dtype=np.int64)))

    return run


def write_shards(docs: DataFrame, path: str, shards: int = 40, bucket_bytes: int = 16 << 20, seed: int = 11) -> DataFrame:
    """Shuffles docs(doc_id, text, ...) into `shards` shards under path (Parquet, a folder a shard,
    a file a bucket, rows in their shuffled order) and returns the written table."""
    spark = docs.sparkSession
    rows = scatter(docs, shards, bucket_bytes, seed)
    shape = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields if f.name not in ("mark1", "mark2", "occurrence")) + ", place bigint"
    rows.groupBy("bucket").applyInArrow(_permuted(seed), shape).write.partitionBy("shard").parquet(path)
    return spark.read.schema(shape).parquet(path)


def shard_slots(files: DataFrame) -> DataFrame:
    """The slot of each row: its place in its bucket after the rows of the shard's earlier buckets."""
    sizes = files.groupBy("shard", "bucket").agg(F.count("*").alias("rows"))
    before = sizes.select("bucket", F.coalesce(F.sum("rows").over(Window.partitionBy("shard").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    return files.join(before, "bucket").withColumn("slot", F.col("place") + F.col("before")).drop("before")


def op7_two_pass_shuffle(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Digest of the written shards of all documents."""
    docs = only(table(spark, sf_dir, "documents"), doc_id="bigint", text="string", lang="string", source="string")
    files = write_shards(docs, shared_path(spark, "shards"))
    return shard_slots(files.select("doc_id", "size", "text_crc32", "shard", "grown_shard", "bucket", "place")).select(
        "doc_id", "size", "text_crc32", F.lit("key").alias("law"), F.col("shard").cast("int").alias("shard"), "slot", F.col("grown_shard").cast("int").alias("grown_shard")
    )
