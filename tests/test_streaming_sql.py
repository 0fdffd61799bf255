"""Streams give what the static table gives; SQL names; the registry is whole."""

import time

import pytest
from pyspark.sql import functions as F

from ebbmine.functions import sqlsurface
from ebbmine.operators.mining import mine
from ebbmine.registry import EVENT_SETS, EVENT_TYPES
from ebbmine.sources import workloads
from ebbmine.sources.tables import read_table
from ebbmine.streaming import baskets as windows

SF = "/root/testdata/sf0.001"


def test_tumbling_stream_equals_table(spark, tmp_path):
    events = read_table(spark, SF, "events")
    parts = events.withColumn("day", F.dayofmonth("ts"))
    for lo, hi in ((1, 10), (11, 20), (21, 31)):
        parts.where(F.col("day").between(lo, hi)).drop("day").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    query = (
        windows.baskets(windows.once(stream), EVENT_TYPES).writeStream.format("memory").queryName("held").outputMode("complete").trigger(availableNow=True)
        .option("checkpointLocation", str(tmp_path / "ck")).start()
    )
    query.awaitTermination()
    got = {tuple(r) for r in spark.table("held").select("user_id", "start", "mask").collect()}
    # files are taken in any order, so rows behind the watermark may be missing, but none may be wrong
    want = {tuple(r) for r in windows.baskets(windows.once(events), EVENT_TYPES).select("user_id", "start", "mask").collect()}
    keys = {(u, s): m for u, s, m in want}
    assert got and all(m & keys[u, s] == m for u, s, m in got)
    supports = windows.support(windows.baskets(events, EVENT_TYPES), EVENT_TYPES, EVENT_SETS)
    assert supports.where("items = 'click'").agg(F.sum("supp")).first()[0] == sum(m & 1 for _, _, m in want)


def test_incremental_miner(spark, tmp_path):
    tx = workloads.w3(spark, SF)
    tx.where(F.crc32("tid") % 2 == 0).coalesce(1).write.parquet(str(tmp_path / "in"))
    tx.where(F.crc32("tid") % 2 == 1).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(tx.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    miner = windows.run_incremental(stream, "0.1", str(tmp_path / "ck"))
    assert miner.batches(spark) == (0, 1)
    again = spark.read.parquet(f"{miner.store}/batch=0")
    again.persist().count()
    miner(again, 0)  # sent again: nothing changes
    want = mine(tx, "0.1", "level").sets
    assert miner.itemsets(spark).sets == want
    # a restart: new rows arrive, a new miner on the same checkpoint covers old and new ones
    more = tx.withColumn("tid", F.concat(F.lit("x"), "tid")).where("item <> 'click'")
    more.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    later = windows.run_incremental(stream, "0.1", str(tmp_path / "ck"))
    assert later is not miner and later.batches(spark) == (0, 1, 2)
    assert later.itemsets(spark).sets == mine(tx.unionAll(more), "0.1", "level").sets != want


def test_sql_surface(spark):
    f = spark.createDataFrame([("a|b|c", 3, 2), ("a", 1, 5)], "items string, k int, supp bigint")
    sqlsurface.register(spark, itemsets=f)
    got = {(r[0], r[1]) for r in spark.sql("SELECT i.items, s.subset FROM itemsets i, LATERAL immediate_subsets(i.items) s").collect()}
    assert got == {("a|b|c", "b|c"), ("a|b|c", "a|c"), ("a|b|c", "a|b")}
    assert spark.sql("SELECT * FROM itemsets i, LATERAL all_splits(i.items)").count() == 6


def test_flagship_and_registry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() == 331
    names = entry.queries()
    assert set(entry.oracle_sql()) <= set(names)
    assert {"w1_icb_m2", "w8_fpt", "count_k8", "rules_lift", "trace_passes", "support_cube"} <= set(names)


def replay(spark, tmp_path, make, label):
    """Three files, a batch each, the last with repeated and late rows; what an append-mode stream emits."""
    events = read_table(spark, SF, "events")
    day = F.dayofmonth(F.col("ts").cast("timestamp"))
    src = str(tmp_path / f"in-{label}")
    late = events.where(day <= 3).withColumn("event_id", F.col("event_id") + 10_000_000)
    files = [events.where(day <= 10), events.where((day > 10) & (day <= 20)), events.where(day > 20).unionAll(events.where(day > 25)).unionAll(late)]
    for f in files:
        f.coalesce(1).write.mode("append").parquet(src)
        time.sleep(1.1)  # files are taken by their time
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(src)
    query = make(windows.once(stream)).writeStream.format("memory").queryName(label).outputMode("append").option("checkpointLocation", str(tmp_path / f"ck-{label}")).trigger(availableNow=True).start()
    query.awaitTermination()
    end = events.agg(F.max(F.col("ts").cast("timestamp")) - F.expr("INTERVAL 10 MINUTES")).first()[0]
    return events, spark.table(label), end


def rows_of(df, *columns):
    return sorted(tuple(r) for r in df.select(*columns).collect())


@pytest.mark.parametrize("kind", ["tumbling", "sliding", "session"])
def test_late_rows_are_left_out_exactly(spark, tmp_path, kind):
    slide = "6 hours" if kind == "sliding" else None
    events, got, end = replay(spark, tmp_path, lambda s: windows.baskets(s, EVENT_TYPES, kind, "1 day", slide), f"late_{kind}")
    want = windows.baskets(windows.once(events), EVENT_TYPES, kind, "1 day", slide).where(F.col("end") <= F.lit(end))
    names = ("user_id", "start", "end", "mask")
    assert got.count() > 0 and rows_of(got, *names) == rows_of(want, *names)


def test_open_baskets_equal_session_windows(spark, tmp_path):
    events, got, end = replay(spark, tmp_path, lambda s: windows.open_baskets(s, EVENT_TYPES), "open")
    want = windows.baskets(windows.once(events), EVENT_TYPES, "session").where(F.col("end") <= F.lit(end))
    names = ("user_id", "start", "end", "mask")
    assert got.count() > 0 and rows_of(got, *names) == rows_of(want, *names)


def test_support_follows_a_stream(spark, tmp_path):
    events, got, end = replay(spark, tmp_path, lambda s: windows.support_stream(windows.baskets(s, EVENT_TYPES), EVENT_TYPES, EVENT_SETS), "supports")
    held = windows.baskets(windows.once(events), EVENT_TYPES).where(F.col("end") <= F.lit(end))
    want = windows.support(held, EVENT_TYPES, EVENT_SETS)
    names = ("start", "items", "supp")
    assert got.count() > 0 and rows_of(got, *names) == rows_of(want, *names)
