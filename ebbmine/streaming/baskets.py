"""Windowed baskets and supports over event streams, and mining that follows a stream of baskets.

Every function takes a batch or a streaming frame; on a static frame it gives what the stream
gives in the end, which is how the stream is tested.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import layout
from ..operators.interval import mine
from ..operators.mining import RESULT, MiningResult


def timed_events(events: DataFrame, late: str = "10 minutes") -> DataFrame:
    """events(event_id, ts, user_id, event_type) with a watermark; ts is read as UTC if it has no zone.
    Events whose ts has a zone are taken as prepared here already."""
    if dict(events.dtypes)["ts"] == "timestamp":
        return events
    df = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return df.withWatermark("ts", late) if df.isStreaming else df


def once(events: DataFrame) -> DataFrame:
    """Repeated events dropped, within the watermark on streams."""
    events = timed_events(events)
    return events.dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else events.dropDuplicates(["event_id"])


def frame(kind: str, length: str = "1 day", slide: str | None = None, gap: str = "30 minutes"):
    if kind == "session":
        return F.session_window("ts", gap)
    return F.window("ts", length, slide) if kind == "sliding" else F.window("ts", length)


def baskets(events: DataFrame, items: list[str], kind: str = "tumbling", length: str = "1 day", slide: str | None = None, gap: str = "30 minutes") -> DataFrame:
    """user_id, start, end, mask: the items (up to 64 event types) of a user's window."""
    bit = F.lit(None).cast("bigint")
    for p, x in enumerate(items):
        bit = F.when(F.col("event_type") == x, F.lit((1 << p) - (1 << 64) if p == 63 else 1 << p).cast("bigint")).otherwise(bit)
    w = frame(kind, length, slide, gap)
    out = timed_events(events).groupBy("user_id", w.alias("w")).agg(F.bit_or(bit).alias("mask"))
    if events.isStreaming:  # the window itself stays, for aggregations that follow
        return out.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), F.coalesce("mask", F.lit(0).cast("bigint")).alias("mask"), "w")
    return out.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), F.coalesce("mask", F.lit(0).cast("bigint")).alias("mask"))


def support(windowed: DataFrame, items: list[str], masks: list[int]) -> DataFrame:
    """start, items, supp: how many baskets of a window hold each set. On streams of baskets a second
    aggregation over the window's start."""
    names = ["|".join(sorted(items[p] for p in range(len(items)) if x >> p & 1)) for x in masks]
    tests = F.filter(F.array(*[F.when(F.col("mask").bitwiseAND(F.lit(x).cast("bigint")) == F.lit(x).cast("bigint"), F.lit(n)) for x, n in zip(masks, names)]), lambda x: x.isNotNull())
    return windowed.select("start", F.explode(tests).alias("items")).groupBy("start", "items").agg(F.count("*").alias("supp"))


def support_stream(windowed: DataFrame, items: list[str], masks: list[int], length: str = "1 day") -> DataFrame:
    """support() for streams in append mode: a basket counts in the window of `length` in which it ended, so the
    second aggregation has a watermark of its own. start is that window's."""
    names = ["|".join(sorted(items[p] for p in range(len(items)) if x >> p & 1)) for x in masks]
    tests = F.filter(F.array(*[F.when(F.col("mask").bitwiseAND(F.lit(x).cast("bigint")) == F.lit(x).cast("bigint"), F.lit(n)) for x, n in zip(masks, names)]), lambda x: x.isNotNull())
    by = F.window(F.window_time("w"), length) if "w" in windowed.columns else F.window("at", length)
    out = windowed.withColumn("items", F.explode(tests)).groupBy(by.alias("day"), "items").agg(F.count("*").alias("supp"))
    return out.select(F.col("day.start").alias("start"), "items", "supp")


#: A basket that a user's silence closed, and the state of a user: baskets that are open, in microseconds of UTC.
CLOSED = "user_id bigint, first bigint, until bigint, mask bigint"
OPEN = "starts array<bigint>, lasts array<bigint>, masks array<bigint>"


def open_baskets(stream: DataFrame, items: list[str], gap: str = "30 minutes") -> DataFrame:
    """Baskets by a state of one's own: a user's events gather in an open basket until none came for `gap`, when an
    event-time timeout closes and emits it. The same baskets as session windows; the state is a few numbers a basket
    (start, last event, mask), however many events it holds. Only baskets that the watermark closed come out; late
    events are dropped before. Events of null user or time join no basket; unknown types set no bit.

    stream: events(event_id, ts, user_id, event_type) with a watermark on ts (see once)."""
    import pandas as pd

    quiet = int(pd.Timedelta(gap).total_seconds() * 1_000_000)
    bit = {x: (1 << p) - (1 << 64) if p == 63 else 1 << p for p, x in enumerate(items)}

    def merged(spans: list[list[int]]) -> list[list[int]]:
        out: list[list[int]] = []
        for start, last, mask in sorted(spans):
            if out and start < out[-1][1] + quiet:
                out[-1][1], out[-1][2] = max(out[-1][1], last), out[-1][2] | mask
            else:
                out.append([start, last, mask])
        return out

    def follow(key, frames, state):
        held = [list(x) for x in zip(*state.get)] if state.exists else []
        for events in frames:
            held = merged(held + [[t, t, bit.get(x, 0)] for t, x in zip(events["at"].tolist(), events["event_type"])])
        mark = state.getCurrentWatermarkMs() * 1000
        done = [x for x in held if x[1] + quiet <= mark]
        held = [x for x in held if x[1] + quiet > mark]
        if held:
            state.update(tuple([x[k] for x in held] for k in range(3)))
            state.setTimeoutTimestamp(-(-(min(x[1] for x in held) + quiet) // 1000))
        elif state.exists:
            state.remove()
        if done:
            yield pd.DataFrame({"user_id": key[0], "first": [x[0] for x in done], "until": [x[1] + quiet for x in done], "mask": [x[2] for x in done]})

    known = stream.where("user_id is not null and ts is not null").withColumn("user_id", F.col("user_id").cast("bigint"))
    known = known.withColumn("at", F.unix_micros("ts"))
    closed = known.groupBy("user_id").applyInPandasWithState(follow, CLOSED, OPEN, "append", "EventTimeTimeout")
    return closed.select("user_id", F.timestamp_micros("first").alias("start"), F.timestamp_micros("until").alias("end"), "mask")


class IncrementalMiner:
    """Micro-batches as chunks: each batch of baskets (tid, item) is a folder batch=<id> under `store`; the result
    covers all chunks there. A batch that is sent again replaces its own folder, and a miner that is
    started anew on the same store finds what earlier ones kept: nothing is held by the driver alone."""

    def __init__(self, minsup: str, store: str, **options):
        self.minsup, self.store, self.options = minsup, store.rstrip("/"), options
        self.seen: tuple[int, ...] = ()
        self.result: MiningResult | None = None

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        batch.select("tid", "item").distinct().write.mode("overwrite").parquet(f"{self.store}/batch={batch_id}")
        self.result = None

    def batches(self, spark: SparkSession) -> tuple[int, ...]:
        """The batches that are kept whole."""
        path = spark._jvm.org.apache.hadoop.fs.Path(f"{self.store}/batch=*/_SUCCESS")
        found = path.getFileSystem(spark._jsc.hadoopConfiguration()).globStatus(path)
        return tuple(sorted(int(x.getPath().getParent().getName().split("=")[1]) for x in found or []))

    def baskets(self, spark: SparkSession) -> DataFrame | None:
        kept = self.batches(spark)
        if not kept:
            return None
        rows = spark.read.option("basePath", self.store).parquet(*[f"{self.store}/batch={k}" for k in kept])
        return rows.select("tid", "item").distinct()

    def itemsets(self, spark: SparkSession | None = None) -> MiningResult | None:
        """Mines the union of the chunks kept; a pass has as many stops as there are chunks, up to eight."""
        spark = spark or SparkSession.getActiveSession()
        kept = self.batches(spark)
        if kept and (self.result is None or kept != self.seen):
            self.result = mine(self.baskets(spark), self.minsup, chunks=max(1, min(8, len(kept))), mode="hash", **self.options)
            self.seen = kept
        return self.result


def run_incremental(stream: DataFrame, minsup: str, checkpoint: str, **options) -> IncrementalMiner:
    """Feeds an available-now stream of (tid, item) through foreachBatch and returns the miner. Chunks lie
    beside the stream's checkpoint, so both tell the same story after a restart."""
    miner = IncrementalMiner(minsup, f"{checkpoint.rstrip('/')}/chunks", **options)
    query = stream.writeStream.foreachBatch(miner).option("checkpointLocation", f"{checkpoint.rstrip('/')}/stream").trigger(availableNow=True).start()
    query.awaitTermination()
    return miner


__all__ = ["IncrementalMiner", "RESULT", "baskets", "frame", "layout", "once", "open_baskets", "run_incremental", "support", "support_stream", "timed_events"]
