"""Preparation shared by all miners: dictionary, bit-encoded transactions, chunks."""

from __future__ import annotations

import math
from dataclasses import dataclass, field
from decimal import ROUND_CEILING, Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..functions.bits import WORD_BITS, cardinality, n_words, word_names
from ..sources.shared import discard, kept

#: Dictionaries of more items than this are joined by a shuffle, not broadcast.
LISTED_ITEMS = 1_000_000


def need_count(minsup: str | float, n: int) -> int:
    """The least count that reaches a support of minsup in n transactions, by exact decimal arithmetic."""
    share = Decimal(str(minsup))
    if not 0 < share <= 1:
        raise ValueError("minsup must be above 0 and at most 1")
    return int((share * n).to_integral_value(rounding=ROUND_CEILING))


@dataclass
class Encoded:
    """Bit-encoded transactions by chunk, with what the miners need to know about them."""

    enc: DataFrame  # chunk INT, w0.. LONG, weight LONG
    items: list[str]  # by item number
    counts: list[int]  # their supports
    n: int
    sizes: list[int]  # transactions of each chunk
    folded: bool = False
    slices: DataFrame | None = None  # chunk INT, n INT, cols BINARY: see sliced()
    counted: int = 0  # items that the first pass counted, those left out since included
    words: int = field(init=False)

    def __post_init__(self):
        self.words = n_words(len(self.items))
        self.counted = max(self.counted, len(self.items))

    @property
    def spark(self) -> SparkSession:
        return self.enc.sparkSession

    def chunk(self, s: int) -> DataFrame:
        """One chunk: a partition-pruned scan."""
        return self.enc if len(self.sizes) == 1 else self.enc.where(F.col("chunk") == s)

    def slice(self, s: int) -> DataFrame | None:
        """One chunk in bit columns, if the table was sliced."""
        if self.slices is None:
            return None
        return self.slices if len(self.sizes) == 1 else self.slices.where(F.col("chunk") == s)

    def release(self) -> None:
        discard(self.enc)


def item_counts(tx: DataFrame) -> DataFrame:
    return tx.groupBy("item").agg((F.sum("weight") if "weight" in tx.columns else F.count("*")).alias("n_tx"))


def dictionary(tx: DataFrame, need: int) -> list[tuple[str, int]]:
    """Items in `need` transactions or more, by falling count, then name: dense low words, rare items high."""
    return counted_dictionary(tx, need)[0]


def counted_dictionary(tx: DataFrame, need: int) -> tuple[list[tuple[str, int]], int]:
    """The dictionary, and how many different items were counted for it, by one job."""
    seen = Observation()
    rows = item_counts(tx).observe(seen, F.count("*").alias("items")).where(F.col("n_tx") >= need).collect()  # the items, not the transactions
    return [(r["item"], r["n_tx"]) for r in sorted(rows, key=lambda r: (-r["n_tx"], r["item"]))], int(seen.get["items"])


def encode(tx: DataFrame, items: list[str], tids: DataFrame | None = None) -> DataFrame:
    """(tid, item) -> tid, w0..: one row a transaction, also for those left without an item."""
    spark, words = tx.sparkSession, n_words(len(items))
    numbers = spark.createDataFrame([(x, k // WORD_BITS, k % WORD_BITS) for k, x in enumerate(items)], "item string, word int, bit int")
    if len(items) <= LISTED_ITEMS:
        numbers = F.broadcast(numbers)
    rows = tx.join(numbers, "item", "left")
    sums = [F.bit_or(F.when(F.col("word") == j, F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col("bit")))).alias(w) for j, w in enumerate(word_names(words))]
    out = rows.groupBy("tid").agg(*sums)
    if tids is not None:
        out = tids.select("tid").distinct().join(out, "tid", "left")
    return out.na.fill(0, word_names(words))


def encode_rows(df: DataFrame, tid: str, bits: list[Column]) -> DataFrame:
    """Records straight to masks without a shuffle: bit p is set where the p-th condition holds."""
    words = n_words(len(bits))
    out = []
    for j in range(words):
        word = F.lit(0).cast("bigint")
        for p, held in enumerate(bits[WORD_BITS * j : WORD_BITS * (j + 1)]):
            word = word.bitwiseOR(F.when(held, F.lit((1 << p) - (1 << 64) if p == 63 else 1 << p).cast("bigint")).otherwise(F.lit(0).cast("bigint")))
        out.append(word.alias(f"w{j}"))
    return df.select(F.col(tid).alias("tid"), *out)


def assign_chunks(enc: DataFrame, chunks: int, n: int, mode: str = "rank") -> DataFrame:
    """Adds chunk. 'rank': runs of ceil(n / chunks) transactions by tid, from a range partitioning and
    the sizes of its partitions (no global sort in one task); 'hash': by a hash of tid, without a shuffle."""
    if chunks == 1:
        return enc.withColumn("chunk", F.lit(0))
    if mode == "hash":
        return enc.withColumn("chunk", F.pmod(F.xxhash64("tid"), F.lit(chunks)).cast("int"))
    ranged = kept(enc.repartitionByRange("tid").sortWithinPartitions("tid").withColumn("_at", F.monotonically_increasing_id()), "ranged")
    part, place = F.shiftrightunsigned("_at", 33), F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))
    before, total = {}, 0
    for row in ranged.groupBy(part.alias("p")).agg(F.count("*").alias("c")).orderBy("p").collect():  # a row a partition
        before[row["p"]] = total
        total += row["c"]
    offsets = enc.sparkSession.createDataFrame(list(before.items()) or [(0, 0)], "p bigint, before bigint")
    length = -(-max(n, 1) // chunks)
    out = ranged.withColumn("p", part).join(F.broadcast(offsets), "p").withColumn("chunk", F.floor((F.col("before") + place) / length).cast("int")).drop("_at", "p", "before")
    out.ranged = ranged
    return out


def fold(enc: DataFrame, words: int) -> DataFrame:
    """Equal masks of a chunk as one row with a weight."""
    return enc.groupBy("chunk", *word_names(words)).agg(F.sum("weight").alias("weight"))


#: Dictionaries of up to so many items are looked up in each row; larger ones are joined.
LOOKED_UP = 256


def encode_baskets(baskets: DataFrame, items: list[str]) -> DataFrame:
    """(tid, held: array of items) -> tid, w0..: a map over the baskets, without a shuffle. Other columns stay."""
    others = [c for c in baskets.columns if c != "held"]
    listed = F.array(*[F.lit(x) for x in items]) if items else F.array().cast("array<string>")
    numbered = baskets.select(*others, F.transform(F.coalesce("held", F.array().cast("array<string>")), lambda x: F.array_position(listed, x) - 1).alias("ids"))
    one, none = F.lit(1).cast("bigint"), F.lit(0).cast("bigint")

    def of_word(j: int):
        return lambda i: i.between(WORD_BITS * j, WORD_BITS * j + WORD_BITS - 1)

    def joined(acc: Column, i: Column) -> Column:
        return acc.bitwiseOR(F.call_function("shiftleft", one, (i % WORD_BITS).cast("int")))

    return numbered.select(*others, *[F.aggregate(F.filter("ids", of_word(j)), none, joined).alias(w) for j, w in enumerate(word_names(n_words(len(items))))])


def encode_arrays(df: DataFrame, tid: str, column: str, items: list[str]) -> DataFrame:
    """Baskets as arrays straight to masks, without a shuffle; null arrays, null elements and items outside
    the dictionary set no bit. Small dictionaries are looked up, larger ones joined by their item."""
    baskets = df.select(F.col(tid).alias("tid"), F.col(column).alias("held"))
    if len(items) <= LOOKED_UP:
        return encode_baskets(baskets, items)
    return encode(baskets.select("tid", F.explode(F.array_distinct("held")).alias("item")), items, baskets.select("tid"))


def store(e: Encoded, path: str, mode: str = "errorifexists") -> None:
    """An encoded table as Parquet by chunk, its dictionary beside it; load() reads both again."""
    e.enc.write.mode(mode).partitionBy("chunk").parquet(f"{path}/chunks")
    known = [(p, x, c) for p, (x, c) in enumerate(zip(e.items, e.counts))]
    e.spark.createDataFrame(known, "place int, item string, n_tx bigint").coalesce(1).write.mode(mode).parquet(f"{path}/items")
    about = [(e.n, [int(s) for s in e.sizes], e.folded)]
    e.spark.createDataFrame(about, "n bigint, sizes array<bigint>, folded boolean").coalesce(1).write.mode(mode).parquet(f"{path}/about")


def load(spark: SparkSession, path: str) -> Encoded:
    known = spark.read.parquet(f"{path}/items").orderBy("place").collect()  # the dictionary
    about = spark.read.parquet(f"{path}/about").first()
    words = word_names(n_words(len(known)))
    shape = ", ".join(f"{w} bigint" for w in words)
    enc = spark.read.schema(f"{shape}, weight bigint, chunk int").parquet(f"{path}/chunks").select("chunk", *words, "weight")
    return Encoded(enc, [r["item"] for r in known], [r["n_tx"] for r in known], about["n"], list(about["sizes"]), about["folded"])


#: Equal rows are kept as one with a weight where fewer than this share of the rows are different.
WORTH_FOLDING = 0.7


def gathered(tx: DataFrame, tids: DataFrame | None = None) -> DataFrame:
    """The baskets (tid, held) of (tid, item) rows, written once; n is their number, distinct about how many are
    different. One shuffle on tid, and none where the workload gives its baskets beside its rows."""
    baskets = vars(tx).get("baskets")
    if baskets is None:
        baskets = tx.groupBy("tid").agg(F.array_sort(F.collect_list("item")).alias("held"))
    if tids is not None:
        baskets = tids.select("tid").distinct().join(baskets, "tid", "left")
    seen = Observation()
    out = kept(baskets.observe(seen, F.approx_count_distinct(F.xxhash64("held")).alias("d")), "baskets")
    out.n, out.distinct = out.count(), int(seen.get["d"])
    return out


def in_one_task(baskets: DataFrame) -> DataFrame:
    """The same baskets, read by one task."""
    out = baskets.coalesce(1)
    out.n, out.distinct = baskets.n, baskets.distinct
    return out


def dealt(baskets: DataFrame, chunks: int, n: int) -> DataFrame:
    """Equal baskets of a 'hash' chunk as one row: tid (a row's number), chunk, held, weight."""
    rows = assign_chunks(baskets, chunks, n, "hash").groupBy("chunk", "held").agg(F.count("*").alias("weight"))
    return kept(rows.select(F.monotonically_increasing_id().alias("tid"), "chunk", "held", "weight"), "dealt")


def prepare(tx: DataFrame, minsup: str | float | None = None, chunks: int = 1, mode: str = "rank", first_pass: bool = True, folded: str | bool = "auto", tids: DataFrame | None = None, only_items: list[str] | None = None, need: int | None = None, baskets: DataFrame | None = None) -> tuple[Encoded, int]:
    """(Encoded, need): counts items (the full first pass), drops infrequent ones if first_pass,
    encodes, assigns chunks and stores the table partitioned by chunk. Empty baskets count in n.
    One shuffle on tid makes the baskets (`baskets`: those of gathered(), not made again); counting and encoding are
    maps over them (and mode 'hash' needs no other). Where many are equal they are folded first, and each is counted
    and encoded once."""
    if only_items is not None:
        tids = tids if tids is not None else tx.select("tid").distinct()
        tx, baskets = tx.where(F.col("item").isin(only_items)), None
    given, baskets = baskets is not None, baskets if baskets is not None else gathered(tx, tids)
    n, used = baskets.n, [] if given else [baskets]
    need = need if need is not None else need_count(minsup, n) if n else 1
    early = n > 0 and (mode == "hash" or chunks == 1) and (baskets.distinct < WORTH_FOLDING * n if folded == "auto" else folded)
    if early:
        baskets = dealt(baskets, chunks, n)
        used.append(baskets)
    beside = ["chunk", "weight"] if early else []
    long = baskets.select("tid", *beside, F.explode("held").alias("item"))
    known, counted = counted_dictionary(long, max(1, need) if first_pass else 1)
    items = [x for x, _ in known]
    words = n_words(len(items))
    if len(items) <= LOOKED_UP:
        enc = encode_baskets(baskets, items)
    else:
        enc = encode(long, items, baskets.select("tid"))
        enc = enc.join(baskets.select("tid", *beside), "tid") if early else enc
    if not early:
        enc = assign_chunks(enc, chunks, n, mode)
        used += [x for x in [getattr(enc, "ranged", None)] if x is not None]
    enc = kept(enc.select("chunk", *word_names(words), "weight" if early else F.lit(1).cast("bigint").alias("weight")), "chunks", by="chunk" if chunks > 1 else None)
    shape = [F.sum("weight").alias("c")] + ([F.approx_count_distinct(F.struct(*word_names(words))).alias("d")] if folded == "auto" and not early else [])
    state = enc.groupBy("chunk").agg(*shape).collect() if chunks > 1 or len(shape) > 1 else []  # a row a chunk
    got = {r["chunk"]: r["c"] for r in state} if chunks > 1 else {0: n}
    if folded == "auto":
        folded = early or n > 0 and sum(r["d"] for r in state) < WORTH_FOLDING * n
    if folded:
        plain, enc = enc, kept(fold(enc, words), "folded", by="chunk" if chunks > 1 else None)
        discard(plain)
    for table in used:
        discard(table)
    return Encoded(enc, items, [c for _, c in known], n, [got.get(s, 0) for s in range(chunks)], bool(folded), counted=counted), need


def from_masks(enc: DataFrame, items: list[str], chunks: int = 1, resident: bool = False) -> Encoded:
    """Encoded from rows w0.. that are masks already, dealt over chunks by hash; resident keeps the
    table in memory (where it fits), as the published runs did."""
    names = word_names(n_words(len(items)))
    one = F.lit(1).cast("bigint").alias("weight")
    chunk = (F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(chunks)).cast("int") if chunks > 1 else F.lit(0)).alias("chunk")
    table = enc.select(chunk, *names, one)
    table = table.persist() if resident else kept(table, "masks", by="chunk" if chunks > 1 else None)
    got = dict(table.groupBy("chunk").agg(F.count("*").alias("c")).collect())  # a row a chunk
    sizes = [got.get(s, 0) for s in range(chunks)]
    return Encoded(table, items, [0] * len(items), sum(sizes), sizes)


#: Transactions of a row of bit columns.
SLICE = 8192


def sliced(e: Encoded, resident: bool = False) -> Encoded:
    """Adds the table turned on its side, prepared once: a row holds SLICE transactions as one bit column an
    item, n * m / 8 bytes in all as before, so that each pass only joins and counts columns. Needs weights of 1."""
    if e.folded:
        return e
    names, m = word_names(e.words), len(e.items)

    def run(batches):
        waiting: dict[int, list[np.ndarray]] = {}

        def turned(chunk: int, rows: np.ndarray):
            wide = np.zeros((SLICE, e_words), np.int64)
            wide[: len(rows)] = rows
            flat = np.unpackbits(wide.view(np.uint8), axis=1, bitorder="little")[:, :m]
            cols = np.packbits(np.ascontiguousarray(flat.T), axis=1, bitorder="little")
            return pa.RecordBatch.from_arrays([pa.array([chunk], pa.int32()), pa.array([len(rows)], pa.int32()), pa.array([cols.tobytes()], pa.binary())], ["chunk", "n", "cols"])

        for batch in batches:
            chunk = batch.column(0).to_numpy(zero_copy_only=False)
            rows = np.stack([batch.column(j + 1).to_numpy(zero_copy_only=False) for j in range(e_words)], 1).astype(np.int64, copy=False)
            for s in np.unique(chunk).tolist():
                got = [*waiting.pop(s, []), rows[chunk == s]]
                if sum(map(len, got)) >= SLICE:
                    full = np.concatenate(got)
                    whole = len(full) // SLICE * SLICE
                    for at in range(0, whole, SLICE):
                        yield turned(s, full[at : at + SLICE])
                    got = [full[whole:]]
                waiting[s] = got
        for s, got in waiting.items():
            rest = np.concatenate(got)
            if len(rest):
                yield turned(s, rest)

    e_words = e.words
    table = e.enc.select("chunk", *names).mapInArrow(run, "chunk int, n int, cols binary")
    if resident:
        e.slices = table.persist()
        e.slices.count()
    else:
        e.slices = kept(table, "slices", by="chunk" if len(e.sizes) > 1 else None)
    return e


def stats(e: Encoded) -> DataFrame:
    """One row: n, m, mean and greatest length, distinct masks, bytes of the masks (n * words * 8)."""
    names = word_names(e.words)
    mean = F.sum(cardinality(e.words) * F.col("weight")) / F.lit(float(max(1, e.n)))
    return e.enc.agg(
        F.lit(e.n).cast("bigint").alias("n"), F.lit(len(e.items)).cast("bigint").alias("m"), F.round(mean, 6).alias("mean_len"), F.max(cardinality(e.words)).cast("bigint").alias("max_len"),
        F.countDistinct(*names).alias("distinct_masks"), F.lit(e.n * e.words * 8).cast("bigint").alias("mask_bytes"),
    )


def size_bytes(n: int, m: int) -> int:
    return n * math.ceil(m / WORD_BITS) * 8
