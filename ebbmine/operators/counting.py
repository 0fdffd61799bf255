"""Support counting of candidate masks in a chunk of encoded transactions.

Strategies (all exact, all return {mask: count}):
set     subset test on item arrays, no bits (ablation)
tx      transactions outside: containment join with broadcast candidates, partial sums a task
itemset candidates outside: candidates dealt over tasks, each scans a broadcast chunk
grid    both dealt in blocks that meet in an equi-join on block numbers, summed at the end
wide    one conditional sum a candidate in one aggregate, for a handful of candidates
vector  NumPy containment by blocks in Arrow batches
scalar  the same with Python loops (ablation: vectorisation off)
anchor  each candidate keyed by its rarest item, transactions exploded on anchor items: an equi-join
vertical bitmaps of items over transactions, intersected
sliced  Arrow batches turned into bit columns, one word for 64 transactions; sets that share a prefix
        share its column, and a count is a population count (the default at scale)
Counting never moves transactions: each task sums its own, the exchange carries (candidate, partial).
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bits import bits_of, contains, contains_literal, item_ids, mask_array, split_mask, word_names

#: At most so many candidates go into one wide aggregate, and so many bytes of a chunk are broadcast.
WIDE, BROADCAST_BYTES = 200, 64 << 20


def _cands(chunk: DataFrame, masks: list[int], words: int, extra: Callable | None = None) -> DataFrame:
    shape = "cid int, " + ", ".join(f"c{j} bigint" for j in range(words)) + (", e array<int>" if extra else "")
    rows = [(k, *split_mask(x, words), *([extra(x)] if extra else [])) for k, x in enumerate(masks)]
    return chunk.sparkSession.createDataFrame(rows, shape)


def _fits(words: int):
    return contains([F.col(w) for w in word_names(words)], [F.col(f"c{j}") for j in range(words)])


def _summed(rows: DataFrame, masks: list[int]) -> dict[int, int]:
    out = dict.fromkeys(masks, 0)
    for r in rows.groupBy("cid").agg(F.sum("weight").alias("s")).collect():  # a row a candidate at most
        out[masks[r["cid"]]] = int(r["s"])
    return out


def count_tx(chunk: DataFrame, masks: list[int], words: int) -> dict[int, int]:
    return _summed(chunk.join(F.broadcast(_cands(chunk, masks, words)), _fits(words)), masks)


def count_set(chunk: DataFrame, masks: list[int], words: int) -> dict[int, int]:
    held = chunk.select(item_ids(words).alias("held"), "weight")
    cands = _cands(chunk, masks, words, bits_of).select("cid", "e")
    return _summed(held.join(F.broadcast(cands), F.size(F.array_except("e", "held")) == 0), masks)


def count_itemset(chunk: DataFrame, masks: list[int], words: int) -> dict[int, int]:
    rows = chunk.agg(F.count("*")).first()[0]
    if rows * 8 * (words + 1) > BROADCAST_BYTES:  # the chunk does not fit a broadcast
        return count_grid(chunk, masks, words)
    tasks = chunk.sparkSession.sparkContext.defaultParallelism
    cands = _cands(chunk, masks, words).repartition(tasks)
    return _summed(cands.join(F.broadcast(chunk.drop("chunk")), _fits(words)), masks)


def count_grid(chunk: DataFrame, masks: list[int], words: int, cand_blocks: int | None = None, tx_blocks: int | None = None) -> dict[int, int]:
    tasks = chunk.sparkSession.sparkContext.defaultParallelism
    cand_blocks = cand_blocks or max(1, min(len(masks), tasks // 2))
    tx_blocks = tx_blocks or max(1, -(-tasks // cand_blocks))
    cands = _cands(chunk, masks, words).withColumn("cb", F.col("cid") % cand_blocks).withColumn("tb", F.explode(F.sequence(F.lit(0), F.lit(tx_blocks - 1))))
    tx = chunk.withColumn("tb", F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(tx_blocks)).cast("int")).withColumn("cb", F.explode(F.sequence(F.lit(0), F.lit(cand_blocks - 1))))
    return _summed(tx.join(cands.hint("shuffle_hash"), ["cb", "tb"]).where(_fits(words)), masks)


def count_wide(chunk: DataFrame, masks: list[int], words: int) -> dict[int, int]:
    out = {}
    for at in range(0, len(masks), WIDE):
        part = masks[at : at + WIDE]
        row = chunk.agg(*[F.sum(F.when(contains_literal(words, x), F.col("weight"))).alias(f"s{k}") for k, x in enumerate(part)]).first()
        out |= {x: int(row[k] or 0) for k, x in enumerate(part)}
    return out


def _kernel(cands: np.ndarray, scalar: bool):
    """Counts of all candidates in one task's transactions, emitted once."""

    def run(batches):
        total = np.zeros(len(cands), np.int64)
        for batch in batches:
            if not batch.num_rows:
                continue
            rows = np.stack([batch.column(j).to_numpy(zero_copy_only=False) for j in range(cands.shape[1])]).astype(np.int64).view(np.uint64)
            weight = batch.column(cands.shape[1]).to_numpy(zero_copy_only=False).astype(np.int64)
            if scalar:
                sets, lists = cands.tolist(), rows.T.tolist()
                for k, c in enumerate(sets):
                    s = 0
                    for t, w in zip(lists, weight.tolist()):
                        for a, b in zip(t, c):
                            if a & b != b:
                                break
                        else:
                            s += w
                    total[k] += s
                continue
            if cands.shape[1] == 1:
                keys, at = np.unique(rows[0], return_inverse=True)
                rows, weight = keys[None, :], np.bincount(at, weight).astype(np.int64)
            plain = bool((weight == 1).all())
            step = max(1, (1 << 18) // rows.shape[1])  # the block stays in cache
            for a in range(0, len(cands), step):
                c = cands[a : a + step]
                hit = np.ones((len(c), rows.shape[1]), bool)
                for j in range(cands.shape[1]):
                    if c[:, j].any():
                        hit &= (rows[j][None, :] & c[:, j][:, None]) == c[:, j][:, None]
                total[a : a + step] += np.count_nonzero(hit, axis=1) if plain else (hit @ weight)
        some = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array(total[some])], ["cid", "weight"])

    return run


def count_vector(chunk: DataFrame, masks: list[int], words: int, scalar: bool = False) -> dict[int, int]:
    cands = mask_array(masks, words)
    return _summed(chunk.select(*word_names(words), "weight").mapInArrow(_kernel(cands, scalar), "cid int, weight bigint"), masks)


def _steps(masks: list[int]):
    """(items of the shared prefix, last items, numbers of the sets), a step a prefix."""
    plan: dict[int, list[tuple[int, int]]] = {}
    for k, x in enumerate(masks):
        top = x.bit_length() - 1
        plan.setdefault(x ^ (1 << top), []).append((top, k))
    return [(bits_of(prefix), np.array([t for t, _ in tails]), np.array([k for _, k in tails])) for prefix, tails in sorted(plan.items())]


def _tally(columns: np.ndarray, steps, total: np.ndarray) -> None:
    for prefix, tails, who in steps:
        some = columns[tails]
        if prefix:
            base = columns[prefix[0]]
            for p in prefix[1:]:
                base = base & columns[p]
            some &= base
        total[who] += np.bitwise_count(some).sum(1, dtype=np.int64)


def count_slices(slices: DataFrame, masks: list[int], items: int) -> dict[int, int]:
    """Counts on a table of bit columns (layout.sliced)."""
    steps = _steps(masks)

    def run(batches):
        total = np.zeros(len(masks), np.int64)
        for batch in batches:
            for cell in batch.column(0):
                _tally(np.frombuffer(cell.as_buffer(), np.uint64).reshape(items, -1), steps, total)
        some = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array(total[some])], ["cid", "weight"])

    return _summed(slices.select("cols").mapInArrow(run, "cid int, weight bigint"), masks)


def _sliced(masks: list[int], words: int, block: int = 1 << 17):
    """Counts by bit columns; weighted rows take the containment kernel."""
    needed = 0
    for x in masks:
        needed |= x
    items = bits_of(needed)
    place = np.full(words * 64, -1)
    place[items] = np.arange(len(items))
    steps = [([int(place[p]) for p in prefix], place[tails], who) for prefix, tails, who in _steps(masks)]
    weighted = _kernel(mask_array(masks, words), False)

    def run(batches):
        total, odd = np.zeros(len(masks), np.int64), []
        for batch in batches:
            weight = batch.column(words).to_numpy(zero_copy_only=False)
            if not (weight == 1).all():
                odd.append(batch)
                if len(odd) >= 8:  # a bounded number of batches
                    for out in weighted(odd):
                        np.add.at(total, out.column(0).to_numpy(), out.column(1).to_numpy())
                    odd = []
                continue
            rows = np.stack([batch.column(j).to_numpy(zero_copy_only=False) for j in range(words)], 1).astype(np.int64, copy=False)
            for at in range(0, len(rows), block):
                part = rows[at : at + block]
                wide = np.zeros((-(-len(part) // 64) * 64, words), np.int64)
                wide[: len(part)] = part
                by_byte = wide.view(np.uint8).reshape(len(wide), words * 8)
                columns = np.empty((len(items), len(wide) // 64), np.uint64)
                for byte in range(words * 8):
                    mine = [p for p in range(byte * 8, byte * 8 + 8) if place[p] >= 0]
                    if mine:
                        octets = np.ascontiguousarray(by_byte[:, byte])
                        for p in mine:
                            columns[place[p]] = np.packbits(octets & np.uint8(1 << p % 8), bitorder="little").view(np.uint64)
                _tally(columns, steps, total)
        if odd:
            for out in weighted(odd):
                np.add.at(total, out.column(0).to_numpy(), out.column(1).to_numpy())
        kept = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(kept.astype(np.int32)), pa.array(total[kept])], ["cid", "weight"])

    return run


def count_sliced(chunk: DataFrame, masks: list[int], words: int) -> dict[int, int]:
    return _summed(chunk.select(*word_names(words), "weight").mapInArrow(_sliced(masks, words), "cid int, weight bigint"), masks)


def count_scalar(chunk: DataFrame, masks: list[int], words: int) -> dict[int, int]:
    return count_vector(chunk, masks, words, scalar=True)


def count_anchor(chunk: DataFrame, masks: list[int], words: int) -> dict[int, int]:
    """The rarest item of a set is its highest bit (the dictionary is ordered by falling count)."""
    anchors = sorted({x.bit_length() - 1 for x in masks})
    cands = _cands(chunk, masks, words, lambda x: [x.bit_length() - 1]).withColumn("anchor", F.col("e")[0]).drop("e")
    listed = F.array(*[F.lit(a) for a in anchors])
    tx = chunk.withColumn("anchor", F.explode(F.array_intersect(item_ids(words), listed)))
    return _summed(tx.join(F.broadcast(cands), "anchor").where(_fits(words)), masks)


def count_vertical(chunk: DataFrame, masks: list[int], words: int) -> dict[int, int]:
    """Items as bitmaps over row numbers in buckets of 32,768; sets by bitmap_and_agg over their items' bitmaps."""
    needed = 0
    for x in masks:
        needed |= x
    listed = F.array(*[F.lit(p) for p in bits_of(needed)])
    rows = chunk.select(F.explode(F.sequence(F.lit(1).cast("bigint"), F.col("weight"))), *word_names(words)).withColumn("n", F.monotonically_increasing_id() + 1)
    items = rows.select("n", F.explode(F.array_intersect(item_ids(words), listed)).alias("item"))
    maps = items.groupBy("item", F.bitmap_bucket_number("n").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("n")).alias("map"))
    cands = _cands(chunk, masks, words, bits_of).select("cid", F.size("e").alias("k"), F.explode("e").alias("item"))
    met = maps.join(F.broadcast(cands), "item").groupBy("cid", "k", "bucket").agg(F.count("*").alias("have"), F.bitmap_and_agg("map").alias("map"))
    return _summed(met.where("have = k").select("cid", F.bitmap_count("map").alias("weight")), masks)


STRATEGIES: dict[str, Callable] = {
    "set": count_set, "tx": count_tx, "itemset": count_itemset, "grid": count_grid, "wide": count_wide,
    "vector": count_vector, "scalar": count_scalar, "anchor": count_anchor, "vertical": count_vertical, "sliced": count_sliced,
}
#: The survey's numbers for them.
BY_NUMBER = {"k0": "set", "k1": "tx", "k2": "itemset", "k3": "grid", "k4": "wide", "k5": "vector", "k6": "scalar", "k7": "anchor", "k8": "vertical"}


def choose(candidates: int, tasks: int, folded: bool = False, n_chunk: int | None = None, words: int = 1, distinct: float | None = None, mean_size: float = 2.0) -> str:
    """The strategy for a stop. As the loops are balanced there: fewer sets than workers split the transactions,
    more sets are dealt to workers, and where neither loop alone fills the workers both are cut into blocks.

    n_chunk: transactions of the chunk; distinct: share of different masks in it; mean_size: mean length of the sets.
    Without n_chunk the table is taken to be large. All answers are exact, so a wrong guess costs time only."""
    if n_chunk is not None and n_chunk < 64 * tasks:  # too few transactions to split
        if candidates > tasks:
            return "itemset" if n_chunk * 8 * (words + 1) <= BROADCAST_BYTES else "grid"
        return "wide"
    if n_chunk is not None and n_chunk < 4096 * tasks and tasks // 2 < candidates < tasks:  # neither loop fills the workers
        return "grid"
    if candidates <= max(tasks, 24):
        return "wide"
    if folded or (distinct is not None and distinct < 0.7):
        return "vector"
    if words > 16 and candidates <= 64 * words:  # wide sparse masks and few sets: rows that hold a rarest item only
        return "anchor" if mean_size <= 3 else "vertical"
    return "sliced"


def count(chunk: DataFrame, masks: list[int], words: int, strategy: str = "auto", folded: bool = False, slices: DataFrame | None = None, items: int = 0, n_chunk: int | None = None) -> dict[int, int]:
    if not masks:
        return {}
    if slices is not None and strategy in ("auto", "sliced"):
        return count_slices(slices, masks, items)
    strategy = BY_NUMBER.get(strategy, strategy)
    if strategy == "auto":
        size = sum(x.bit_count() for x in masks) / len(masks)
        strategy = choose(len(masks), chunk.sparkSession.sparkContext.defaultParallelism, folded, n_chunk, words, mean_size=size)
    return STRATEGIES[strategy](chunk, masks, words)
