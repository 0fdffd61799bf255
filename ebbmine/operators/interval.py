"""Interval counting: the candidate state is revised at stops inside a pass over the data.

mine (IC-B): bit-encoded transactions, a full first pass, bound pruning, counting strategies.
mine_classic (IC-4): every item is watched from the start, no pruning.
One Spark job a stop, over one chunk; only (candidate, count) pairs reach the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame

from . import layout
from .counting import count
from .lattice import LIKELY, SETTLED, UNLIKELY, Lattice, joined, make_candidates
from .mining import TRACE, MiningResult, decoded, one_task


def plan_chunks(n: int, m: int | None = None, chunks: int | None = None) -> int:
    """Stops in a pass: ceil(n / M). By default M = n / 2, as in the published experiments."""
    if m is not None:
        return max(1, -(-n // m)) if n else 1
    return chunks or 2


def _run(e: layout.Encoded, need: int, first_pass: bool, prune: str, bound: str, grow: str, subset_test: bool, counter: str, max_len: int | None, group_of: dict | None, max_candidates: int, snapshot: str | None = None) -> MiningResult:
    chunks, words = len(e.sizes), e.words
    lattice = Lattice(max_candidates)
    groups = [group_of.get(x) for x in e.items] if group_of else None
    frequent = [p for p, c in enumerate(e.counts) if c >= need]
    kept_state = restore(e.spark, snapshot, lattice) if snapshot else None
    if kept_state:
        pass
    elif first_pass:
        for p, c in enumerate(e.counts):
            lattice.add(1 << p, 0, phase=SETTLED, shape=LIKELY if c >= need else UNLIKELY, supp=c, exact=True)
        if max_len is None or max_len > 1:
            for x in sorted(joined([1 << p for p in frequent])):
                if groups is None or groups[x.bit_length() - 1] is None or groups[x.bit_length() - 1] != groups[(x & -x).bit_length() - 1]:
                    lattice.add(x, 0)
    else:
        for p in range(len(e.items)):
            lattice.add(1 << p, 0)
    length = max(e.sizes) if e.sizes else 0
    trace, stop = kept_state or ([], 0)
    if first_pass and not kept_state:  # the full pass over all items, stop 0
        trace.append((0, -1, e.n, e.counted, len(frequent), len(lattice.watched()), 0, e.counted, 0, e.counted * e.n))
    while True:
        watched = lattice.watched()
        if not watched:
            break
        s = stop % chunks
        stop += 1
        delta = count(e.chunk(s), [x.mask for x in watched], words, counter, e.folded, e.slice(s), len(e.items), e.sizes[s]) if e.sizes[s] else {}
        for x in watched:
            x.supp += delta.get(x.mask, 0)
            x.stops += 1
        promoted = lattice.promote(need)
        lost = above = 0
        if prune != "none":

            def unseen(x, s=s):
                if bound == "uniform":
                    return length * (chunks - x.stops)
                return sum(e.sizes[(s + 1 + i) % chunks] for i in range(chunks - x.stops))

            lost, above = lattice.prune(need, unseen, supersets=prune == "bound")
        new = make_candidates(lattice, promoted, frequent or range(len(e.items)), grow, subset_test, max_len, groups)
        for x in new:
            lattice.add(x, stop)
        settled = lattice.settle(chunks)
        trace.append((stop, s, e.sizes[s], len(watched), len(lattice.likely()), len(new), lost + above, settled, above, len(watched) * e.sizes[s]))
        if snapshot:
            save(e.spark, snapshot, lattice, trace, stop)
    found = {x.mask: x.supp for x in lattice.result()}
    out = MiningResult(e.spark, decoded(found, e.items), e.n, need, trace, (1 if first_pass else 0) + stop / chunks)
    out.lattice = lattice
    return out


def mine(
    tx: DataFrame, minsup: str | float, M: int | None = None, chunks: int | None = None, counter: str = "auto", first_pass: bool = True, prune: str = "bound", bound: str = "chunk_exact", grow: str = "all",
    subset_test: bool = True, mode: str = "hash", folded: str | bool = "auto", tids: DataFrame | None = None, only_items: list[str] | None = None, max_len: int | None = None, group_of: dict | None = None, max_candidates: int = 5_000_000,
    baskets: DataFrame | None = None,
) -> MiningResult:
    """The bit-encoded interval miner. M transactions between stops, or a number of chunks;
    prune: none, self or bound (with supersets); bound: chunk_exact or uniform; grow: all or delta;
    counter: see counting; max_len, only_items and group_of (item -> group, at most one item of a
    group in a set) restrict what is looked for; baskets: those of tx, where layout.gathered made them before."""
    if M is not None:
        n = (tids if tids is not None else tx).select("tid").distinct().count()
        chunks = plan_chunks(n, M)
    e, need = layout.prepare(tx, minsup, chunks or 2, mode, first_pass, folded, tids, only_items, baskets=baskets)
    try:
        return _run(e, need, first_pass, prune, bound, grow, subset_test, counter, max_len, group_of, max_candidates)
    finally:
        e.release()


def mine_encoded(
    e: layout.Encoded, minsup: str | float, counter: str = "auto", first_pass: bool = True, prune: str = "bound", bound: str = "chunk_exact", grow: str = "all", subset_test: bool = True, max_len: int | None = None,
    max_candidates: int = 5_000_000, snapshot: str | None = None,
) -> MiningResult:
    """The same on a table that is encoded already (layout.from_masks, layout.load); with first_pass the item counts
    are one full pass over it. With `snapshot`, a folder that all executors share, the state is written there after
    every stop, and a run on the same stored table and thresholds goes on from the last whole one."""
    if first_pass:
        got: dict[int, int] = {}
        for s in range(len(e.sizes)):
            for x, c in count(e.chunk(s), [1 << p for p in range(len(e.items))], e.words, "sliced", e.folded, e.slice(s), len(e.items)).items():
                got[x] = got.get(x, 0) + c
        e.counts = [got[1 << p] for p in range(len(e.items))]
    return _run(e, layout.need_count(minsup, e.n), first_pass, prune, bound, grow, subset_test, counter, max_len, None, max_candidates, snapshot)


STATE = "mask string, phase string, shape string, supp bigint, stops int, born int, exact boolean"


def _stops_kept(spark, snapshot: str) -> tuple[list[int], object]:
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{snapshot}/lattice/stop=*/_SUCCESS")
    fs = path.getFileSystem(spark._jsc.hadoopConfiguration())
    return sorted(int(x.getPath().getParent().getName().split("=")[1]) for x in fs.globStatus(path) or []), fs


def save(spark, snapshot: str, lattice: Lattice, trace: list[tuple], stop: int) -> None:
    """Trace first, then the lattice, whose mark says that both are whole; the stop before stays, older ones go."""
    spark.createDataFrame(trace, TRACE).coalesce(1).write.mode("overwrite").parquet(f"{snapshot}/trace/stop={stop}")
    rows = [(format(x.mask, "x"), x.phase, x.shape, x.supp, x.stops, x.born, x.exact) for x in lattice.ledger.values()]
    spark.createDataFrame(rows, STATE).write.mode("overwrite").parquet(f"{snapshot}/lattice/stop={stop}")
    old, fs = _stops_kept(spark, snapshot)
    for k in old:
        if k < stop - 1:
            for part in ("lattice", "trace"):
                fs.delete(spark._jvm.org.apache.hadoop.fs.Path(f"{snapshot}/{part}/stop={k}"), True)


def restore(spark, snapshot: str, lattice: Lattice) -> tuple[list[tuple], int] | None:
    """Fills the lattice from the last whole stop; its trace and number, or None if there is none."""
    kept, _ = _stops_kept(spark, snapshot)
    if not kept:
        return None
    stop = kept[-1]
    for r in spark.read.schema(STATE).parquet(f"{snapshot}/lattice/stop={stop}").collect():  # the lattice, held by the driver anyway
        lattice.add(int(r["mask"], 16), r["born"], phase=r["phase"], shape=r["shape"], supp=r["supp"], stops=r["stops"], exact=r["exact"])
    rows = spark.read.schema(TRACE).parquet(f"{snapshot}/trace/stop={stop}").orderBy("stop").collect()
    return [tuple(r) for r in rows], stop


def mine_classic(tx: DataFrame, minsup: str | float, M: int | None = None, chunks: int | None = None, counter: str = "tx", parallelism: int | None = None, **options) -> MiningResult:
    """The four-state miner without the two added stages; parallelism=1 counts in one task."""
    options = {"first_pass": False, "prune": "none", "folded": False} | options
    if parallelism == 1:
        with one_task(tx.sparkSession):
            return mine(tx.coalesce(1), minsup, M, chunks, counter, **options)
    return mine(tx, minsup, M, chunks, counter, **options)
