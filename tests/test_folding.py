"""Equal baskets: folded before they are encoded, made once, and dealt as copies; results stay those of single ones."""

import pytest
from pyspark.sql import functions as F

from ebbmine import experiments
from ebbmine.operators import layout, treegrowth
from ebbmine.operators.counting import count
from ebbmine.operators.mining import mine
from ebbmine.sources import workloads


def _equal_baskets(spark, names):
    """40 times one basket of `names` and once another, beside an empty one."""
    rows = [(k, x) for k in range(40) for x in names] + [(40, names[0]), (40, None)]
    return spark.createDataFrame(rows, "tid bigint, item string"), spark.range(42).select(F.col("id").alias("tid"))


@pytest.mark.parametrize("m", [3, 300])
def test_equal_baskets_fold_before_they_are_encoded(spark, m, monkeypatch):
    """Counts, sizes of chunks and supports are those of the unfolded table, and each different basket of a chunk is encoded once."""
    tx, tids = _equal_baskets(spark, [f"i{j:03d}" for j in range(m)])
    tx, seen = tx.where("item is not null"), []
    for name in ("encode_baskets", "encode"):
        real = getattr(layout, name)
        monkeypatch.setattr(layout, name, lambda df, items, *more, real=real: (seen.append((more[0] if more else df).count()), real(df, items, *more))[1])
    plain, need = layout.prepare(tx, "0.5", 2, "hash", True, False, tids)
    once, same = layout.prepare(tx, "0.5", 2, "hash", True, "auto", tids)
    assert need == same == 21 and once.folded and not plain.folded
    assert (once.n, once.items, once.counts, once.sizes, once.counted) == (plain.n, plain.items, plain.counts, plain.sizes, plain.counted)
    assert once.counts == [41] + [40] * (m - 1) and sum(once.sizes) == 42
    assert seen[0] == 42 and seen[1] <= 6
    pairs = [0b11, 0b101, 1 << m - 1 | 1]
    for s in (0, 1):
        assert count(once.chunk(s), pairs, once.words, "vector", True) == count(plain.chunk(s), pairs, plain.words, "vector")
    plain.release()
    once.release()


def test_levels_make_their_baskets_once(spark, monkeypatch):
    """e4_tables gathers the baskets of a workload once for all its runs, which find what a run of its own finds."""
    tx, _ = _equal_baskets(spark, ["a", "b", "c"])
    groups = spark.sparkContext.accumulator(0)

    def seen(batches):
        for batch in batches:
            groups.add(batch.num_rows)
            yield batch

    tx = tx.where("item is not null")
    held = tx.groupBy("tid").agg(F.collect_list("item").alias("held")).mapInArrow(seen, "tid bigint, held array<string>")
    tx.baskets = held
    monkeypatch.setitem(workloads.BASKETS, "given", lambda spark, sf_dir: tx)
    rows = experiments.e4_tables(spark, "", (("given", ("0.99", "0.5")),)).collect()
    assert [(r["tasks"], r["minsup"], r["n_sets"]) for r in rows] == [("one", 0.99, 1), ("one", 0.5, 7), ("all", 0.99, 1), ("all", 0.5, 7)]
    assert groups.value == 41


def test_mllib_is_dealt_equal_baskets_as_copies(spark, monkeypatch):
    """What is written for Spark's miner has a row for many equal baskets; it still mines every transaction."""
    rows = [(k, x) for k in range(150) for x in ("a", "b", "c")] + [(k, x) for k in range(150, 170) for x in ("b", "d")]
    tx, tids = spark.createDataFrame(rows, "tid bigint, item string"), spark.range(175).select(F.col("id").alias("tid"))
    written, real = [], treegrowth.kept
    monkeypatch.setattr(treegrowth, "kept", lambda df, *more: (out := real(df, *more), written.append(out.count()))[0])
    got, want = (mine(tx, "0.1", method, tids=tids) for method in ("mllib", "level"))
    assert got.sets == want.sets and (got.n, got.need) == (want.n, want.need) == (175, 18) and len(got.sets) == 9
    assert written == [5]  # 64 + 64 + 22 copies, 20 and 5 empty ones


def test_records_are_baskets_already(spark):
    """The baskets that w4 gives beside its rows are those that the rows make."""
    tx = workloads.w4(spark, "/root/testdata/sf0.001")
    shape = lambda df: df.select(F.array_sort("held").alias("held")).groupBy("held").count().collect()
    made = tx.groupBy("tid").agg(F.collect_list("item").alias("held"))
    assert sorted(map(str, shape(tx.baskets))) == sorted(map(str, shape(made)))
