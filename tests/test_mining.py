"""The miners against each other, brute force and the worked example; invariants of the interval loop."""

import random

import pytest

from ebbmine.functions import bits
from ebbmine.operators import bruteforce, counting, interval, lattice, layout, measures, result, rules
from ebbmine.operators.mining import mine
from ebbmine.plans.inspect import formatted
from ebbmine.sources import tables, workloads

WORKED = ["ab", "abc", "bc", "ab"]
WORKED_SETS = [(("a",), 3), (("a", "b"), 3), (("b",), 4), (("b", "c"), 2), (("c",), 2)]
METHODS = [
    ("ic_b", {}), ("ic_b", {"M": 3}), ("ic_b", {"chunks": 5, "mode": "hash", "grow": "delta"}), ("ic_b", {"chunks": 3, "first_pass": False, "prune": "none"}), ("ic_b", {"chunks": 4, "bound": "uniform", "prune": "self"}),
    ("ic_4", {"chunks": 2}), ("level", {}), ("level_distributed", {}), ("vert", {"layout": "tidlist"}), ("vert", {"layout": "bitmap"}), ("vert", {"layout": "diffset"}), ("fpt", {}), ("mllib", {}),
]


def baskets(spark, rows):
    return spark.createDataFrame([(k, x) for k, row in enumerate(rows) for x in row], "tid bigint, item string")


@pytest.mark.parametrize(("method", "options"), METHODS)
def test_worked_example(spark, method, options):
    assert mine(baskets(spark, WORKED), "0.5", method, **options).sets == WORKED_SETS


def test_worked_traces(spark):
    tx = baskets(spark, WORKED)
    b = mine(tx, "0.5", "ic_b", M=2)
    assert [(t[0], t[3]) for t in b.trace] == [(0, 3), (1, 3), (2, 3), (3, 1), (4, 1)][: len(b.trace)] and b.passes in (2.0, 2.5, 3.0)
    c = mine(tx, "0.5", "ic_4", M=2)
    assert c.passes == 2.0 and c.tests == 24 and [t[-1] for t in c.trace] == [6, 8, 6, 4]


@pytest.mark.parametrize("seed", range(3))
def test_random_baskets(spark, seed):
    rng = random.Random(seed)
    rows = [{f"i{min(rng.randrange(9), rng.randrange(9))}" for _ in range(rng.randrange(1, 7))} for _ in range(47)]
    tx = baskets(spark, rows)
    want = bruteforce.mine(tx, "0.15").sets
    for method, options in METHODS:
        assert mine(tx, "0.15", method, **options).sets == want, (method, options)
    assert mine(tx.repartition(7), "0.15", "ic_b", chunks=6).sets == want


def test_same_result_whatever_the_chunks_and_counter(spark):
    tx = workloads.synthetic(spark, 400, m=70, avg_len=8, n_patterns=6)
    want = mine(tx, "0.08", "level").sets
    assert max(len(x) for x, _ in want) >= 2
    for chunks in (1, 2, 7):
        assert mine(tx, "0.08", "ic_b", chunks=chunks).sets == want
    for counter in ("set", "tx", "itemset", "grid", "wide", "vector", "scalar", "anchor", "vertical", "sliced"):
        assert mine(tx, "0.08", "level", counter=counter, folded=False).sets == want, counter


def test_invariants(spark):
    tx = workloads.synthetic(spark, 500, m=40, avg_len=9, n_patterns=8)
    run = mine(tx, "0.06", "ic_b", chunks=40)
    supports = dict(run.sets)
    for x, s in run.sets:  # closed downwards, supports fall
        for i in range(len(x)):
            if len(x) > 1:
                assert supports[x[:i] + x[i + 1 :]] >= s
    exact = {e.mask for e in run.lattice.ledger.values()}
    assert len(exact) == len(run.lattice.ledger)
    assert any(t[6] for t in run.trace)  # the bound acts, since there are more stops than 1/minsup
    truth = {m for m in exact}
    level = mine(tx, "0.06", "level")
    assert run.sets == level.sets and truth
    for e in run.lattice.ledger.values():  # a pruned set is truly infrequent
        if e.phase == "settled" and e.shape == "unlikely" and not e.exact:
            assert e.supp < run.need
    assert measures.summary(spark, {"a": run, "b": level}).count() == 2


def test_full_passes_count_the_same_tests(spark):
    tx = workloads.synthetic(spark, 300, m=20, avg_len=6, n_patterns=5)
    level = mine(tx, "0.1", "level", folded=False)
    for chunks in (1, 3, 6):
        assert mine(tx, "0.1", "ic_b", chunks=chunks, prune="none").tests == level.tests
    one = mine(tx, "0.1", "ic_b", chunks=1, prune="none")
    assert one.passes == level.passes


def test_joining_watched_sets_only_is_incomplete():
    likely = [0b011, 0b101, 0b110]
    assert lattice.joined(likely) == {0b111}
    assert lattice.joined([0b110]) == set()  # the others are settled: nothing would be made


@pytest.mark.parametrize("method", ["ic_b", "ic_4", "level", "vert", "fpt", "mllib"])
def test_edges(spark, method):
    none = baskets(spark, [])
    assert mine(none, "0.5", method).sets == []
    assert mine(baskets(spark, ["ab", "cd", "ef"]), "0.9", method).sets == []
    assert mine(baskets(spark, ["a", "ab"]), "1", method).sets == [(("a",), 2)]
    full = mine(baskets(spark, ["abcd"] * 5), "1", method)
    assert len(full.sets) == 15 and {s for _, s in full.sets} == {5}
    tids = spark.createDataFrame([(k,) for k in range(10)], "tid bigint")
    assert mine(baskets(spark, ["ab"] * 5), "0.6", method, tids=tids).sets == []
    assert len(mine(baskets(spark, ["ab"] * 5), "0.5", method, tids=tids).sets) == 3


def test_need_is_exact():
    assert layout.need_count("0.1", 1674) == 168 and layout.need_count(0.1, 1680) == 168 and layout.need_count("1", 7) == 7
    for bad in ("0", "-0.1", "1.1"):
        with pytest.raises(ValueError):
            layout.need_count(bad, 10)


def test_words_beyond_64_items(spark):
    rows = [[f"x{k:03d}" for k in range(130)]] * 3 + [["x063", "x064", "x129"]] * 4
    got = dict(mine(baskets(spark, rows), "0.9", "ic_b").sets)
    assert got == {("x063",): 7, ("x064",): 7, ("x129",): 7, ("x063", "x064"): 7, ("x063", "x129"): 7, ("x064", "x129"): 7, ("x063", "x064", "x129"): 7}
    assert bits.signed(1 << 63) == -(1 << 63) and bits.bits_of(1 << 129 | 1) == [0, 129]


def test_constraints(spark):
    tx = baskets(spark, ["abc", "abc", "abd"])
    assert max(len(x) for x, _ in mine(tx, "0.6", "ic_b", max_len=2).sets) == 2
    assert mine(tx, "0.6", "ic_b", only_items=["a", "c"]).sets == [(("a",), 3), (("a", "c"), 2), (("c",), 2)]
    assert (("a", "b"), 3) not in mine(tx, "0.6", "ic_b", group_of={"a": 1, "b": 1}).sets
    assert (("a", "b"), 3) not in mine(tx, "0.6", "level", group_of={"a": 1, "b": 1}).sets
    with pytest.raises(RuntimeError):
        mine(tx, "0.3", "ic_b", max_candidates=3)


def test_states_only_move_forward():
    x = lattice.Lattice()
    e = x.add(1, 0)
    x.move(e, shape="likely")
    x.move(e, phase="settled")
    for bad in ({"phase": "watched"}, {"shape": "unlikely"}, {"phase": "settled"}):
        with pytest.raises(AssertionError):
            x.move(e, **bad)
    with pytest.raises(AssertionError):
        x.add(1, 3)


def test_rules_and_results(spark):
    r = mine(baskets(spark, WORKED), "0.5", "level")
    f = r.itemsets()
    got = {(x["antecedent"], x["consequent"]): (x["supp"], x["confidence"], x["lift"]) for x in rules.derive(f, r.n, 0.6).collect()}
    assert got == {("a", "b"): (3, 1.0, 1.0), ("b", "a"): (3, 0.75, 1.0), ("c", "b"): (2, 1.0, 1.0)}
    assert {x["items"] for x in result.maximal(f).collect()} == {"a|b", "b|c"}
    assert {x["items"] for x in result.closed(f).collect()} == {"b", "a|b", "b|c"}
    assert result.compare(f, f).count() == 0
    assert [tuple(x) for x in result.longest(f).collect()] == [(2, 5)]
    assert rules.about(rules.derive(f, r.n, 0.6), antecedent_has="c").count() == 1
    assert {x["tid"] for x in rules.fired(rules.derive(f, r.n, 0.6).where("antecedent = 'c'"), baskets(spark, WORKED)).collect()} == {1, 2}
    assert r.itemsets(as_array=True).schema.simpleString() == "struct<items:array<string>,k:int,supp:bigint,support:double>"


def test_sources(spark, tmp_path):
    (tmp_path / "b.txt").write_text("1 2 3\n\n 2 2 4 \n")
    got = tables.read_baskets(spark, str(tmp_path / "b.txt")).collect()
    assert sorted(r["item"] for r in got) == ["1", "2", "2", "3", "4"]
    wide = spark.createDataFrame([(1, True, False), (2, True, None)], "id int, x boolean, y boolean")
    assert sorted(tuple(r) for r in tables.from_wide(wide, "id").collect()) == [(1, "x"), (2, "x")]
    rows = spark.createDataFrame([(1, "a", 4.0), (2, None, 11.0), (3, "b", None)], "id int, c string, v double")
    assert sorted(tuple(r) for r in tables.attributes(rows, "id", ["c", "v"], {"v": 5.0}).collect()) == [(1, "c=a"), (1, "v=0"), (2, "v=2"), (3, "c=b")]
    assert sorted(tuple(r) for r in tables.attributes(rows, "id", ["v"], {"v": [0.0, 10.0]}).collect()) == [(1, "v=1"), (2, "v=2")]
    arrays = spark.createDataFrame([(1, ["a", "a", None]), (None, ["b"])], "id int, items array<string>")
    assert [tuple(r) for r in tables.from_arrays(arrays, "id", "items").collect()] == [(1, "a")]
    tables.write_itemsets(mine(baskets(spark, WORKED), "0.5", "level").itemsets(), str(tmp_path / "out"), "csv")
    assert spark.read.csv(str(tmp_path / "out"), header=True).count() == 5


def test_plans(spark):
    tx = workloads.synthetic(spark, 300, m=20)
    e, _ = layout.prepare(tx, "0.05", chunks=3, mode="hash")
    assert "PartitionFilters: [isnotnull(chunk" in formatted(e.chunk(1))
    cands = counting._cands(e.enc, [3, 5], 1)
    from pyspark.sql import functions as F

    joined = e.enc.join(F.broadcast(cands), counting._fits(1)).groupBy("cid").agg(F.sum("weight"))
    text = formatted(joined)
    assert "BroadcastNestedLoopJoin" in text and "CartesianProduct" not in text and "partial_sum" in text
    lines = formatted(tables.read_table(spark, "/root/testdata/sf0.001", "lineitem").where("l_quantity > 10").select("l_orderkey"))
    assert "PushedFilters" in lines and "ReadSchema: struct<l_orderkey:bigint,l_quantity:double>" in lines
    assert counting.choose(4, 8) == "wide" and counting.choose(5000, 8) == "sliced" and counting.choose(5000, 8, folded=True) == "vector"


def test_encoded_masks(spark):
    masks = workloads.synthetic_masks(spark, 3000)
    names = [f"m{p:02d}" for p in range(64)]
    e = layout.from_masks(masks, names, chunks=3)
    got = interval.mine_encoded(e, "0.1", counter="sliced")
    assert interval.mine_encoded(layout.sliced(e), "0.1").sets == got.sets
    rows = [[names[p] for p in bits.bits_of(r["w0"] & bits.LOW)] for r in masks.collect()]
    assert got.sets == mine(baskets(spark, rows), "0.1", "fpt").sets


def test_encode_rows_and_sizes(spark):
    df = spark.createDataFrame([(1, 5), (2, -5)], "id int, v int")
    got = layout.encode_rows(df, "id", [df["v"] > 0, df["v"] < 0] + [df["v"] > 100] * 61 + [df["v"] == 5, df["v"] == -5]).collect()
    assert [tuple(r) for r in got] == [(1, 1 - (1 << 63), 0), (2, 2, 1)]
    assert layout.size_bytes(17_771, 480_189) == 17_771 * 7503 * 8
    assert interval.plan_chunks(10, 3) == 4 and interval.plan_chunks(10) == 2 and interval.plan_chunks(10, 50) == 1
    assert measures.speedup(2.0, 2.0) == 1 and measures.efficiency(8.0, 2.0, 4) == 1 and measures.gain(3.0, 1.5) == 2


def test_mllib_makes_its_baskets_once(spark):
    """What the baskets are made from is read once, however many counts and passes follow."""
    rows = spark.sparkContext.accumulator(0)

    def seen(batches):
        for batch in batches:
            rows.add(batch.num_rows)
            yield batch

    tx = spark.createDataFrame([(k, f"i{j}") for k in range(40) for j in range(3)], "tid bigint, item string").mapInArrow(seen, "tid bigint, item string")
    found = mine(tx, "0.5", "mllib")
    assert len(found.sets) == 7 and found.n == 40
    assert rows.value == 120
