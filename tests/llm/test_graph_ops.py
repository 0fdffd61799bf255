"""Components, URL rules, licences, Jaccard join, sharding, embeddings, pipeline: brute force and edge cases."""

import random
import zlib
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from ebbmine.llm import embedding_dedup, jaccard, licences, sharding, url_rules
from ebbmine.llm.common import shared_path
from ebbmine.llm.graph import components


def closure(nodes, edges):
    root = {x: x for x in nodes}

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        a, b = top(a), top(b)
        root[max(a, b)] = min(a, b)
    return {x: top(x) for x in nodes}


def test_components(spark):
    rng = random.Random(4)
    edges = [(rng.randrange(60), rng.randrange(60)) for _ in range(40)] + [(100 + k, 101 + k) for k in range(40)] + [(500, k) for k in range(501, 600)]
    df = spark.createDataFrame([*edges, (None, 1), (2, None), (7, 7)], "a bigint, b bigint")
    got = {r["node"]: r["component"] for r in components(df).collect()}
    want = closure({x for e in edges for x in e}, edges)
    assert got == {x: r for x, r in want.items() if any(x in e and e[0] != e[1] for e in edges)}
    assert components(df.limit(0)).count() == 0


RULES = [("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block")]


def test_url_rules(spark):
    rows = [
        (1, "http://a.example.com/en/1"), (2, "http://WWW.Example.com/en/2?x=/es/"), (3, "https://x.net/es/"), (4, "https://x.net/ES/"), (5, None), (6, "nothing"), (7, "http://notexample.com/en/1"), (8, "http://alias.org/p"),
        (9, "http://far.org/q#f"), (10, "http://b.com/ok"), (11, "http://"), (12, "http://x.net?/es/"), (1, "http://a.example.com/en/1"),
    ]
    pages = spark.createDataFrame([(*r, "v") for r in rows], "page_id bigint, url string, verdict string")
    links = spark.createDataFrame([("http://alias.org/p", "http://a.example.com/en/1"), ("http://far.org/q#f", "http://alias.org/p"), ("http://b.com/ok", "http://alias.org/p"), (None, "x"), ("y", None)], "src string, dst string")
    rules = spark.createDataFrame(RULES, "host string, path string, verdict string")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"], r["via"]) for r in url_rules.judge(pages, rules, links).collect()}
    assert got[1] == ("a.example.com", "/en/1", "example.com/en/", "block", "rule")
    assert got[2] == ("www.example.com", "/en/2", "www.example.com/en/", "allow", "rule")
    assert got[3][2:4] == ("net/es/", "block") and got[4][2:] == (None, "allow", "none")
    assert got[5] == got[6] == ("", "", None, "allow", "none") and got[11][:2] == ("", "") and got[12][:2] == ("x.net", "")
    assert got[7][2] == "com/"
    assert got[8][3:] == got[9][3:] == ("block", "alias")  # the block reaches aliases of aliases
    assert got[10][3:] == ("allow", "rule")  # explicit allow wins
    assert url_rules.judge(pages, rules, links).count() == len(rows)
    assert url_rules.judge(pages.limit(0), rules.limit(0), links.limit(0)).count() == 0


def test_page_links(spark):
    rows = [
        ("http://a.com/x/y", '<LINK href="/z" rel="canonical">'), ("http://a.com/x/y", "<link rel=canonical href='q?1'>"), ("http://a.com", '<meta http-equiv="refresh" content="0; url=//b.org/r">'),
        ("http://a.com/x", '<link rel="stylesheet" href="s.css">'), ("http://a.com/x", '<link rel="canonical" href="#top">'), (None, '<link rel="canonical" href="/z">'),
    ]
    rows += [
        ("http://c.com/", '<link rel="canonical" href="http://d.com/?a=1&amp;b=2&#38;c&#x2F;d&unknown;"/><link rel="alternate canonical" href=/second><link title="rel=canonical href=/no" rel=icon href="/i">'),
        ("http://e.com/", '<!-- <link rel="canonical" href="http://bad.com/"> --><script>"<link rel=canonical href=/no>"</script><meta content="5;URL=\'/go\'" http-equiv=Refresh><style>'), ("http://f.com/", "<link rel=canonical href='/>'><!--><link rel=canonical href=/f2>"),
    ]
    got = url_rules.page_links(spark.createDataFrame(rows, "url string, html string")).where("dst is not null").collect()
    assert {(r["src"], r["dst"]) for r in got} == {
        ("http://a.com/x/y", "http://a.com/z"), ("http://a.com/x/y", "http://a.com/x/q?1"), ("http://a.com", "http://b.org/r"), ("http://c.com/", "http://d.com/?a=1&b=2&c/d&unknown;"), ("http://c.com/", "http://c.com/second"),
        ("http://e.com/", "http://e.com/go"), ("http://f.com/", "http://f.com/>"),
    }


def test_aliases_by_normal_names(spark):
    rules = spark.createDataFrame([("bad.com", "/", "block"), ("good.com", "/", "allow")], "host string, path string, verdict string")
    rows = [
        (1, "http://one.org/", '<link rel=canonical href="HTTP://BAD.com:80?x&amp;y#f">'), (2, "http://two.org", '<link rel=canonical href="http://One.org:80/#top">'), (3, "https://two.org/", None), (4, "http://bad.com", None), (5, "http://good.com/a", "<link rel=canonical href=http://bad.com/>"),
        (6, "http://x." + "a." * 3000 + "bad.com/", None), (7, "http://six.org/", "<!--<link rel=canonical href=http://bad.com/>-->"), (8, "http://good.com:80/a", "<link rel=canonical href=http://bad.com/>"),
    ]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string")
    got = {r["page_id"]: (r["rule"], r["verdict"], r["via"]) for r in url_rules.judge(pages, rules, url_rules.page_links(pages)).collect()}
    assert got == {1: (None, "block", "alias"), 2: (None, "block", "alias"), 3: (None, "allow", "none"), 4: (None, "block", "alias"), 5: ("good.com/", "allow", "rule"), 6: ("bad.com/", "block", "rule"), 7: (None, "allow", "none"), 8: (None, "allow", "alias")}


def test_planted_redirects_at_scale(spark):
    """Chains, stars and rings of redirects over thousands of pages, against a plain union-find."""
    rng = random.Random(12)
    names = [f"http://{'bad' if rng.random() < 0.02 else 'good' if rng.random() < 0.1 else 'h'}{k % 3}.org/p{k}" for k in range(4000)]
    edges = [(k, k + 1) for k in range(0, 300)] + [(1000, k) for k in range(1001, 1500)] + [(rng.randrange(1500, 4000), rng.randrange(1500, 4000)) for _ in range(1500)]
    out = defaultdict(list)
    for a, b in edges:
        out[a].append(b)
    pages = spark.createDataFrame([(k, u, "".join(f'<link rel="canonical" href="{names[b]}">' for b in out[k])) for k, u in enumerate(names)], "page_id bigint, url string, html string")
    rules = spark.createDataFrame([(f"bad{k}.org", "/", "block") for k in range(3)] + [(f"good{k}.org", "/", "allow") for k in range(3)], "host string, path string, verdict string")
    root = closure(range(4000), edges)
    hit = {root[k] for k, u in enumerate(names) if "//bad" in u}
    got = {r["page_id"]: r["verdict"] for r in url_rules.judge(pages, rules, url_rules.page_links(pages)).collect()}
    assert got == {k: "allow" if "//good" in u else "block" if root[k] in hit else "allow" for k, u in enumerate(names)}


def test_licences(spark):
    text = "Prose goes here and there. "
    rows = [
        ("p/LICENSE", "Released under the MIT License"), ("p/a/code.py", text), ("p/a/b/other.py", text + "Licensed under the Apache License, Version 2.0.\n" + text), ("p/a/LICENSE.txt", "This work is licensed under the GNU General Public License, version 3"),
        ("q/code.py", text), ("p/x.py", None), ("p/y.py", ""), (None, text), ("p/a/b/c/d.py", text), ("p/z.py", "Die Leute gehen mit dem Hund. MIT!"),
    ]
    df = spark.createDataFrame([(*r, 1) for r in rows], "path string, text string, licence int")
    got = {r["path"]: (r["licence"], r["via"], r["source"]) for r in licences.scan_licences(df, licences.default_templates(spark)).collect()}
    assert got["p/LICENSE"][:2] == ("MIT", "own") and got["p/a/b/other.py"][:2] == ("Apache-2.0", "own")
    assert got["p/a/code.py"] == ("GPL-3.0", "inherited", "p/a/") == got["p/a/b/c/d.py"]
    assert got["p/x.py"] == ("MIT", "inherited", "p/") == got["p/y.py"] == got["p/z.py"]
    assert got["q/code.py"] == got[None] == (None, "none", None)
    assert licences.scan_licences(df.limit(0), licences.default_templates(spark)).count() == 0


def shingles(text, k):
    w = (text or "").encode().lower().split()
    return frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else [])


@pytest.mark.parametrize(("k", "num", "den"), [(3, 9, 10), (5, 4, 5)])
def test_jaccard(spark, k, num, den, monkeypatch):
    rng = random.Random(k)
    vocabulary = [f"v{i}" for i in range(3000)]
    passage = rng.choices(vocabulary, k=60)
    docs = []
    for n in (1, 2, 3, 8, 11, 12, 20, 40, 150, 230, 400):
        base = rng.choices(vocabulary, k=n)
        for _ in range(8):
            x = list(base)
            for _ in range(rng.randrange(0, 1 + n // 25)):
                x[rng.randrange(n)] = rng.choice(vocabulary)
            docs.append(" ".join(x))
    docs += [" ".join(passage + rng.choices(vocabulary, k=rng.randrange(5, 90))) for _ in range(60)]
    docs += [docs[30], docs[30].upper(), "a\x0bb c", "", "   ", None]
    monkeypatch.setattr(jaccard, "UNIT_DOCS", 12)  # clusters beyond a task's bound
    df = spark.createDataFrame([(i, t, 0, "x") for i, t in enumerate(docs)] + [(None, docs[3], 0, "x"), (5, docs[5], 0, "x")], "doc_id bigint, text string, component_id int, mark string")
    got = jaccard.jaccard_components(df, k, num, den).collect()
    assert len(got) == len(docs) + 2
    sets = {i: shingles(t, k) for i, t in enumerate(docs)}
    links = [(i, j) for i in sets for j in range(i) if sets[i] and den * len(sets[i] & sets[j]) >= num * len(sets[i] | sets[j])]
    want = closure(sets, links)
    assert links
    for r in got:
        if r["doc_id"] is None:
            assert r["component_id"] is None
        else:
            assert (r["n_shingles"], r["component_id"]) == (len(sets[r["doc_id"]]), want[r["doc_id"]]), r
    kept = jaccard.one_of_each(df, k, num, den)
    assert kept.columns == df.columns
    assert sorted((r["doc_id"] for r in kept.collect()), key=str) == sorted([*(i for i in sets if want[i] == i), None], key=str)
    assert jaccard.jaccard_components(df.limit(0), k, num, den).count() == 0


def test_jaccard_sends_only_documents_that_may_link(spark, monkeypatch):
    """A family of like texts: most have too many words of their own for any link, and are not sent from group to group."""
    rng, words = random.Random(3), [f"b{k}" for k in range(240)]
    texts = []
    for k in range(160):
        mine = list(words)
        for at in rng.sample(range(240), 5 if k < 140 else 2):
            mine[at] = f"own{k}x{at}"
        texts.append(" ".join(mine))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    monkeypatch.setattr(jaccard, "UNIT_DOCS", 10)
    sent, write = {}, jaccard.written

    def counted(table, label, *more):
        out = write(table, label, *more)
        sent[label] = sent.get(label, 0) + out.count()
        return out

    monkeypatch.setattr(jaccard, "written", counted)
    got = {r["doc_id"]: r["component_id"] for r in jaccard.jaccard_components(df, 3, 9, 10).collect()}
    assert sent["large-cells"] and sent.get("group-units", 0) < 4 * len(texts)
    sets = [set(zip(w, w[1:], w[2:])) for w in (t.split() for t in texts)]
    root = list(range(len(texts)))
    for a in range(len(texts)):
        for b in range(a):
            if 10 * len(sets[a] & sets[b]) >= 9 * len(sets[a] | sets[b]) and root[a] != root[b]:
                low, high = sorted((root[a], root[b]))
                root = [low if x == high else x for x in root]
    assert got == dict(enumerate(root)) and 100 < len(set(root)) < 160


def test_jaccard_pair_on_both_sides_of_the_early_tokens(spark):
    """Of two near copies one has just as many counted tokens as early places, the other one fewer; nobody else holds them."""
    inside, outside = [], []
    for k in range(1500):
        (outside if int(jaccard.Shingler(1).set_of(b"w%d" % k)[0]) % 3 else inside).append(f"w{k}")
    common = [f"c{k}" for k in range(80)]
    rare = [f"r{k}" for k in range(21)]
    docs = [rare + common[:79], rare[:20] + common]  # space 0: 21 early places
    docs += [common + [f"own{j}x{k}" for k in range(300)] for j in range(4)]  # what makes the common words common
    docs += [inside[:61] + outside[:239], inside[:60] + outside[:240]]  # space 1: 61 early places, a third of the hashes counted
    df = spark.createDataFrame([(k, " ".join(x)) for k, x in enumerate(docs)], "doc_id bigint, text string")
    got = {r["doc_id"]: r["component_id"] for r in jaccard.jaccard_components(df, 1, 4, 5).collect()}
    assert got == {0: 0, 1: 0, 2: 2, 3: 3, 4: 4, 5: 5, 6: 6, 7: 6}


def test_sharding(spark):
    rows = [(i, f"text {i % 7} é", "a", 0) for i in range(3000)] + [(None, None, "b", 0)] * 3 + [(None, "", "b", 0)] + [(9, "same", "c", 0)] * 2500 + [(11, f"hot id {k}", "c", 0) for k in range(1500)] + [(k, None, "n", 1) for k in range(4000, 5000)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, before string, slot int")
    path = shared_path(spark, "test-shards")
    files = sharding.write_shards(df.repartition(3), path, shards=8, bucket_bytes=4000)
    got = sharding.shard_slots(files).collect()
    assert sorted(((r["doc_id"], r["text"]) for r in got), key=str) == sorted(((r[0], r[1]) for r in rows), key=str)
    slots, size = defaultdict(list), defaultdict(int)
    for r in got:
        slots[r["shard"]].append(r["slot"])
        size[r["bucket"]] += r["size"]
        assert r["grown_shard"] in (r["shard"], 8) and r["size"] == len((r["text"] or "").encode()) + 16
        assert r["text_crc32"] == zlib.crc32((r["text"] or "").encode())
    assert all(sorted(v) == list(range(len(v))) for v in slots.values()) and set(slots) <= set(range(8))
    assert max(size.values()) < 1.6 * 4000  # copies, a hot id and null texts fill no bucket beyond its bound
    assert len({(r["doc_id"], r["shard"]) for r in got}) == len({r[0] for r in rows})
    # other partitions, the same buckets, places and slots
    again = sharding.shard_slots(sharding.write_shards(df.repartition(7, "text"), shared_path(spark, "test-shards"), shards=8, bucket_bytes=4000))
    assert sorted((str(r["doc_id"]), str(r["text"]), r["bucket"], r["slot"]) for r in again.collect()) == sorted((str(r["doc_id"]), str(r["text"]), r["bucket"], r["slot"]) for r in got)
    assert sharding.write_shards(df.limit(0), shared_path(spark, "test-shards")).count() == 0


def test_shards_against_plain_recomputation(spark):
    """Shards by jumping through the steps one by one, with hashes asked of Spark; slots by swapping a list."""
    rows = [(k % 700, f"t{k % 900}") for k in range(1000)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    got = sharding.shard_slots(sharding.write_shards(df, shared_path(spark, "test-shards"), shards=6, bucket_bytes=1000, seed=11)).collect()
    hashes = {(r["k"], r["s"]): r["h"] for r in spark.range(700).select(F.col("id").alias("k"), F.explode(F.sequence(F.lit(1), F.lit(6))).alias("s")).select("k", "s", F.xxhash64("k", "s", F.lit(11)).alias("h")).collect()}

    def shard(k, n):
        at = 0
        for s in range(1, n):
            if hashes[k, s] % (s + 1) == 0:
                at = s
        return at

    assert all((r["shard"], r["grown_shard"]) == (shard(r["doc_id"], 6), shard(r["doc_id"], 7)) for r in got)
    buckets = defaultdict(list)
    for r in sorted(got, key=lambda r: r["place"]):
        buckets[r["bucket"]].append((r["doc_id"], r["text_crc32"]))
    moved = 0
    for b, placed in buckets.items():
        draw = np.random.default_rng([11, b]).random(len(placed))
        want = sorted(placed)
        for i in reversed(range(1, len(want))):
            j = int(draw[i] * (i + 1))
            want[i], want[j] = want[j], want[i]
        assert placed == want
        moved += placed != sorted(placed)
    assert moved > 0.9 * len(buckets) > 5


def test_embeddings(spark):
    rng = np.random.default_rng(2)
    base = rng.standard_normal((120, 48))
    rows = [base[rng.integers(120)] + rng.standard_normal(48) * rng.choice([0.05, 0.2, 0.35]) for _ in range(700)]
    rows += [base[0] + rng.standard_normal(48) * 0.1 for _ in range(300)] + [base[1]] * 200
    data = [(i, [float(np.float32(x)) for x in v], 1) for i, v in enumerate(rows)]
    odd = [(9001, None, 1), (9002, [0.0] * 48, 1), (9003, [float("nan")] * 48, 1), (9004, [None, *[1.0] * 47], 1), (9005, [], 1), (9006, [1.0, 2.0], 1), (None, data[0][1], 1)]
    df = spark.createDataFrame(data + odd, "vec_id bigint, embedding array<float>, kept int")
    e = np.array([d[1] for d in data])
    e /= np.linalg.norm(e, axis=1, keepdims=True)
    close = np.triu(e @ e.T >= 0.95, 1)
    counts = close.sum(0) + close.sum(1)
    want = closure(range(len(data)), np.argwhere(close).tolist())
    for bucket in (2048, 128):  # the small one cuts hot buckets into blocks
        got = {r["vec_id"]: r for r in embedding_dedup.link_embeddings(df, bucket_rows=bucket).collect()}
        found = sum(got[i]["n_links"] for i in range(len(data)))
        assert 0.9 * counts.sum() <= found <= counts.sum()
        assert all(got[i]["n_links"] <= counts[i] for i in range(len(data)))
        same = sum(got[i]["component_id"] == want[i] for i in range(len(data)))
        assert same >= 0.98 * len(data)
        assert all(got[i]["n_links"] == 0 and got[i]["kept"] for i in (9001, 9002, 9003, 9004, 9005, 9006))
    assert embedding_dedup.link_embeddings(df.limit(0)).count() == 0


def test_codes_estimate_without_bias():
    rng = np.random.default_rng(1)
    x = rng.standard_normal((400, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    estimates = []
    for seed in range(40):
        coder = embedding_dedup.Coder(64, 1, 4, seed)
        packed, factor = coder.code(x)
        assert packed.shape == (400, coder.width // 8)
        estimates.append(coder.estimate(packed[200:], factor[200:], coder.turned(x[:200])).T)
        off = np.abs(estimates[-1] - x[:200] @ x[200:].T)
        assert (off > coder.slack(factor[200:], 4.0)).mean() < 1e-3  # the confidence bound holds
    off = np.mean(estimates, 0) - x[:200] @ x[200:].T
    assert abs(off.mean()) < 0.005 and np.abs(off).mean() < 0.02


def test_repeated_ids_of_different_vectors(spark):
    """An id that stands for several vectors: each row has its own links."""
    rows = [(1, [1.0, 0.0, 0.0]), (1, [0.0, 1.0, 0.0]), (2, [1.0, 0.01, 0.0]), (3, [0.0, 1.0, 0.01]), (4, [0.0, 0.0, 5.0]), (4, [0.0, 0.0, 5.0])]
    got = embedding_dedup.link_embeddings(spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")).collect()
    assert sorted((r["vec_id"], r["n_links"], r["component_id"]) for r in got) == [(1, 1, 1), (1, 1, 1), (2, 1, 1), (3, 1, 1), (4, 1, 4), (4, 1, 4)]


def test_pipeline_stages(spark, tmp_path):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns, name
        assert stage(spark, docs.limit(0), sf).count() == 0
        strange = docs.select("doc_id", F.when(F.col("doc_id") > 3, F.col("text")).alias("text"), "lang", "source", "n_chars", F.lit(1).alias("row"), F.lit("q").alias("spans"), F.lit(2).alias("mark"), F.lit(0).alias("score"))
        odd = stage(spark, strange.unionAll(strange.limit(5)), sf)
        assert odd.columns == strange.columns and odd.count() > 0
    done = corpus_pipeline.run(spark, sf).collect()
    assert done and all(r["round_trip"] for r in done)
    assert len({r["doc_id"] for r in done}) == len(done)
