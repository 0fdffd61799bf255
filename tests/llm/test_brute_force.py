"""Plain re-computations on the small tables, beside the operators' own way."""

import html
import math
import random
import re
import zlib
from collections import Counter

import pytest

from ebbmine.llm import decontamination, licences, queries, toxicity
from ebbmine.llm.decontamination import SeedIndex

SF = "/root/testdata/sf0.001"


def test_main_text_of_the_given_pages(spark):
    pages = {r["page_id"]: r["html"] for r in spark.read.parquet(f"{SF}/pages.parquet").collect()}
    got = queries.op1_main_text(spark, SF).collect()
    assert len(got) == len(pages)
    for r in got:
        article = re.search(r"<article>(.*?)</article>", pages[r["page_id"]], re.S)[1]
        parts = (re.sub(r"\s+", " ", html.unescape(re.sub(r"<[^>]+>", " ", x))).strip() for x in re.split(r"</?(?:p|h1)>", article))
        assert r["text"] == "\n\n".join(x for x in parts if x) and r["n_chars"] == len(r["text"])


def test_licences_against_plain_cosines(spark):
    """Each unit of each document against each template, then the licence files of its folder."""
    docs = {r["doc_id"]: r for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    terms = lambda t: re.findall(r"[a-z]+|[0-9]+(?:\.[0-9]+)*", t.lower())
    df = Counter(w for r in docs.values() for w in set(terms(r["text"])))
    idf = lambda w: math.log((1 + len(docs)) / (1 + df[w])) + 1

    def vector(text):
        return {w: (1 + math.log(n)) * idf(w) for w, n in Counter(terms(text)).items()}

    templates = [(name, vector(t)) for name, t in licences.TEMPLATES]
    own, folder, named = {}, {}, {}
    for doc, r in docs.items():
        named[doc] = bool(re.search("licensed under|released under the|license, version|public license", r["text"], re.I))
        folder[doc] = f"{r['source']}/{r['lang']}/{doc // 100}/"
        for unit in [*re.split(r"\n+|(?<=[.;!?])\s+", r["text"]), *([r["text"]] if named[doc] else [])]:
            v = vector(unit)
            for name, u in templates:
                shared = v.keys() & u.keys()
                if len(shared) >= 2:
                    score = round(sum(v[w] * u[w] for w in shared) / math.sqrt(sum(x * x for x in v.values())) / math.sqrt(sum(x * x for x in u.values())), 6)
                    if score >= 0.6:
                        own[doc] = max(own.get(doc, (0, "")), (score, name))
    given = {}
    for doc, (score, name) in own.items():
        if named[doc]:
            given[folder[doc]] = min(given.get(folder[doc], (0, "", "")), (-score, f"{folder[doc]}LICENSE.{doc}", name))
    want = {d: (own[d][1], "own") if d in own else (given[folder[d]][2], "inherited") if folder[d] in given else (None, "none") for d in docs}
    got = {r["doc_id"]: (r["licence"], r["via"]) for r in queries.op5_tfidf_licences(spark, SF).collect()}
    assert got == want and {"own", "inherited", "none"} == {x[1] for x in want.values()}


def test_seeds_against_all_layouts():
    rng = random.Random(8)
    words = [f"t{k}" for k in range(50)]
    items = [(k, " ".join(rng.choices(words, k=rng.randrange(6, 40)))) for k in range(12)]
    index = SeedIndex(items)
    for _ in range(150):
        _, item = rng.choice(items)
        part = item.split()
        a = rng.randrange(0, max(1, len(part) - 13))
        part = part[a : a + rng.randrange(13, 40)]
        for _ in range(rng.randrange(0, 4)):
            part[rng.randrange(len(part))] = rng.choice(words + ["zz"])
        text = " ".join(rng.choices(words, k=rng.randrange(0, 20)) + part + rng.choices(words, k=rng.randrange(0, 20)))
        row = text.split()
        found = {h[0] for h in index.hits(text)}
        for k, t in items:
            other = t.split()
            least = min(13, len(other))
            near = sure = False
            for shift in range(-len(other) + 1, len(row)):
                same = [0 <= shift + i < len(row) and row[shift + i] == w for i, w in enumerate(other)]
                for n in range(least, len(other) + 1):
                    for i in range(len(other) - n + 1):
                        if 0 <= shift + i and shift + i + n <= len(row):
                            hits = sum(same[i : i + n])
                            near = near or hits >= 0.8 * n
                            sure = sure or (n == least == 13 and hits >= 11)
            assert not sure or k in found  # what the masks promise
            assert k not in found or near  # and nothing that does not agree


def test_leaks_of_the_given_documents(spark):
    """Every document against every item, laid at every shift: no index, no masks."""
    import numpy as np

    docs = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    items = [r["text"] for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    number: dict[str, int] = {}
    of = lambda t: np.array([number.setdefault(w, len(number)) for w in re.findall(r"[^\W_]+", t.lower())], int)
    rows, wanted = {d: of(t) for d, t in docs.items()}, [of(t) for t in items]
    sure, near = set(), set()
    for d, row in rows.items():
        for item in wanted:
            least = min(13, len(item))
            same = row[:, None] == item[None, :]
            for shift in range(-len(item) + least, len(row) - least + 1):
                hit = np.diagonal(same, -shift)
                if hit.sum() < 0.8 * least:
                    continue
                total = np.append(0, np.cumsum(hit))
                runs = total[least:] - total[:-least]
                if (runs >= least - (2 if least == 13 else 0)).any():
                    sure.add(d)  # what the masks promise
                gain = np.append(0.0, np.cumsum(np.where(hit, 1.0, -4.0)))
                if any(gain[j] - gain[: j - least + 1].min() >= -1e-9 for j in range(least, len(gain))):
                    near.add(d)
    got = {r["doc_id"] for r in queries.op9_spaced_seed_leaks(spark, SF).collect()}
    assert sure and sure <= got <= near
    assert decontamination.find_leaks(spark.read.parquet(f"{SF}/documents.parquet").limit(0), spark.read.parquet(f"{SF}/benchmark.parquet")).count() == 0


def test_toxicity_scores_by_hand(spark):
    """The noisy-or of the sentences, sentence by sentence, from the fitted weights."""
    docs, labels = (spark.read.parquet(f"{SF}/{n}.parquet") for n in ("documents", "labels"))
    model = toxicity.train(docs, labels)
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    for r in queries.op4_noisy_or_toxicity(spark, SF).collect():
        clean = 1.0
        for sentence in re.findall(r"[^.!?\n]+", texts[r["doc_id"]] or ""):
            words = set(re.findall(r"[^\W\d_]+", sentence.lower()))
            if words:
                z = model.bias + sum(float(model.weights[toxicity.features(w, len(model.weights))].sum()) for w in words)
                clean *= 1 - 1 / (1 + math.exp(-z))
        odds = math.inf if clean < 1e-13 else math.log(1 / clean - 1) + model.shift if clean < 1 else -math.inf
        want = 1.0 if odds > 700 else 1 / (1 + math.exp(-odds)) if odds > -700 else 0.0
        assert r["score"] == pytest.approx(want, abs=1e-9)
        assert r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) and r["predicted"] == (r["score"] >= 0.7)


def test_toxicity_sample_is_bounded(spark):
    """Rows that share an id count once, held-out rows never, and no more bytes than allowed are taken."""
    seen = []
    rows = [(k, f"text {k} " + ("rotten " if k % 2 else "") + "x" * (200 if k % 5 else 5000)) for k in range(300)] + [(2, f"again {k}") for k in range(400)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    labels = spark.createDataFrame([(k, k % 2) for k in range(300)], "doc_id bigint, toxic int")
    real = toxicity.calibrated
    toxicity.calibrated = lambda texts, toxic: seen.extend(texts) or real(texts, toxic)
    try:
        toxicity.train(docs, labels, per_class=50, most_bytes=20_000)
    finally:
        toxicity.calibrated = real
    assert 20 < len(seen) <= 100 and sum(map(len, seen)) <= 20_000
    assert sum(x.startswith("again") or x.startswith("text 2 ") for x in seen) <= 1
    assert not any(zlib.crc32(x.split()[1].encode()) % 3 == 1 for x in seen if x.startswith("text"))


def test_pieces_and_toxicity_queries_are_whole(spark):
    n = spark.read.parquet(f"{SF}/documents.parquet").count()
    rows = queries.op10_shared_prefix_pieces(spark, SF).collect()
    assert len(rows) == n and all(r["round_trip"] and r["n_tokens"] == len(r["ids"]) for r in rows)
    rows = queries.op4_noisy_or_toxicity(spark, SF).collect()
    assert len(rows) == n and all(0 <= r["score"] <= 1 for r in rows)
