"""Main text, personal data, toxicity, decontamination, pieces: brute force and edge cases."""

import hashlib
import itertools
import math
import random
import re

import pytest
from pyspark.sql import functions as F

from ebbmine.llm import decontamination, pieces, private_data, toxicity
from ebbmine.plans.inspect import formatted
from ebbmine.llm.main_text import extract_main_text, main_text

LONG = "word, " * 40


def test_main_text_keeps_the_article_only():
    page = f"""<html><head><title>t</title><style>p{{}}</style><script>var a="<p>x</p>";</script></head><body><header><h1>Site</h1></header><nav><a href=x>menu</a></nav>
<div class="sidebar"><p>{LONG}</p></div><article><h1>A &amp; B</h1><p><b>One  {LONG}<br><p>Two\n {LONG}</p></article><div class="comments"><p>{LONG}</p></div>
<div class="cookie-notice">we use</div><form><p>{LONG}</p></form><footer>&copy; x</footer></body></html>"""
    got = main_text(page).split("\n\n")
    assert got == ["A & B", "One " + LONG.strip(), "Two " + LONG.strip()]


def test_main_text_edges(spark):
    assert main_text(None) == main_text("") == main_text("<div></div>") == ""
    assert main_text("a < b") == "a < b"
    assert len(main_text("<p>" + "x" * 300_000)) == 300_000
    assert main_text("<div>" * 5000 + "deep" + "</div>" * 5000) == "deep"
    rows = [(1, "u", None, 5), (1, "u", None, 5), (2, None, "<p>x</p>", 6), (None, "v", "", 7)]
    df = spark.createDataFrame(rows, "page_id bigint, url string, html string, text int")
    assert sorted(extract_main_text(df).collect(), key=str) == sorted([(1, "u", "", 0), (1, "u", "", 0), (2, None, "x", 1), (None, "v", "", 0)], key=str)
    assert extract_main_text(df.limit(0)).count() == 0


PATTERNS = [
    ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"),
    ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]"),
]


def _luhn(d):
    return sum((2 * int(c) - 9 * (int(c) > 4)) if i % 2 else int(c) for i, c in enumerate(reversed(d))) % 10 == 0


def base(text):
    out = []
    for k, (name, p) in enumerate(PATTERNS):
        for m in re.finditer(p, text or ""):
            d = re.sub("[^0-9]", "", m[0])
            ok = {"email": lambda: True, "ip": lambda: all(int(x) <= 255 for x in m[0].split(".")), "card": lambda: 14 <= len(d) <= 19 and _luhn(d), "phone": lambda: 10 <= len(d) <= 15}[name]()
            if ok:
                out.append((m.start(), k, m.end(), name))
    return sorted(out)


TEXTS = [
    None, "", "x", "a@b.com_x@y.zz a@b..c a@@b.c ü.é@x.de %@-.-", "1.2.3.4.5.6.7.8 256.1.1.1 000255.1.1.01 1.2.3.4", "4111 1111 1111 1111 4111-1111-1111-1111x 4111111111111112",
    "+1 (988) 555-2485 +1234567890123456 +12(345)678-90 ++49 30 1234567", "😀 mail 😀 a@b.com 😀 10.0.0.1", "1" * 50_000, "a" * 50_000 + "@", "1 " * 20_000 + "2", "+1" + " (" * 5_000 + "2", "a.b@c.d " * 300,
]


def test_base_patterns(spark):
    rows = [(k, t, "x") for k, t in enumerate(TEXTS)] + [(3, TEXTS[3], "x"), (None, TEXTS[4], "y")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, spans string")
    got = private_data.digest(private_data.protect(df)).collect()
    assert len(got) == len(rows)
    for doc, text, _ in rows:
        want = base(text)
        mine = [g for g in got if g["doc_id"] == doc]
        assert mine
        for g in mine:
            assert g["base_sha256"] == hashlib.sha256(",".join(f"{n}:{a}:{b}" for a, _, b, n in want).encode()).hexdigest(), (doc, g["spans"][:200])
            assert [g[f"n_{n}"] for n, _ in PATTERNS] == [sum(x[3] == n for x in want) for n, _ in PATTERNS]
    assert private_data.digest(private_data.protect(df.limit(0))).count() == 0


def test_terms_that_disclose(spark):
    """A surname that stands by one address in several texts reveals it; common words do not."""
    plain = [(k, f"Some common letters about weather number {k} from anyone") for k in range(100, 200)]
    told = [(k, f"Some common words{k} here Zyxwvut wrote from zy@mail.com about weather") for k in range(5)]
    df = spark.createDataFrame(plain + told, "doc_id bigint, text string")
    got = {r["doc_id"]: r for r in private_data.protect(df).collect()}
    assert all("zyxwvut" in [t["value"] for t in got[k]["terms"]] for k in range(5))
    assert not any(t["value"] in ("some", "common", "about", "weather") for k in range(5) for t in got[k]["terms"])
    assert not any(got[k]["terms"] for k in range(100, 200))
    clean = {r["doc_id"]: r["text"] for r in private_data.without_private_data(df.withColumn("row", F.lit(1)).withColumn("windows", F.lit("w"))).collect()}
    assert "zy@mail.com" not in clean[0] and "Zyxwvut" not in clean[0] and "[EMAIL]" in clean[0] and clean[100] == dict(plain)[100]


def test_copies_of_a_text_count_once(spark):
    """Five texts name Zyxwvut by one address; that one of them has many copies makes the name no less telling."""
    plain = [(k, f"Some common letters about weather number {k} from anyone") for k in range(1000, 1400)]
    told = [(k, f"Some common words{k} here Zyxwvut wrote from zy@mail.com about weather") for k in range(5)]
    df = spark.createDataFrame(plain + told + [(k, told[0][1]) for k in range(5, 305)], "doc_id bigint, text string")
    base = private_data.find_base(df)
    telling = {r["term"]: r["disclosure"] for r in private_data.disclosures(df, base, *private_data.terms_with(base)).collect()}
    assert telling["zyxwvut"] == pytest.approx(1.0)
    assert telling["weather"] == pytest.approx(0.0)
    got = private_data.protect(df).collect()
    assert all(("zyxwvut", True) in [(t["value"], t["cut"]) for t in r["terms"]] for r in got if r["doc_id"] < 1000)


def test_terms_are_counted_without_shuffling_texts(spark, monkeypatch):
    """No text goes through a shuffle, whether the counted terms and the copied texts are broadcast or not, and the counts are the same."""
    rows = [f"common words {'x' * (k % 9 + 4)} by an{k % 3}@mail.com" for k in range(40)] + [f"common weather {'y' * (k % 5 + 4)}" for k in range(30)]
    df = spark.createDataFrame(list(enumerate(rows)), "doc_id bigint, text string")
    base, found = private_data.find_base(df), []
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        for listed in (1000, 0):
            monkeypatch.setattr(private_data, "LISTED", listed, raising=False)
            got = private_data.disclosures(df, base, *private_data.terms_with(base))
            assert not re.search(r"\) Exchange\nInput \[\d+\]: \[[^\]]*\btext#", formatted(got))
            found.append({(r["entity"], r["term"]): r["disclosure"] for r in got.collect()})
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    assert len(found[0]) > 10 and found[0] == found[1]


def test_terms_far_from_a_value_disclose(spark):
    """The name stands hundreds of characters away from the address, and twice."""
    filler = "Nothing else happened there. " * 20
    plain = [(k, f"{filler} Some letters about weather number {k}") for k in range(100, 200)]
    told = [(k, f"Zyxwvut was here. {filler} Write to zy@mail.com about weather. {filler} Zyxwvut") for k in range(1)] + [(k, f"Zyxwvut was here, day {k}. {filler} Write to zy@mail.com {filler} Zyxwvut") for k in range(1, 5)]
    df = spark.createDataFrame(plain + told, "doc_id bigint, text string")
    clean = {r["doc_id"]: r["text"] for r in private_data.without_private_data(df).collect()}
    assert not any("Zyxwvut" in clean[k] or "zy@" in clean[k] for k in range(5))
    assert all("Nothing else happened there." in clean[k] for k in clean) and clean[100] == plain[0][1]


def test_disclosures_against_plain_counts(spark):
    """All counts by sets of texts, with copies, near copies and shared values."""
    rng = random.Random(5)
    names = [f"name{chr(97 + k)}{chr(97 + j)}" for k in range(6) for j in range(4)]
    texts = [" ".join(rng.choices(["alpha", "beta", "gamma", "delta", "epsilon", "zeta"], k=8)) + f" number{k}" for k in range(200)]
    for k in range(60):
        e = rng.randrange(8)
        texts.append(f"{rng.choice(names[3 * e : 3 * e + 4])} wrote {rng.choice(['alpha', 'beta'])} to u{e}@mail.com and {rng.choice(names)} day {'x' * (k % 7 + 4)}")
    rows = texts + texts[200:210] * 30
    df = spark.createDataFrame(list(enumerate(rows)), "doc_id bigint, text string")
    base = private_data.find_base(df)
    held, terms = private_data.terms_with(base)
    got = {(r["entity"], r["term"]): r["disclosure"] for r in private_data.disclosures(df, base, held, terms).collect()}
    units = {t: ({w for w in re.findall(r"[a-z]{4,}", t)} | {w[:4] + "*" for w in re.findall(r"[a-z]{4,}", t)}, set(re.findall(r"u\d@mail\.com", t))) for t in set(rows)}
    outside = {t: {w for w in re.findall(r"[a-z]{4,}", re.sub(r"\S+@\S+", " ", t))} for t in units}
    want = {}
    for e in {e for _, es in units.values() for e in es}:
        of = [t for t, (_, es) in units.items() if e in es]
        for w in {x for t in of for x in outside[t] | {y[:4] + "*" for y in outside[t]}}:
            n_both = sum(w in outside[t] or w in {y[:4] + "*" for y in outside[t]} for t in of) - 1
            n_term, n_e, total = sum(w in ws for ws, _ in units.values()) - 1, len(of) - 1, len(units) - 1
            if n_both > 0:
                want["0:" + e, w] = math.log2(total * n_both / (max(n_term, n_both) * n_e)) / math.log2(total / n_e)
    assert len(want) > 50 and got.keys() == want.keys()
    assert all(got[k] == pytest.approx(want[k]) for k in want)
    # what is masked: all places of the telling words, in the texts of that value only
    for r, text in ((r, rows[r["doc_id"]]) for r in private_data.protect(df).collect()):
        words = {}
        for e in units[text][1]:
            for w in outside[text]:
                words[w] = max(words.get(w, 0), want.get(("0:" + e, w), 0))
        spans = [(m.start(), m.end(), words[m[0]] >= 0.8) for m in re.finditer(r"[a-z]{4,}", text) if words.get(m[0], 0) >= 0.5]
        assert [(t["start"], t["end"], t["cut"]) for t in r["terms"]] == spans


def test_generalised_to_a_stem(spark):
    """A word that tells much, with first letters that tell little, is replaced by these."""
    told = [(k, f"Westerby{'' if k % 4 else 'x'} was seen, day {'x' * (k + 4)}, by an@mail.com today") for k in range(8)]
    plain = [(k, f"Western winds blow over hill {'y' * (k % 40 + 4)} {'Westerby' if k < 104 else 'Westfalen'} today") for k in range(100, 180)]
    df = spark.createDataFrame(told + plain, "doc_id bigint, text string")
    clean = {r["doc_id"]: r["text"] for r in private_data.without_private_data(df).collect()}
    assert clean[1].startswith("west* was") and "[EMAIL]" in clean[1] and clean[150] == dict(plain)[150]


def test_toxicity_finds_sentences(spark):
    good = [(k, f"The weather is fine in town {k}. People walk and talk there. Nothing else happened."  , 0) for k in range(0, 90)]
    bad = [(k, f"The weather is fine in town {k}. You rotten scoundrel! People walk there.", 1) for k in range(100, 160)]
    docs = spark.createDataFrame([(k, t) for k, t, _ in good + bad], "doc_id bigint, text string")
    labels = spark.createDataFrame([(k, y, 9) for k, _, y in good + bad], "doc_id bigint, toxic int, text int")
    model = toxicity.train(docs, labels)
    more = docs.unionAll(spark.createDataFrame([(None, None), (7, ""), (8, "no words 123 !?")], docs.schema))
    rows = toxicity.score(more.withColumn("score", F.lit(3)), model).collect()
    assert len(rows) == 153
    right = sum((r["score"] >= toxicity.THRESHOLD) == (r["doc_id"] is not None and r["doc_id"] >= 100) for r in rows)
    assert right >= 150
    spans = [r for r in rows if r["doc_id"] == 105][0]["offending"]
    assert any("scoundrel" in bad[5][1][s["start"] : s["end"]] for s in spans)
    assert {r["score"] for r in rows if r["doc_id"] is None} == {0.0}
    empty = toxicity.train(docs.limit(0), labels.limit(0))
    assert all(r["score"] < toxicity.THRESHOLD for r in toxicity.score(docs, empty).collect())
    assert toxicity.without_toxic(docs.withColumn("lang", F.lit("en")), model).columns == ["doc_id", "text", "lang"]


def test_masks_hit_all_stretches():
    n, k = 13, 2
    places = [{s + i for i, c in enumerate(m) if c == "1"} for m in decontamination.MASKS for s in range(n - len(m) + 1)]
    assert all(any(not p & set(subs) for p in places) for subs in itertools.combinations(range(n), k))


def test_leaks(spark):
    words = [f"w{k}" for k in range(400)]
    item = " ".join(words[:30])
    changed = words[:30]
    changed[10], changed[20] = "other", "thing"
    docs = [
        (1, "intro Text " + item.upper() + ". more"), (2, "x y z " + ", ".join(changed) + " tail"), (3, " ".join(words[100:200])), (4, " ".join(words[:8])), (5, None), (6, ""), (7, "alpha beta"), (8, "say alpha-beta now"),
        (9, " ".join(words[5:20])), (10, "İ " + item), (None, item), (1, "intro Text " + item.upper() + ". more"),
    ]
    df = spark.createDataFrame([(*d, 0) for d in docs], "doc_id bigint, text string, item_id int")
    bench = spark.createDataFrame([(50, item), (51, "alpha beta"), (52, None), (53, "..."), (50, item)], "item_id bigint, text string")
    got = [(r["doc_id"], r["item_ids"]) for r in decontamination.find_leaks(df, bench).collect()]
    assert sorted(got, key=str) == sorted([(1, [50]), (1, [50]), (2, [50]), (7, [51]), (8, [51]), (9, [50]), (10, [50]), (None, [50])], key=str)
    span = [r for r in decontamination.find_leaks(df, bench).collect() if r["doc_id"] == 10][0]["spans"][0]
    assert docs[9][1][span["start"] : span["end"]] == item
    sliced = decontamination.find_leaks(df, bench, slice_words=1).select("doc_id", "item_ids").collect()
    assert sorted(map(tuple, sliced), key=str) == sorted(got, key=str)
    assert decontamination.find_leaks(df, bench.limit(0)).count() == 0 and decontamination.find_leaks(df.limit(0), bench).count() == 0
    assert sorted(r["doc_id"] for r in decontamination.without_leaks(df, bench).collect()) == [3, 4, 5, 6]


MODEL = "/opt/tokenizers/piece_bpe_32k.model"
PIECE_TEXTS = ["", " ", "  a", "a  b   c ", "\n\n x", "日本語 テスト", "😀 hi", "x" * 3000, " " * 300, "aaaa " * 50, "tab\tsep", None, "<s> </s> <0x41>", "é́", "Hello, world! Hello, wonder.", "internationalisation internationally", "a▁b"]


def test_pieces_match_the_reference_library(spark):
    sentencepiece = pytest.importorskip("sentencepiece")
    reference = sentencepiece.SentencePieceProcessor(model_file=MODEL)
    model = pieces.PieceModel(MODEL)
    df = spark.createDataFrame([(k, t, 1) for k, t in enumerate(PIECE_TEXTS)] + [(None, "x y", 2), (3, "x y", 2)], "doc_id bigint, text string, ids int")
    rows = pieces.decode_ids(pieces.encode_texts(df, model, verify=True), model).collect()
    assert len(rows) == len(PIECE_TEXTS) + 2
    for r in rows:
        assert r["ids"] == reference.encode(r["text"] or "")
        assert r["round_trip"] and r["decoded"] == (r["text"] or "").replace("▁", " ")
    assert pieces.encode_texts(df.limit(0), model).count() == 0


def test_unigram_forward_is_the_best_score():
    class Tiny:
        bpe, bytes, unknown, longest = False, {}, 0, 3
        scores = {"a": -1.0, "b": -1.0, "ab": -1.5, "abc": -4.0, "c": -1.0, "bc": -1.2}
        ids = {p: k + 1 for k, p in enumerate(scores)}

    e = pieces.Encoder(Tiny())
    e.forward(sorted(["abc", "ab", "abcab", "bca"]))

    def best(w):
        if not w:
            return 0.0, []
        return max(((best(w[n:])[0] + Tiny.scores[w[:n]], [Tiny.ids[w[:n]], *best(w[n:])[1]]) for n in (1, 2, 3) if w[:n] in Tiny.scores), key=lambda x: x[0])

    import numpy as np

    for w in ("abc", "ab", "abcab", "bca"):
        assert np.frombuffer(e.words[w], np.int32).tolist() == best(w)[1]
