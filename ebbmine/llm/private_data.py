"""Personal data: base patterns, and information-theoretic sanitisation of what gives them away.

The base finds e-mail addresses, IP addresses, payment cards and phone numbers. Each value found is
a protected entity. The corpus tells how strongly a term reveals an entity e, with distinct texts as units:
pmi(t, e) = log2(D * n(t, e) / (n(t) * n(e))) against the information content ic(e) = log2(D / n(e)),
where n(t, e) counts the texts that hold both. A term's disclosure is pmi / ic. All four counts leave out one text
that holds both (the one at hand): a pair known from a single text is no evidence, since every
rare word beside a value that occurs once would score the maximum otherwise.

From `generalise_at` on a term is generalised: to its stem, the class of all words with its first letters,
if the corpus shows that the stem reveals the entity less than that; else to a placeholder. From `remove_at`
on it is removed. Both happen wherever the term stands in a text with that entity.

DataFrame expressions only. Pairs are the distinct terms (and stems) of a whole text with its distinct values;
values of one text have no evidence and make no pairs. Counts are pre-aggregated before each
shuffle, and copies of a text count once. Null or empty text: no span. Repeated rows and repeated
or null ids: each row has its own result. Very long texts are searched whole; all patterns run in
linear time without backtracking over long runs. Words under 4 letters are no terms. Extra columns are ignored, or carried whole.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import found_spans, only, written

KINDS = ("email", "ip", "card", "phone", "term")
# The patterns of the contract, with possessive repeats and fenced starts: same matches, linear time.
EMAIL = r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
ADDRESS = r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}"
CARD = r"[0-9]++(?:[\x20-][0-9]++)*+"
PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
TERM = r"\p{L}{4,}+"
#: Letters of a stem; its sign is no letter, so no term is a stem.
STEM, SIGN = 4, "*"
#: Terms, or hashes of texts, that are broadcast at most.
LISTED = 1_000_000
NO_TERMS = "array<struct<start:int,kind:int,end:int,value:string,cut:boolean>>"


def _digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def _luhn(value: Column) -> Column:
    def step(total: Column, k: Column) -> Column:
        d = F.substring(F.reverse(_digits(value)), k, F.lit(1)).cast("int") * F.when(k % 2 == 0, 2).otherwise(1)
        return total + F.when(d > 9, d - 9).otherwise(d)

    return F.aggregate(F.sequence(F.lit(1), F.length(_digits(value))), F.lit(0), step) % 10 == 0


def _labelled(kind: int):
    return lambda s: F.struct(s["start"].alias("start"), F.lit(kind).alias("kind"), s["end"].alias("end"), s["value"].alias("value"), F.lit(True).alias("cut"))


def _of_kind(kind: int):
    return lambda s: s["kind"] == kind


def base_spans(text: Column) -> Column:
    """array<struct<start,kind,end,value,cut>> of the base, by start, then kind; kind as an index of KINDS."""
    text = F.coalesce(text, F.lit(""))

    def small(part: Column) -> Column:
        bare = F.regexp_replace(part, "^0+", "")
        return (F.length(bare) <= 3) & (F.coalesce(bare.try_cast("int"), F.lit(0)) <= 255)

    def counted(low: int, high: int):
        return lambda s: F.length(_digits(s["value"])).between(low, high)

    rules = (
        (EMAIL, "@", lambda s: F.lit(True)),
        (ADDRESS, ".", lambda s: F.forall(F.split(s["value"], r"\."), small)),
        (CARD, None, lambda s: F.when(counted(14, 19)(s), _luhn(s["value"])).otherwise(False)),
        (PHONE, "+", counted(10, 15)),
    )
    none = F.array().cast(NO_TERMS)
    parts = []
    for kind, (pattern, sign, keep) in enumerate(rules):
        hits = F.transform(F.filter(found_spans(text, pattern), keep), _labelled(kind))
        may = F.contains(text, F.lit(sign)) if sign else text.rlike("[0-9](?:[ -]?[0-9]){13}")
        parts.append(F.when(may, hits).otherwise(none))
    return F.array_sort(F.concat(*parts))


def _entities(spans: Column) -> Column:
    """The distinct values of the base spans."""

    def entity(s: Column) -> Column:
        value = F.when(s["kind"] >= 2, _digits(s["value"])).otherwise(F.lower(s["value"]))
        return F.concat_ws(":", s["kind"].cast("string"), value)

    return F.array_distinct(F.transform(spans, entity))


def find_base(docs: DataFrame, carry: bool = False) -> DataFrame:
    """docs(doc_id, text) -> row, doc_id, text_hash, spans, entities and held (the text, where a value was
    found), written to the shared folder; with carry also the text and `carried`, a struct of all columns of docs (so no name can clash)."""
    whole = [F.struct(*[docs[f"`{c}`"] for c in docs.columns]).alias("carried")] if carry else []
    rows = docs.select(docs["doc_id"].cast("bigint").alias("doc_id"), docs["text"].cast("string").alias("text"), *whole)
    found = rows.withColumn("spans", base_spans(F.col("text")))
    found = found.select(
        F.monotonically_increasing_id().alias("row"), "doc_id", *(["carried"] if carry else []), F.xxhash64("text").alias("text_hash"), "spans",
        _entities(F.col("spans")).alias("entities"), F.when(F.size("spans") > 0, F.col("text")).alias("held"),
    )
    return written(found, "private-base")


def _stem(term: Column) -> Column:
    return F.concat(F.substring(term, 1, STEM), F.lit(SIGN))


def terms_with(base: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(row, text_hash, entity) of the values found, and (row, text_hash, term, start, end) of the words
    of the whole texts that hold one. Both only for values of several distinct texts: the others have no evidence."""
    held = base.where(F.size("spans") > 0).select("row", "text_hash", F.explode("entities").alias("entity"))
    often = held.groupBy("entity").agg(F.min("text_hash").alias("a"), F.max("text_hash").alias("b")).where("a < b").select("entity")
    held = written(held.join(often, "entity"), "private-entities")
    rows = base.join(held.select("row").distinct(), "row").select("row", "text_hash", "spans", F.explode(found_spans(F.col("held"), TERM)).alias("t"))
    # words inside another base span are part of that span, not terms
    apart = ~F.exists("spans", lambda s: (s["start"] < F.col("t.end")) & (s["end"] > F.col("t.start")))
    return held, written(rows.where(apart).select("row", "text_hash", F.lower("t.value").alias("term"), "t.start", "t.end"), "private-terms")


def _listed(df: DataFrame) -> DataFrame:
    """A side of a join: broadcast if it has no more rows than LISTED, else joined by a shuffle."""
    df = written(df, "private-listed")
    return F.broadcast(df) if df.count() <= LISTED else df


def disclosures(docs: DataFrame, base: DataFrame, held: DataFrame, terms: DataFrame) -> DataFrame:
    """entity, term, disclosure of the pairs with evidence, terms and stems. All four counts run over distinct texts, without the one at hand."""
    words = terms.select("text_hash", "term").distinct()
    both = words.unionAll(words.select("text_hash", _stem(F.col("term")).alias("term"))).distinct()
    by_text = held.select("entity", "text_hash").distinct().join(both, "text_hash")
    pairs = written(by_text.groupBy("entity", "term").agg((F.count("*") - 1).alias("n_both")).where("n_both > 0"), "private-pairs")
    entities = held.select("entity", "text_hash").distinct().groupBy("entity").agg((F.count("*") - 1).alias("n_entity"))
    texts = written(base.groupBy("text_hash").agg(F.count("*").alias("rows")), "private-texts")
    total = F.lit(texts.count() - 1)
    # only terms of a pair are counted; they and the copied texts go to the rows, so that no text is shuffled
    wanted = _listed(pairs.select("term").distinct())
    # a text that comes c times adds c rows to its terms' counts of such texts, which are divided by c: no hash travels with a term
    copied = _listed(texts.where("rows > 1"))
    rows = docs.select(docs["text"].cast("string").alias("text"))
    found = rows.select(F.xxhash64("text").alias("text_hash"), F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(TERM), F.lit(0))).alias("words"))
    found = found.join(copied, "text_hash", "left").select("words", F.coalesce("rows", F.lit(1).cast("bigint")).alias("rows"))
    every = found.select("rows", F.explode(F.concat("words", F.array_distinct(F.transform("words", _stem)))).alias("term")).join(wanted, "term")
    counts = every.groupBy("term", "rows").agg(F.count("*").alias("n")).groupBy("term").agg((F.sum(F.expr("n div rows")) - 1).alias("n_term"))
    pmi = F.log2(total * F.col("n_both") / (F.greatest("n_term", "n_both") * F.col("n_entity")))
    return (
        pairs.join(counts, "term").join(entities, "entity")
        .select("entity", "term", F.when(total > F.col("n_entity"), pmi / F.log2(total / F.col("n_entity"))).otherwise(0.0).alias("disclosure"))
    )


def protect(docs: DataFrame, generalise_at: float = 0.5, remove_at: float = 0.8, carry: bool = False) -> DataFrame:
    """One row per document: row, doc_id, (carried,) spans, terms, where terms are
    array<struct<start,kind,end,value,cut>>: the terms to generalise (cut false; value is a stem, or the
    term if the stem tells as much) or remove (cut true)."""
    base = find_base(docs, carry)
    held, terms = terms_with(base)
    telling = disclosures(docs, base, held, terms).where(F.col("disclosure") >= generalise_at)
    telling = written(telling, "private-telling")
    of_row = held.select("row", "entity").join(telling, "entity").groupBy("row", "term").agg(F.max("disclosure").alias("disclosure"))
    told = of_row.where(~F.endswith("term", F.lit(SIGN)))
    stems = of_row.where(F.endswith("term", F.lit(SIGN))).select("row", F.col("term").alias("stem"), F.lit(True).alias("stem_tells"))
    hits = (
        told.withColumn("stem", _stem(F.col("term"))).join(stems, ["row", "stem"], "left").join(terms, ["row", "term"])
        .groupBy("row", "start", "end")
        .agg(F.max("disclosure").alias("disclosure"), F.min(F.when(F.col("stem_tells"), F.col("term")).otherwise(F.col("stem"))).alias("value"))
    )
    spans = F.struct("start", F.lit(KINDS.index("term")).alias("kind"), "end", "value", (F.col("disclosure") >= remove_at).alias("cut"))
    hits = hits.groupBy("row").agg(F.array_sort(F.collect_list(spans)).alias("terms"))
    return base.drop("entities", "held", "text_hash").join(hits, "row", "left").withColumn("terms", F.coalesce("terms", F.array().cast(NO_TERMS)))


def listing(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))), ",")


def sanitised(text: Column, spans: Column) -> Column:
    """The text with each span replaced by its kind in brackets; generalised terms by their stem, where that
    is less telling; removed terms leave nothing. Overlapping spans are covered together, under the first one's label."""
    names = F.array(*[F.lit(f"[{k.upper()}]") for k in KINDS])

    def step(acc: Column, s: Column) -> Column:
        fresh = s["start"] >= acc["at"]
        term = s["kind"] == KINDS.index("term")
        label = F.when(term & s["cut"], "").when(term & F.endswith(s["value"], F.lit(SIGN)), s["value"]).otherwise(F.get(names, s["kind"]))
        return F.struct(
            F.greatest(acc["at"], s["end"]).alias("at"),
            F.when(fresh, F.concat(acc["out"], F.substring(text, acc["at"] + 1, s["start"] - acc["at"]), label)).otherwise(acc["out"]).alias("out"),
        )

    whole = F.aggregate(spans, F.struct(F.lit(0).alias("at"), F.lit("").alias("out")), step, lambda acc: F.concat(acc["out"], F.substring(text, acc["at"] + 1, F.length(text))))
    return F.when(F.size(spans) > 0, whole).otherwise(text)


def digest(protected: DataFrame) -> DataFrame:
    counts = [F.size(F.filter("spans", _of_kind(k))).cast("bigint").alias(f"n_{KINDS[k]}") for k in range(4)]
    return protected.select(
        "doc_id", *counts,
        F.sha2(listing(F.col("spans")).cast("binary"), 256).alias("base_sha256"),
        listing(F.array_sort(F.concat("spans", "terms"))).alias("spans"),
        F.size("terms").cast("bigint").alias("n_term"),
    )


def without_private_data(docs: DataFrame) -> DataFrame:
    """docs, with all their columns, the texts sanitised; n_chars, if there is one, follows a changed text."""
    found = protect(docs, carry=True)
    spans = F.array_sort(F.concat("spans", "terms"))
    rows = found.select("carried", F.size(spans).alias("n"), sanitised(F.col("carried.text").cast("string"), spans).alias("clean"))
    out = []
    for f in docs.schema.fields:
        old = F.col(f"carried.`{f.name}`")
        if f.name == "text":
            old = F.col("clean")
        elif f.name == "n_chars":
            old = F.when(F.col("n") > 0, F.length("clean").cast(f.dataType)).otherwise(old)
        out.append(old.alias(f.name))
    return rows.select(*out)
