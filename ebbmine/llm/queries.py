"""The queries of the corpus operators and, where SQL can express them, their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontamination, licences, pieces, private_data, toxicity, url_rules
from .common import table
from .embedding_dedup import link_embeddings
from .jaccard import jaccard_components
from .main_text import extract_main_text
from .sharding import op7_two_pass_shuffle


def op1_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_main_text(table(spark, sf_dir, "pages"))


#: The rules of the query: host, path, verdict.
URL_RULES = [("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block")]


def op2_redirect_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    rules = spark.createDataFrame(URL_RULES, "host string, path string, verdict string")
    return url_rules.judge(pages, rules, url_rules.page_links(pages))


OP2_SQL = r"""
WITH RECURSIVE parts AS (
  SELECT page_id, url, html, CASE WHEN contains(url, '://') THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages
), placed AS (
  SELECT page_id, url, html, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM parts
), rules(rhost, rpath, rverdict) AS (
  VALUES ('com', '/', 'allow'), ('example.com', '/en/', 'block'), ('www.example.com', '/en/', 'allow'), ('net', '/es/', 'block'), ('net', '/fr/', 'block')
), fitted AS (
  SELECT DISTINCT p.url, r.rhost || r.rpath AS rule, r.rverdict, length(r.rhost) + length(r.rpath) AS size, length(r.rhost) AS hsize
  FROM placed p JOIN rules r ON (p.host = r.rhost OR ends_with(p.host, '.' || r.rhost)) AND starts_with(p.path, r.rpath)
), ruled AS (
  SELECT url, rule, rverdict FROM fitted QUALIFY row_number() OVER (PARTITION BY url ORDER BY size DESC, hsize DESC, rverdict DESC) = 1
), links AS (
  SELECT url AS a, regexp_extract(html, '(?is)<link [^>]*rel="canonical"[^>]*href="([^"]*://[^"]*)"', 1) AS b FROM placed WHERE contains(lower(html), 'canonical')
), edges AS (SELECT a, b FROM links WHERE b <> '' UNION SELECT b, a FROM links WHERE b <> ''
), reach(url) AS (
  SELECT url FROM ruled WHERE rverdict = 'block' UNION SELECT e.b FROM reach r JOIN edges e ON e.a = r.url
)
SELECT p.page_id, coalesce(p.host, '') AS host, coalesce(p.path, '') AS path, r.rule,
  coalesce(r.rverdict, CASE WHEN p.url IN (SELECT url FROM reach) THEN 'block' ELSE 'allow' END) AS verdict,
  CASE WHEN r.rule IS NOT NULL THEN 'rule' WHEN p.url IN (SELECT url FROM reach) THEN 'alias' ELSE 'none' END AS via
FROM placed p LEFT JOIN ruled r ON r.url = p.url
"""


def op3_disclosure_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return private_data.digest(private_data.protect(table(spark, sf_dir, "documents")))


def op4_noisy_or_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = toxicity.train(docs, table(spark, sf_dir, "labels"))
    scored = toxicity.score(docs, model)
    return scored.select(
        "doc_id",
        (~toxicity.in_training(F.col("doc_id"))).alias("held_out"),
        "score",
        F.when(F.col("score") >= toxicity.THRESHOLD, 1).otherwise(0).alias("predicted"),
        "offending",
    )


#: What announces a licence; documents with such a notice are the licence files of their folder.
NOTICE = r"(?i)licensed under|released under the|license, version|public license"


def as_files(docs: DataFrame) -> DataFrame:
    """Documents as files source/lang/hundred/name, where a folder holds the documents of one source and language whose
    ids agree but for the last two digits. A document that holds a notice is a licence file of its folder
    (named LICENSE.doc_id), so that its licence governs the other documents there; all others are named by their id."""
    notice = F.coalesce(F.col("text").rlike(NOTICE), F.lit(False))
    name = F.when(notice, F.concat(F.lit("LICENSE."), F.col("doc_id").cast("string"))).otherwise(F.col("doc_id").cast("string"))
    return docs.select(F.concat_ws("/", "source", "lang", F.floor(F.col("doc_id") / 100).cast("string"), name).alias("path"), "text", "doc_id")


def op5_tfidf_licences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents as files (as_files): own notices by cosine, the others inherit from the nearest folder above them with a licence file."""
    found = licences.scan_licences(as_files(table(spark, sf_dir, "documents")), licences.default_templates(spark), carry={"doc_id": "bigint"})
    return found.select("doc_id", "path", "licence", "score", "via", "source")


# Every unit of every document against every template, without anchors; then the folder's best licence file.
OP5_SQL = (
    r"""
WITH d AS (
  SELECT doc_id, coalesce(text, '') AS text, concat_ws('/', source, lang, CAST(floor(doc_id / 100) AS BIGINT)) || '/' AS folder,
    coalesce(regexp_matches(text, 'licensed under|released under the|license, version|public license', 'i'), false) AS named FROM documents
), f AS (SELECT *, folder || CASE WHEN named THEN 'LICENSE.' ELSE '' END || doc_id AS path FROM d
), u AS (
  SELECT doc_id, unnest(list_concat(regexp_split_to_array(regexp_replace(text, '([.;!?])\s+', '' || chr(10), 'g'), '
+'), CASE WHEN named THEN [text] ELSE [] END)) AS unit FROM f
), k AS MATERIALIZED (SELECT doc_id, row_number() OVER () AS unit, regexp_extract_all(lower(unit), '[a-z]+|[0-9]+(?:\.[0-9]+)*') AS terms FROM u
), n AS (SELECT count(*) AS n FROM documents
), df AS MATERIALIZED (SELECT term, count(*) AS df FROM (SELECT DISTINCT doc_id, unnest(regexp_extract_all(lower(text), '[a-z]+|[0-9]+(?:\.[0-9]+)*')) AS term FROM f) GROUP BY term
), tv(licence, text) AS (VALUES """
    + ", ".join(f"('{a}', '{b}')" for a, b in licences.TEMPLATES)
    + r"""
), tt AS (SELECT t, licence, term, count(*) AS tf FROM (SELECT row_number() OVER () AS t, licence, unnest(regexp_extract_all(lower(text), '[a-z]+|[0-9]+(?:\.[0-9]+)*')) AS term FROM tv) GROUP BY ALL
), tw AS (SELECT t, licence, tt.term, (1 + ln(tf)) * (ln((1.0 + (SELECT n FROM n)) / (1 + coalesce(df, 0))) + 1) AS w FROM tt LEFT JOIN df ON df.term = tt.term
), ts AS MATERIALIZED (SELECT t, licence, term, w / sqrt(sum(w * w) OVER (PARTITION BY t)) AS w FROM tw
), ut AS (SELECT doc_id, unit, term, count(*) AS tf FROM (SELECT doc_id, unit, unnest(terms) AS term FROM k WHERE len(list_intersect(terms, (SELECT list(DISTINCT term) FROM ts))) >= 2) GROUP BY ALL
), uw AS MATERIALIZED (SELECT doc_id, unit, ut.term, (1 + ln(tf)) * (ln((1.0 + (SELECT n FROM n)) / (1 + df)) + 1) AS w FROM ut JOIN df ON df.term = ut.term
), un AS (SELECT unit, sqrt(sum(w * w)) AS norm FROM uw GROUP BY unit
), sc AS (SELECT doc_id, licence, round(sum(uw.w * ts.w) / any_value(norm), 6) AS score FROM uw JOIN ts ON ts.term = uw.term JOIN un ON un.unit = uw.unit GROUP BY doc_id, uw.unit, t, licence HAVING count(*) >= 2
), own AS (SELECT doc_id, max({'score': score, 'licence': licence}) AS b FROM sc WHERE score >= 0.6 GROUP BY doc_id
), given AS (SELECT folder, min({'less': -b.score, 'path': path, 'licence': b.licence}) AS g, max(b.score) AS score FROM f JOIN own ON own.doc_id = f.doc_id WHERE named GROUP BY folder)
SELECT f.doc_id, path, coalesce(b.licence, g.licence) AS licence, coalesce(b.score, given.score) AS score,
  CASE WHEN b IS NOT NULL THEN 'own' WHEN g IS NOT NULL THEN 'inherited' ELSE 'none' END AS via, CASE WHEN b IS NULL THEN given.folder END AS source
FROM f LEFT JOIN own ON own.doc_id = f.doc_id LEFT JOIN given ON given.folder = f.folder
"""
)


def op6_token_group_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(table(spark, sf_dir, "documents"), words=3, num=9, den=10).drop("mark")


# Shingles as strings, overlaps counted over shared shingles, components by recursion.
OP6_SQL = r"""
WITH RECURSIVE w AS MATERIALIZED (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS words FROM documents
), s AS MATERIALIZED (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(words) = 0 THEN [] WHEN len(words) < 3 THEN [array_to_string(words, ' ')] ELSE list_transform(range(1, len(words) - 1), lambda i: words[i] || ' ' || words[i + 1] || ' ' || words[i + 2]) END) AS shingle FROM w
), n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id
), pairs AS (
  SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS n_both FROM s a JOIN s b ON a.shingle = b.shingle AND a.doc_id < b.doc_id GROUP BY a.doc_id, b.doc_id
), links AS MATERIALIZED (
  SELECT a, b FROM pairs JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * n_both >= 90 * (x.n + y.n - n_both)
), edges AS (SELECT a, b FROM links UNION ALL SELECT b, a FROM links
), reach(doc_id, other) AS (SELECT a, b FROM edges UNION SELECT r.doc_id, e.b FROM reach r JOIN edges e ON e.a = r.other)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, least(d.doc_id, coalesce(r.low, d.doc_id)) AS component_id
FROM documents d LEFT JOIN n ON n.doc_id = d.doc_id LEFT JOIN (SELECT doc_id, min(other) AS low FROM reach GROUP BY doc_id) r ON r.doc_id = d.doc_id
"""
OP8_SQL = """
WITH RECURSIVE v AS MATERIALIZED (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings WHERE embedding IS NOT NULL),
links AS MATERIALIZED (SELECT x.vec_id AS a, y.vec_id AS b FROM v x JOIN v y ON x.vec_id <> y.vec_id AND list_cosine_similarity(x.e, y.e) >= 0.95),
reach(a, b) AS (SELECT a, b FROM links UNION SELECT r.a, l.b FROM reach r JOIN links l ON l.a = r.b)
SELECT i.vec_id, (SELECT count(*) FROM links WHERE a = i.vec_id) AS n_links, least(i.vec_id, coalesce(r.low, i.vec_id)) AS component_id, i.vec_id = least(i.vec_id, coalesce(r.low, i.vec_id)) AS kept
FROM embeddings i LEFT JOIN (SELECT a, min(b) AS low FROM reach GROUP BY a) r ON r.a = i.vec_id
"""


def op8_rotation_code_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link_embeddings(table(spark, sf_dir, "embeddings"))


def op9_spaced_seed_leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    leaks = decontamination.find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return leaks.select("doc_id", F.lit(True).alias("contaminated"), "item_ids", "spans")


#: The public vocabulary of the tokeniser; read on the driver only.
PIECE_MODEL = "/opt/tokenizers/piece_bpe_32k.model"


def op10_shared_prefix_pieces(spark: SparkSession, sf_dir: str, model_path: str = PIECE_MODEL) -> DataFrame:
    model = pieces.PieceModel(model_path)
    encoded = pieces.encode_texts(table(spark, sf_dir, "documents"), model, verify=True)
    return encoded.select("doc_id", F.size("ids").cast("bigint").alias("n_tokens"), "ids", "round_trip")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    return {
        "pipeline": pipeline,
        "op1_main_text": op1_main_text,
        "op2_redirect_url_filter": op2_redirect_url_filter,
        "op3_disclosure_pii": op3_disclosure_pii,
        "op4_noisy_or_toxicity": op4_noisy_or_toxicity,
        "op5_tfidf_licences": op5_tfidf_licences,
        "op6_token_group_jaccard": op6_token_group_jaccard,
        "op8_rotation_code_dedup": op8_rotation_code_dedup,
        "op9_spaced_seed_leaks": op9_spaced_seed_leaks,
        "op10_shared_prefix_pieces": op10_shared_prefix_pieces,
        "op7_two_pass_shuffle": op7_two_pass_shuffle,
    }


def oracle_sql() -> dict[str, str]:
    return {"op2_redirect_url_filter": OP2_SQL, "op5_tfidf_licences": OP5_SQL, "op6_token_group_jaccard": OP6_SQL, "op8_rotation_code_dedup": OP8_SQL}
