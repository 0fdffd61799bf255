"""URL filtering with redirect equivalence.

Allow and block rules name a host with its subdomains and a path prefix; the longest fitting rule
decides. Pages joined by redirects or canonical links are aliases: a block decided by a rule for
one alias reaches every alias of its connected component that no rule decides itself. An explicit
allow rule of a URL takes precedence over any block that its aliases bring. URLs are aliases of
one another, too, if they differ in the case of scheme or host, a default port, an empty path or
the fragment only. All canonical and refresh elements of a page count, with references decoded;
what stands in comments or raw text does not.

DataFrame expressions only. Rules and links meet pages by equi-joins over distinct URLs, so a hot
host or a URL held by many rows is summed up before it is shuffled; of a host only as many labels
are tried as the longest rule has. Null url, or none with "://":
host and path empty, no rule, no alias, allowed. Repeated rows: each has its own result. Empty
tables: empty result. Extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import only, written
from .graph import components

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
# What no element is read from: comments, and elements whose content is text or shown to nobody.
ASIDE = r"(?is)<!--.*?(?:--!?>|\z)|<(script|style|noscript|template|textarea|title|xmp|iframe)\b.*?(?:</\1[^>]*>|\z)"
ELEMENT = r"""(?is)<(?:link|meta)(?=[\s/])(?:[^>"']++|"[^"]*+"|'[^']*+')*+>"""
ATTRIBUTE = r"""[^\s"'<>/=]++\s*+=\s*+(?:"[^"]*+"|'[^']*+'|[^\s"'>]++)"""
REFERENCE = r"&(?:#[0-9]{1,7}|#[xX][0-9a-fA-F]{1,6}|[a-zA-Z]{2,8});?"
# Named references that addresses hold.
NAMED = {"amp": "&", "quot": '"', "apos": "'", "lt": "<", "gt": ">", "nbsp": "\u00a0", "colon": ":", "sol": "/", "period": ".", "num": "#", "quest": "?", "equals": "=", "lowbar": "_", "percnt": "%"}


def _rest(url: Column) -> Column:
    return F.when(F.contains(url, F.lit("://")), F.regexp_extract(url, r"(?s)^.*?://(.*)$", 1)).otherwise("")


def host_of(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(_rest(url), r"^[^/?#]*", 0), UPPER, LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(_rest(url), r"^[^/?#]*([^?#]*)", 1), F.lit(""))


def decoded(value: Column) -> Column:
    """Character references replaced, in one run from left to right."""
    names = F.create_map(*[F.lit(x) for pair in NAMED.items() for x in pair])

    def one(ref: Column) -> Column:
        body = F.regexp_replace(ref, "^&|;$", "")
        number = F.when(F.startswith(body, F.lit("#x")) | F.startswith(body, F.lit("#X")), F.conv(F.substring(body, 3, 9), 16, 10)).otherwise(F.regexp_replace(body, "^#", "")).try_cast("int")
        # surrogates and what lies beyond the last code point stay as they are
        fine = number.between(1, 0xD7FF) | number.between(0xE000, 0x10FFFF)
        char = F.decode(F.unhex(F.lpad(F.hex(F.when(fine, number)), 8, "0")), "UTF-32")
        return F.coalesce(F.when(F.startswith(body, F.lit("#")), char).otherwise(F.get(F.array(F.try_element_at(names, body)), F.lit(0))), ref)

    refs = F.transform(F.regexp_extract_all(value, F.lit(REFERENCE), F.lit(0)), one)
    gaps = F.split(value, REFERENCE, -1)
    joined = F.array_join(F.zip_with(gaps, refs, lambda g, r: F.concat(g, F.coalesce(r, F.lit("")))), "")
    return F.when(F.contains(value, F.lit("&")), joined).otherwise(value)


def normal(url: Column) -> Column:
    """The name under which a URL is compared: scheme and host in lower case, no default port, no fragment,
    "/" for an empty path. Null if there is no "://"."""
    scheme = F.lower(F.regexp_extract(url, r"(?s)^(.*?)://", 1))
    host = F.when(scheme == "https", F.regexp_replace(host_of(url), ":(?:443)?$", "")).when(scheme == "http", F.regexp_replace(host_of(url), ":(?:80)?$", "")).otherwise(host_of(url))
    path = path_of(url)
    query = F.regexp_extract(_rest(url), r"^[^?#]*(\?[^#]*)", 1)
    return F.when(F.contains(url, F.lit("://")), F.concat(scheme, F.lit("://"), host, F.when(path == "", "/").otherwise(path), query))


def resolved(base: Column, link: Column) -> Column:
    """link as an absolute URL, seen from base; null if it is empty or of another scheme."""
    link = F.trim(F.regexp_replace(link, r"[\t\r\n]", ""))
    scheme = F.regexp_extract(base, r"^([^:/?#]+)://", 1)
    site = F.concat(scheme, F.lit("://"), F.regexp_extract(_rest(base), r"^[^/?#]*", 0))
    folder = F.concat(site, F.regexp_extract(path_of(base), r"^(?:.*/)?", 0))
    folder = F.when(F.endswith(folder, F.lit("/")), folder).otherwise(F.concat(site, F.lit("/")))
    return (
        F.when(link.rlike(r"^[A-Za-z][A-Za-z0-9+.-]*://"), link)
        .when(F.startswith(link, F.lit("//")), F.concat(scheme, F.lit(":"), link))
        .when(F.startswith(link, F.lit("/")), F.concat(site, link))
        .when(F.startswith(link, F.lit("?")), F.concat(site, path_of(base), link))
        .when((link == "") | link.rlike("^[A-Za-z][A-Za-z0-9+.-]*:") | F.startswith(link, F.lit("#")), F.lit(None))
        .otherwise(F.concat(folder, link))
    )


def page_links(pages: DataFrame) -> DataFrame:
    """src, dst: all canonical links and refresh redirects that pages(url, html) declare, outside of comments
    and raw text, attributes read one by one and their references decoded."""
    rows = only(pages, url="string", html="string").where(F.contains("url", F.lit("://")) & F.col("html").rlike(r"(?i)canonical|refresh"))
    elements = F.regexp_extract_all(F.regexp_replace("html", ASIDE, " "), F.lit(ELEMENT), F.lit(0))
    tags = rows.select("url", F.explode(elements).alias("tag"))
    rest = F.regexp_replace("tag", "^<[a-zA-Z]+", "")
    pairs = F.transform(F.regexp_extract_all(rest, F.lit(ATTRIBUTE), F.lit(0)), lambda a: F.struct(F.lower(F.regexp_extract(a, r"^([^\s=]+)", 1)).alias("name"), F.regexp_replace(a, r"""^[^\s=]+\s*=\s*["']?|["']$""", "").alias("value")))
    held = tags.select("url", F.lower(F.substring("tag", 2, 4)).alias("kind"), pairs.alias("pairs"))

    def value(name: str) -> Column:
        return F.get(F.filter("pairs", lambda p: p["name"] == name), F.lit(0))["value"]

    # a column a step: an expression that is used twice is written once
    raw = held.select("url", "kind", value("rel").alias("rel"), value("href").alias("href"), value("http-equiv").alias("equiv"), value("content").alias("content"))
    canonical = (F.col("kind") == "link") & F.array_contains(F.split(F.lower("rel"), r"\s+"), "canonical")
    refresh = (F.col("kind") == "meta") & (F.lower(F.trim("equiv")) == "refresh")
    some = raw.select("url", F.when(canonical, F.col("href")).when(refresh, F.regexp_extract("content", r"""(?is)^[\s\d.]*[;,\s]\s*(?:url\s*=\s*)?["']?([^"']*)""", 1)).alias("link")).where("link is not null and link <> ''")
    found = some.select("url", decoded(F.col("link")).alias("link"))
    return found.select(F.col("url").alias("src"), resolved(F.col("url"), F.col("link")).alias("dst"))


def rule_verdicts(urls: DataFrame, rules: DataFrame) -> DataFrame:
    """urls(url, host, path), rules(host, path, verdict) -> url, rule, verdict of the longest fitting rule.
    Of rules of equal length the longer host wins, then a block."""
    longest = rules.agg(F.max(F.size(F.split("host", r"\."))).alias("n")).first()["n"] or 1  # labels of a rule's host
    count = F.least(F.size(F.split("host", r"\.")), F.lit(longest))
    suffixes = F.transform(F.sequence(F.lit(1), count), lambda k: F.call_function("substring_index", F.col("host"), F.lit("."), -k))
    places = urls.where(F.col("host") != "").select("url", F.col("path").alias("at"), F.explode(F.array_distinct(suffixes)).alias("host"))
    rules = rules.select("host", "path", "verdict").distinct()
    fits = places.join(rules, "host").where(F.startswith("at", "path"))
    rank = F.struct(F.length("host") + F.length("path"), F.length("host"), "verdict", F.concat("host", "path").alias("rule"))
    return fits.groupBy("url").agg(F.max(rank).alias("best")).select("url", "best.rule", "best.verdict")


def judge(pages: DataFrame, rules: DataFrame, links: DataFrame) -> DataFrame:
    """pages(page_id, url) with rules(host, path, verdict) and links(src, dst) -> page_id, host,
    path, rule, verdict, via (rule, alias or none)."""
    rows = only(pages, page_id="bigint", url="string").withColumn("key", normal(F.col("url")))
    edges = written(links.select(normal(F.col("src")).alias("a"), normal(F.col("dst")).alias("b")).distinct(), "links").where("a is not null and b is not null and a <> b")
    own = rule_verdicts(_placed(only(pages, url="string")), rules).select("url", "rule", F.col("verdict").alias("ruled"))
    names = rows.select(F.col("key").alias("url")).unionAll(edges.select("a")).unionAll(edges.select("b"))
    by_name = rule_verdicts(_placed(names), rules).select(F.col("url").alias("key"), F.col("verdict").alias("named"))
    member = components(edges)
    blocked = member.join(by_name.where("named = 'block'"), member["node"] == by_name["key"]).select("component").distinct()
    by_alias = member.join(blocked, "component", "left_semi").select(F.col("node").alias("key"), F.lit(True).alias("alias"))
    known = by_name.join(by_alias, "key", "full_outer")
    found = rows.join(own, "url", "left").join(known, "key", "left")
    alias = F.coalesce("named", F.when(F.col("alias"), "block"))
    return found.select(
        "page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"), "rule", F.coalesce("ruled", alias, F.lit("allow")).alias("verdict"),
        F.when(F.col("rule").isNotNull(), "rule").when((alias == "block") | F.col("named").isNotNull(), "alias").otherwise("none").alias("via"),
    )


def _placed(urls: DataFrame) -> DataFrame:
    """The distinct URLs with host and path."""
    urls = urls.where(F.contains("url", F.lit("://"))).distinct()
    return urls.withColumn("host", host_of(F.col("url"))).withColumn("path", path_of(F.col("url")))
