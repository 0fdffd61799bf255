"""The experiment workloads as (tid, item) baskets, in Spark and, for the checks, in SQL."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import attributes, from_long, read_table


def w1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Retail baskets: the brands of an order."""
    lines, part = read_table(spark, sf_dir, "lineitem"), read_table(spark, sf_dir, "part")
    return from_long(lines.select("l_orderkey", "l_partkey").join(part.select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey")), "l_orderkey", "p_brand")


def w2(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Node log: per rack, shelf and time slot the status bits of four values of six nodes."""
    e = read_table(spark, sf_dir, "events")
    key = ["rack", "shelf", "slot"]
    rows = e.select(
        (F.col("user_id") % 8).alias("rack"), (F.col("event_id") % 8).alias("shelf"), F.expr("(event_id div 8) % 6").alias("node"), F.expr("event_id div 384").alias("slot"),
        "value", F.get_json_object("props", "$.k").cast("double").alias("k"), F.hour("ts").alias("h"), "event_id", "event_type",
    )
    v = rows.groupBy(*key, "node").agg(F.max("value").alias("v0"), F.avg("k").alias("v1"), F.max("h").alias("v2"), F.max_by("event_type", "event_id").alias("v3"))

    def status(c: str, error: float, high: float, low: float):  # 3 error, 2 high, 1 low, 0 norm
        return F.when(F.col(c) >= error, 3).when(F.col(c) >= high, 2).when(F.col(c) < low, 1).otherwise(0)

    last = F.when(F.col("v3") == "error", 3).when(F.col("v3") == "purchase", 2).when(F.col("v3") == "signup", 1).otherwise(0)
    codes = F.array(status("v0", 100, 20, 5), status("v1", 95, 70, 30), status("v2", 22, 16, 8), last)
    tid = F.concat_ws("-", *key).alias("tid")
    bits = v.select(tid, "node", F.posexplode(codes).alias("m", "code"))
    name = F.concat(F.lit("n"), F.col("node").cast("string"), F.lit(".m"), F.col("m").cast("string"))
    bits = bits.select("tid", F.explode(F.array(F.when(F.col("code").isin(1, 3), F.concat(name, F.lit(".b0"))), F.when(F.col("code").isin(2, 3), F.concat(name, F.lit(".b1"))))).alias("item"))
    place = v.select(tid, F.explode(F.array(F.concat(F.lit("rack"), "rack"), F.concat(F.lit("shelf"), "shelf"))).alias("item"))
    return from_long(bits.unionAll(place), "tid", "item")


def w3(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five items: the event types of a user's day."""
    e = read_table(spark, sf_dir, "events")
    return from_long(e.select(F.concat_ws(":", "user_id", F.to_date("ts")).alias("tid"), "event_type"), "tid", "event_type")


def w4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Records as baskets: ten attributes of each order line; a basket a row."""
    t = {n: read_table(spark, sf_dir, n) for n in ("lineitem", "orders", "customer", "part")}
    rows = (
        t["lineitem"].select(F.monotonically_increasing_id().alias("tid"), "*")
        .join(t["orders"], F.col("l_orderkey") == F.col("o_orderkey"))
        .join(t["customer"], F.col("o_custkey") == F.col("c_custkey"))
        .join(t["part"], F.col("l_partkey") == F.col("p_partkey"))
    )
    items = F.array(
        F.concat(F.lit("rf="), "l_returnflag"), F.concat(F.lit("ls="), "l_linestatus"), F.concat(F.lit("ln="), F.col("l_linenumber").cast("string")),
        F.concat(F.lit("os="), "o_orderstatus"), F.concat(F.lit("pr="), "o_orderpriority"), F.concat(F.lit("seg="), "c_mktsegment"), F.concat(F.lit("pt="), "p_type"),
        F.concat(F.lit("q="), F.floor((F.col("l_quantity") - 1) / 10).cast("string")), F.concat(F.lit("d="), F.round(F.col("l_discount") * 100).cast("int").cast("string")),
        F.concat(F.lit("y="), F.year("l_shipdate").cast("string")),
    )
    out = rows.select("tid", F.explode(items).alias("item"))  # ten different items of one row: distinct already
    out.baskets = rows.select("tid", F.array_compact(items).alias("held"))  # a row is a basket: nothing to gather
    return out


def w5(spark: SparkSession, sf_dir: str, top: int = 64) -> DataFrame:
    """Documents as sets of the most common tokens."""
    d = read_table(spark, sf_dir, "documents")
    words = from_long(d.select("doc_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("w")), "doc_id", "w")
    best = words.groupBy("item").count().orderBy(F.desc("count"), "item").limit(top).select("item")
    return words.join(F.broadcast(best), "item", "left_semi").select("tid", "item")  # `top` rows


def w5_tids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents, so that those without a common token still count."""
    return read_table(spark, sf_dir, "documents").select(F.col("doc_id").alias("tid"))


def w6(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The positive dimensions of an embedding."""
    e = read_table(spark, sf_dir, "embeddings")
    signs = e.select("vec_id", F.posexplode("embedding").alias("d", "v")).where("v > 0")
    return signs.select(F.col("vec_id").alias("tid"), F.concat(F.lit("d"), F.lpad(F.col("d").cast("string"), 2, "0")).alias("item")).distinct()


def w7(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Dense baskets: the brands of a customer."""
    o, lines, part = (read_table(spark, sf_dir, n) for n in ("orders", "lineitem", "part"))
    rows = lines.select("l_orderkey", "l_partkey").join(o.select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).join(part.select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    return from_long(rows, "o_custkey", "p_brand")


def w8(spark: SparkSession, sf_dir: str) -> DataFrame:
    """More than 64 items: brand and type of an order's parts."""
    lines, part = read_table(spark, sf_dir, "lineitem"), read_table(spark, sf_dir, "part")
    rows = lines.select("l_orderkey", "l_partkey").join(part.select("p_partkey", F.concat_ws("/", "p_brand", "p_type").alias("bt")), F.col("l_partkey") == F.col("p_partkey"))
    return from_long(rows, "l_orderkey", "bt")


def w10_customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, n, r = (read_table(spark, sf_dir, x) for x in ("customer", "nation", "region"))
    rows = c.join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))
    return attributes(rows, "c_custkey", ["c_mktsegment", "n_name", "r_name", "c_acctbal"], {"c_acctbal": 2500.0})


def w10_suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    x, n, r = (read_table(spark, sf_dir, t) for t in ("supplier", "nation", "region"))
    rows = x.join(n, F.col("s_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))
    return attributes(rows, "s_suppkey", ["n_name", "r_name", "s_acctbal"], {"s_acctbal": 2500.0})


def w10_benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The words of a benchmark item."""
    b = read_table(spark, sf_dir, "benchmark")
    return from_long(b.select("item_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("w")), "item_id", "w")


def w10_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    d, lab = read_table(spark, sf_dir, "documents").select("doc_id", "lang", "source"), read_table(spark, sf_dir, "labels")
    return attributes(d.join(lab, "doc_id"), "doc_id", ["lang", "source", "quality", "toxic"])


def w10_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The element names that a page opens."""
    p = read_table(spark, sf_dir, "pages")
    return from_long(p.select("page_id", F.explode(F.regexp_extract_all(F.lower("html"), F.lit("<([a-z][a-z0-9]*)"), F.lit(1))).alias("e")), "page_id", "e")


def w10_conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = read_table(spark, sf_dir, "conversations")
    return from_long(c.select("conv_id", F.concat_ws("/", "role", F.least(F.col("turn"), F.lit(5)).cast("string")).alias("i")), "conv_id", "i")


def synthetic(spark: SparkSession, n: int, m: int = 64, avg_len: int = 15, n_patterns: int = 40, avg_pattern: int = 4, seed: int = 1, partitions: int | None = None) -> DataFrame:
    """W9, a market-basket generator for any n: each basket unites patterns (fixed item sets drawn by
    hash, popular ones more often) and a few random items. Seeded hashes of row ids only, no shuffle."""
    ids = spark.range(0, n, 1, partitions) if partitions else spark.range(n)
    picks = max(1, round(avg_len * 0.7 / avg_pattern))
    noise = max(1, avg_len - picks * avg_pattern)

    def uniform(*key):
        return F.pmod(F.xxhash64(*key, F.lit(seed)), F.lit(1 << 30)) / float(1 << 30)

    def from_pattern(k):
        which = F.floor(n_patterns * F.pow(uniform("id", F.lit("p"), k), 2.0)).cast("int")  # low numbers are popular
        return F.transform(F.sequence(F.lit(1), F.lit(avg_pattern)), lambda j: F.when(uniform("id", k, j, F.lit("drop")) < 0.9, F.pmod(F.xxhash64(which, j, F.lit(seed + 1)), F.lit(m))))

    planted = F.flatten(F.transform(F.sequence(F.lit(1), F.lit(picks)), from_pattern))
    extra = F.transform(F.sequence(F.lit(1), F.lit(noise)), lambda j: F.pmod(F.xxhash64("id", j, F.lit(seed + 2)), F.lit(m)))
    held = F.array_distinct(F.filter(F.concat(planted, extra), lambda x: x.isNotNull()))
    return ids.select(F.col("id").alias("tid"), F.explode(held).alias("i")).select("tid", F.concat(F.lit("i"), F.lpad(F.col("i").cast("string"), 4, "0")).alias("item"))


def synthetic_masks(spark: SparkSession, n: int, n_patterns: int = 40, avg_pattern: int = 4, picks: int = 3, noise: int = 4, seed: int = 1, partitions: int | None = None) -> DataFrame:
    """W9 straight as masks of 64 items: unions of pattern masks and a few random bits; no shuffle, no Python.
    The defaults give the published log data its shape: mean length 14, some 335 sets at .1, up to 5 items."""
    import random

    rng = random.Random(seed)
    masks = [sum(1 << p for p in rng.sample(range(64), avg_pattern)) for _ in range(n_patterns)]
    listed = F.array(*[F.lit(x - (1 << 64) if x >> 63 else x).cast("bigint") for x in masks])
    ids = spark.range(0, n, 1, partitions) if partitions else spark.range(n)
    mask = F.lit(0).cast("bigint")
    for k in range(picks):
        h = F.pmod(F.xxhash64("id", F.lit(seed), F.lit(k)), F.lit(1 << 30)) / float(1 << 30)
        mask = mask.bitwiseOR(F.get(listed, F.floor(F.lit(n_patterns) * h * h).cast("int")))
    for k in range(noise):
        mask = mask.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.pmod(F.xxhash64("id", F.lit(seed + 1), F.lit(k)), F.lit(64)).cast("int")))
    return ids.select(mask.alias("w0"))


def drawn_patterns(m: int, n_patterns: int, avg_pattern: float, correlation: float, seed: int) -> list[tuple[int, float, int]]:
    """(mask, share of picks, level of corruption): lengths are Poisson draws, a part of each pattern comes from the
    one before, shares fall exponentially; a corrupted pattern loses each item with 1/8, 1/4 or 1/2."""
    import random

    rng = random.Random(seed)
    made: list[tuple[int, float, int]] = []
    before: list[int] = []
    for _ in range(n_patterns):
        size, left = 0, math.exp(-avg_pattern)
        u = rng.random()
        while u > left and size < m:  # inverse of the Poisson distribution
            u -= left
            size += 1
            left *= avg_pattern / size
        size = max(1, size)
        old = rng.sample(before, min(len(before), round(size * min(1.0, rng.expovariate(1 / correlation))))) if correlation else []
        rest = [p for p in range(m) if p not in old]
        before = (old + rng.sample(rest, max(0, min(len(rest), size - len(old)))))[:size]
        made.append((sum(1 << p for p in before), rng.expovariate(1.0), min(2, max(0, round(rng.gauss(1, 0.7))))))
    total = sum(w for _, w, _ in made)
    return [(x, w / total, c) for x, w, c in made]


def market_masks(spark: SparkSession, n: int, n_patterns: int = 60, avg_pattern: float = 4.0, avg_picks: float = 6.0, noise: int = 2, correlation: float = 0.5, seed: int = 1, partitions: int | None = None) -> DataFrame:
    """W9 in the shape of the published synthetic data: 64 items, baskets that unite a drawn number of correlated,
    corrupted patterns and a few random items. n rows of one LONG, from seeded hashes of the row's id: no shuffle, no
    Python. The mean length grows with avg_picks and avg_pattern."""
    made = drawn_patterns(64, n_patterns, avg_pattern, correlation, seed)
    edges, at = [], 0.0
    for _, w, _ in made:
        at += w
        edges.append(at)
    signed = [x - (1 << 64) if x >> 63 else x for x, _, _ in made]
    masks = F.array(*[F.lit(x).cast("bigint") for x in signed])
    levels = F.array(*[F.lit(c) for _, _, c in made])
    steps = 1024  # the draw of a pattern by its share, looked up
    table, k = [], 0
    for s in range(steps):
        while k < len(edges) - 1 and edges[k] <= (s + 0.5) / steps:
            k += 1
        table.append(k)
    runs = F.array(*[F.lit(x) for x in table])
    ids = spark.range(0, n, 1, partitions) if partitions else spark.range(n)

    def h(*key):
        return F.xxhash64("id", *[F.lit(x) for x in key], F.lit(seed))

    most = max(1, math.ceil(2 * avg_picks - 1))
    picks = F.lit(1) + F.pmod(h(1), F.lit(most)).cast("int")  # 1 .. most, mean avg_picks
    ids = ids.select("id", picks.alias("picks"), *[F.get(runs, F.pmod(h(2, k), F.lit(steps)).cast("int")).alias(f"p{k}") for k in range(most)])
    mask = F.lit(0).cast("bigint")
    for k in range(most):
        level = F.get(levels, F.col(f"p{k}"))
        half = h(3, k)
        keep = F.when(level == 2, half).when(level == 1, half.bitwiseOR(h(4, k))).otherwise(half.bitwiseOR(h(4, k)).bitwiseOR(h(5, k)))
        mask = mask.bitwiseOR(F.when(F.col("picks") > k, F.get(masks, F.col(f"p{k}")).bitwiseAND(keep)).otherwise(F.lit(0).cast("bigint")))
    for k in range(noise):
        mask = mask.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.pmod(h(6, k), F.lit(64)).cast("int")))
    return ids.select(mask.alias("w0"))


BASKETS = {"w1": w1, "w2": w2, "w3": w3, "w4": w4, "w5": w5, "w6": w6, "w7": w7, "w8": w8}
TIDS = {"w5": w5_tids}

_BY_ORDER = "SELECT DISTINCT l_orderkey AS tid, {item} AS item FROM lineitem JOIN part ON l_partkey = p_partkey"
SQL = {
    "w1": _BY_ORDER.format(item="p_brand"),
    "w2": """
SELECT DISTINCT tid, item FROM (
  WITH v AS (
    SELECT user_id % 8 AS rack, event_id % 8 AS shelf, (event_id // 8) % 6 AS node, event_id // 384 AS slot, max(value) AS v0, avg(CAST(json_extract_string(props, '$.k') AS DOUBLE)) AS v1, max(hour(ts)) AS v2, arg_max(event_type, event_id) AS v3
    FROM events GROUP BY 1, 2, 3, 4
  ), c AS (
    SELECT rack || '-' || shelf || '-' || slot AS tid, rack, shelf, 'n' || node || '.m' AS node, unnest([0, 1, 2, 3]) AS m, unnest([
      CASE WHEN v0 >= 100 THEN 3 WHEN v0 >= 20 THEN 2 WHEN v0 < 5 THEN 1 ELSE 0 END, CASE WHEN v1 >= 95 THEN 3 WHEN v1 >= 70 THEN 2 WHEN v1 < 30 THEN 1 ELSE 0 END,
      CASE WHEN v2 >= 22 THEN 3 WHEN v2 >= 16 THEN 2 WHEN v2 < 8 THEN 1 ELSE 0 END, CASE v3 WHEN 'error' THEN 3 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 1 ELSE 0 END]) AS code FROM v
  )
  SELECT tid, node || m || '.b0' AS item FROM c WHERE code IN (1, 3) UNION ALL SELECT tid, node || m || '.b1' FROM c WHERE code IN (2, 3)
  UNION ALL SELECT tid, 'rack' || rack FROM c UNION ALL SELECT tid, 'shelf' || shelf FROM c)""",
    "w3": "SELECT DISTINCT user_id || ':' || CAST(ts AS DATE) AS tid, event_type AS item FROM events",
    "w4": """
SELECT tid, unnest(['rf=' || l_returnflag, 'ls=' || l_linestatus, 'ln=' || l_linenumber, 'os=' || o_orderstatus, 'pr=' || o_orderpriority, 'seg=' || c_mktsegment, 'pt=' || p_type,
  'q=' || CAST(floor((l_quantity - 1) / 10) AS BIGINT), 'd=' || CAST(round(l_discount * 100) AS INT), 'y=' || year(l_shipdate)]) AS item
FROM (SELECT row_number() OVER () AS tid, * FROM lineitem) JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey""",
    "w5": """
SELECT tid, item FROM (WITH t AS (SELECT DISTINCT doc_id AS tid, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS item FROM documents)
  SELECT tid, item FROM t WHERE item IN (SELECT item FROM t GROUP BY item ORDER BY count(*) DESC, item LIMIT 64))""",
    "w6": "SELECT DISTINCT tid, 'd' || lpad(CAST(d - 1 AS VARCHAR), 2, '0') AS item FROM (SELECT vec_id AS tid, unnest(embedding) AS v, generate_subscripts(embedding, 1) AS d FROM embeddings) WHERE v > 0",
    "w7": "SELECT DISTINCT o_custkey AS tid, p_brand AS item FROM orders JOIN lineitem ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey",
    "w8": _BY_ORDER.format(item="p_brand || '/' || p_type"),
}
#: The number of transactions, where it is not the number of different tids in the baskets.
SQL_N = {"w5": "SELECT count(*) FROM documents"}
