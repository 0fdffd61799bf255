"""All queries of the mining engine and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import experiments
from .operators import layout, measures, result, rules
from .operators.counting import BY_NUMBER
from .operators.mining import mine
from .sources import oracle, workloads
from .sources.tables import attributes, read_table
from .streaming import baskets as windows

#: Minimum support of each workload's runs.
MINSUP = {"w1": "0.01", "w2": "0.1", "w3": "0.1", "w4": "0.05", "w5": "0.4", "w6": "0.25", "w7": "0.6", "w8": "0.01"}
#: Runs of each workload: name -> (method, options).
RUNS: dict[str, tuple[str, dict]] = {
    "icb_m2": ("ic_b", {"chunks": 2}),
    "icb_m4": ("ic_b", {"chunks": 4, "grow": "delta", "mode": "hash"}),
    "icb_m10": ("ic_b", {"chunks": 10, "bound": "uniform"}),
    "ic4_m4": ("ic_4", {"chunks": 4}),
    "level": ("level", {}),
    "vert_tidlist": ("vert", {"layout": "tidlist"}),
    "vert_bitmap": ("vert", {"layout": "bitmap"}),
    "vert_diffset": ("vert", {"layout": "diffset"}),
    "fpt": ("fpt", {}),
    "fpt_mllib": ("mllib", {}),
}
ITEMSETS = ["items", "k", "supp"]


def _tx(spark: SparkSession, sf_dir: str, w: str) -> tuple[DataFrame, DataFrame | None]:
    return workloads.BASKETS[w](spark, sf_dir), workloads.TIDS[w](spark, sf_dir) if w in workloads.TIDS else None


def run(spark: SparkSession, sf_dir: str, w: str, name: str = "icb_m2", minsup: str | None = None, **more):
    tx, tids = _tx(spark, sf_dir, w)
    method, options = RUNS[name]
    return mine(tx, minsup or MINSUP[w], method, tids=tids, **(options | more))


def _encoded(spark: SparkSession, sf_dir: str, w: str, **options):
    tx, tids = _tx(spark, sf_dir, w)
    return layout.prepare(tx, MINSUP[w], tids=tids, **({"folded": False} | options))


def _freq(w: str, minsup: str | None = None, max_len: int | None = None) -> str:
    return oracle.fim_ctes(workloads.SQL[w], minsup or MINSUP[w], workloads.SQL_N.get(w), max_len)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The bit-encoded interval miner on the node log."""
    return run(spark, sf_dir, "w2").itemsets()


def _stats(w: str) -> tuple[Callable, str]:
    n = workloads.SQL_N.get(w) or "SELECT count(DISTINCT tid) FROM b"
    sql = f"""WITH b AS MATERIALIZED ({workloads.SQL[w]}), f AS (SELECT item FROM b GROUP BY item HAVING count(*) >= {oracle.need_sql(MINSUP[w], n)}),
t AS (SELECT tid, list(item ORDER BY item) AS held FROM b WHERE item IN (SELECT item FROM f) GROUP BY tid)
SELECT CAST(({n}) AS BIGINT) AS n, (SELECT count(*) FROM f) AS m, round(sum(len(held)) / CAST(({n}) AS DOUBLE), 6) AS mean_len, CAST(max(len(held)) AS BIGINT) AS max_len,
  count(DISTINCT held) + CASE WHEN count(*) < ({n}) THEN 1 ELSE 0 END AS distinct_masks, CAST(({n}) * ((SELECT count(*) FROM f) + 63) // 64 * 8 AS BIGINT) AS mask_bytes FROM t"""
    sql = sql.replace(f"({n}) * ((SELECT count(*) FROM f) + 63) // 64 * 8", f"({n}) * (((SELECT count(*) FROM f) + 63) // 64) * 8")
    return lambda s, d: layout.stats(_encoded(s, d, w)[0]), sql


def _singletons(w: str) -> tuple[Callable, str]:
    return (lambda s, d: mine(*_tx(s, d, w)[:1], MINSUP[w], "level", tids=_tx(s, d, w)[1], max_len=1).itemsets()), _freq(w, max_len=1) + "\nSELECT items, k, supp FROM freq WHERE k = 1"


def _counted(number: str) -> Callable:
    """Supports of fixed item sets of w4, by one counting strategy."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        e, _ = _encoded(spark, sf_dir, "w4", chunks=2, mode="hash", folded=number == "k5")
        return result.support_of(e, GIVEN, BY_NUMBER[number])

    return query


#: Item sets of w4 whose supports are asked for.
GIVEN = [["ls=O", "os=O"], ["ls=F", "os=F", "rf=A"], ["ln=1", "ls=O"], ["q=0", "rf=N"], ["d=5"], ["pr=1-URGENT", "seg=BUILDING"], ["d=1", "ln=2", "ls=F"]]
GIVEN_SQL = f"WITH b AS MATERIALIZED ({workloads.SQL['w4']}), g(items) AS (VALUES " + ", ".join(f"('{'|'.join(sorted(x))}')" for x in GIVEN) + """),
q AS (SELECT items, unnest(string_split(items, '|')) AS item, len(string_split(items, '|')) AS k FROM g),
h AS (SELECT q.items, q.k, b.tid FROM q JOIN b ON b.item = q.item GROUP BY q.items, q.k, b.tid HAVING count(*) = q.k)
SELECT g.items, CAST(len(string_split(g.items, '|')) AS INT) AS k, count(h.tid) AS supp FROM g LEFT JOIN h ON h.items = g.items GROUP BY g.items"""


def support_of_given(spark: SparkSession, sf_dir: str) -> DataFrame:
    return result.support_of(_encoded(spark, sf_dir, "w4")[0], GIVEN)


def fold_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    e, _ = _encoded(spark, sf_dir, "w3", folded=True)
    return e.enc.agg(F.count("*").alias("rows"), F.sum("weight").alias("transactions"), F.max("weight").alias("heaviest"))


def chunk_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    e, _ = _encoded(spark, sf_dir, "w1", chunks=4)
    return spark.createDataFrame(list(enumerate(e.sizes)), "chunk int, n_chunk bigint")


def _first_pass_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mine(_tx(spark, sf_dir, "w1")[0], MINSUP["w1"], "ic_b", max_len=2).itemsets().where("k = 2")


def _rules(**options) -> Callable:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        r = run(spark, sf_dir, "w2", "level")
        found = rules.derive(r.itemsets(), r.n, **options)
        return found.withColumn("confidence", F.round("confidence", 9)).withColumn("lift", F.round("lift", 9))

    return query


def _rules_sql(where: str) -> str:
    return _freq("w2") + f""", s AS (SELECT items, string_split(items, '|') AS p, supp, unnest(range(1, (1 << k) - 1)) AS m FROM freq WHERE k > 1),
t AS (SELECT list_aggregate(list_filter(p, lambda x, i: (m >> (i - 1)) & 1 = 1), 'string_agg', '|') AS antecedent, list_aggregate(list_filter(p, lambda x, i: (m >> (i - 1)) & 1 = 0), 'string_agg', '|') AS consequent, supp FROM s),
r AS (SELECT t.antecedent, t.consequent, t.supp, t.supp / a.supp AS confidence, t.supp * CAST((SELECT count(DISTINCT tid) FROM b) AS DOUBLE) / a.supp / c.supp AS lift FROM t JOIN freq a ON a.items = t.antecedent JOIN freq c ON c.items = t.consequent)
SELECT antecedent, consequent, supp, round(confidence, 9) AS confidence, round(lift, 9) AS lift FROM r WHERE {where}"""


def _on(w: str, f: Callable) -> Callable:
    return lambda spark, sf_dir: f(run(spark, sf_dir, w, "level").itemsets())


def _by_group(kind: str) -> Callable:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        c, n, r = (read_table(spark, sf_dir, x) for x in ("customer", "nation", "region"))
        groups = c.join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("c_custkey").alias("tid"), "r_name", "c_mktsegment")
        return result.support_by_group(workloads.w7(spark, sf_dir), groups, ["r_name", "c_mktsegment"], kind)

    return query


def _by_group_sql(kind: str) -> str:
    return f"""WITH b AS ({workloads.SQL['w7']}), g AS (SELECT c_custkey AS tid, r_name, c_mktsegment FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)
SELECT r_name, c_mktsegment, item, count(*) AS supp, CAST(grouping(r_name, c_mktsegment, item) AS INT) AS level FROM b JOIN g USING (tid) GROUP BY {kind}(r_name, c_mktsegment, item) HAVING item IS NOT NULL"""


def contrast_returnflag(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Attribute sets frequent among returned lines and not among those never returned."""
    out = []
    for flag in ("R", "N"):
        lines = read_table(spark, sf_dir, "lineitem").where(F.col("l_returnflag") == flag).select(F.monotonically_increasing_id().alias("tid"), "l_linestatus", "l_linenumber", "l_discount", "l_quantity")
        lines = lines.withColumn("l_discount", F.round(F.col("l_discount") * 100).cast("int"))
        tx = attributes(lines, "tid", ["l_linestatus", "l_linenumber", "l_discount", "l_quantity"], {"l_quantity": 10.0})
        out.append(mine(tx, "0.02", "level").itemsets())
    return result.contrast(*out)


def _contrast_sql() -> str:
    def baskets(flag: str) -> str:
        return f"""SELECT tid, unnest(['l_linestatus=' || l_linestatus, 'l_linenumber=' || l_linenumber, 'l_discount=' || CAST(round(l_discount * 100) AS INT), 'l_quantity=' || CAST(floor(l_quantity / 10) AS BIGINT)]) AS item
FROM (SELECT row_number() OVER () AS tid, * FROM lineitem WHERE l_returnflag = '{flag}')"""

    return f"SELECT * FROM ({oracle.fim_sql(baskets('R'), '0.02')}) r WHERE items NOT IN (SELECT items FROM ({oracle.fim_sql(baskets('N'), '0.02')}) n)"


def constraint_maxlen(spark: SparkSession, sf_dir: str) -> DataFrame:
    """At most two items, from a subset of the attributes."""
    keep = [x for x, _ in layout.dictionary(workloads.w4(spark, sf_dir), 1) if x.split("=")[0] in ("rf", "ls", "ln", "os", "q")]
    return mine(workloads.w4(spark, sf_dir), MINSUP["w4"], "ic_b", max_len=2, only_items=keep).itemsets()


def constraint_group(spark: SparkSession, sf_dir: str) -> DataFrame:
    """At most one item of a node in a set of the node log."""
    tx = workloads.w2(spark, sf_dir)
    groups = {x: x.split(".")[0] for x, _ in layout.dictionary(tx, 1)}
    return mine(tx, MINSUP["w2"], "ic_b", group_of=groups).itemsets()


def constraint_must(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sets that hold an open line status and no return flag."""
    return mine(workloads.w4(spark, sf_dir), MINSUP["w4"], "ic_b", must=["ls=O"], never=["rf=N", "os=O"]).itemsets()


SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]


def support_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Supports of the brands of w7, a column a market segment."""
    groups = read_table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("tid"), "c_mktsegment")
    return result.support_pivot(workloads.w7(spark, sf_dir), groups, "c_mktsegment", SEGMENTS)


def trace_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stops of a run beside their neighbours."""
    return result.trace_steps(run(spark, sf_dir, "w2", "icb_m10", mode="rank").trace_frame())


EVENT_TYPES = ["click", "error", "purchase", "signup", "view"]
EVENT_SETS = [1, 2, 4, 8, 16, 3, 5, 17, 20, 21]


def _windowed(kind: str, length: str = "1 day", slide: str | None = None) -> Callable:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        held = windows.baskets(windows.once(read_table(spark, sf_dir, "events")), EVENT_TYPES, kind, length, slide)
        if kind == "session":
            held = held.withColumn("start", F.date_trunc("day", "start"))
        return windows.support(held, EVENT_TYPES, EVENT_SETS).withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))

    return query


def _windowed_sql(kind: str) -> str:
    if kind == "tumbling":
        base = "SELECT user_id, date_trunc('day', ts) AS start, event_type FROM events"
    elif kind == "sliding":
        base = "SELECT user_id, time_bucket(INTERVAL 6 HOURS, ts) - to_hours(6 * h) AS start, event_type FROM events, (SELECT unnest([0, 1, 2, 3]) AS h)"
    else:
        base = """SELECT user_id, date_trunc('day', s) AS start, event_type, user_id || ':' || s AS u FROM (
  SELECT *, min(ts) OVER (PARTITION BY user_id, g) AS s FROM (SELECT *, sum(n) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM (
    SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTES THEN 0 ELSE 1 END AS n FROM events)))"""
    unit = "u" if kind == "session" else "user_id"
    sets = ", ".join(f"('{'|'.join(sorted(x for p, x in enumerate(EVENT_TYPES) if m >> p & 1))}')" for m in EVENT_SETS)
    return f"""WITH w AS ({base}), t AS (SELECT {unit}, start, list(DISTINCT event_type) AS held FROM w GROUP BY ALL HAVING true), s(items) AS (VALUES {sets})
SELECT strftime(start, '%Y-%m-%d %H:%M:%S') AS start, items, count(*) AS supp FROM t JOIN s ON list_has_all(held, string_split(items, '|')) GROUP BY start, items""".replace("GROUP BY ALL HAVING true", f"GROUP BY {unit}, start")


def asof_event_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each purchase the user's last view before it, at most six hours old."""
    from pyspark.sql import Window

    e = read_table(spark, sf_dir, "events").where(F.col("event_type").isin("view", "purchase"))
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    view = F.last(F.when(F.col("event_type") == "view", F.struct("ts", "event_id")), ignorenulls=True).over(before)
    rows = e.withColumn("v", view).where("event_type = 'purchase'")
    near = F.col("v.ts") >= F.col("ts") - F.expr("INTERVAL 6 HOURS")
    return rows.where(near).select(F.col("event_id").alias("purchase_id"), F.col("v.event_id").alias("view_id"))


ASOF_SQL = """SELECT purchase_id, view_id FROM (
  SELECT event_type, ts, event_id AS purchase_id, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER w AS view_id, last_value(CASE WHEN event_type = 'view' THEN ts END IGNORE NULLS) OVER w AS v
  FROM events WHERE event_type IN ('view', 'purchase') WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))
WHERE event_type = 'purchase' AND v >= ts - INTERVAL 6 HOURS"""


def trace_passes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Passes, stops, peak of watched sets, tests and pruned sets by the number of stops in a pass."""
    out = {f"ic_b S={s}": run(spark, sf_dir, "w2", chunks=s, bound="uniform", mode="rank") for s in (1, 2, 4, 10)}
    out |= {"ic_4 S=4": run(spark, sf_dir, "w2", "ic4_m4", mode="rank"), "level": run(spark, sf_dir, "w2", "level")}
    return measures.summary(spark, out)


def trace_stops(spark: SparkSession, sf_dir: str) -> DataFrame:
    return run(spark, sf_dir, "w2", "icb_m10", mode="rank").trace_frame()


def ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """First pass on and off by pruning off, own bound, with supersets; stops close enough for the bound to act."""
    runs = {f"first_pass={f} prune={p}": run(spark, sf_dir, "w7", "icb_m10", first_pass=f, prune=p, mode="rank") for f in (True, False) for p in ("none", "self", "bound")}
    return measures.summary(spark, runs)


def w9_synthetic(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The generator's baskets, wide masks (130 items), mined."""
    return mine(workloads.synthetic(spark, 5_000, m=130, avg_len=15), "0.1", "ic_b", chunks=4, mode="hash").itemsets()


_W10 = {
    "w10_customers": (workloads.w10_customers, "0.05", """SELECT c_custkey AS tid, unnest(['c_mktsegment=' || c_mktsegment, 'n_name=' || n_name, 'r_name=' || r_name, 'c_acctbal=' || CAST(floor(c_acctbal / 2500) AS BIGINT)]) AS item
FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"""),
    "w10_labels": (workloads.w10_labels, "0.05", "SELECT doc_id AS tid, unnest(['lang=' || lang, 'source=' || source, 'quality=' || quality, 'toxic=' || toxic]) AS item FROM documents JOIN labels USING (doc_id)"),
    "w10_pages": (workloads.w10_pages, "0.9", "SELECT DISTINCT page_id AS tid, unnest(regexp_extract_all(lower(html), '<([a-z][a-z0-9]*)', 1)) AS item FROM pages"),
    "w10_suppliers": (workloads.w10_suppliers, "0.02", """SELECT s_suppkey AS tid, unnest(['n_name=' || n_name, 'r_name=' || r_name, 's_acctbal=' || CAST(floor(s_acctbal / 2500) AS BIGINT)]) AS item
FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"""),
    "w10_benchmark": (workloads.w10_benchmark, "0.3", "SELECT DISTINCT item_id AS tid, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS item FROM benchmark"),
    "w10_conversations": (workloads.w10_conversations, "0.1", "SELECT DISTINCT conv_id AS tid, role || '/' || least(turn, 5) AS item FROM conversations"),
}


def _all() -> dict[str, tuple[Callable, str | None]]:
    q: dict[str, tuple[Callable, str | None]] = {}
    for w in workloads.BASKETS:
        q[f"{w}_encode_stats"] = _stats(w)
        q[f"{w}_singletons"] = _singletons(w)
        for name in RUNS:
            q[f"{w}_{name}"] = ((lambda s, d, w=w, name=name: run(s, d, w, name).itemsets()), _freq(w) + "\nSELECT items, k, supp FROM freq")
    q["w1_pairs"] = (_first_pass_pairs, _freq("w1", max_len=2) + "\nSELECT items, k, supp FROM freq WHERE k = 2")
    q["w2_level_distributed"] = ((lambda s, d: mine(_tx(s, d, "w2")[0], MINSUP["w2"], "level_distributed").itemsets()), _freq("w2") + "\nSELECT items, k, supp FROM freq")
    q["w2_icb_low"] = ((lambda s, d: run(s, d, "w2", "icb_m4", "0.05").itemsets()), _freq("w2", "0.05") + "\nSELECT items, k, supp FROM freq")
    q["w5_icb_low"] = ((lambda s, d: run(s, d, "w5", "icb_m2", "0.35").itemsets()), _freq("w5", "0.35") + "\nSELECT items, k, supp FROM freq")
    for name, (f, minsup, sql) in _W10.items():
        q[name] = ((lambda s, d, f=f, minsup=minsup: mine(f(s, d), minsup, "level").itemsets()), oracle.fim_sql(sql, minsup))
    q["support_of_given"] = (support_of_given, GIVEN_SQL)
    for number in BY_NUMBER:
        if number != "k6":
            q[f"count_{number}"] = (_counted(number), GIVEN_SQL)
    q["fold_duplicates"] = (fold_duplicates, f"SELECT count(*) AS rows, CAST(sum(w) AS BIGINT) AS transactions, max(w) AS heaviest FROM (SELECT held, count(*) AS w FROM (SELECT tid, list(item ORDER BY item) AS held FROM ({workloads.SQL['w3']}) GROUP BY tid) GROUP BY held)")
    q["chunk_sizes"] = (chunk_sizes, f"SELECT CAST(c AS INT) AS chunk, count(*) AS n_chunk FROM (SELECT (row_number() OVER (ORDER BY tid) - 1) // CAST(ceil(count(*) OVER () / 4.0) AS BIGINT) AS c FROM (SELECT DISTINCT tid FROM ({workloads.SQL['w1']}))) GROUP BY c")
    q["profile_by_k"] = (_on("w2", result.profile), _freq("w2") + "\nSELECT k, count(*) AS n_sets, min(supp) AS min_supp, max(supp) AS max_supp FROM freq GROUP BY k")
    q["kmax"] = (_on("w2", result.longest), _freq("w2") + "\nSELECT max(k) AS k_max, count(*) AS n_sets FROM freq")
    subset = "SELECT array_to_string(list_filter(p, lambda x: x <> y), '|') AS items, supp FROM (SELECT string_split(items, '|') AS p, unnest(string_split(items, '|')) AS y, supp FROM freq WHERE k > 1)"
    q["maximal"] = (_on("w2", result.maximal), _freq("w2") + f"\nSELECT items, k, supp FROM freq WHERE items NOT IN (SELECT items FROM ({subset}))")
    q["closed"] = (_on("w2", result.closed), _freq("w2") + f"\nSELECT f.items, f.k, f.supp FROM freq f LEFT JOIN (SELECT items, max(supp) AS above FROM ({subset}) GROUP BY items) u ON u.items = f.items WHERE above IS NULL OR above < f.supp")
    q["rules_conf"] = (_rules(min_conf=0.5), _rules_sql("confidence >= 0.5"))
    q["rules_lift"] = (_rules(min_conf=0.3, min_lift=1.05, max_consequent=1), _rules_sql("confidence >= 0.3 AND lift >= 1.05 AND NOT contains(consequent, '|')"))
    q["topk_per_size"] = (_on("w2", lambda f: result.top_k(f, 5)), _freq("w2") + "\nSELECT items, k, supp, CAST(r AS INT) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY k ORDER BY supp DESC, items) AS r FROM freq) WHERE r <= 5")
    for kind in ("rollup", "cube"):
        q[f"support_{kind}"] = (_by_group(kind), _by_group_sql(kind))
    sets = "GROUPING SETS ((r_name, item), (c_mktsegment, item), (r_name, c_mktsegment, item))"
    q["support_grouping_sets"] = (_by_group("grouping_sets"), _by_group_sql("@").replace("@(r_name, c_mktsegment, item)", sets))
    q["support_pivot"] = (support_pivot, f"WITH b AS ({workloads.SQL['w7']}) SELECT item, " + ", ".join(f"count(*) FILTER (WHERE c_mktsegment = '{x}') AS \"{x}\"" for x in SEGMENTS) + " FROM b JOIN customer ON c_custkey = tid GROUP BY item")
    q["ranked_sets"] = (_on("w2", result.ranked), _freq("w2") + """
SELECT items, k, supp, CAST(rank() OVER w AS INT) AS rank, CAST(dense_rank() OVER w AS INT) AS dense_rank, round(percent_rank() OVER w, 9) AS percent_rank, CAST(ntile(4) OVER (PARTITION BY k ORDER BY supp DESC, items) AS INT) AS bucket
FROM freq WINDOW w AS (PARTITION BY k ORDER BY supp DESC)""")
    q["near_support"] = (_on("w2", lambda f: result.near_support(f, 10)), _freq("w2") + "\nSELECT items, k, supp, count(*) OVER (PARTITION BY k ORDER BY supp RANGE BETWEEN 10 PRECEDING AND 10 FOLLOWING) AS near FROM freq")
    q["constraint_must"] = (constraint_must, _freq("w4") + "\nSELECT items, k, supp FROM freq WHERE list_contains(string_split(items, '|'), 'ls=O') AND NOT list_has_any(string_split(items, '|'), ['rf=N', 'os=O'])")
    q["contrast_returnflag"] = (contrast_returnflag, _contrast_sql())
    keep = workloads.SQL["w4"].strip()
    q["constraint_maxlen"] = (constraint_maxlen, oracle.fim_ctes(f"SELECT tid, item FROM ({keep}) WHERE split_part(item, '=', 1) IN ('rf', 'ls', 'ln', 'os', 'q')", MINSUP["w4"], "SELECT count(*) FROM lineitem", 2) + "\nSELECT items, k, supp FROM freq")
    q["constraint_group"] = (constraint_group, _freq("w2") + "\nSELECT items, k, supp FROM freq WHERE len(list_distinct(list_transform(string_split(items, '|'), lambda x: split_part(x, '.', 1)))) = k")
    q["tumbling_support"] = (_windowed("tumbling"), _windowed_sql("tumbling"))
    q["sliding_support"] = (_windowed("sliding", "1 day", "6 hours"), _windowed_sql("sliding"))
    q["session_support"] = (_windowed("session"), _windowed_sql("session"))
    q["asof_event_pairs"] = (asof_event_pairs, ASOF_SQL)
    for f in (trace_passes, trace_stops, trace_steps, ablation, w9_synthetic):
        q[f.__name__] = (f, None)
    for name, f in experiments.ALL.items():
        q[name] = (f, None)
    return q


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for name, (f, _) in _all().items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in _all().items() if sql}
