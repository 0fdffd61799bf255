"""SQL for the checks: frequent itemsets by a recursion over tid lists, independent of bit masks."""

from __future__ import annotations

from fractions import Fraction


def need_sql(minsup: str, n_sql: str) -> str:
    f = Fraction(minsup)
    return f"((({n_sql}) * {f.numerator} + {f.denominator - 1}) // {f.denominator})"


def fim_ctes(baskets: str, minsup: str, n_sql: str | None = None, max_len: int | None = None) -> str:
    """CTEs b (baskets), need, and freq(items, k, supp)."""
    n = n_sql or "SELECT count(DISTINCT tid) FROM b"
    stop = f" AND k < {max_len}" if max_len else ""
    return f"""WITH RECURSIVE b AS MATERIALIZED ({baskets}), need AS (SELECT {need_sql(minsup, n)} AS need),
g AS (SELECT item AS items, item AS last, 1 AS k, list(tid) AS tids FROM b GROUP BY item HAVING count(*) >= (SELECT need FROM need)
  UNION ALL
  SELECT x.items || '|' || b.item, b.item, x.k + 1, list(b.tid) FROM (SELECT items, last, k, unnest(tids) AS tid FROM g WHERE true{stop}) x
  JOIN b ON b.tid = x.tid AND b.item > x.last GROUP BY x.items, b.item, x.k HAVING count(*) >= (SELECT need FROM need)),
freq AS (SELECT items, CAST(k AS INT) AS k, CAST(len(tids) AS BIGINT) AS supp FROM g)"""


def fim_sql(baskets: str, minsup: str, n_sql: str | None = None, max_len: int | None = None) -> str:
    return fim_ctes(baskets, minsup, n_sql, max_len) + "\nSELECT items, k, supp FROM freq"
