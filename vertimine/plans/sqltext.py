"""DuckDB SQL for mining results, independent of the engine: each view's SQL, then joins and list intersections."""

from __future__ import annotations

from vertimine.sources.baskets import COUNT_SQL, VIEW_SQL

TEXT = "array_to_string(list_sort(items), '|')"


def head(view: str, min_support: str | None = None, min_count: int | None = None, source: str | None = None, count: str | None = None) -> str:
    """WITH clauses v (tid, item), n (transactions), c (least count), s (frequent items with tids, support and rank)."""
    total = count or COUNT_SQL.get(view, "SELECT count(DISTINCT tid) FROM v")
    least = str(min_count) if min_count is not None else f"CAST(ceil(CAST('{min_support}' AS DECIMAL(12, 9)) * (SELECT n FROM n)) AS BIGINT)"
    return f"""v AS MATERIALIZED ({source or VIEW_SQL[view]}),
n AS (SELECT ({total}) AS n),
c AS (SELECT {least} AS c),
s AS MATERIALIZED (SELECT item, list(tid ORDER BY tid) AS tids, count(*) AS support, CAST(row_number() OVER (ORDER BY count(*), item) - 1 AS INT) AS rank
      FROM v GROUP BY item HAVING count(*) >= (SELECT c FROM c))"""


def itemsets(view: str, min_support: str | None = None, min_count: int | None = None, **options) -> str:
    """WITH clauses up to f (items, k, support): grown by later items while enough tids are shared."""
    return f"""WITH RECURSIVE {head(view, min_support, min_count, **options)},
g AS (SELECT [item] AS items, rank AS last, tids, len(tids) AS support FROM s
      UNION ALL
      SELECT items, last, tids, len(tids) FROM (
        SELECT list_append(g.items, s.item) AS items, s.rank AS last, list_intersect(g.tids, s.tids) AS tids FROM g JOIN s ON s.rank > g.last)
      WHERE len(tids) >= (SELECT c FROM c)),
f AS MATERIALIZED (SELECT list_sort(items) AS items, CAST(len(items) AS INT) AS k, CAST(support AS BIGINT) AS support FROM g)"""


def frequent(view: str, min_support: str | None = None, min_count: int | None = None, **options) -> str:
    return f"{itemsets(view, min_support, min_count, **options)}\nSELECT {TEXT} AS itemset, k, support FROM f"


def pairs(view: str, min_support: str | None = None, min_count: int | None = None) -> str:
    """WITH clauses up to p (i, j, support) over ranks."""
    return f"""WITH {head(view, min_support, min_count)},
e AS MATERIALIZED (SELECT tid, rank FROM v JOIN s USING (item)),
p AS MATERIALIZED (SELECT a.rank AS i, b.rank AS j, count(*) AS support FROM e a JOIN e b ON a.tid = b.tid AND a.rank < b.rank
      GROUP BY 1, 2 HAVING count(*) >= (SELECT c FROM c))"""


def place(kind: str, p: int) -> str:
    return {
        "per_class": "i",
        "modulo": f"i % {p}",
        "reflect": f"CASE WHEN i < {p} THEN i ELSE {p - 1} - i % {p} END",
        "snake": f"CASE WHEN (i // {p}) % 2 = 0 THEN i % {p} ELSE {p - 1} - i % {p} END",
    }[kind]
