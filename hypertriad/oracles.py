"""DuckDB SQL for the queries: an independent route, by lead joins over all links and the region signature."""

from __future__ import annotations

from .functions.patterns import CORE, CORELESS, FAMILIES, PATTERN_TABLE, members_of

_EV = "day(ts)"
#: builder -> its (e, v) rows
BUILDER_SQL = {
    "bucket_users": "SELECT (epoch_us(ts) // 600000000) * 600 AS e, user_id AS v FROM events",
    "user_day_types": f"SELECT user_id * 100 + {_EV} AS e, event_type AS v FROM events",
    "user_day_keys": f"SELECT user_id * 100 + {_EV} AS e, CAST(json_extract_string(props, '$.k') AS BIGINT) AS v FROM events",
    "purchase_hour_users": "SELECT (epoch_us(ts) // 3600000000) * 3600 AS e, user_id AS v FROM events WHERE event_type = 'purchase'",
    "user_keys": "SELECT user_id AS e, CAST(json_extract_string(props, '$.k') AS BIGINT) AS v FROM events WHERE event_type = 'purchase'",
    "customer_nations": "SELECT o_custkey AS e, CAST(s_nationkey AS BIGINT) AS v FROM orders JOIN lineitem ON l_orderkey = o_orderkey JOIN supplier ON s_suppkey = l_suppkey WHERE l_returnflag = 'R' AND o_orderpriority = '1-URGENT'",
    "customer_brands": "SELECT o_custkey AS e, p_brand AS v FROM orders JOIN lineitem ON l_orderkey = o_orderkey JOIN part ON p_partkey = l_partkey WHERE l_returnflag = 'R' AND o_orderpriority = '1-URGENT'",
    "order_parts": "SELECT l_orderkey AS e, l_partkey AS v FROM lineitem",
    "order_suppliers": "SELECT l_orderkey AS e, l_suppkey AS v FROM lineitem WHERE l_returnflag = 'R' AND year(l_shipdate) = 1995",
    "day_customers": "SELECT date_diff('day', DATE '1970-01-01', CAST(o_orderdate AS DATE)) AS e, o_custkey AS v FROM orders",
    "doc_lines": "SELECT doc_id AS e, unnest(string_split(text, chr(10))) AS v FROM documents",
    "labelled_doc_lines": "SELECT doc_id AS e, unnest(string_split(text, chr(10))) AS v FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)",
    "benchmark_passages": "SELECT e, unnest(string_split(text, chr(10))) AS v FROM (SELECT doc_id AS e, text FROM documents UNION ALL SELECT -1 - item_id, text FROM benchmark)",
    "conv_tokens": "SELECT * FROM (SELECT conv_id AS e, unnest(regexp_split_to_array(lower(text), '[^a-z]+')) AS v FROM conversations) WHERE v <> ''",
    "page_links": "SELECT page_id AS e, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS v FROM pages",
    "vector_top_dims": "SELECT e, v FROM (SELECT e, v, row_number() OVER (PARTITION BY e ORDER BY x DESC, v) AS r FROM (SELECT vec_id AS e, unnest(embedding) AS x, generate_subscripts(embedding, 1) - 1 AS v FROM embeddings)) WHERE r <= 3",
    "interval_users": "SELECT p.event_id AS e, a.user_id AS v FROM events p JOIN events a ON a.ts <= p.ts AND epoch_us(a.ts) >= epoch_us(p.ts) - 1800000000 WHERE p.event_type = 'purchase'",
    "asof_clickers": "SELECT e, v FROM (SELECT event_type, user_id AS e, last_value(CASE WHEN event_type = 'click' THEN user_id END IGNORE NULLS) OVER (PARTITION BY epoch_us(ts) // 3600000000 ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS v FROM events WHERE event_type IN ('purchase', 'click')) WHERE event_type = 'purchase'",
    "latest_clickers": "SELECT e, v FROM (SELECT event_type, user_id AS e, last_value(CASE WHEN event_type = 'click' THEN user_id END IGNORE NULLS) OVER (ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS v FROM events WHERE event_type IN ('purchase', 'click') AND ts IS NOT NULL) WHERE event_type = 'purchase'",
    "rolling_users": "SELECT p.event_id AS e, a.user_id AS v FROM events p JOIN events a ON epoch_us(a.ts) // 1000000 BETWEEN epoch_us(p.ts) // 1000000 - 3600 AND epoch_us(p.ts) // 1000000 WHERE p.event_type = 'purchase' AND a.event_type = 'purchase'",
    "trailing_users": "SELECT p.event_id AS e, a.user_id AS v FROM events p JOIN events a ON CAST(a.ts AS DATE) = CAST(p.ts AS DATE) AND epoch_us(a.ts) // 1000000 BETWEEN epoch_us(p.ts) // 1000000 - 3600 AND epoch_us(p.ts) // 1000000 WHERE p.event_type = 'purchase' AND a.event_type = 'purchase'",
}


def edges_cte(builder: str, sigma_millionths: int | None = None, seed: int = 0, where: str = "") -> str:
    """raw, mem, edges (e, n, m), inc (e, v); with sigma, edges are the induced ones."""
    keep = "canon" if sigma_millionths is None else f"(SELECT e, m FROM (SELECT *, row_number() OVER (ORDER BY md5(CAST(e AS VARCHAR) || ':{seed}')) AS r, count(*) OVER () AS c FROM canon) WHERE r <= (c * {sigma_millionths} + 999999) // 1000000)"
    return f"""
raw AS (SELECT CAST(e AS BIGINT) AS e, v FROM ({BUILDER_SQL[builder]}) WHERE e IS NOT NULL AND v IS NOT NULL{where}),
mem AS (SELECT e, list_sort(list(DISTINCT v)) AS m FROM raw GROUP BY e),
canon AS (SELECT min(e) AS e, m FROM mem GROUP BY m),
edges AS (SELECT e, CAST(len(m) AS INTEGER) AS n, m FROM {keep}),
inc AS (SELECT e, n, unnest(m) AS v FROM edges)"""


LINKS_CTE = """
links AS (SELECT a.e AS i, b.e AS j, any_value(a.n) AS ni, any_value(b.n) AS nj, CAST(count(*) AS INTEGER) AS w, list(a.v) AS s,
                 CASE WHEN count(*) = least(any_value(a.n), any_value(b.n)) THEN 'C' ELSE 'T' END AS kind
          FROM inc a JOIN inc b ON a.v = b.v AND a.e < b.e GROUP BY a.e, b.e)"""

_CASES = " ".join(f"WHEN {1000 * n + 100 * c + 10 * d + s} THEN {p}" for p, (_, n, c, d, s) in PATTERN_TABLE.items())
TRIADS_CTE = f"""
open3 AS (SELECT a.i, a.j, b.j AS k, a.w AS wij, b.w AS wik, c.w AS wjk, a.ni, a.nj, b.nj AS nk, CAST(len(list_intersect(a.s, b.s)) AS INTEGER) AS g
          FROM links a JOIN links b ON a.i = b.i AND a.j < b.j JOIN links c ON c.i = a.j AND c.j = b.j),
tri AS (SELECT *, CASE 1000 * ((wij = least(ni, nj))::INT + (wik = least(ni, nk))::INT + (wjk = least(nj, nk))::INT) + 100 * (g > 0)::INT
                       + 10 * ((wij > g)::INT + (wik > g)::INT + (wjk > g)::INT)
                       + (ni - wij - wik + g > 0)::INT + (nj - wij - wjk + g > 0)::INT + (nk - wik - wjk + g > 0)::INT
                  {_CASES} END AS pattern FROM open3)"""
EVERY = "(SELECT CAST(unnest(generate_series(1, 20)) AS INTEGER) AS pattern)"
COUNTS_CTE = f"""
counts AS (SELECT p.pattern, CAST(coalesce(c.cnt, 0) AS BIGINT) AS cnt FROM {EVERY} p
           LEFT JOIN (SELECT pattern, count(*) AS cnt FROM tri GROUP BY pattern) c USING (pattern))"""
DEGREES_CTE = "deg AS (SELECT x, count(*) AS d FROM (SELECT i AS x FROM links UNION ALL SELECT j FROM links) GROUP BY x)"
OPEN_CTE = f"""{DEGREES_CTE},
open AS (SELECT c.closed, CAST(coalesce((SELECT sum(d * (d - 1) // 2) FROM deg), 0) - 3 * c.closed AS BIGINT) AS open FROM (SELECT CAST(coalesce(sum(cnt), 0) AS BIGINT) AS closed FROM counts) c)"""


def with_(builder: str, body: str, *parts: str, sigma: int | None = None, where: str = "") -> str:
    return "WITH " + ",".join([edges_cte(builder, sigma, where=where), *parts]) + "\n" + body


def links_sql(builder: str) -> str:
    return with_(builder, "SELECT i, j, ni, nj, w, kind, CASE WHEN ni > nj THEN i ELSE j END AS big, CASE WHEN ni > nj THEN j ELSE i END AS small FROM links", LINKS_CTE)


def summary_sql(builder: str) -> str:
    return with_(builder, "SELECT (SELECT count(DISTINCT v) FROM inc) AS vertices, (SELECT count(*) FROM edges) AS edges, (SELECT max(n) FROM edges) AS max_size, (SELECT round(sum(n) / count(*), 6) FROM edges) AS avg_size, (SELECT count(*) FROM links) AS links", LINKS_CTE)


def triads_sql(builder: str, body: str, sigma: int | None = None, *more: str) -> str:
    return with_(builder, body, LINKS_CTE, TRIADS_CTE, COUNTS_CTE, *more, sigma=sigma)


def counts_sql(builder: str, patterns: tuple[int, ...] = tuple(PATTERN_TABLE), sigma: int | None = None) -> str:
    return triads_sql(builder, f"SELECT pattern, cnt FROM counts WHERE pattern IN ({', '.join(map(str, patterns))})", sigma)


def enumerate_sql(builder: str, patterns: tuple[int, ...], sigma: int | None = None) -> str:
    return triads_sql(builder, f"SELECT i, j, k, wij, wik, wjk, g, ni, nj, nk, pattern FROM tri WHERE pattern IN ({', '.join(map(str, patterns))})", sigma)


def request_patterns(name: str) -> tuple[int, ...]:
    return {"core": CORE, "coreless": CORELESS}.get(name) or members_of(name.upper())


FAMILY_CASE = "CASE " + " ".join(f"WHEN pattern IN ({', '.join(map(str, members_of(f)))}) THEN '{f}'" for f in FAMILIES) + " END"
