"""Every query with its SQL: methods, variants, baselines, measures, workloads and helpers on the given tables."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import oracles as O
from ..functions import relational as R
from ..functions import udfs
from ..functions.patterns import PATTERN_TABLE, family_of, register_sql
from ..model import Hypergraph, canonicalize, dictionary_encode, summary, vertex_degrees
from ..operators import baseline, blocks, families, measures, sampling
from ..operators.block_samples import LinksInBlocks
from ..operators.links import bruteforce_links, build_links, links_at_least, project
from ..sources.builders import BUILDERS, hypergraph, interval_edges, lines_of_lang, read_table
from ..sources.files import from_lists
from ..stages import stage, stage_links
from . import workloads
from .planner import triads

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

#: Builders whose exact counts are compared everywhere; order_parts is counted whole too, but without SQL.  Only queries of
#: sampling read an induced fifth of the edges.
EXACT = ("user_day_types", "order_suppliers", "purchase_hour_users", "doc_lines", "labelled_doc_lines", "benchmark_passages", "day_customers", "user_keys", "vector_top_dims", "page_links", "conv_tokens", "asof_clickers", "latest_clickers", "bucket_users", "user_day_keys", "customer_nations", "customer_brands")
FIFTH = 200_000
SIGMA = 0.2


def add(name: str, query: Query, sql: str | None = None) -> None:
    if name in QUERIES:
        raise ValueError(f"two queries named {name}")
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def graph(spark: SparkSession, d: str, builder: str, sigma: float | None = None) -> Hypergraph:
    hg = hypergraph(spark, d, builder)
    return sampling.induce(hg, sigma) if sigma else hg


def linked(hg: Hypergraph) -> DataFrame:
    return stage_links(build_links(hg, with_shared=True))


def counted(spark: SparkSession, d: str, builder: str) -> tuple[Hypergraph, DataFrame, DataFrame]:
    """Hypergraph, staged links and staged counts."""
    hg = graph(spark, d, builder)
    links = linked(hg)
    return hg, links, stage(triads(hg, mode="count", links=links))


def tallied(hg: Hypergraph) -> tuple[None, DataFrame, DataFrame]:
    """No links, the counts, and the pairs of neighbours, from one census by blocks."""
    found = blocks.census(hg)
    return None, measures.pattern_counts(blocks.triad_counts(found), counted=True), blocks.figure(found, "two_hop").withColumnRenamed("two_hop", "pairs")


# --- data and links -------------------------------------------------------------------------------------------------

for b in BUILDERS:
    if b not in ("interval_users", "trailing_users", "rolling_users"):
        add(f"dataset_summary_{b}", lambda s, d, b=b: summary(hg := graph(s, d, b), None, blocks.link_figures(hg)), O.summary_sql(b))
for b in ("interval_users", "trailing_users", "rolling_users", "asof_clickers", "latest_clickers"):
    add(f"edges_{b}", lambda s, d, b=b: (interval_edges(s, d) if b == "interval_users" else graph(s, d, b).edges).select("e", "n", F.concat_ws(",", "members").alias("members")), O.with_(b, "SELECT e, n, array_to_string(m, ',') AS members FROM edges"))
for strategy in ("join", "blocked", "array"):
    add(f"links_{strategy}_order_suppliers", lambda s, d, t=strategy: build_links(graph(s, d, "order_suppliers"), strategy=t, block=8), O.links_sql("order_suppliers"))
add("links_auto_customer_nations", lambda s, d: build_links(graph(s, d, "customer_nations"), strategy="auto"), O.links_sql("customer_nations"))
add("links_shuffle_hash_purchase_hour_users", lambda s, d: build_links(graph(s, d, "purchase_hour_users"), join_hint="shuffle_hash"), O.links_sql("purchase_hour_users"))
add("links_bruteforce_user_day_types", lambda s, d: bruteforce_links(graph(s, d, "user_day_types")), O.with_("user_day_types", "SELECT i, j, w FROM links", O.LINKS_CTE))
add("projection_order_suppliers", lambda s, d: project(graph(s, d, "order_suppliers")), O.with_("order_suppliers", "SELECT i, j FROM links", O.LINKS_CTE))
add("links_at_least_2_purchase_hour_users", lambda s, d: links_at_least(build_links(graph(s, d, "purchase_hour_users")), 2).select("i", "j", "w"), O.with_("purchase_hour_users", "SELECT i, j, w FROM links WHERE w >= 2", O.LINKS_CTE))
add("vertex_degrees_order_parts", lambda s, d: vertex_degrees(graph(s, d, "order_parts")), O.with_("order_parts", "SELECT v, count(*) AS d FROM inc GROUP BY v"))
add("dictionary_doc_lines", lambda s, d: dictionary_encode(BUILDERS["doc_lines"](s, d).select("e", F.sha2("v", 256).alias("v")), "v", "code").groupBy("code").agg(F.count(F.lit(1)).alias("edges")), f"WITH raw AS (SELECT DISTINCT e, sha256(v) AS v FROM ({O.BUILDER_SQL['doc_lines']})) SELECT dense_rank() OVER (ORDER BY v) - 1 AS code, count(*) AS edges FROM raw GROUP BY v")

# --- exact search ---------------------------------------------------------------------------------------------------

for b in EXACT:
    add(f"counts_all_{b}", lambda s, d, b=b: triads(graph(s, d, b), mode="count"), O.counts_sql(b))
add("counts_all_order_parts", lambda s, d: triads(graph(s, d, "order_parts"), mode="count"))
for f in ("ccc", "tcc", "ttc", "ttt", "core", "coreless"):
    request = f if f.startswith("core") else f.upper()
    add(f"counts_{f}_purchase_hour_users", lambda s, d, r=request: triads(graph(s, d, "purchase_hour_users"), r, "count"), O.counts_sql("purchase_hour_users", O.request_patterns(f)))
    add(f"counts_{f}_customer_nations", lambda s, d, r=request: triads(graph(s, d, "customer_nations"), r, "count"), O.counts_sql("customer_nations", O.request_patterns(f)))
for p in PATTERN_TABLE:
    add(f"enumerate_p{p}_user_day_types", lambda s, d, p=p: triads(graph(s, d, "user_day_types"), p), O.enumerate_sql("user_day_types", (p,)))
add("enumerate_all_order_suppliers", lambda s, d: triads(graph(s, d, "order_suppliers")), O.enumerate_sql("order_suppliers", tuple(PATTERN_TABLE)))
for k in ("vertex", "grouped"):
    add(f"core_{k}_purchase_hour_users", lambda s, d, k=k: triads(graph(s, d, "purchase_hour_users"), "core", core_strategy=k), O.enumerate_sql("purchase_hour_users", O.request_patterns("core")))
add("degree_led_purchase_hour_users", lambda s, d: triads(graph(s, d, "purchase_hour_users"), "TTT", lead="degree"), O.enumerate_sql("purchase_hour_users", O.request_patterns("ttt")))
add("parallel_counts_order_suppliers", lambda s, d: triads(graph(s, d, "order_suppliers"), mode="count", parallelism=16), O.counts_sql("order_suppliers"))
add("unified_counts_customer_nations", lambda s, d: measures.pattern_counts(families.unified_triads(linked(graph(s, d, "customer_nations")))), O.counts_sql("customer_nations"))

# --- the exhaustive baseline ----------------------------------------------------------------------------------------

for b in ("order_suppliers", "purchase_hour_users", "user_day_types"):
    add(f"baseline_counts_{b}", lambda s, d, b=b: measures.pattern_counts(baseline.baseline_triads(graph(s, d, b))), O.counts_sql(b))
add("baseline_two_hop_order_suppliers", lambda s, d: baseline.baseline_triads(graph(s, d, "order_suppliers"), keep_two_hop=True), O.enumerate_sql("order_suppliers", tuple(PATTERN_TABLE)))
add("baseline_parallel_user_day_types", lambda s, d: measures.pattern_counts(baseline.baseline_triads(graph(s, d, "user_day_types"), parallelism=16)), O.counts_sql("user_day_types"))
_OPEN_ROWS = """
ends AS (SELECT i AS x, j AS y FROM links UNION ALL SELECT j, i FROM links),
gap AS (SELECT a.x, a.y, b.y AS z FROM ends a JOIN ends b ON a.x = b.x AND a.y < b.y LEFT JOIN links l ON l.i = a.y AND l.j = b.y WHERE l.i IS NULL)"""
add("baseline_motifs_order_suppliers", lambda s, d: baseline.baseline_motifs(graph(s, d, "order_suppliers")), O.triads_sql("order_suppliers", "SELECT i, j, k, pattern FROM tri UNION ALL SELECT least(x, y, z), CASE WHEN x < y THEN y WHEN x < z THEN x ELSE z END, greatest(x, y, z), 0 FROM gap", None, _OPEN_ROWS).replace("CASE WHEN x < y THEN y WHEN x < z THEN x ELSE z END", "x + y + z - least(x, y, z) - greatest(x, y, z)"))

# --- measures -------------------------------------------------------------------------------------------------------

for b in ("user_day_types", "order_suppliers", "purchase_hour_users", "day_customers"):
    add(f"coefficient_{b}", lambda s, d, b=b: measures.clustering_coefficient(*tallied(graph(s, d, b))).withColumn("coefficient", F.round("coefficient", 9)), O.triads_sql(b, "SELECT closed, open, round(CASE WHEN open <> 0 THEN 3.0 * closed / CAST(open AS DOUBLE) END, 9) AS coefficient FROM open", None, O.OPEN_CTE))
for b in ("user_day_types", "purchase_hour_users", "doc_lines", "order_suppliers", "page_links", "vector_top_dims", "day_customers", "asof_clickers", "latest_clickers"):
    add(f"profile_{b}", lambda s, d, b=b: measures.coefficient_profile(*tallied(graph(s, d, b))).withColumns({"coefficient": F.round("coefficient", 9), "share": F.round("share", 9)}), O.triads_sql(b, "SELECT pattern, cnt, round(CASE WHEN open <> 0 THEN 3.0 * cnt / CAST(open AS DOUBLE) END, 9) AS coefficient, round(CASE WHEN closed <> 0 THEN cnt / CAST(closed AS DOUBLE) END, 9) AS share FROM counts, open", None, O.OPEN_CTE))
_HALF = {p: 0.5 for p in range(9, 21)}
add("weighted_coefficient_purchase_hour_users", lambda s, d: measures.weighted_coefficient(*counted(s, d, "purchase_hour_users")[1:], _HALF).withColumn("coefficient", F.round("coefficient", 9)), O.triads_sql("purchase_hour_users", "SELECT t.weighted, open, round(CASE WHEN open <> 0 THEN 3 * t.weighted / open END, 9) AS coefficient FROM open, (SELECT CAST(sum(cnt * CASE WHEN pattern >= 9 THEN 0.5 ELSE 1.0 END) AS DOUBLE) AS weighted FROM counts) t", None, O.OPEN_CTE))
add("open_triads_order_suppliers", lambda s, d: measures.open_triads(build_links(graph(s, d, "order_suppliers"))), O.with_("order_suppliers", "SELECT x, y, z FROM gap", O.LINKS_CTE, _OPEN_ROWS))
add("triads_per_edge_order_suppliers", lambda s, d: measures.triads_per_edge(triads(graph(s, d, "order_suppliers"))), O.triads_sql("order_suppliers", "SELECT e, pattern, count(*) AS cnt FROM (SELECT unnest([i, j, k]) AS e, pattern FROM tri) GROUP BY e, pattern"))


def _per_vertex(s: SparkSession, d: str) -> DataFrame:
    hg = graph(s, d, "order_suppliers")
    return measures.triads_per_vertex(triads(hg), hg)


add("triads_per_vertex_order_suppliers", _per_vertex, O.triads_sql("order_suppliers", "SELECT v, pattern, count(*) AS cnt FROM (SELECT DISTINCT v, i, j, k, pattern FROM (SELECT i, j, k, pattern, unnest([i, j, k]) AS e FROM tri) t JOIN inc USING (e)) GROUP BY v, pattern"))
def _space(s: SparkSession, d: str, b: str) -> DataFrame:
    hg = graph(s, d, b)
    return measures.space_model(hg, None, blocks.link_figures(hg)).withColumn("ratio", F.round("ratio", 9))


for b in ("bucket_users", "user_day_keys", "customer_nations", "customer_brands", "order_parts", "day_customers"):
    add(f"space_{b}", lambda s, d, b=b: _space(s, d, b), O.with_(b, "SELECT CAST(m + l AS BIGINT) AS baseline_one_hop, CAST(m + l + h AS BIGINT) AS baseline_two_hop, CAST(m + o AS BIGINT) AS proposed, round(CAST(m + o AS DOUBLE) / (m + l), 9) AS ratio FROM (SELECT (SELECT sum(n) FROM edges) m, (SELECT count(*) FROM links) l, (SELECT sum(w) FROM links) o, (SELECT sum(d * (d - 1) // 2) FROM deg) h)", O.LINKS_CTE, O.DEGREES_CTE))
for b in ("order_suppliers", "purchase_hour_users", "doc_lines"):
    add(f"space_{b}", lambda s, d, b=b: _space(s, d, b), O.with_(b, "SELECT CAST(m + l AS BIGINT) AS baseline_one_hop, CAST(m + l + h AS BIGINT) AS baseline_two_hop, CAST(m + o AS BIGINT) AS proposed, round(CAST(m + o AS DOUBLE) / (m + l), 9) AS ratio FROM (SELECT (SELECT sum(n) FROM edges) m, (SELECT count(*) FROM links) l, (SELECT sum(w) FROM links) o, (SELECT sum(d * (d - 1) // 2) FROM deg) h)", O.LINKS_CTE, O.DEGREES_CTE))
    add(f"work_counters_{b}", lambda s, d, b=b: measures.work_counters(*counted(s, d, b)[1:]), O.triads_sql(b, "SELECT (SELECT count(*) FROM links) AS links, (SELECT count(*) FROM links WHERE kind = 'C') AS nest_links, (SELECT count(*) FROM links WHERE kind = 'T') AS cross_links, CAST(coalesce((SELECT sum(c * (c - 1) // 2) FROM (SELECT count(*) AS c FROM links GROUP BY i)), 0) AS BIGINT) AS lead_pairs, closed, open FROM open", None, O.OPEN_CTE))
_TERMS = """
t AS (SELECT * FROM links WHERE kind = 'T'),
c AS (SELECT CASE WHEN ni > nj THEN i ELSE j END AS big, CASE WHEN ni > nj THEN j ELSE i END AS small FROM links WHERE kind = 'C'),
ot AS (SELECT i AS e, count(*) AS n FROM t GROUP BY i),
aa AS (SELECT e, count(*) AS n FROM (SELECT i AS e FROM t UNION ALL SELECT j FROM t) GROUP BY e),
bs AS (SELECT e, count(*) AS n FROM (SELECT big AS e FROM c UNION ALL SELECT small FROM c) GROUP BY e),
ttt AS (SELECT coalesce(sum(n * w), 0) AS x FROM t JOIN ot ON e = i),
meet AS (SELECT coalesce(sum(a.w), 0) AS x FROM t a JOIN t b ON a.i = b.i AND a.j < b.j WHERE len(list_intersect(a.s, b.s)) > 0),
one AS (SELECT coalesce(sum(ni + nj), 0) AS x FROM links)"""
add("complexity_terms_order_suppliers", lambda s, d: measures.complexity_terms(hg := graph(s, d, "order_suppliers"), linked(hg)), O.with_("order_suppliers", """SELECT method, CAST(step_one AS BIGINT) AS step_one, CAST(step_two AS BIGINT) AS step_two FROM (
SELECT 'exhaustive' AS method, CAST(sum(n * d) AS BIGINT) AS step_one, CAST(sum(n * d * d) AS BIGINT) AS step_two FROM edges JOIN deg ON x = e
UNION ALL SELECT 'one_nest', (SELECT x FROM one), (SELECT coalesce(sum(n), 0) FROM c JOIN aa ON e = big)
UNION ALL SELECT 'two_nests', (SELECT x FROM one), (SELECT coalesce(sum(n), 0) FROM t JOIN bs ON e = i)
UNION ALL SELECT 'nest_chain', (SELECT x FROM one), (SELECT coalesce(sum(n * n), 0) FROM (SELECT count(*) AS n FROM c GROUP BY big))
UNION ALL SELECT 'cross', (SELECT x FROM one), (SELECT x FROM ttt)
UNION ALL SELECT 'core', (SELECT x FROM one), (SELECT x FROM meet)
UNION ALL SELECT 'coreless', (SELECT x FROM one), (SELECT x FROM ttt))""", O.LINKS_CTE, O.DEGREES_CTE, _TERMS))
#: The rounds are unrolled; those after the last that takes an edge away change nothing.
_ROUNDS = ["left0 AS (SELECT e FROM edges)", *(f"left{r} AS (SELECT e FROM (SELECT unnest([i, j, k]) AS e FROM tri WHERE pattern >= 9 AND i IN (SELECT e FROM left{r - 1}) AND j IN (SELECT e FROM left{r - 1}) AND k IN (SELECT e FROM left{r - 1})) GROUP BY e HAVING count(*) >= 3)" for r in range(1, 9))]
add("triad_core_order_suppliers", lambda s, d: measures.triad_core(graph(s, d, "order_suppliers"), 3, lambda g: triads(g, "TTT")), O.triads_sql("order_suppliers", "SELECT e, n FROM edges WHERE e IN (SELECT e FROM left8)", None, *_ROUNDS))
add("clique_edges_order_suppliers", lambda s, d: measures.clique_edges(build_links(graph(s, d, "order_suppliers")), 3), O.triads_sql("order_suppliers", "SELECT i, j, w FROM links JOIN (SELECT l.i AS i, l.j AS j FROM (SELECT unnest([{'i': i, 'j': j}, {'i': i, 'j': k}, {'i': j, 'j': k}]) AS l FROM tri) GROUP BY ALL HAVING count(*) >= 3) USING (i, j)"))

# --- sampling -------------------------------------------------------------------------------------------------------

_FEW = "order_suppliers"
_LINK_KEY = "md5(CAST(i AS VARCHAR) || ',' || CAST(j AS VARCHAR) || ':0')"
_EST = "SELECT p.pattern, CAST(coalesce(raw, 0) AS DOUBLE) AS raw, round(coalesce(raw, 0) * {factor}, 6) AS est FROM " + O.EVERY + " p LEFT JOIN got USING (pattern)"


def _rounded(df: DataFrame) -> DataFrame:
    return df.select("pattern", F.round("raw", 6).alias("raw"), F.round("est", 6).alias("est"))


add("induced_edges_order_parts", lambda s, d: graph(s, d, "order_parts", SIGMA).edges.select("e", "n"), O.with_("order_parts", "SELECT e, n FROM edges", sigma=FIFTH))
add("induced_threshold_order_parts", lambda s, d: sampling.induce(graph(s, d, "order_parts"), SIGMA, how="threshold").edges.select("e", "n"), O.with_("order_parts", f"SELECT e, n FROM edges WHERE CAST('0x' || substr(md5(CAST(e AS VARCHAR) || ':0'), 1, 8) AS BIGINT) < {int(SIGMA * 2**32)}"))
add("sample_link", lambda s, d: _rounded(sampling.sample_by_link(linked(graph(s, d, _FEW)), 300)), O.triads_sql(_FEW, _EST.format(factor="(SELECT count(*) / CAST(least(count(*), 300) AS DOUBLE) FROM links)"), None, f"pick AS (SELECT i, j FROM links ORDER BY {_LINK_KEY} LIMIT 300)", "got AS (SELECT pattern, count(*) AS raw FROM tri JOIN pick USING (i, j) GROUP BY pattern)"))
add("sample_edge", lambda s, d: _rounded(sampling.sample_by_edge(hg := graph(s, d, _FEW), linked(hg), 80)), O.triads_sql(_FEW, _EST.format(factor="(SELECT count(*) / CAST(least(count(*), 80) AS DOUBLE) FROM edges)"), None, "pick AS (SELECT e FROM edges ORDER BY md5(CAST(e AS VARCHAR) || ':0') LIMIT 80)", "got AS (SELECT pattern, count(*) AS raw FROM tri JOIN pick ON e = i GROUP BY pattern)"))
for fix in (False, True):
    add(f"sample_vertex{'_corrected' * fix}", lambda s, d, c=fix: _rounded(sampling.sample_by_vertex(hg := graph(s, d, _FEW), linked(hg), 40, correct=c)), O.triads_sql(_FEW, _EST.format(factor="(SELECT count(DISTINCT v) / CAST(least(count(DISTINCT v), 40) AS DOUBLE) FROM inc)").replace("CAST(coalesce(raw, 0) AS DOUBLE)", "round(CAST(coalesce(raw, 0) AS DOUBLE), 6)"), None, "pick AS (SELECT v FROM (SELECT DISTINCT v FROM inc) ORDER BY md5(CAST(v AS VARCHAR) || ':0') LIMIT 40)", "load AS (SELECT e, count(*) AS m FROM inc JOIN pick USING (v) GROUP BY e)", f"got AS (SELECT pattern, sum({'m / CAST(ni AS DOUBLE)' if fix else 'm'}) AS raw FROM tri JOIN load ON e = i GROUP BY pattern)"))
add("sample_links_any_order", lambda s, d: _rounded(sampling.sample_links_any_order(linked(graph(s, d, _FEW)), 300)), O.triads_sql(_FEW, "SELECT p.pattern, CAST(coalesce(raw, 0) AS DOUBLE) AS raw, round(coalesce(raw, 0) * (SELECT count(*) / CAST(least(count(*), 300) AS DOUBLE) FROM links) / CASE WHEN p.pattern = 0 THEN 2.0 ELSE 3.0 END, 6) AS est FROM (SELECT CAST(unnest(generate_series(0, 20)) AS INTEGER) AS pattern) p LEFT JOIN got USING (pattern)", None, _OPEN_ROWS, f"pick AS (SELECT i, j FROM links ORDER BY {_LINK_KEY} LIMIT 300)", "got AS (SELECT pattern, count(*) AS raw FROM (SELECT pattern, unnest([{'i': i, 'j': j}, {'i': i, 'j': k}, {'i': j, 'j': k}]) AS l FROM tri) t JOIN pick ON pick.i = l.i AND pick.j = l.j GROUP BY pattern UNION ALL SELECT 0, count(*) FROM (SELECT unnest([{'i': least(x, y), 'j': greatest(x, y)}, {'i': least(x, z), 'j': greatest(x, z)}]) AS l FROM gap) g JOIN pick ON pick.i = l.i AND pick.j = l.j)"))
_STRATA = f"""
pools AS (SELECT count(*) FILTER (kind = 'T') AS t, count(*) FILTER (kind = 'C') AS c FROM links),
share AS (SELECT least(t, greatest(1, CAST(round_even(300 * t * t / CAST((t + c) * (t + c) AS DOUBLE), 0) AS BIGINT))) AS a1, least(c, greatest(1, CAST(round_even(300 * c * c / CAST((t + c) * (t + c) AS DOUBLE), 0) AS BIGINT))) AS a2,
                 greatest(1, CAST(round_even(300 * t * c / CAST((t + c) * (t + c) AS DOUBLE), 0) AS BIGINT)) AS a3, t, c FROM pools),
rt AS (SELECT i, j, row_number() OVER (ORDER BY {_LINK_KEY}) AS r FROM links WHERE kind = 'T'),
rc AS (SELECT i, j, row_number() OVER (ORDER BY {_LINK_KEY}) AS r FROM links WHERE kind = 'C'),
led AS (SELECT pattern, f, CASE f WHEN 'TTT' THEN {{'a': i, 'b': j}}
                    WHEN 'CCC' THEN CASE WHEN ni < nj AND ni < nk THEN {{'a': j, 'b': k}} WHEN nj < ni AND nj < nk THEN {{'a': i, 'b': k}} ELSE {{'a': i, 'b': j}} END
                    WHEN 'TCC' THEN CASE WHEN wij < least(ni, nj) THEN {{'a': i, 'b': j}} WHEN wik < least(ni, nk) THEN {{'a': i, 'b': k}} ELSE {{'a': j, 'b': k}} END
                    ELSE CASE WHEN wij = least(ni, nj) THEN {{'a': i, 'b': j}} WHEN wik = least(ni, nk) THEN {{'a': i, 'b': k}} ELSE {{'a': j, 'b': k}} END END AS l
        FROM (SELECT *, {O.FAMILY_CASE} AS f FROM tri)),
got AS (SELECT pattern, count(*) AS raw, any_value(CASE f WHEN 'TTT' THEN t / CAST(a1 AS DOUBLE) WHEN 'CCC' THEN c / CAST(a2 AS DOUBLE) WHEN 'TCC' THEN t / CAST(least(t, a3) AS DOUBLE) ELSE c / CAST(least(c, a3) AS DOUBLE) END) AS factor
        FROM led, share LEFT JOIN rt ON rt.i = l.a AND rt.j = l.b LEFT JOIN rc ON rc.i = l.a AND rc.j = l.b
        WHERE (f = 'TTT' AND rt.r <= a1) OR (f = 'CCC' AND rc.r <= a2) OR (f = 'TCC' AND rt.r <= least(t, a3)) OR (f = 'TTC' AND rc.r <= least(c, a3)) GROUP BY pattern)"""
add("sample_family", lambda s, d: _rounded(sampling.sample_by_family(linked(graph(s, d, _FEW)), 300)), O.triads_sql(_FEW, _EST.format(factor="coalesce(factor, 0)"), None, _STRATA))
add("sample_family_one_nest_only", lambda s, d: _rounded(sampling.sample_by_family(linked(graph(s, d, _FEW)), 10**6, families=("TTC",))), O.triads_sql(_FEW, "SELECT pattern, CAST(CASE WHEN pattern IN (6, 7, 8) THEN cnt ELSE 0 END AS DOUBLE) AS raw, CAST(CASE WHEN pattern IN (6, 7, 8) THEN cnt ELSE 0 END AS DOUBLE) AS est FROM counts"))
_TURN = "CAST('0x' || substr(md5(CAST(id AS VARCHAR) || ':0'), 1, 15) AS BIGINT)"
_TURNS = "(SELECT unnest(range(300)) AS id)"
add("sample_link_with_replacement", lambda s, d: _rounded(sampling.sample_by_link(linked(graph(s, d, _FEW)), 300, replacement=True)), O.triads_sql(_FEW, _EST.format(factor="(SELECT count(*) / 300.0 FROM links)"), None, "lined AS (SELECT i, j, row_number() OVER (ORDER BY i, j) - 1 AS p FROM links)", f"pick AS (SELECT {_TURN} % (SELECT count(*) FROM links) AS p, count(*) AS m FROM {_TURNS} GROUP BY 1)", "got AS (SELECT pattern, sum(m) AS raw FROM tri JOIN lined USING (i, j) JOIN pick USING (p) GROUP BY pattern)"))
_AGAIN = f"""
strata AS (SELECT 'TTT' AS f, 'T' AS kind, t AS pool, a1 AS a FROM share UNION ALL SELECT 'CCC', 'C', c, a2 FROM share UNION ALL SELECT 'TCC', 'T', t, least(t, a3) FROM share UNION ALL SELECT 'TTC', 'C', c, least(c, a3) FROM share),
lined AS (SELECT kind, i, j, row_number() OVER (PARTITION BY kind ORDER BY i, j) - 1 AS p FROM links),
hits AS (SELECT f, kind, pool, a, {_TURN} % pool AS p, count(*) AS m FROM strata, {_TURNS} WHERE id < a GROUP BY ALL),
again AS (SELECT led.pattern, sum(m) AS raw, any_value(pool / CAST(a AS DOUBLE)) AS factor FROM led JOIN hits ON hits.f = led.f JOIN lined ON lined.kind = hits.kind AND lined.p = hits.p AND lined.i = led.l.a AND lined.j = led.l.b GROUP BY led.pattern)"""
add("sample_family_with_replacement", lambda s, d: _rounded(sampling.sample_by_family(linked(graph(s, d, _FEW)), 300, replacement=True)), O.triads_sql(_FEW, _EST.format(factor="coalesce(factor, 0)").replace("JOIN got USING", "JOIN again USING"), None, _STRATA, _AGAIN))
for element, value in (("vertex", "sum(ni)"), ("edge", "count(*)"), ("link", "count(*)")):
    add(f"expectation_{element}", lambda s, d, e=element: sampling.sampling_expectation(linked(graph(s, d, _FEW)), e), O.triads_sql(_FEW, f"SELECT p.pattern, CAST(coalesce(x, 0) AS BIGINT) AS expected FROM {O.EVERY} p LEFT JOIN (SELECT pattern, {value} AS x FROM tri GROUP BY pattern) USING (pattern)"))
for element, keys in (("edge", "i"), ("link", "i, j")):
    for joint, third in (("assumed", "3.0"), ("lead", "1.0")):
        add(f"variance_{element}_{joint}", lambda s, d, e=element, q=joint: sampling.variance_uniform(linked(graph(s, d, _FEW)), e, 100, 1500, q).withColumn("variance", F.round("variance", 6)), O.triads_sql(_FEW, f"SELECT p.pattern, CAST(coalesce(h, 0) AS BIGINT) AS triads, CAST(coalesce(h, 0) * (coalesce(h, 0) - 1) AS BIGINT) AS pairs, CAST(coalesce(s, 0) AS BIGINT) AS sharing, round(100.0 * (coalesce(h, 0) * (1 / 1500.0 - 1 / (1500.0 * 1500.0)) + coalesce(s, 0) / ({third} * 1500.0) - coalesce(h, 0) * (coalesce(h, 0) - 1) / (1500.0 * 1500.0)), 6) AS variance FROM {O.EVERY} p LEFT JOIN (SELECT pattern, sum(c) AS h, sum(c * (c - 1)) AS s FROM (SELECT pattern, {keys}, count(*) AS c FROM tri GROUP BY pattern, {keys}) GROUP BY pattern) USING (pattern)"))
add("variance_by_family", lambda s, d: sampling.variance_by_family(linked(graph(s, d, _FEW)), 300).select("pattern", "triads", "sharing", F.round("alpha", 6).alias("alpha"), F.round("variance", 6).alias("variance")), O.triads_sql(_FEW, f"SELECT pattern, CAST(h AS BIGINT) AS triads, CAST(s AS BIGINT) AS sharing, round(al, 6) AS alpha, round(al * (h * (1 / dl - 1 / (dl * dl)) + s / (3 * dl) - h * (h - 1) / (dl * dl)), 6) AS variance FROM (SELECT p.pattern, CAST(coalesce(h, 0) AS DOUBLE) AS h, CAST(coalesce(s, 0) AS DOUBLE) AS s, CAST(CASE WHEN f IN ('TTT', 'TCC') THEN t ELSE c END AS DOUBLE) AS dl, 300.0 * CASE f WHEN 'TTT' THEN t * t WHEN 'CCC' THEN c * c ELSE t * c END / CAST((t + c) * (t + c) AS DOUBLE) AS al FROM (SELECT pattern, {O.FAMILY_CASE} AS f FROM {O.EVERY}) p LEFT JOIN (SELECT pattern, sum(n) AS h, sum(n * (n - 1)) AS s FROM (SELECT pattern, l, count(*) AS n FROM led GROUP BY pattern, l) GROUP BY pattern) USING (pattern), pools)", None, _STRATA))
_COST = """
near AS (SELECT x, count(*) FILTER (kind = 'T') AS nt, count(*) FILTER (kind = 'C') AS nc FROM (SELECT i AS x, kind FROM links UNION ALL SELECT j, kind FROM links) GROUP BY x),
later AS (SELECT i AS x, count(*) AS d, count(*) FILTER (kind = 'T') AS dt FROM links GROUP BY i),
sums AS (SELECT CAST(count(*) AS DOUBLE) AS n, CAST(count(*) FILTER (kind = 'T') AS DOUBLE) AS t, CAST(count(*) FILTER (kind = 'C') AS DOUBLE) AS c, CAST(sum(d * w) AS DOUBLE) AS u,
                CAST(coalesce(sum(dt * w) FILTER (kind = 'T'), 0) AS DOUBLE) AS a1, CAST(coalesce(sum(s.nc) FILTER (kind = 'C'), 0) AS DOUBLE) AS a2,
                CAST(coalesce(sum(f.nc) FILTER (kind = 'T'), 0) AS DOUBLE) AS a3, CAST(coalesce(sum(s.nt) FILTER (kind = 'C'), 0) AS DOUBLE) AS a4
         FROM links JOIN later ON later.x = i JOIN near f ON f.x = i JOIN near s ON s.x = CASE WHEN ni > nj THEN j ELSE i END)"""
add("sampled_cost", lambda s, d: sampling.sampled_cost(linked(graph(s, d, _FEW)), 300).withColumn("entries", F.round("entries", 6)), O.with_(_FEW, "SELECT 'uniform' AS method, round(u * 300 / n, 6) AS entries FROM sums UNION ALL SELECT 'stratified', round((t * a1 + c * a2 + c * a3 + t * a4) * 300 / (n * n), 6) FROM sums", O.LINKS_CTE, _COST))
add("replicated_edge", lambda s, d: sampling.replicate(lambda seed: sampling.sample_by_edge(hg, links, 80, seed), [1, 2, 3]).select("pattern", "runs", F.round("mean", 6).alias("mean")) if (hg := graph(s, d, _FEW)) and (links := linked(hg)) else None, O.triads_sql(_FEW, f"SELECT p.pattern, CAST(3 AS BIGINT) AS runs, round(coalesce(raw, 0) * (SELECT count(*) / CAST(least(count(*), 80) AS DOUBLE) FROM edges) / 3.0, 6) AS mean FROM {O.EVERY} p LEFT JOIN got USING (pattern)", None, *[f"pick{k} AS (SELECT e FROM edges ORDER BY md5(CAST(e AS VARCHAR) || ':{k}') LIMIT 80)" for k in (1, 2, 3)], "pick AS (SELECT * FROM pick1 UNION ALL SELECT * FROM pick2 UNION ALL SELECT * FROM pick3)", "got AS (SELECT pattern, count(*) AS raw FROM tri JOIN pick ON e = i GROUP BY pattern)"))
_ERR = "SELECT round(avg(CASE WHEN cnt > 0 THEN abs(cnt - est) / cnt END), 6) AS error, round(1 - avg(CASE WHEN cnt > 0 THEN abs(cnt - est) / cnt END), 6) AS accuracy FROM (SELECT c.cnt, coalesce(raw, 0) * {factor} AS est FROM counts c LEFT JOIN got USING (pattern))"


def _error(sampler: Callable[[DataFrame], DataFrame], builder: str = _FEW, sigma: float | None = None) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        if sigma:  # the large inputs: links and triads are taken by blocks
            hg = graph(s, d, builder, sigma)
            links, counts = LinksInBlocks(hg), stage(triads(hg, mode="count"))
        else:
            _, links, counts = counted(s, d, builder)
        return measures.mean_relative_error(counts, sampler(links)).select(F.round("error", 6).alias("error"), F.round("accuracy", 6).alias("accuracy"))

    return run


add("error_sample_link", _error(lambda x: sampling.sample_by_link(x, 300)), O.triads_sql(_FEW, _ERR.format(factor="(SELECT count(*) / CAST(least(count(*), 300) AS DOUBLE) FROM links)"), None, f"pick AS (SELECT i, j FROM links ORDER BY {_LINK_KEY} LIMIT 300)", "got AS (SELECT pattern, count(*) AS raw FROM tri JOIN pick USING (i, j) GROUP BY pattern)"))
add("error_sample_family", _error(lambda x: sampling.sample_by_family(x, 300)), O.triads_sql(_FEW, _ERR.format(factor="coalesce(factor, 0)"), None, _STRATA))

#: The four largest inputs of the sampling experiment, each an induced fifth of its edges, as the experiment has it.
for b in ("order_parts", "customer_nations", "user_day_keys", "bucket_users"):
    for alpha in (500, 5000):
        add(f"error_sample_link_{b}_{alpha}", _error(lambda x, a=alpha: sampling.sample_by_link(x, a), b, SIGMA), O.triads_sql(b, _ERR.format(factor=f"(SELECT count(*) / CAST(least(count(*), {alpha}) AS DOUBLE) FROM links)"), FIFTH, f"pick AS (SELECT i, j FROM links ORDER BY {_LINK_KEY} LIMIT {alpha})", "got AS (SELECT pattern, count(*) AS raw FROM tri JOIN pick USING (i, j) GROUP BY pattern)"))
        add(f"error_sample_family_{b}_{alpha}", _error(lambda x, a=alpha: sampling.sample_by_family(x, a), b, SIGMA), O.triads_sql(b, _ERR.format(factor="coalesce(factor, 0)"), FIFTH, _STRATA.replace("300", str(alpha))))

# --- workloads and helpers ------------------------------------------------------------------------------------------

COAUTHORS = [[1, 2, 3], [3, 4, 5], [2, 3, 4, 6], [2, 3, 4, 7], [4, 8, 9, 10]]
MAIL_HUB = [[1, 29, 41, 51, 62, 65, 97, 107, 133], [1, 51], [1, 133], [29, 97], [41, 97], [29, 65]]


def literal(lists: list[list[int]]) -> Query:
    from ..model import canonicalize

    return lambda s, d: triads(canonicalize(from_lists(s, lists)))


for name, lists in (("coauthors", COAUTHORS), ("mail_hub", MAIL_HUB)):
    O.BUILDER_SQL[name] = "SELECT * FROM (VALUES " + ", ".join(f"({k}, {v})" for k, m in enumerate(lists, 1) for v in m) + ") t(e, v)"
    add(f"case_{name}", literal(lists), O.enumerate_sql(name, tuple(PATTERN_TABLE)))
_HUBS = "SELECT e, count(*) AS cnt FROM (SELECT CASE greatest(ni, nj, nk) WHEN ni THEN i WHEN nj THEN j ELSE k END AS e FROM tri WHERE pattern = 5) GROUP BY e ORDER BY cnt DESC, e LIMIT 10"
add("hub_edges_p5_customer_nations", lambda s, d: measures.hub_edges(triads(graph(s, d, "customer_nations"), 5), 10), O.triads_sql("customer_nations", _HUBS))
add("hub_value_customer_nations", lambda s, d: R.hub_value(measures.hub_edges(triads(graph(s, d, "customer_nations"), 5), 10), read_table(s, d, "orders")).withColumn("value", F.col("value").cast("string")), O.triads_sql("customer_nations", f"SELECT h.e, h.cnt, CAST(CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) AS DECIMAL(18,2)) AS VARCHAR) AS value FROM ({_HUBS}) h LEFT JOIN orders ON o_custkey = h.e GROUP BY h.e, h.cnt"))
add("describe_nested_customers", lambda s, d: R.describe_triads(triads(graph(s, d, "customer_nations"), 4), read_table(s, d, "customer").select(F.col("c_custkey").alias("e"), F.col("c_name").alias("name"))).select("i", "j", "k", "name_i", "name_j", "name_k"), O.triads_sql("customer_nations", "SELECT i, j, k, a.c_name AS name_i, b.c_name AS name_j, c.c_name AS name_k FROM tri LEFT JOIN customer a ON a.c_custkey = i LEFT JOIN customer b ON b.c_custkey = j LEFT JOIN customer c ON c.c_custkey = k WHERE pattern = 4"))
add("regions_order_suppliers", lambda s, d: R.select_regions(triads(graph(s, d, "order_suppliers"))), O.triads_sql("order_suppliers", "SELECT i, j, k, ni - wij - wik + g AS only_i, nj - wij - wjk + g AS only_j, nk - wik - wjk + g AS only_k, wij - g AS only_ij, wjk - g AS only_jk, wik - g AS only_ik, g AS all_ijk FROM tri"))
_SIZE = "n BETWEEN 2 AND 3"
add("filtered_edges_order_suppliers", lambda s, d: triads(R.filter_edges(graph(s, d, "order_suppliers"), 2, 3), mode="count"), O.counts_sql("order_suppliers").replace("inc AS (SELECT e, n, unnest(m) AS v FROM edges)", f"inc AS (SELECT e, n, unnest(m) AS v FROM edges WHERE {_SIZE})"))
add("filtered_vertices_order_suppliers", lambda s, d: R.filter_vertices(graph(s, d, "order_suppliers"), 5), O.with_("order_suppliers", "SELECT e, v FROM inc WHERE v IN (SELECT v FROM inc GROUP BY v HAVING count(*) <= 5)"))
add("unlabelled_edges_doc_lines", lambda s, d: R.restrict_edges(graph(s, d, "doc_lines"), read_table(s, d, "labels").select(F.col("doc_id").alias("e")), "left_anti").edges.select("e", "n"), O.with_("doc_lines", "SELECT e, n FROM edges WHERE e NOT IN (SELECT doc_id FROM labels)"))
add("sizes_exact_order_parts", lambda s, d: R.size_preview(graph(s, d, "order_parts"), exact=True), O.with_("order_parts", "SELECT count(DISTINCT e) AS edges, count(DISTINCT v) AS vertices FROM inc"))
add("degree_stats_order_parts", lambda s, d: R.degree_stats(graph(s, d, "order_parts")), O.with_("order_parts", "SELECT count(*) AS edges, round(avg(n), 9) AS mean, round(stddev_samp(n), 9) AS deviation, min(n) AS least, max(n) AS most, (SELECT e FROM edges ORDER BY n DESC, e LIMIT 1) AS largest, round(quantile_cont(n, 0.5), 9) AS median, round(quantile_cont(n, 0.9), 9) AS p90 FROM edges"))
add("counts_rollup_order_suppliers", lambda s, d: _named(R.counts_rollup(counted(s, d, "order_suppliers")[2])), O.triads_sql("order_suppliers", f"SELECT coalesce(family, 'all') AS family, coalesce(CAST(pattern AS VARCHAR), 'all') AS pattern, CAST(sum(cnt) AS BIGINT) AS cnt, CAST(grouping(family, pattern) AS INTEGER) AS level FROM (SELECT *, {O.FAMILY_CASE} AS family FROM counts) GROUP BY ROLLUP (family, pattern)"))


def _named(df: DataFrame) -> DataFrame:
    """Group columns as words, with ``all`` where a grouping leaves one out."""
    return df.select(*[F.coalesce(F.col(c).cast("string"), F.lit("all")).alias(c) if c in ("slice", "family", "pattern") else F.col(c) for c in df.columns])


def _by_lang(s: SparkSession, d: str) -> DataFrame:
    """Counts of every language of the table, documents of null language being a slice of their own."""
    langs = [r["lang"] for r in read_table(s, d, "documents").select("lang").distinct().collect()]
    unknown = "null"
    while unknown in langs:
        unknown = f"({unknown})"
    parts = [stage(triads(canonicalize(lines_of_lang(s, d, g)), mode="count")).select(F.lit(unknown if g is None else g).alias("slice"), "pattern", "cnt") for g in langs]
    return stage(reduce(DataFrame.unionByName, parts, s.createDataFrame([], "slice string, pattern int, cnt long")))


def _lang_sql(body: str) -> str:
    parts = [f"SELECT '{g}' AS slice, pattern, cnt FROM ({O.counts_sql('doc_lines').replace('FROM documents', f'FROM documents WHERE lang = {chr(39)}{g}{chr(39)}')})" for g in ("de", "en", "es", "fr")]
    return f"WITH sliced AS ({' UNION ALL '.join(parts)}) {body}"


add("counts_cube_lang", lambda s, d: _named(R.counts_cube(_by_lang(s, d))), _lang_sql("SELECT coalesce(slice, 'all') AS slice, coalesce(CAST(pattern AS VARCHAR), 'all') AS pattern, CAST(sum(cnt) AS BIGINT) AS cnt, CAST(grouping(slice, pattern) AS INTEGER) AS level FROM sliced GROUP BY CUBE (slice, pattern)"))
add("counts_grouping_sets_lang", lambda s, d: _named(R.counts_grouping_sets(s, _by_lang(s, d))), _lang_sql("SELECT coalesce(slice, 'all') AS slice, coalesce(CAST(pattern AS VARCHAR), 'all') AS pattern, CAST(sum(cnt) AS BIGINT) AS cnt FROM sliced GROUP BY GROUPING SETS ((slice), (pattern))"))
add("profile_matrix_lang", lambda s, d: R.profile_matrix(_by_lang(s, d)), _lang_sql("SELECT slice, " + ", ".join(f"CAST(sum(cnt) FILTER (pattern = {p}) AS BIGINT) AS p{p}" for p in PATTERN_TABLE) + " FROM sliced GROUP BY slice"))
add("profile_unpivot_lang", lambda s, d: R.unpivoted(R.profile_matrix(_by_lang(s, d))), _lang_sql("SELECT slice, pattern, cnt FROM sliced"))


def _distance(s: SparkSession, d: str) -> DataFrame:
    a, b = counted(s, d, "customer_nations")[2], counted(s, d, "customer_brands")[2]
    return measures.profile_distance(a, b).select(F.round("l1", 9).alias("l1"), F.round("cosine", 9).alias("cosine"))


add("profile_distance_customers", _distance, f"WITH a AS ({O.counts_sql('customer_nations')}), b AS ({O.counts_sql('customer_brands')}), x AS (SELECT a.cnt / (SELECT CAST(sum(cnt) AS DOUBLE) FROM a) AS p, b.cnt / (SELECT CAST(sum(cnt) AS DOUBLE) FROM b) AS q FROM a JOIN b USING (pattern)) SELECT round(sum(abs(p - q)), 9) AS l1, round(sum(p * q) / sqrt(sum(p * p) * sum(q * q)), 9) AS cosine FROM x")
add("edge_ranks_order_suppliers", lambda s, d: measures.edge_ranks(measures.triads_per_edge(triads(graph(s, d, "order_suppliers")))).withColumn("share", F.round("share", 9)), O.triads_sql("order_suppliers", "SELECT e, pattern, cnt, ntile(4) OVER (PARTITION BY pattern ORDER BY cnt DESC, e) AS quarter, rank() OVER w AS rnk, dense_rank() OVER w AS dense, row_number() OVER (PARTITION BY pattern ORDER BY cnt DESC, e) AS pos, round(percent_rank() OVER w, 9) AS share FROM (SELECT e, pattern, count(*) AS cnt FROM (SELECT unnest([i, j, k]) AS e, pattern FROM tri) GROUP BY e, pattern) WINDOW w AS (PARTITION BY pattern ORDER BY cnt DESC)"))


def _daily_edges(s: SparkSession, d: str) -> DataFrame:
    """(day, e, members): hours of each day with their purchasers, no two of a day with equal ones."""
    ev = read_table(s, d, "events").where("event_type = 'purchase'")
    edges = ev.groupBy(F.to_date("ts").cast("string").alias("day"), F.hour("ts").alias("e")).agg(F.sort_array(F.collect_set("user_id")).alias("members"))
    return edges.groupBy("day", "members").agg(F.min("e").alias("e"))


def _daily(s: SparkSession, d: str) -> DataFrame:
    """Triads of each day's small hypergraph: edges are hours with their purchasers."""
    return families.triads_by_group(_daily_edges(s, d), "day")


_DAILY_SQL = f"""WITH hours AS (SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, hour(ts) AS h, list_sort(list(DISTINCT user_id)) AS m FROM events WHERE event_type = 'purchase' GROUP BY ALL),
ed AS (SELECT day, min(h) AS e, m FROM hours GROUP BY day, m), edges AS (SELECT day, e, CAST(len(m) AS INTEGER) AS n, m FROM ed), inc AS (SELECT day, e, n, unnest(m) AS v FROM edges),
links AS (SELECT a.day, a.e AS i, b.e AS j, any_value(a.n) AS ni, any_value(b.n) AS nj, CAST(count(*) AS INTEGER) AS w, list(a.v) AS s FROM inc a JOIN inc b ON a.day = b.day AND a.v = b.v AND a.e < b.e GROUP BY a.day, a.e, b.e),
{O.TRIADS_CTE.replace('SELECT a.i,', 'SELECT a.day, a.i,').replace('ON a.i = b.i AND', 'ON a.day = b.day AND a.i = b.i AND').replace('ON c.i = a.j', 'ON c.day = a.day AND c.i = a.j')},
daily AS (SELECT day, pattern, count(*) AS cnt FROM tri GROUP BY day, pattern)"""
add("triads_by_day", _daily, _DAILY_SQL + " SELECT day, pattern, cnt FROM daily")
add("counts_trend_by_day", lambda s, d: R.counts_trend(_daily(s, d)).withColumn("before", F.coalesce("before", F.lit(0))), _DAILY_SQL + " SELECT day, pattern, cnt, coalesce(lag(cnt) OVER (PARTITION BY pattern ORDER BY day), 0) AS before, CAST(sum(cnt) OVER (PARTITION BY pattern ORDER BY day ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running FROM daily")
add("shingles_benchmark", lambda s, d: R.shingles_of(read_table(s, d, "benchmark"), "item_id", "text").groupBy("item_id").agg(F.count(F.lit(1)).alias("shingles")), "WITH t AS (SELECT item_id, [x for x in regexp_split_to_array(lower(text), '[^a-z]+') if x <> ''] AS ws FROM benchmark) SELECT item_id, count(DISTINCT array_to_string(ws[i:i + 2], ' ')) AS shingles FROM (SELECT item_id, ws, unnest(generate_series(1, len(ws) - 2)) AS i FROM t WHERE len(ws) >= 3) GROUP BY item_id")
add("calendar_events", lambda s, d: read_table(s, d, "events").groupBy(*R.calendar_parts(F.col("ts"))).agg(F.count(F.lit(1)).alias("events")).withColumn("day", F.col("day").cast("string")), "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, CAST(hour(ts) AS INTEGER) AS hour, CAST(dayofweek(ts) + 1 AS INTEGER) AS weekday, count(*) AS events FROM events GROUP BY ALL")
add("common_edges_customers", lambda s, d: R.common_edges(graph(s, d, "purchase_hour_users"), graph(s, d, "bucket_users")).agg(F.count(F.lit(1)).alias("edges")), f"SELECT count(*) AS edges FROM (SELECT m FROM (WITH {O.edges_cte('purchase_hour_users')} SELECT m FROM edges) INTERSECT SELECT m FROM (WITH {O.edges_cte('bucket_users')} SELECT m FROM edges))")
add("same_triads_core", lambda s, d: R.same_triads(triads(hg := graph(s, d, "order_suppliers"), "core"), triads(hg, "core", core_strategy="grouped")), O.triads_sql("order_suppliers", "SELECT i, j, k, pattern, 'left' AS side FROM tri WHERE false"))


def _sql_view(s: SparkSession, d: str) -> DataFrame:
    hg, links, counts = counted(s, d, "order_suppliers")
    R.create_views(hg, links, triads(hg, links=links), counts)
    return s.sql("SELECT pattern, count(*) AS triads, CAST(max(wij + wik + wjk) AS INT) AS most FROM ht_triads GROUP BY pattern")


add("sql_view_triads", _sql_view, O.triads_sql("order_suppliers", "SELECT pattern, count(*) AS triads, max(wij + wik + wjk) AS most FROM tri GROUP BY pattern"))


def _sql_function(s: SparkSession, d: str) -> DataFrame:
    register_sql(s)
    hg = graph(s, d, "order_suppliers")
    m = lambda x: hg.edges.select(F.col("e").alias(x), F.col("members").alias(f"m{x}"))
    return triads(hg).select("i", "j", "k").join(m("i"), "i").join(m("j"), "j").join(m("k"), "k").select("i", "j", "k", F.expr("hyper_pattern(mi, mj, mk)").alias("pattern"))


add("sql_function_pattern", _sql_function, O.triads_sql("order_suppliers", "SELECT i, j, k, pattern FROM tri"))


def _table_function(s: SparkSession, d: str) -> DataFrame:
    """Triads of each day's small hypergraph of hours and their purchasers, from the table function; ids are hours."""
    udfs.register(s)
    _daily_edges(s, d).groupBy("day").agg(F.sort_array(F.collect_list(F.struct("e", "members"))).alias("edges")).createOrReplaceTempView("ht_days")
    at = lambda x: f"CAST(edges[t.{x}].e AS BIGINT) AS {x}"
    return s.sql(f"SELECT day, {at('i')}, {at('j')}, {at('k')}, t.pattern FROM ht_days, LATERAL hyper_triangles(transform(edges, x -> x.members)) t")


add("table_function_triads", _table_function, _DAILY_SQL + " SELECT day, i, j, k, pattern FROM tri")


def _frequency(s: SparkSession, d: str, b: str = "purchase_hour_users") -> DataFrame:
    c = stage(triads(graph(s, d, b), mode="count")).withColumn("family", family_of(F.col("pattern")))
    return c.groupBy("family").agg(F.sum("cnt").alias("cnt")).join(c.agg(F.sum("cnt").alias("total"))).select("family", "cnt", F.round(F.col("cnt") / F.col("total"), 9).alias("share"))


add("family_frequency_purchase_hour_users", _frequency, O.triads_sql("purchase_hour_users", f"SELECT {O.FAMILY_CASE} AS family, CAST(sum(cnt) AS BIGINT) AS cnt, round(sum(cnt) / (SELECT CAST(sum(cnt) AS DOUBLE) FROM counts), 9) AS share FROM counts GROUP BY 1"))
for b in EXACT:
    if b != "purchase_hour_users":
        add(f"family_frequency_{b}", lambda s, d, b=b: _frequency(s, d, b), O.triads_sql(b, f"SELECT {O.FAMILY_CASE} AS family, CAST(sum(cnt) AS BIGINT) AS cnt, round(sum(cnt) / (SELECT CAST(sum(cnt) AS DOUBLE) FROM counts), 9) AS share FROM counts GROUP BY 1"))


def _profile_of_width(s: SparkSession, d: str, minutes: int) -> DataFrame:
    return measures.coefficient_profile(*tallied(hypergraph(s, d, "bucket_users", minutes=minutes))).withColumns({"coefficient": F.round("coefficient", 9), "share": F.round("share", 9)})


for minutes in (10, 20, 30):
    name = f"bucket_users_{minutes}"
    O.BUILDER_SQL[name] = f"SELECT (epoch_us(ts) // {60_000_000 * minutes}) * {60 * minutes} AS e, user_id AS v FROM events"
    add(f"profile_{name}", lambda s, d, m=minutes: _profile_of_width(s, d, m), O.triads_sql(name, "SELECT pattern, cnt, round(CASE WHEN open <> 0 THEN 3.0 * cnt / CAST(open AS DOUBLE) END, 9) AS coefficient, round(CASE WHEN closed <> 0 THEN cnt / CAST(closed AS DOUBLE) END, 9) AS share FROM counts, open", None, O.OPEN_CTE))


#: The inputs of the runtime experiment; the exhaustive search and the core ones are left out on three dense ones, where each
#: takes minutes at sf0.01.
for b in workloads.SEVEN:
    without = ("baseline", "core_vertex", "core_grouped") if b in ("customer_nations", "customer_brands", "user_day_keys") else ()
    cases = {"baseline": "true", "nest_chain": "pattern = 1", "nest_chain_enumerated": "pattern = 1", "two_nests": "pattern BETWEEN 2 AND 5", "one_nest": "pattern BETWEEN 6 AND 8", "cross": "pattern >= 9", "core_vertex": "pattern BETWEEN 9 AND 16", "core_grouped": "pattern BETWEEN 9 AND 16", "coreless": "pattern >= 17", "all": "true"}
    sql = O.triads_sql(b, " UNION ALL ".join(f"SELECT '{m}' AS method, CAST(coalesce(sum(cnt) FILTER ({w}), 0) AS BIGINT) AS triads FROM counts" for m, w in cases.items() if m not in without))
    add(f"counts_by_method_{b}", lambda s, d, b=b, w=without: workloads.counts_by_method(s, d, b, w), None if b == "order_parts" else sql)
for b in ("user_day_types", "order_suppliers"):
    add(f"pattern_by_pattern_{b}", lambda s, d, b=b: workloads.pattern_by_pattern(s, d, b), O.counts_sql(b))
add("sampler_bias_user_day_types", lambda s, d: workloads.bias_of_samplers(s, d, "user_day_types", runs=4))
add("family_frequency_order_parts", lambda s, d: _frequency(s, d, "order_parts"))


def _case_documents(s: SparkSession, d: str) -> DataFrame:
    """Documents in triads of patterns 10 and 12 (as in the co-authorship case) with their attributes: by pattern and language."""
    at = blocks.triads_per_edge(graph(s, d, "doc_lines"), (10, 12)).withColumnRenamed("cnt", "n")
    lang = read_table(s, d, "documents").select(F.col("doc_id").alias("e"), "lang")
    return at.join(lang, "e").groupBy("pattern", "lang").agg(F.sum("n").alias("cnt"))


add("case_documents_p10_p12", _case_documents, O.triads_sql("doc_lines", "SELECT pattern, lang, count(*) AS cnt FROM (SELECT pattern, unnest([i, j, k]) AS e FROM tri WHERE pattern IN (10, 12)) t JOIN documents ON doc_id = e GROUP BY pattern, lang"))
add("edges_like_german", lambda s, d: R.edges_like(graph(s, d, "doc_lines"), read_table(s, d, "documents"), "doc_id", lang="de").edges.select("e", "n"), O.with_("doc_lines", "SELECT e, n FROM edges WHERE e IN (SELECT doc_id FROM documents WHERE lang = 'de')"))


def _regions_of_sets(s: SparkSession, d: str) -> DataFrame:
    hg = graph(s, d, "order_suppliers")
    m = lambda x: hg.edges.select(F.col("e").alias(x), F.col("members").alias(f"m{x}"))
    rows = triads(hg).select("i", "j", "k").join(m("i"), "i").join(m("j"), "j").join(m("k"), "k")
    return rows.select("i", "j", "k", *[F.array_join(F.sort_array(c).cast("array<string>"), ",").alias(n) for n, c in R.regions_of_sets(F.col("mi"), F.col("mj"), F.col("mk")).items()])


_SETS = {"only_a": ("a", "NOT b AND NOT c"), "only_b": ("b", "NOT a AND NOT c"), "only_c": ("c", "NOT a AND NOT b"), "only_ab": ("a AND b", "NOT c"), "only_bc": ("b AND c", "NOT a"), "only_ac": ("a AND c", "NOT b"), "all_abc": ("a AND b", "c")}
add("regions_of_sets_order_suppliers", _regions_of_sets, O.triads_sql("order_suppliers", "SELECT i, j, k, " + ", ".join(f"coalesce(string_agg(CAST(v AS VARCHAR), ',' ORDER BY v) FILTER ({x} AND {y}), '') AS {n}" for n, (x, y) in _SETS.items()) + " FROM (SELECT i, j, k, v, bool_or(e = i) AS a, bool_or(e = j) AS b, bool_or(e = k) AS c FROM (SELECT i, j, k, unnest([i, j, k]) AS e FROM tri) t JOIN inc USING (e) GROUP BY i, j, k, v) GROUP BY i, j, k"))


def _observed(s: SparkSession, d: str) -> DataFrame:
    """Work counters from an observation that rides on the count itself."""
    rows, watch = R.observed(triads(graph(s, d, "order_suppliers")))
    stage(rows.groupBy("pattern").agg(F.count(F.lit(1)).alias("cnt")))
    got = watch.get
    return s.createDataFrame([(k, int(got[k] or 0)) for k in ("rows", "CCC", "TCC", "TTC", "TTT")], "counter string, n long")


add("observed_order_suppliers", _observed, O.triads_sql("order_suppliers", f"SELECT 'rows' AS counter, CAST(coalesce(sum(cnt), 0) AS BIGINT) AS n FROM counts UNION ALL SELECT family, CAST(sum(cnt) AS BIGINT) FROM (SELECT {O.FAMILY_CASE} AS family, cnt FROM counts) GROUP BY family"))


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The flagship: counts of all 20 patterns on customers and the nations that supply them."""
    return triads(graph(spark, sf_dir, "customer_nations"), mode="count")
