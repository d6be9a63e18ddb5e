"""Queries over whole tables, against brute force on small ones."""

from itertools import combinations

from helpers import TINY
from pyspark.sql import functions as F

from hypertriad.functions.patterns import members_of
from hypertriad.functions.udfs import pattern_of_python_sets
from hypertriad.plans.registry import QUERIES
from hypertriad.sources.builders import BUILDERS


def brute(rows):
    """pattern -> [(i, j, k)] of all (e, v) rows."""
    sets = {}
    for e, v in rows:
        sets.setdefault(e, set()).add(v)
    least = {}
    for e in sorted(sets):
        least.setdefault(frozenset(sets[e]), e)
    edges, out = {e: m for m, e in least.items()}, {}
    for i, j, k in combinations(sorted(edges), 3):
        a, b, c = edges[i], edges[j], edges[k]
        if a & b and a & c and b & c:
            out.setdefault(pattern_of_python_sets(a, b, c), []).append((i, j, k))
    return out, edges


def counts(df):
    return {r["pattern"]: r["cnt"] for r in df.collect() if r["cnt"]}


def test_customers_are_all_read(spark):
    found, edges = brute(BUILDERS["customer_nations"](spark, TINY).collect())
    want = {p: len(x) for p, x in found.items()}
    for f in ("ccc", "tcc", "ttc", "ttt"):
        assert counts(QUERIES[f"counts_{f}_customer_nations"](spark, TINY)) == {p: n for p, n in want.items() if p in members_of(f.upper())}
    assert counts(QUERIES["unified_counts_customer_nations"](spark, TINY)) == want
    hubs = {}
    for t in found[5]:
        e = max(t, key=lambda x: len(edges[x]))
        hubs[e] = hubs.get(e, 0) + 1
    best = sorted(hubs.items(), key=lambda x: (-x[1], x[0]))[:10]
    assert sorted((r["e"], r["cnt"]) for r in QUERIES["hub_edges_p5_customer_nations"](spark, TINY).collect()) == sorted(best)
    assert sorted(tuple(r[c] for c in "ijk") for r in QUERIES["describe_nested_customers"](spark, TINY).collect()) == sorted(found[4])


def test_all_orders_are_read(spark, tmp_path):
    lines = spark.read.parquet(f"{TINY}/lineitem.parquet").where("l_orderkey <= 300").withColumn("l_partkey", F.col("l_partkey") % 40)
    lines.write.parquet(f"{tmp_path}/lineitem.parquet")
    found, _ = brute(BUILDERS["order_parts"](spark, str(tmp_path)).collect())
    got = counts(QUERIES["counts_all_order_parts"](spark, str(tmp_path)))
    assert got == {p: len(x) for p, x in found.items()} and sum(got.values()) > 0


def test_every_language_is_a_slice(spark, tmp_path):
    texts = ["a\nb", "b\nc", "a\nb\nc", "c\nd"]
    rows = [(10 * k + n, x, lang) for k, lang in enumerate(("en", "xx", None)) for n, x in enumerate(texts[: 2 + k])]
    spark.createDataFrame(rows, "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    want = {"en": {}}
    for lang, k in (("xx", 1), ("null", 2)):
        want[lang] = {p: len(x) for p, x in brute([(e, v) for e, text, _ in rows if e // 10 == k for v in text.split("\n")])[0].items()}
    got = {}
    for r in QUERIES["profile_unpivot_lang"](spark, str(tmp_path)).collect():
        got.setdefault(r["slice"], {}).update({r["pattern"]: r["cnt"]} if r["cnt"] else {})
    assert got == want and want["xx"] and want["null"]
    whole = [r["cnt"] for r in QUERIES["counts_cube_lang"](spark, str(tmp_path)).collect() if r["slice"] == r["pattern"] == "all"]
    assert whole == [sum(sum(x.values()) for x in want.values())]
    assert {r["slice"] for r in QUERIES["counts_grouping_sets_lang"](spark, str(tmp_path)).collect()} == {"en", "xx", "null", "all"}


def test_windows_pass_full_hours_and_midnight(spark, tmp_path):
    rows = [
        (1, "click", 7, "2024-01-01 10:59:00"), (2, "purchase", 1, "2024-01-01 11:01:00"), (3, "click", 8, "2024-01-01 11:02:00"), (4, "purchase", 2, "2024-01-01 11:02:00"),
        (5, "view", 9, "2024-01-01 23:00:00"), (6, "purchase", 3, "2024-01-01 23:50:00"), (7, "purchase", 4, "2024-01-02 00:50:00"), (8, "purchase", 5, "2024-01-02 00:51:00"),
        (9, "click", None, "2024-01-02 00:10:00"), (10, "purchase", 6, "2024-01-01 09:00:00"),
    ]
    df = spark.createDataFrame(rows, "event_id long, event_type string, user_id long, ts string").withColumn("ts", F.col("ts").cast("timestamp"))
    df.write.parquet(f"{tmp_path}/events.parquet")
    assert sorted(map(tuple, BUILDERS["latest_clickers"](spark, str(tmp_path)).collect())) == [(1, 7), (2, 8), (3, 8), (4, 8), (5, 8)]
    assert sorted(map(tuple, BUILDERS["rolling_users"](spark, str(tmp_path)).collect())) == [(2, 1), (4, 1), (4, 2), (6, 3), (7, 3), (7, 4), (8, 4), (8, 5), (10, 6)]


def test_workloads_are_registered():
    from hypertriad.plans.registry import EXACT
    from hypertriad.plans.workloads import SEVEN

    assert {f"space_{b}" for b in SEVEN} | {f"family_frequency_{b}" for b in EXACT} | {f"profile_bucket_users_{m}" for m in (10, 20, 30)} <= set(QUERIES)
