from itertools import combinations
from math import comb

import pytest
from helpers import TINY
from pyspark.sql import functions as F

from hypertriad.functions.relational import same_triads
from hypertriad.functions.udfs import pattern_of_python_sets
from hypertriad.model import canonicalize
from hypertriad.operators import baseline, families, measures
from hypertriad.operators.links import bruteforce_links, build_links, cross, load_links, nest, save_links
from hypertriad.plans.planner import explain_plan, patterns_of, plan_for, triads
from hypertriad.plans.registry import COAUTHORS, MAIL_HUB
from hypertriad.sources.builders import hypergraph
from hypertriad.sources.files import from_lists
from hypertriad.stages import stage

POWER_SET = {1: 390, 2: 195, 3: 180, 4: 195, 5: 180, 6: 360, 7: 360, 8: 120, 9: 60, 10: 60, 11: 60, 13: 60, 14: 60, 17: 65, 18: 180, 19: 60}
NATIONS = {1: 982, 2: 1311, 3: 1868, 4: 88, 5: 958, 6: 3610, 7: 935, 8: 4233, 9: 1922, 10: 3926, 11: 968, 12: 2423, 13: 24, 14: 436, 15: 983, 16: 394, 17: 62, 18: 1384, 19: 3725, 20: 1746}


def some(df):
    return {r["pattern"]: r["cnt"] for r in df.collect() if r["cnt"]}


def graph_of(spark, lists):
    return canonicalize(from_lists(spark, lists))


@pytest.fixture(scope="module")
def power(spark):
    hg = hypergraph(spark, TINY, "user_day_types")
    return hg, build_links(hg, with_shared=True).cache()


@pytest.fixture(scope="module")
def nations(spark):
    hg = hypergraph(spark, TINY, "customer_nations")
    return hg, build_links(hg, with_shared=True).cache()


def test_published_cases(spark):
    hg = graph_of(spark, COAUTHORS)
    links = build_links(hg, with_shared=True)
    counts = triads(hg, mode="count")
    assert some(counts) == {10: 5, 12: 2}
    got = measures.clustering_coefficient(links, counts).first()
    assert (got["closed"], got["open"], got["coefficient"]) == (7, 3, 7.0)
    assert links.count() == 9 and nest(links).count() == 0
    listed = {(r["i"], r["j"], r["k"]): r["pattern"] for r in triads(hg).collect()}
    assert listed[1, 2, 3] == 12 and listed[2, 3, 4] == 10 and listed[3, 4, 5] == 10

    hub = graph_of(spark, MAIL_HUB)
    counts = triads(hub, mode="count")
    assert some(counts) == {5: 3}
    got = measures.clustering_coefficient(build_links(hub), counts).first()
    assert got["open"] == 8 and got["coefficient"] == 9 / 8
    assert {(r["i"], r["j"], r["k"]) for r in triads(hub).collect()} == {(1, 2, 3), (1, 4, 5), (1, 4, 6)}


@pytest.mark.parametrize("n", [4, 6])
def test_chain_and_star(spark, n):
    chain = graph_of(spark, [list(range(1, k + 1)) for k in range(1, n + 1)])
    counts = triads(chain, mode="count")
    assert some(counts) == {1: comb(n, 3)}
    assert measures.clustering_coefficient(build_links(chain), counts).first()["coefficient"] is None
    star = graph_of(spark, [[0, x] for x in range(1, n + 1)])
    assert some(triads(star, mode="count")) == {9: comb(n, 3)}


@pytest.mark.parametrize(("lists", "edges", "links"), [([[1, 2], [2, 1], [1, 2, 2]], 1, 0), ([[1], [2]], 2, 0), ([[1]], 1, 0), ([], 0, 0)])
def test_degenerate_inputs(spark, lists, edges, links):
    hg = graph_of(spark, lists)
    assert hg.edges.count() == edges and build_links(hg).count() == links
    counts = triads(hg, mode="count")
    assert counts.count() == 20 and some(counts) == {}
    assert triads(hg).count() == 0


def test_rim(spark):
    assert some(triads(graph_of(spark, [[1, 2], [2, 3], [1, 3]]), mode="count")) == {17: 1}


def test_power_set_by_every_search(power):
    hg, links = power
    assert some(triads(hg, mode="count")) == POWER_SET
    assert some(measures.pattern_counts(families.unified_triads(links))) == POWER_SET
    assert some(measures.pattern_counts(baseline.baseline_triads(hg))) == POWER_SET
    assert families.nest_chain_count(links).first()["cnt"] == 390
    total = measures.open_triad_count(links, triads(hg, mode="count")).first()
    assert (total["closed"], total["open"]) == (2585, 1275)
    assert measures.open_triads(links).count() == 1275


def test_nations_by_every_search(nations):
    hg, links = nations
    whole = families.unified_triads(links).cache()
    assert some(measures.pattern_counts(whole)) == NATIONS
    assert same_triads(whole, triads(hg)).count() == 0
    assert same_triads(whole.where("pattern BETWEEN 9 AND 16"), families.core_triads(links)).count() == 0
    assert same_triads(whole.where("pattern BETWEEN 9 AND 16"), families.core_triads(links, strategy="grouped")).count() == 0
    assert same_triads(whole.where("pattern >= 17"), families.coreless_triads(links)).count() == 0
    assert same_triads(whole.where("pattern >= 9"), families.degree_led_triads(links)).count() == 0
    # what a test of containment, and no test of the closing link, would give instead
    assert families.core_triads(links, strategy="grouped").count() == 11_076 not in (11_811, 13_884)


def test_targeted_searches_add_up(power):
    hg, links = power
    whole = {(r["i"], r["j"], r["k"], r["pattern"]) for r in families.unified_triads(links).collect()}
    parts = [{(r["i"], r["j"], r["k"], r["pattern"]) for r in triads(hg, p, links=links).collect()} for p in range(1, 21)]
    assert set().union(*parts) == whole and sum(map(len, parts)) == len(whole)


def test_against_python_sets(spark):
    hg = hypergraph(spark, TINY, "order_suppliers")
    sets = {r["e"]: set(r["members"]) for r in hg.edges.collect()}
    want = {(a, b, c, p) for (a, x), (b, y), (c, z) in combinations(sorted(sets.items()), 3) if (p := pattern_of_python_sets(x, y, z))}
    assert {(r["i"], r["j"], r["k"], r["pattern"]) for r in triads(hg).collect()} == want


def test_link_strategies_agree(spark, nations):
    hg, links = nations
    want = {(r["i"], r["j"], r["w"], r["kind"]) for r in links.collect()}
    for strategy in ("join", "blocked", "array", "auto"):
        assert {(r["i"], r["j"], r["w"], r["kind"]) for r in build_links(hg, strategy=strategy, block=7).collect()} == want
    small = hypergraph(spark, TINY, "order_suppliers")
    assert {tuple(r) for r in bruteforce_links(small).collect()} == {(r["i"], r["j"], r["w"]) for r in build_links(small).collect()}


def test_hot_vertex_in_blocks(spark):
    hg = graph_of(spark, [[0, k] for k in range(1, 121)])
    got = build_links(hg, with_shared=True, strategy="blocked", block=10)
    assert got.count() == comb(120, 2) and got.select("i", "j").distinct().count() == comb(120, 2)


def test_stored_links_by_kind(spark, tmp_path, nations):
    _, links = nations
    save_links(links, str(tmp_path / "links"))
    back = load_links(spark, str(tmp_path / "links"))
    assert back.where("kind = 'C'").count() == nest(links).count() and cross(back).count() == cross(links).count()
    assert "PartitionFilters: [isnotnull(kind" in back.where("kind = 'C'")._jdf.queryExecution().toString()


def test_invariance(spark):
    lists = [[1, 2, 3], [2, 3], [3, 4, 5], [1, 5], [2, 5, 6], [1, 2, 3, 4]]
    want = some(triads(graph_of(spark, lists), mode="count"))
    assert some(triads(graph_of(spark, lists[::-1]), mode="count")) == want
    assert some(triads(graph_of(spark, [[10 - v for v in m] for m in lists] + [lists[0][::-1] and [10 - v for v in lists[0]]]), mode="count")) == want
    assert some(triads(graph_of(spark, lists), mode="count", parallelism=3, strategy="blocked")) == want


def test_removal_takes_an_edges_triads(spark):
    lists = [[1, 2, 3], [2, 3], [3, 4, 5], [1, 5], [2, 5, 6], [1, 2, 3, 4]]
    found = triads(graph_of(spark, lists))
    per = {r["e"]: r["t"] for r in measures.triads_per_edge(found).groupBy("e").agg(F.sum("cnt").alias("t")).collect()}
    assert sum(per.values()) == 3 * found.count()
    less = triads(graph_of(spark, lists[:-1])).count()
    assert less == found.count() - per.get(6, 0)


def test_planner():
    assert plan_for(1).link_kinds == ("C",) and not plan_for(1).need_shared
    assert plan_for("core").link_kinds == ("T",) and plan_for("core").need_shared
    assert plan_for([2, 7]).link_kinds == ("T", "C") and not plan_for([2, 7]).need_shared
    assert patterns_of("TTC") == (6, 7, 8)
    for bad in ("XYZ", [0], [21]):
        with pytest.raises(ValueError, match="unknown"):
            patterns_of(bad)


def test_explain(spark):
    text = explain_plan(graph_of(spark, COAUTHORS), 7)
    assert "TriadPlan(links=T+C, shared=False, one_nest=(7,)" in text and "Physical Plan" in text


def test_motifs(spark):
    hg = graph_of(spark, COAUTHORS)
    rows = baseline.baseline_motifs(hg).collect()
    assert sum(r["pattern"] == 0 for r in rows) == 3 and sum(r["pattern"] > 0 for r in rows) == 7
    assert baseline.baseline_motifs(hg, include_open=False).count() == 7


def test_triad_core(spark):
    hg = graph_of(spark, [[0, x] for x in range(1, 5)] + [[9, 10]])
    assert sorted(r["e"] for r in measures.triad_core(hg, 3, triads).collect()) == [1, 2, 3, 4]
    assert measures.triad_core(hg, 4, triads).count() == 0


def test_fused_and_led_by_degree(spark):
    hg = hypergraph(spark, TINY, "customer_brands")
    links = stage(build_links(hg, with_shared=True))
    want = {r["pattern"]: r["cnt"] for r in triads(hg, mode="count", links=links, fused=False, lead="id").collect()}
    for lead in ("id", "degree"):
        assert {r["pattern"]: r["cnt"] for r in triads(hg, mode="count", links=links, fused=True, lead=lead).collect()} == want
    assert sum(want.values()) > 0
