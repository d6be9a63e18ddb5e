import pytest
from helpers import TINY
from pyspark.sql import functions as F

from hypertriad.operators import measures, sampling
from hypertriad.operators.families import unified_triads
from hypertriad.operators.links import build_links
from hypertriad.plans.planner import triads
from hypertriad.sources.builders import hypergraph


@pytest.fixture(scope="module")
def few(spark):
    hg = hypergraph(spark, TINY, "order_suppliers")
    links = build_links(hg, with_shared=True).cache()
    return hg, links, {r["pattern"]: r["cnt"] for r in triads(hg, mode="count", links=links).collect()}


def est(df):
    return {r["pattern"]: round(r["est"], 6) for r in df.collect()}


def test_exhaustive_draws_are_exact(few):
    hg, links, exact = few
    n, e = links.count(), hg.edges.count()
    assert est(sampling.sample_by_link(links, n)) == exact
    assert est(sampling.sample_by_edge(hg, links, e)) == exact
    assert est(sampling.sample_by_family(links, 100 * n)) == exact
    v = hg.incidence.select("v").distinct().count()
    over = {r["pattern"]: r["expected"] for r in sampling.sampling_expectation(links, "vertex").collect()}
    assert est(sampling.sample_by_vertex(hg, links, v)) == over
    assert est(sampling.sample_by_vertex(hg, links, v, correct=True)) == exact
    assert sum(over.values()) > sum(exact.values())


def test_whole_subgraph_and_scales(few):
    hg, *_ = few
    assert sampling.induce(hg, 1.0).edges.count() == hg.edges.count()
    n = hg.edges.count()
    assert sampling.induce(hg, 0.2).edges.count() == -(-n // 5)
    assert sampling.scale_up(0.5) == 8
    assert sampling.scale_up(0.5, 10, 5) == 10 * 9 * 8 / (5 * 4 * 3)
    with pytest.raises(ValueError, match="unknown"):
        sampling.induce(hg, 0.2, how="other")


def test_draws_repeat_under_any_partitioning(few):
    _, links, _ = few
    a = sampling.draw(links.repartition(3), ["i", "j"], 20, 5).select("i", "j").collect()
    b = sampling.draw(links.repartition(11), ["i", "j"], 20, 5).select("i", "j").collect()
    assert sorted(a) == sorted(b)


def test_draws_with_replacement(few):
    _, links, exact = few
    got = sampling.draw(links, ["i", "j"], 200, 3, replacement=True)
    assert got.agg(F.sum("mult")).first()[0] == 200
    runs = sampling.replicate(lambda s: sampling.sample_by_link(links, 60, s, replacement=True), [1, 2, 3, 4]).collect()
    assert all(r["runs"] == 4 for r in runs)
    assert 0.5 < sum(r["mean"] for r in runs) / sum(exact.values()) < 1.6


def test_allocation():
    got = sampling.allocate(800, 200, 100)
    assert got == {"CCC": 4, "TCC": 16, "TTC": 16, "TTT": 64} and sum(got.values()) == 100
    assert sampling.allocate(10, 0, 100)["CCC"] == 0
    assert sampling.allocate(800, 2, 100)["CCC"] == 1
    assert sampling.allocate(800, 200, 100, families=("TTC",)) == {"TTC": 100}
    assert sum(sampling.allocate(800, 200, 100, "equal").values()) == 100


def test_estimates_are_unbiased_over_seeds(few):
    hg, links, exact = few
    n = hg.edges.count()
    got = sampling.replicate(lambda s: sampling.sample_by_edge(hg, links, n // 2, s), list(range(6))).collect()
    assert abs(sum(r["mean"] for r in got) / sum(exact.values()) - 1) < 0.5


def test_variance_reduces_to_uniform(few):
    _, links, _ = few
    a = {r["pattern"]: r for r in sampling.variance_uniform(links, "link", 100, links.count()).collect()}
    assert all(a[p]["variance"] is not None for p in a)
    loads = unified_triads(links).groupBy("pattern", "i", "j").count().groupBy("pattern").agg(F.sum(F.col("count") * (F.col("count") - 1)).alias("s"))
    for r in loads.collect():
        assert a[r["pattern"]]["sharing"] == r["s"]
    h, s, d = a[9]["triads"], a[9]["sharing"], links.count()
    exact = {r["pattern"]: r["variance"] for r in sampling.variance_uniform(links, "link", 100, d, "lead").collect()}
    assert exact[9] == pytest.approx(100 * ((h + s) / d - (h / d) ** 2))  # alpha times the variance of a lead's load


def test_error_of_estimates(spark):
    counts = spark.createDataFrame([(1, 10), (2, 0), (3, 4)], "pattern int, cnt long")
    estimates = spark.createDataFrame([(1, 5.0), (2, 1.0), (3, 4.0)], "pattern int, est double")
    assert measures.mean_relative_error(counts, estimates).first()["error"] == 0.25
    assert measures.mean_relative_error(counts, estimates).first()["accuracy"] == 0.75
    assert measures.mean_relative_error(counts, estimates, "strict").first()["error"] is None


def test_any_order_sampler_exhausts(few):
    _, links, exact = few
    got = est(sampling.sample_links_any_order(links, links.count()))
    opened = measures.open_triads(links).count()
    assert got.pop(0) == opened
    assert {p: v for p, v in got.items()} == exact


def test_least_keys_are_the_first_in_order(spark):
    pool = spark.range(5000).withColumnRenamed("id", "e").repartition(7)
    for size in (0, 1, 37, 4999, 5000, 9000):
        got = sorted(r["e"] for r in sampling.least_keys(pool, ["e"], size, 3).collect())
        want = sorted(r["e"] for r in pool.orderBy(sampling.draw_key(3, "e")).limit(size).collect())
        assert got == want
