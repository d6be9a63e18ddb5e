import pytest
from helpers import TINY

from hypertriad.operators import measures
from hypertriad.operators.links import build_links
from hypertriad.plans import workloads
from hypertriad.plans.planner import triads
from hypertriad.sources.builders import hypergraph


@pytest.fixture(scope="module")
def few(spark):
    hg = hypergraph(spark, TINY, "order_suppliers")
    links = build_links(hg, with_shared=True).cache()
    return hg, links, triads(hg, mode="count", links=links).cache()


def test_identities(few):
    _, links, counts = few
    got = measures.clustering_coefficient(links, counts).first()
    assert got["open"] == measures.open_triads(links).count()
    assert measures.weighted_coefficient(links, counts, {}).first()["coefficient"] == pytest.approx(got["coefficient"])
    profile = measures.coefficient_profile(links, counts).collect()
    assert sum(r["coefficient"] for r in profile) == pytest.approx(got["coefficient"])
    assert sum(r["share"] for r in profile) == pytest.approx(1)
    assert measures.profile_distance(counts, counts).first()["l1"] == 0


def test_weights_are_checked(few):
    _, links, counts = few
    for bad in ({1: 2.0}, {21: 0.5}, {3: -0.1}):
        with pytest.raises(ValueError, match="weight"):
            measures.weighted_coefficient(links, counts, bad)


def test_space_and_work(few):
    hg, links, counts = few
    space = measures.space_model(hg, links).first()
    assert space["baseline_one_hop"] < space["baseline_two_hop"] and space["proposed"] > 0
    work = measures.work_counters(links, counts).first()
    assert work["nest_links"] + work["cross_links"] == work["links"] and work["closed"] <= work["lead_pairs"]


def test_workloads(spark):
    got = {r["method"]: r["seconds"] for r in workloads.exact_runtimes(spark, TINY, "user_day_types").collect()}
    assert {"baseline", "nest_chain", "two_nests", "one_nest", "cross", "core_vertex", "core_grouped", "coreless", "all"} <= set(got)
    errors = workloads.error_by_time(spark, TINY, "user_day_types", 1.0, (0.5,)).collect()
    assert len(errors) == 2 and all(r["error"] >= 0 for r in errors)
    each = {r["pattern"]: r["cnt"] for r in workloads.pattern_by_pattern(spark, TINY, "user_day_types").collect()}
    assert sum(each.values()) == 2585
