import pytest
from helpers import TINY

from hypertriad.functions import relational as R
from hypertriad.operators.families import triads_by_group
from hypertriad.model import canonicalize, dictionary_encode, edge_sizes, vertex_degrees
from hypertriad.plans.planner import triads
from hypertriad.sources import files
from hypertriad.sources.builders import BUILDERS, hypergraph, read_table


def test_edge_lines_round_trip(spark, tmp_path):
    hg = canonicalize(files.from_lists(spark, [[1, 2], [2, 3, 4], [1, 4]]))
    files.write_edge_lines(hg.edges, str(tmp_path / "lines"))
    back = canonicalize(files.read_edge_lines(spark, str(tmp_path / "lines")))
    assert sorted(r["members"] for r in back.edges.collect()) == sorted(r["members"] for r in hg.edges.collect())


@pytest.mark.parametrize("fmt", ["csv", "json", "orc", "parquet"])
def test_incidence_formats(spark, tmp_path, fmt):
    inc = files.from_lists(spark, [[1, 2], [2, 3]])
    files.write_rows(inc, str(tmp_path / fmt), fmt)
    assert sorted(files.read_incidence(spark, str(tmp_path / fmt), fmt).collect()) == sorted(inc.collect())
    files.write_rows(inc, None, "noop")


def test_nulls_and_repeats_go(spark):
    df = spark.createDataFrame([(1, 1), (1, 1), (1, None), (None, 2), (2, 1)], "e long, v long")
    hg = canonicalize(df.dropna().distinct())
    assert [tuple(r) for r in hg.edges.select("e", "n").collect()] == [(1, 1)]


def test_builders_give_rows(spark):
    for name in BUILDERS:
        hg = hypergraph(spark, TINY, name)
        assert hg.edges.count() > 0, name
        assert hg.edges.select("members").distinct().count() == hg.edges.count(), name
    with pytest.raises(ValueError, match="unknown table"):
        read_table(spark, TINY, "nothing")


def test_filters_reach_the_scan(spark):
    plan = BUILDERS["order_suppliers"](spark, TINY)._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(l_returnflag)" in plan and "ReadSchema: struct<l_orderkey:bigint,l_suppkey:bigint,l_returnflag:string,l_shipdate" in plan


def test_helpers(spark):
    hg = canonicalize(files.from_lists(spark, [[1, 2], [2, 3, 4], [1, 4]]))
    assert {r["e"]: r["n"] for r in edge_sizes(hg).collect()} == {1: 2, 2: 3, 3: 2}
    assert {r["v"]: r["d"] for r in vertex_degrees(hg).collect()} == {1: 2, 2: 2, 3: 1, 4: 2}
    assert R.filter_edges(hg, 3).edges.count() == 1
    assert R.restrict_edges(hg, spark.createDataFrame([(1,)], "e long"), "left_anti").edges.count() == 2
    coded = dictionary_encode(spark.createDataFrame([("b",), ("a",), (None,), ("b",)], "x string"), "x", "c").collect()
    assert sorted((r["x"] or "", r["c"]) for r in coded if r["x"]) == [("a", 0), ("b", 1), ("b", 1)]
    assert sum(r["c"] is None for r in coded) == 1
    two = R.shingles_of(spark.createDataFrame([(1, "A b, c d"), (2, "x y")], "k long, t string"), "k", "t").collect()
    assert sorted(r["shingle"] for r in two) == ["a b c", "b c d"]
    assert [r["dim"] for r in R.top_dims(spark.createDataFrame([(1, [1.0, 3.0, 3.0])], "k long, v array<double>"), "k", "v", 2).collect()] == [1, 2]


def test_approximate_sizes(spark):
    hg = hypergraph(spark, TINY, "order_parts")
    near, exact = R.size_preview(hg).first(), R.size_preview(hg, exact=True).first()
    assert abs(near["edges"] / exact["edges"] - 1) < 0.15 and exact["vertices"] == 200


def test_groups_of_small_hypergraphs(spark):
    rows = [("a", 1, [1, 2]), ("a", 2, [2, 3]), ("a", 3, [1, 3]), ("b", 1, [1]), ("b", 2, [1, 2]), ("b", 3, [1, 2, 3])]
    got = triads_by_group(spark.createDataFrame(rows, "g string, e long, members array<long>"), "g").collect()
    assert sorted(tuple(r) for r in got) == [("a", 17, 1), ("b", 1, 1)]


def test_views(spark):
    hg = canonicalize(files.from_lists(spark, [[1, 2], [2, 3], [1, 3]]))
    from hypertriad.operators.links import build_links

    found = triads(hg)
    R.create_views(hg, build_links(hg), found, found.groupBy("pattern").count())
    assert spark.sql("SELECT pattern FROM ht_triads").first()[0] == 17
    named = R.describe_triads(found, spark.createDataFrame([(1, "one"), (2, "two")], "e long, name string")).first()
    assert (named["name_i"], named["name_j"], named["name_k"]) == ("one", "two", None)
