from itertools import combinations, product

import pytest
from pyspark.sql import functions as F

from hypertriad.functions.patterns import CORE, CORELESS, PATTERN_TABLE, members_of, pattern_of_sets, register_sql
from hypertriad.functions.udfs import pattern_of_python_sets, register

ORDERED = [6, 3, 3, 3, 3, 6, 6, 6, 1, 3, 3, 3, 1, 3, 3, 1, 1, 3, 3, 1]


def sets_of(mask):
    """Three sets with one vertex in each chosen region (i, j, k, ij, jk, ik, ijk)."""
    where = [(0,), (1,), (2,), (0, 1), (1, 2), (0, 2), (0, 1, 2)]
    out = [set(), set(), set()]
    for v, (on, at) in enumerate(zip(mask, where)):
        for s in at:
            if on:
                out[s].add(v)
    return out


def proper(a, b, c):
    return a & b and a & c and b & c and a != b and a != c and b != c


def test_all_region_masks_fall_into_twenty_classes():
    seen = [0] * 21
    for mask in product((0, 1), repeat=7):
        s = sets_of(mask)
        if proper(*s):
            p = pattern_of_python_sets(*s)
            assert p in PATTERN_TABLE
            seen[p] += 1
    assert seen[1:] == ORDERED and sum(seen) == 62


def test_families_partition_the_patterns():
    assert sorted(p for f in ("CCC", "TCC", "TTC", "TTT") for p in members_of(f)) == list(range(1, 21))
    assert CORE == tuple(range(9, 17)) and CORELESS == tuple(range(17, 21))


def test_expression_sql_and_arrow_functions_agree_with_sets(spark):
    rows = [tuple(sorted(x) for x in s) for s in map(sets_of, product((0, 1), repeat=7)) if proper(*s)]
    register_sql(spark)
    register(spark)
    df = spark.createDataFrame(rows, "a array<long>, b array<long>, c array<long>")
    got = df.select("a", "b", "c", pattern_of_sets(F.col("a"), F.col("b"), F.col("c")).alias("p"), F.expr("hyper_pattern(a, b, c)").alias("q"), F.expr("hyper_pattern_arrow(a, b, c)").alias("r")).collect()
    assert len(got) == 62
    for r in got:
        assert r["p"] == r["q"] == r["r"] == pattern_of_python_sets(set(r["a"]), set(r["b"]), set(r["c"]))


def test_disjoint_sets_have_no_pattern(spark):
    df = spark.createDataFrame([([1], [2], [1, 2])], "a array<long>, b array<long>, c array<long>")
    assert df.select(pattern_of_sets(F.col("a"), F.col("b"), F.col("c"))).first()[0] is None


@pytest.mark.parametrize("n", [3, 5])
def test_table_function(spark, n):
    register(spark)
    chain = ", ".join(f"array({', '.join(map(str, range(1, k + 1)))})" for k in range(1, n + 1))
    got = spark.sql(f"SELECT * FROM hyper_triangles(array({chain}))").collect()
    assert len(got) == len(list(combinations(range(n), 3))) and all(r["pattern"] == 1 for r in got)
