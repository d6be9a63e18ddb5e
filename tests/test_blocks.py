"""Counts by blocks against brute force over sets."""

import random
from itertools import combinations

import pytest
from test_whole import brute

from hypertriad.functions.patterns import PATTERN_TABLE
from hypertriad.model import canonicalize
from hypertriad.operators import blocks


def made(kind):
    r = random.Random(7)
    if kind == "dense":
        return [(e, v) for e in range(40) for v in r.sample(range(9), r.randint(1, 6))]
    if kind == "private":  # many edges that differ by private vertices only
        return [(e, v) for e in range(60) for v in [*r.sample(range(5), r.randint(0, 3)), *range(1000 + 10 * e, 1000 + 10 * e + r.randint(0, 2))]]
    if kind == "wide":  # edges of more than 64 vertices
        return [(e, v) for e in range(30) for v in r.sample(range(300), r.randint(60, 90))] + [(40, v) for v in range(300)]
    return [(e, str(v)) for e in range(90) for v in r.sample(range(400), r.randint(2, 12))]


@pytest.mark.parametrize("matrix", [8_000, 0])
@pytest.mark.parametrize("kind", ["dense", "private", "wide", "sparse"])
def test_census_is_brute_force(spark, monkeypatch, kind, matrix):
    import pyarrow as pa

    if not matrix:
        monkeypatch.setattr(blocks, "MATRIX", 0)
        monkeypatch.setattr(blocks, "BITS", 0)
    rows = made(kind)
    found, edges = brute(rows)
    hg = canonicalize(spark.createDataFrame(rows, f"e long, v {'string' if kind == 'sparse' else 'long'}"))
    types, members = blocks.edge_types(hg)
    # the blocks run here, so that the limits set above hold; what Spark deals is the same
    tables = [pa.Table.from_pandas(t) for _, t in blocks._dealt(types).toPandas().groupby("b")]
    got, per = {}, {}
    of = {}
    for r in members.collect():
        of.setdefault((tuple(r["codes"]), r["own"]), []).append(r["e"])
    names = {r["t"]: of[tuple(r["codes"]), r["own"]] for r in types.collect()}
    for t in tables:
        for r in blocks._census(t).to_pylist():
            got[r["key"]] = got.get(r["key"], 0) + r["cnt"]
        for r in blocks._per_edge(t, tuple(PATTERN_TABLE)).to_pylist():
            for e in names[r["t"]]:
                per[e, r["pattern"]] = per.get((e, r["pattern"]), 0) + r["cnt"]
    links = [(i, j) for i, j in combinations(sorted(edges), 2) if edges[i] & edges[j]]
    deg = {}
    for i, j in links:
        deg[i], deg[j] = deg.get(i, 0) + 1, deg.get(j, 0) + 1
    want = {str(p): len(x) for p, x in found.items()} | {"links": len(links), "overlaps": sum(len(edges[i] & edges[j]) for i, j in links), "two_hop": sum(d * (d - 1) // 2 for d in deg.values())}
    assert got == want
    each = {}
    for p, x in found.items():
        for t in x:
            for e in t:
                each[e, p] = each.get((e, p), 0) + 1
    assert per == each
    monkeypatch.setattr(blocks, "HELD", 50)  # others in slices
    assert blocks.link_figures(hg).first().asDict() == {k: want[k] for k in ("links", "overlaps", "two_hop")}
    assert matrix == 0 or {r["key"]: r["cnt"] for r in blocks.census(hg).collect()} == want


def test_census_of_nothing(spark):
    empty = canonicalize(spark.createDataFrame([], "e long, v long"))
    assert blocks.link_figures(empty).collect() == [(0, None, None)]
    assert blocks.census(empty).count() == 0 and blocks.triads_per_edge(empty, (10, 12)).count() == 0
