"""The exact methods inside blocks, against brute force over sets and against the searches by joins."""

import pyarrow as pa
import pytest
from pyspark.sql.group import GroupedData
from test_blocks import made
from test_whole import brute

from hypertriad.model import canonicalize
from hypertriad.operators import block_searches, blocks, sparse_searches
from hypertriad.operators.links import build_links
from hypertriad.plans import workloads
from hypertriad.plans.planner import triads
from hypertriad.plans.registry import QUERIES
from hypertriad.sources.builders import BUILDERS

OF = {"baseline": range(1, 21), "nest_chain": (1,), "nest_chain_enumerated": (1,), "two_nests": range(2, 6), "one_nest": range(6, 9), "cross": range(9, 21), "core_vertex": range(9, 17), "core_grouped": range(9, 17), "coreless": range(17, 21), "all": range(1, 21)}


@pytest.mark.parametrize("matrix", [8_000, 0])
@pytest.mark.parametrize("kind", ["dense", "private", "wide", "sparse"])
def test_each_method_is_brute_force(spark, monkeypatch, kind, matrix):
    if not matrix:
        monkeypatch.setattr(blocks, "MATRIX", 0)
        monkeypatch.setattr(blocks, "BITS", 0)
        monkeypatch.setattr(block_searches, "CELLS", 8)  # matrices in many pieces
    found, _ = brute(made(kind))
    hg = canonicalize(spark.createDataFrame(made(kind), f"e long, v {'string' if kind == 'sparse' else 'long'}"))
    got = {}
    for _, t in blocks._dealt(blocks.edge_types(hg)[0]).toPandas().groupby("b"):
        for r in block_searches._searched(pa.Table.from_pandas(t), tuple(OF)).to_pylist():
            got[r["method"], r["pattern"]] = got.get((r["method"], r["pattern"]), 0) + r["cnt"]
    assert got == {(m, p): len(found[p]) for m, among in OF.items() for p in among if p in found}
    if matrix:
        assert {(r["method"], r["pattern"]): r["cnt"] for r in block_searches.searched(hg).collect()} == got


def test_each_method_is_its_join(spark):
    hg = canonicalize(spark.createDataFrame(made("dense"), "e long, v long"))
    links = build_links(hg, with_shared=True)
    got = {(r["method"], r["pattern"]): r["cnt"] for r in block_searches.searched(hg).collect()}
    want = {(name, r["pattern"]): r["cnt"] for name, run in workloads.methods(hg, links).items() for r in run().collect() if r["cnt"]}
    assert got == want


@pytest.mark.parametrize("builder", ["bucket_users", "order_parts"])
def test_counts_by_method_write_no_links(spark, tmp_path, monkeypatch, builder):
    def never(*args, **kwargs):
        raise AssertionError("links or lead pairs are written")

    monkeypatch.setattr(workloads, "build_links", never)
    monkeypatch.setattr(workloads, "stage_links", never)
    lines = [(o, (o * k) % 11) for o in range(40) for k in range(1, 2 + o % 4)]
    spark.createDataFrame(lines, "l_orderkey long, l_partkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    seen = [(o, p, f"2024-01-01 {o // 6:02}:{10 * (o % 6):02}:00") for o, p in lines]
    spark.createDataFrame(seen, "event_id long, user_id long, ts string").selectExpr("event_id", "user_id", "timestamp(ts) AS ts").write.parquet(f"{tmp_path}/events.parquet")
    found, _ = brute(BUILDERS[builder](spark, str(tmp_path)).collect())
    want = {m: sum(len(found.get(p, ())) for p in among) for m, among in OF.items()}
    assert {r["method"]: r["triads"] for r in workloads.counts_by_method(spark, str(tmp_path), builder).collect()} == want and want["coreless"]


def test_no_triads_are_zero(spark, tmp_path):
    spark.createDataFrame([(1, 1), (2, 2)], "l_orderkey long, l_partkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    got = workloads.counts_by_method(spark, str(tmp_path), "order_parts")
    assert {r["method"]: r["triads"] for r in got.collect()} == dict.fromkeys(OF, 0)


@pytest.mark.parametrize("kinds", [0, 1 << 18])
@pytest.mark.parametrize("kind", ["dense", "wide", "sparse"])
def test_near_edges_in_small_pieces_are_brute_force(spark, monkeypatch, kind, kinds):
    for module, limits in ((blocks, {"MATRIX": 0, "BITS": 0, "HELD": 50, "NEAR": 9, "LEADS": 4}), (sparse_searches, {"PAIRS": 5, "MEETINGS": 40, "MARKS": 1_000, "MOST_PAIRS": 600, "MEMBERS": 5, "KINDS": kinds})):
        for name, value in limits.items():
            monkeypatch.setattr(module, name, value)
    rows = [(e, int(v)) for e, v in made(kind)]
    found, _ = brute(rows)
    dealt = blocks.dealt_near(canonicalize(spark.createDataFrame(rows, "e long, v long"))).toPandas()
    got, batched = {}, []
    search = sparse_searches.search
    monkeypatch.setattr(sparse_searches, "search", lambda block, *args: batched.append((block.lead.sum(), len(rest := search(block, *args)))) or rest)
    for _, t in dealt.groupby("b"):
        for r in block_searches._searched(pa.Table.from_pandas(t), tuple(OF)).to_pylist():
            got[r["method"], r["pattern"]] = got.get((r["method"], r["pattern"]), 0) + r["cnt"]
    assert got == {(m, p): len(found[p]) for m, among in OF.items() for p in among if p in found}
    assert any(rest for _, rest in batched) and (kind == "wide" or any(rest < leads for leads, rest in batched))  # both ways are taken


def test_copies_are_dealt_to_few_blocks(spark, monkeypatch):
    """Disjoint copies of edges share no block but by chance: what is dealt grows with the edges, not with edges times blocks."""
    one = sorted({(e, (e * k * k + e // 7 + k) % 20) for e in range(60) for k in range(1, 2 + e % 4)})
    found, edges = brute(one)
    copies = 40
    hg = canonicalize(spark.createDataFrame([(e + 100 * c, v + 20 * c) for c in range(copies) for e, v in one], "e long, v long"))
    monkeypatch.setattr(blocks, "MATRIX", 0)
    dealt, run = [], GroupedData.applyInArrow
    monkeypatch.setattr(GroupedData, "applyInArrow", lambda self, *args: dealt.append(self._df) or run(self, *args))
    got = {(r["method"], r["pattern"]): r["cnt"] for r in block_searches.searched(hg).collect()}
    assert got == {(m, p): copies * len(found[p]) for m, among in OF.items() for p in among if p in found}
    assert sum(df.count() for df in dealt) <= 4 * copies * len(edges)


def test_order_parts_takes_every_method(spark, tmp_path):
    lines = [(o, (o * k) % 11) for o in range(40) for k in range(1, 2 + o % 4)]
    spark.createDataFrame(lines, "l_orderkey long, l_partkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    found, _ = brute(lines)
    got = {r["method"]: r["triads"] for r in QUERIES["counts_by_method_order_parts"](spark, str(tmp_path)).collect()}
    assert got == {m: sum(len(found.get(p, ())) for p in among) for m, among in OF.items()}


def test_counts_of_sparse_edges_are_dealt_to_few_blocks(spark, monkeypatch):
    """Counts of all patterns deal near edges too: what is dealt grows with the edges, and no block repeats a member's list."""
    one = sorted({(e, (e * k * k + e // 7 + k) % 20) for e in range(60) for k in range(1, 2 + e % 4)})
    found, edges = brute(one)
    copies = 40
    hg = canonicalize(spark.createDataFrame([(e + 100 * c, v + 20 * c) for c in range(copies) for e, v in one], "e long, v long"))
    monkeypatch.setattr(blocks, "MATRIX", 0)
    monkeypatch.setattr(block_searches, "SPARSE", 1)
    dealt, run = [], GroupedData.applyInArrow
    monkeypatch.setattr(GroupedData, "applyInArrow", lambda self, *args: dealt.append(self._df) or run(self, *args))
    got = {r["pattern"]: r["cnt"] for r in triads(hg, mode="count").collect()}
    assert got == {p: copies * len(found.get(p, ())) for p in range(1, 21)}
    assert sum(df.count() for df in dealt) <= 4 * copies * len(edges)
    assert dict(dealt[0].dtypes)["codes"] == "array<int>"
    far = canonicalize(spark.createDataFrame([(e, v + 2**40) for e, v in one], "e long, v long"))
    assert {r["pattern"]: r["cnt"] for r in triads(far, mode="count").collect()} == {p: len(found.get(p, ())) for p in range(1, 21)}
