"""Samples taken from links in blocks are those taken from a table of links, and no such table is made."""

import pytest
from helpers import TINY, duck, rows_of_duck, rows_of_spark
from test_blocks import made

from hypertriad.model import canonicalize
from hypertriad.operators import block_samples, block_searches, blocks, sampling
from hypertriad.operators.links import build_links
from hypertriad.plans import registry


@pytest.mark.parametrize("kind", ["dense", "sparse"])
def test_samples_are_those_of_the_links(spark, monkeypatch, kind):
    for name, value in {"HELD": 50, "NEAR": 9, "LEADS": 4}.items():
        monkeypatch.setattr(blocks, name, value)  # several blocks
    rows = made(kind)
    hg = canonicalize(spark.createDataFrame(rows, f"e long, v {'string' if kind == 'sparse' else 'long'}"))
    links, inside = build_links(hg, with_shared=True).cache(), block_samples.LinksInBlocks(hg)
    got = lambda df: sorted((r["pattern"], r["raw"], round(r["est"], 6)) for r in df.collect())
    for alpha, seed in ((9, 0), (40, 3), (10**6, 0)):
        assert got(sampling.sample_by_link(inside, alpha, seed)) == got(sampling.sample_by_link(links, alpha, seed))
        assert got(sampling.sample_by_family(inside, alpha, seed)) == got(sampling.sample_by_family(links, alpha, seed))


@pytest.mark.parametrize("query", ["error_sample_link_customer_nations_500", "error_sample_family_customer_nations_500", "error_sample_link_customer_nations_5000", "error_sample_family_user_day_keys_5000"])
def test_errors_of_large_inputs_write_no_links(spark, monkeypatch, query):
    def never(*args, **kwargs):
        raise AssertionError("links are written")

    monkeypatch.setattr(registry, "build_links", never)
    monkeypatch.setattr(registry, "stage_links", never)
    assert rows_of_spark(registry.QUERIES[query](spark, TINY)) == rows_of_duck(duck(TINY), registry.ORACLES[query])


def test_dense_blocks_are_compared_as_matrices(spark, monkeypatch):
    for name, value in {"MATRIX": 0, "BITS": 0}.items():
        monkeypatch.setattr(blocks, name, value)
    monkeypatch.setattr(block_searches, "SPARSE", 0)
    hg = canonicalize(spark.createDataFrame(made("dense"), "e long, v long"))
    counts = []
    for share in (-1.0, 2.0):
        monkeypatch.setattr(block_searches, "DENSE", share)
        counts.append(sorted(map(tuple, block_searches.counted(hg).collect())))
    assert counts[0] == counts[1] == sorted((int(r["key"]), r["cnt"]) for r in blocks.census(hg).collect() if r["key"].isdigit())
