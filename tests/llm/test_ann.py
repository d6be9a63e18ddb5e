import numpy as np
import pytest
from helpers import SMALL

from hypertriad.llm import ann


def brute(rows, every, k):
    able = [(i, np.array(x, float)) for i, x in rows]
    out = {}
    for q, v in able:
        if q % every == 0:
            d = sorted((float(np.sqrt(((x - v) ** 2).sum())), i) for i, x in able if i != q)
            out[q] = d[:k]
    return out


def test_recall_of_given_vectors(spark):
    df = spark.read.parquet(f"{SMALL}/embeddings.parquet")
    rows = [(r["vec_id"], r["embedding"]) for r in df.collect()]
    want = brute(rows, 100, 10)
    got = {}
    for r in ann.search(df).orderBy("query_id", "rank").collect():
        got.setdefault(r["query_id"], []).append((r["score"], r["vec_id"]))
    assert set(got) == set(want) and all(len(v) == 10 for v in got.values())
    hit = sum(len({i for _, i in got[q]} & {i for _, i in want[q]}) for q in want)
    assert hit / (10 * len(want)) >= 0.9
    x = dict(rows)
    for q, v in got.items():
        for s, i in v:
            assert s == float(np.sqrt(((np.array(x[i], float) - np.array(x[q], float)) ** 2).sum()))


def test_learned_partitions_route_clusters():
    r = np.random.default_rng(0)
    centres = r.standard_normal((12, 16)) * 4
    x = np.concatenate([c + r.standard_normal((150, 16)) for c in centres])
    near = ann.exact_neighbours(x, 10)
    part = ann.balanced_parts(x, near, 12)
    assert np.bincount(part).max() <= np.ceil(len(x) / 12 * 1.05)
    assert (part[near] == part[:, None]).mean() > 0.9
    net = ann.learn(x, near, part, 12)
    home = net.home(x)
    assert net.parts == 12 and (home[near] == home[:, None]).mean() > 0.9
    assert (home == net.home(x + 0.01)).mean() > 0.98


def recall_of(spark, x, k=10):
    """Share of the true neighbours found, share of the parts probed; every score is exact."""
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>").repartition(16)
    store = ann.Stored(spark)
    index = ann.build_index(store.put(ann.usable(df)), store, k)
    got = {}
    for r in ann.search(df, k).collect():
        got.setdefault(r["query_id"], {})[r["vec_id"]] = r["score"]
    hit = 0
    for q in range(0, len(x), 100):
        d = np.sqrt(((x - x[q]) ** 2).sum(axis=1))
        assert len(got[q]) == k and all(d[i] == s for i, s in got[q].items())
        d[q] = np.inf
        hit += len(set(np.argsort(d)[:k].tolist()) & set(got[q]))
    assert len(got) == -(-len(x) // 100)
    return hit / (k * len(got)), index


@pytest.mark.parametrize("n", [2_000, 50_000])
def test_routing_leaves_parts_out(spark, n):
    x = np.random.default_rng(n).standard_normal((n, 64))  # without any structure, the hardest case
    recall, index = recall_of(spark, x / np.linalg.norm(x, axis=1, keepdims=True))
    assert recall >= 0.9 and index.levels == 1
    assert index.probes <= index.parts * (0.5 if n == 50_000 else 0.55), (index.probes, index.parts)


def test_clusters_need_few_parts(spark):
    r = np.random.default_rng(4)
    x = r.standard_normal((300, 24))[r.integers(0, 300, 20_000)] * 3 + r.standard_normal((20_000, 24)) * 0.5
    recall, index = recall_of(spark, x)
    assert recall >= 0.9 and index.probes <= index.parts * 0.1, (recall, index.probes, index.parts)


def test_large_parts_are_cut_again(spark, monkeypatch):
    monkeypatch.setattr(ann, "SAMPLE", 600)
    monkeypatch.setattr(ann, "SPLIT_ROWS", 100)
    r = np.random.default_rng(5)
    x = r.standard_normal((100, 16))[r.integers(0, 100, 12_000)] * 2 + r.standard_normal((12_000, 16)) * 0.6
    recall, index = recall_of(spark, x)
    assert index.levels == 2 and recall >= 0.9 and index.probes < index.parts
    assert index.placed.count() == 12_000 and index.placed.select("leaf").distinct().count() > 3 * index.parts


def test_odd_vectors(spark):
    rows = [(0, [1.0, 0.0]), (100, [1.0, 0.0]), (3, [1.0, 0.0]), (3, [1.0, 0.0]), (1, None), (2, [0.0, 0.0]), (4, [float("nan"), 1.0]), (5, [None, 1.0]), (6, [float("inf"), 1.0]), (7, [1.0, 2.0, 3.0]), (8, []), (None, [1.0, 1.0]), (9, [2.0, 0.0])]
    df = spark.createDataFrame([(*r, 1, 1.0) for r in rows], "vec_id long, embedding array<float>, rank int, score double")
    got = sorted((r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in ann.search(df).collect())
    assert got == [(0, 1, 3, 0.0), (0, 2, 3, 0.0), (0, 3, 100, 0.0), (0, 4, 9, 1.0), (100, 1, 0, 0.0), (100, 2, 3, 0.0), (100, 3, 3, 0.0), (100, 4, 9, 1.0)]
    assert ann.search(df.where("false")).count() == 0


def test_many_copies_of_a_vector(spark):
    r = np.random.default_rng(2)
    rows = [(i, [1.0] * 8 if i % 3 == 0 else r.standard_normal(8).tolist()) for i in range(3000)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = {}
    for x in ann.search(df).orderBy("query_id", "rank").collect():
        got.setdefault(x["query_id"], []).append(x["vec_id"])
    assert got[300] == [0, 3, 6, 9, 12, 15, 18, 21, 24, 27]


def test_blocks_of_rows_and_queries_do_not_change_results(spark, monkeypatch):
    df = spark.read.parquet(f"{SMALL}/embeddings.parquet")
    want = sorted(ann.search(df, every=3).collect())
    monkeypatch.setattr(ann, "BLOCK_ROWS", 20)
    monkeypatch.setattr(ann, "QUERY_ROWS", 7)
    assert sorted(ann.search(df, every=3).collect()) == want


def test_repeated_query_rows(spark):
    rows = [(i, [float(i), 1.0]) for i in range(1, 40)] + [(100, [0.0, 1.0])] * 10 + [(200, [0.0, 1.0]), (200, [41.0, 1.0])]
    got = {}
    for r in ann.search(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), k=15).collect():
        got.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    assert sorted(got[100]) == [(1, 200, 0.0)] + [(k + 1, k, float(k)) for k in range(1, 15)]
    assert sorted(got[200]) == sorted([(k + 1, 100, 0.0) for k in range(10)] + [(k + 10, k, float(k)) for k in range(1, 6)] + [(k, 40 - k, float(k + 1)) for k in range(1, 16)])
