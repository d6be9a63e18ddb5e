import collections
import random
import time

import numpy as np
from helpers import SMALL
from pyspark.sql import functions as F

from hypertriad.llm import neardup as N
from hypertriad.llm.common import Stored
from hypertriad.llm.components import components


def brute(texts, weights, threshold=N.THRESHOLD):
    """class of each text by the weighted similarity of all pairs that share a shingle."""
    ids = N._WordIds()
    made = [N.shingles(t, ids) for t in texts]
    vec = [dict(zip(h.tolist(), weights.of(h, tf).astype(float).tolist())) for h, tf in made]
    parent = list(range(len(texts)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    shared = collections.defaultdict(list)
    for k, v in enumerate(vec):
        for s in v:
            shared[s].append(k)
    pairs = {(a, b) for ks in shared.values() for i, a in enumerate(ks) for b in ks[i + 1 :]}
    pairs |= {(a, b) for a in range(len(texts)) for b in range(a + 1, len(texts)) if texts[a] == texts[b] and texts[a] is not None}
    for a, b in pairs:
        both = sum(min(w, vec[b][s]) for s, w in vec[a].items() if s in vec[b])
        union = sum(vec[a].values()) + sum(vec[b].values()) - both
        if texts[a] == texts[b] or both / union >= threshold - 1e-9:
            parent[max(root(a), root(b))] = min(root(a), root(b))
    return [root(k) for k in range(len(texts))]


def test_classes_against_all_pairs(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    rows = docs.select("doc_id", "text").orderBy("doc_id").collect()
    weights = N.Weights(*N.frequency_sketch(docs))
    want = brute([r["text"] for r in rows], weights)
    got = {r["doc_id"]: r["class_id"] for r in N.classes(docs).collect()}
    assert got == {r["doc_id"]: rows[c]["doc_id"] for r, c in zip(rows, want)}


def test_large_group_of_edited_copies(spark):
    r = random.Random(3)
    words = [f"w{k}" for k in range(120)]
    texts = [" ".join(words)] * 40
    for _ in range(700):
        t = list(words)
        for _ in range(r.randint(0, 9)):
            t[r.randrange(120)] = f"x{r.randrange(10**6)}"
        texts.append(" ".join(t))
    texts += [f"quite other text number {k} with its own words {k * 7} {k * 11}" for k in range(60)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    want = brute(texts, N.Weights(*N.frequency_sketch(docs)))
    got = {x["doc_id"]: x["class_id"] for x in N.classes(docs).collect()}
    wrong = sum(got[k] != want[k] for k in got)
    assert wrong <= 2  # samples may miss a pair at the very threshold
    assert len({got[k] for k in range(40)}) == 1 and all(got[k] == k for k in range(740, 800))


def test_shingles_of_many_texts_at_once():
    r, ids, long = random.Random(5), N._WordIds(), "q" * (N.WINDOW - 2)
    texts = [" ".join(r.choice("abcdefg") * r.randint(1, 3) for _ in range(r.randint(0, 60))) for _ in range(300)]
    texts += ["", None, "...", " A-b ", "\u00c9 \u0391\u03a3 \u65e5\u672c", "\ud800 k", " " * (2 * N.WINDOW) + "k"]
    texts += [f"{a}{long + 'q' * k}{b}" for k in range(5) for a, b in (("", ""), ("x ", ""), ("", " y"), ("x ", " y"))]
    h, tf, lens = N.shingles_of(texts, ids)
    plain, once, all_ = N.shingles_of(texts, ids, distinct=False)
    ends, all_ends, seen = np.cumsum(lens), np.cumsum(all_), {}
    for text, a, b, c, d in zip(texts, ends - lens, ends, all_ends - all_, all_ends):
        words = N.plain_bytes(text or "").split()
        n = min(N.WORDS, len(words))
        want = [tuple(words[k : k + n]) for k in range(len(words) - n + 1) if n]
        assert [seen.setdefault(s, x) for s, x in zip(want, plain[c:d].tolist())] == plain[c:d].tolist() and len(want) == d - c
        count = collections.Counter(seen[s] for s in want)
        assert list(zip(h[a:b].tolist(), tf[a:b].tolist())) == sorted(count.items())
        one = N.shingles(text, ids)
        assert (one[0] == h[a:b]).all() and (one[1] == tf[a:b]).all()
    assert len(set(seen.values())) == len(seen) and (once == 1).all()
    assert [len(x) for x in N.shingles_of([], ids)] == [0, 0, 0]


def test_shingling_costs_less_than_a_call_for_each_word():
    r = random.Random(8)
    texts = [" ".join(f"w{r.randrange(30_000)}" for _ in range(400)) for _ in range(600)]
    ids, known = N._WordIds(), {f"w{k}".encode(): 2**63 + k for k in range(30_000)}

    def seconds(f):
        took = []
        for _ in range(3):
            start = time.process_time()
            f()
            took.append(time.process_time() - start)
        return min(took)

    calls = seconds(lambda: [np.fromiter(map(known.__getitem__, N.plain_bytes(t).split()), np.uint64) for t in texts])
    assert seconds(lambda: N.shingles_of(texts, ids)) < calls


def test_sketch_counts(spark):
    own = lambda k: " ".join(f"o{k}x{j}" for j in range(40))
    docs = spark.createDataFrame([(k, own(k) + " a b c d e" * (k % 2)) for k in range(200)], "doc_id long, text string")
    counts, n = N.frequency_sketch(docs)
    h, _ = N.shingles("a b c d e", N._WordIds())
    assert n == 200 and min(counts.ravel()[c][0] for c in N._cells(h)) == 100


def test_copies_count_as_about_one_document(spark):
    same = " ".join(f"s{j}" for j in range(200))
    edited = [" ".join(f"s{j}" if j != 3 * k % 200 else f"e{k}" for j in range(200)) for k in range(300)]
    docs = spark.createDataFrame(list(enumerate([same] * 500 + edited + [" ".join(f"t{k}x{j}" for j in range(9)) for k in range(100)])), "doc_id long, text string")
    counts, n = N.frequency_sketch(docs)
    h, _ = N.shingles("s100 s101 s102 s103 s104", N._WordIds())
    assert 100 <= n <= 106 and min(counts.ravel()[c][0] for c in N._cells(h)) <= 4
    weights = N.Weights(counts, n)
    assert weights.of(h, np.ones(1))[0] > 0.7


def test_common_shingles_weigh_little(spark):
    own = lambda k: " ".join(f"o{k}x{j}" for j in range(40))
    docs = spark.createDataFrame([(k, own(k) + " a b c d e") for k in range(1500)], "doc_id long, text string")
    weights, ids = N.Weights(*N.frequency_sketch(docs)), N._WordIds()
    of = lambda t: float(weights.of(N.shingles(t, ids)[0], np.ones(1))[0])
    assert of("a b c d e") < 0.01 and of("o7x0 o7x1 o7x2 o7x3 o7x4") > 0.95


def test_every_pair_verified_on_request(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "text")
    assert sorted(N.classes(docs, least_estimate=0).collect()) == sorted(N.classes(docs).collect())


def test_samples_estimate_weighted_similarity():
    r = np.random.default_rng(1)
    h = np.unique(r.integers(1, 2**63, 400, dtype=np.uint64))
    w = r.uniform(0.5, 3, len(h)).astype(np.float32)
    a, b = slice(0, 300), slice(60, 360)
    s = N.Sampler()
    same = []
    for shift in range(30):
        hh = np.sort(h ^ np.uint64(shift * 7919))
        x, y = s.samples(hh[a], w[a], np.array([0])), s.samples(hh[b], w[b], np.array([0]))
        same.append((x == y).mean())
    true = w[60:300].sum() / w[0:360].sum()
    assert abs(np.mean(same) - true) < 0.04


def test_components_of_paths_and_stars(spark):
    links = [(k, k + 1) for k in range(40)] + [(100, k) for k in range(101, 160)] + [(200, 201), (201, 200), (300, 300)]
    got = {r["node"]: r["comp"] for r in components(spark.createDataFrame(links, "u long, v long"), Stored(spark)).collect()}
    assert all(got[k] == 0 for k in range(41)) and all(got[k] == 100 for k in range(100, 160)) and got[201] == 200 and 300 not in got
    assert components(spark.createDataFrame([], "u long, v long"), Stored(spark)).count() == 0


def test_odd_documents(spark, odd_docs, no_docs):
    got = N.classes(odd_docs).collect()
    assert len(got) == odd_docs.count()
    by = collections.defaultdict(set)
    for r in got:
        by[r["doc_id"]].add(r["class_id"])
    assert by[5] == by[6] == {5} and by[0] == {0} and by[1] == {1} and by[2] == {2}
    kept = N.keep_one(odd_docs)
    assert kept.columns == odd_docs.columns
    assert sorted(str(r["doc_id"]) for r in kept.collect()) == sorted(["0", "1", "2", "3", "4", "5", "7", "8", "9", "10", "None"])
    assert N.classes(no_docs).count() == 0 and N.keep_one(no_docs).count() == 0


def test_pairs_across_components_in_blocks(spark, monkeypatch):
    monkeypatch.setattr(N, "BLOCK", 8)
    rows = [(0, 5, k, 0 if k < 30 else k) for k in range(50)]
    df = Stored(spark).put(spark.createDataFrame(rows, "band int, key long, node long, comp long"))
    dealt = N._block_pairs(df).collect()
    met = set()
    runs = collections.defaultdict(list)
    for r in dealt:
        runs[r["g"]].append(r)
    for run in runs.values():
        left, right = [r for r in run if r["side"] != 1], [r for r in run if r["side"] != 0]
        met |= {frozenset((a["node"], b["node"])) for a in left for b in right if a["node"] != b["node"]}
    want = {frozenset((a[2], b[2])) for a in rows for b in rows if a[3] != b[3]}
    assert want <= met
    pure = [r for run in runs.values() if all(r["comp"] == 0 for r in run) for r in run]
    assert not pure
    assert df.agg(F.count("*")).first()[0] == 50
