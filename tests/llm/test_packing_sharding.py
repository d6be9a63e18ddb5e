import math
import random
import zlib

import pytest
from helpers import SMALL, TINY
from pyspark.sql import functions as F

from hypertriad.llm import packing, sharding
from hypertriad.llm.common import Stored, gapless, row_uid


def check_sequences(rows, capacity):
    at = {}
    for r in sorted(rows, key=lambda r: (r["sequence_id"], r["offset"])):
        assert r["offset"] == at.get(r["sequence_id"], 0)
        at[r["sequence_id"]] = r["offset"] + r["length"]
    assert max(at.values(), default=0) <= capacity
    return len(at)


def test_pieces_follow_the_published_tokenizer(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    t.encode_special_tokens = True
    docs = spark.read.parquet(f"{TINY}/documents.parquet")
    texts = {r["doc_id"]: r["text"] for r in docs.collect()} | {-1: "<|endoftext|> special   \x00 text", -2: None}
    odd = spark.createDataFrame([(k, texts[k]) for k in (-1, -2)], "doc_id long, text string")
    got = packing.pack(docs.select("doc_id", "text").unionByName(odd)).collect()
    by = {}
    for r in sorted(got, key=lambda r: r["piece"]):
        assert r["start"] == len(by.setdefault(r["doc_id"], [])) and r["length"] == len(r["ids"])
        assert zlib.crc32(packing.ids_bytes(r["ids"])) == r["ids_crc32"]
        assert r["length"] == 1024 or r["piece"] == 0
        by[r["doc_id"]] += r["ids"]
    for k, text in texts.items():
        assert by[k] == [*t.encode(text or "", add_special_tokens=False).ids, packing.END_ID]
    n = check_sequences(got, 1024)
    total = sum(r["length"] for r in got)
    assert n <= -(-total // 1024) + 2
    joined = packing.sequences(spark.createDataFrame(got)).collect()
    assert len(joined) == n and all(len(r["ids"]) <= 1024 for r in joined)


@pytest.mark.parametrize("seed", range(6))
def test_plan_places_every_item(seed):
    r = random.Random(seed)
    capacity = r.choice((10, 64, 1024))
    counts = {}
    for _ in range(r.randint(1, 400)):
        n = r.randint(1, capacity)
        counts[n] = counts.get(n, 0) + r.randint(1, 9)
    plan = packing.Plan(counts, capacity)
    rows = []
    import numpy as np

    for n, c in counts.items():
        seq, off = plan.place(np.full(c, n), np.arange(c))
        rows += [{"sequence_id": int(s), "offset": int(o), "length": n} for s, o in zip(seq, off)]
    bins = check_sequences(rows, capacity)
    assert bins == plan.sequences
    # one-by-one best fit on the same items, as a yardstick
    gaps = []
    for n in sorted((n for n, c in counts.items() for _ in range(c)), reverse=True):
        fit = min((g for g in gaps if g >= n), default=None)
        if fit is None:
            gaps.append(capacity - n)
        else:
            gaps.remove(fit)
            gaps.append(fit - n)
    assert bins <= len(gaps)


def test_large_items_pair_at_most_twice():
    plan = packing.Plan({400: 3, 500: 2, 700: 1, 342: 4}, 1024)
    assert all(sum(3 * x > 1024 for x in items) <= 2 for _, items in plan.groups)


def test_packing_odd_and_empty(odd_docs, no_docs):
    rows = packing.pack(odd_docs, keep_ids=False).collect()
    assert sum(r["length"] == 1 and r["doc_id"] in (0, 1) for r in rows) == 2
    assert sum(r["doc_id"] == 5 for r in rows) == 2
    check_sequences(rows, 1024)
    assert packing.pack(no_docs).count() == 0


def test_shards_of_documents(spark):
    docs = spark.read.parquet(f"{TINY}/documents.parquet")
    rows = sharding.shard_documents(docs, 7).collect()
    texts = {r["doc_id"]: r["text"].encode() for r in docs.collect()}
    total, slots = {}, {}
    for r in rows:
        assert r["size"] == len(texts[r["doc_id"]]) + 16 and r["text_crc32"] == zlib.crc32(texts[r["doc_id"]]) and r["law"] == "bytes" and r["grown_shard"] is None
        total[r["shard"]] = total.get(r["shard"], 0) + r["size"]
        slots.setdefault(r["shard"], set()).add(r["slot"])
    assert set(total) == set(range(7)) and len(rows) == len(texts)
    assert all(s == set(range(len(s))) for s in slots.values())
    mean = sum(total.values()) / 7
    assert max(abs(t - mean) for t in total.values()) <= 3 * max(map(len, texts.values()))


def test_shards_are_native(spark):
    docs = spark.read.parquet(f"{TINY}/documents.parquet")
    plan = sharding.shard_documents(docs, 4)._jdf.queryExecution().toString()
    assert not any(w in plan for w in ("Python", "Pandas", "Arrow"))


def test_splits_go_along_the_widest_dimension(spark):
    df = spark.range(1000).select("id", (F.col("id") % 10).alias("a"), F.lit(1).alias("b"))
    got = sharding.kd_tree_shards(df, {"a": F.col("a"), "b": F.col("b")}, F.lit(1), 2, F.col("id").cast("string"), keep={"a": F.col("a")})
    ends = got.groupBy("shard").agg(F.min("a"), F.max("a"), F.count("*")).orderBy("shard").collect()
    assert [tuple(r)[1:] for r in ends] == [(0, 4, 500), (5, 9, 500)]


def brute_kd(points, weights, shards):
    """Shard of each point by exact weighted medians along the widest dimension; no two positions of a dimension are equal."""
    lo, hi = [min(x) for x in zip(*points)], [max(x) for x in zip(*points)]
    at = [[min(math.floor((v - a) / (b - a) * 2.0**20), 2**20 - 1) for v, a, b in zip(p, lo, hi)] for p in points]
    out = {}

    def split(some, leaves, first):
        if leaves == 1:
            return out.update(dict.fromkeys(some, first))
        spans = [max(at[i][k] for i in some) - min(at[i][k] for i in some) for k in range(len(lo))]
        dim = spans.index(max(spans))
        some = sorted(some, key=lambda i: at[i][dim])
        want, total, n = sum(weights[i] for i in some) * (leaves // 2) / leaves, 0, 0
        while total + weights[some[n]] < want:
            total += weights[some[n]]
            n += 1
        n += total + weights[some[n]] - want < want - total
        split(some[:n], leaves // 2, first)
        split(some[n:], leaves - leaves // 2, first + leaves // 2)

    split(list(range(len(points))), shards, 0)
    return out


def test_tree_against_exact_medians(spark):
    r = random.Random(8)
    xs, ys = r.sample(range(1, 4000), 1500), r.sample(range(1, 9000), 1500)
    rows = [(i, x * 7.0, y * y * 0.5, r.randint(1, 30)) for i, (x, y) in enumerate(zip(xs, ys))]
    df = spark.createDataFrame(rows, "id int, x double, y double, w int").repartition(5)
    got = sharding.kd_tree_shards(df, {"x": F.col("x"), "y": F.col("y")}, F.col("w"), 5, F.col("id").cast("string"), keep={"id": F.col("id")})
    assert {q["id"]: q["shard"] for q in got.collect()} == brute_kd([q[1:3] for q in rows], [q[3] for q in rows], 5)


def test_equal_texts_share_a_shard(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").repartition(6)
    rows = sharding.shard_documents(docs).collect()
    text = {r["doc_id"]: r["text"] for r in docs.collect()}
    homes, size, total, longest = {}, {}, [0] * 40, max(r["size"] for r in rows)
    for r in rows:
        homes.setdefault(text[r["doc_id"]], set()).add(r["shard"])
        size[text[r["doc_id"]]] = size.get(text[r["doc_id"]], 0) + r["size"]
        total[r["shard"]] += r["size"]
    mean = sum(total) / 40
    assert all(len(h) == 1 for t, h in homes.items() if size[t] <= mean)
    assert max(total) <= max(1.1 * mean, longest) and min(total) >= 0.9 * mean, (mean, longest, sorted(total))


def test_strings_with_a_common_prefix_are_told_apart(spark, monkeypatch):
    df = spark.range(400).select("id", F.concat(F.lit("a-very-long-common-prefix-"), F.format_string("%03d", F.col("id") % 100)).alias("s"))
    for most in (10_000, 30):
        monkeypatch.setattr(sharding, "RANKED_AT_ONCE", most)
        got = sharding.kd_tree_shards(df, {"s": F.col("s")}, F.lit(1), 4, F.col("id").cast("string"), keep={"s": F.col("s")})
        ends = got.groupBy("shard").agg(F.min("s"), F.max("s"), F.count("*")).orderBy("shard").collect()
        assert [(r[1][-3:], r[2][-3:], r[3]) for r in ends] == [("000", "024", 100), ("025", "049", 100), ("050", "074", 100), ("075", "099", 100)]


def test_copies_larger_than_a_shard_are_split(spark):
    df = spark.range(3000).select(F.lit("same").alias("text"), F.lit(0).alias("a"))
    got = sharding.kd_tree_shards(df, {"a": F.col("a")}, F.lit(5), 5, F.col("text"))
    counts = [r["count"] for r in got.groupBy("shard").count().collect()]
    assert len(counts) == 5 and max(abs(c - 600) for c in counts) <= 20  # pieces are a 64th of a shard


def test_sharding_odd_and_empty(odd_docs, no_docs):
    rows = sharding.shard_documents(odd_docs, 3).collect()
    assert len(rows) == odd_docs.count()
    assert [r["size"] for r in rows if r["doc_id"] == 0] == [16]
    assert sharding.shard_documents(no_docs, 3).count() == 0


def test_gapless_numbers(spark):
    store = Stored(spark)
    df = store.put(spark.range(5000).select((F.col("id") % 3).alias("k"), row_uid().alias("u")))
    got = gapless(df, ["k"], "u", "r", 5000).groupBy("k").agg(F.count_distinct("r").alias("n"), F.max("r").alias("m"), F.count("*").alias("c")).collect()
    assert all(r["n"] == r["c"] == r["m"] + 1 for r in got)
