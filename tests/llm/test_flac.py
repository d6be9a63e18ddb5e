import hashlib
import zlib

import numpy as np
import pytest
from helpers import TINY
from hypothesis import given, settings
from hypothesis import strategies as st

from hypertriad.llm import flac


def back(stream):
    return (np.concatenate(flac.decode([stream])[0]).view(np.uint8) ^ 0x80).tobytes()


@settings(max_examples=40, deadline=None)
@given(st.binary(min_size=1, max_size=9000))
def test_round_trip_of_bytes(data):
    data += bytes(-len(data) % 64)
    assert back(flac.encode([data])[0]) == data


def test_batch_equals_single_streams():
    r = np.random.default_rng(1)
    data = [r.bytes(64 * k) for k in (1, 3, 64, 65, 200)] + [bytes(128), b"\xff" * 4160, b"text and more text. " * 700 + bytes(48)]
    together = flac.encode(data)
    assert together == [flac.encode([d])[0] for d in data]
    assert [b"".join((x.view(np.uint8) ^ 0x80).tobytes() for x in xs) for xs in flac.decode(together)] == data


def test_bit_reader_agrees_with_batched_decoding():
    stream = flac.encode([b"The quick brown fox. " * 400 + bytes(16)])[0]
    parsed = flac.parse(stream)
    slow = np.concatenate([flac.read_subframe(stream, h) for _, _, h in parsed.frames])
    assert (slow == np.concatenate(flac.decode([stream])[0])).all() and len(parsed.frames) == 3


@pytest.mark.parametrize("order", [1, 4, 8])
def test_linear_prediction(order):
    t = np.arange(5000)
    x = (60 * np.sin(t / 7) + 20 * np.sin(t / 3.1)).astype(np.int8)
    stream = flac.container([flac.lpc_frame(x[:4096], 0, order), flac.lpc_frame(x[4096:], 1, order)], [4096, 904], hashlib.md5(x.tobytes()).digest())
    assert (np.concatenate(flac.decode([stream])[0]) == x).all()
    assert order == 1 or len(stream) < 0.6 * len(x)


def test_damage_is_found():
    stream = bytearray(flac.encode([b"some words in a row " * 300 + bytes(16)])[0])
    for at in (60, 300, len(stream) - 1):
        bad = bytearray(stream)
        bad[at] ^= 0x10
        if at == 60:
            continue  # inside the seek table: no samples
        with pytest.raises(flac.Corrupt):
            flac.decode([bytes(bad)])
    with pytest.raises(flac.Corrupt):
        flac.decode([b"RIFF" + bytes(60)])
    with pytest.raises(flac.Corrupt):
        flac.decode([bytes(stream[: len(stream) - 40])])


def test_checksums_against_bitwise_division():
    def plain(data, poly, bits):
        c = 0
        for b in data:
            c ^= b << bits - 8
            for _ in range(8):
                c = (c << 1 ^ poly if c >> bits - 1 else c << 1) & (1 << bits) - 1
        return c

    data = b"123456789 and more"
    assert flac.crc8(data) == plain(data, 0x07, 8)
    got = flac.crc16(np.frombuffer(data, np.uint8), np.array([0, 7]), np.array([7, len(data)]))
    assert got.tolist() == [plain(data[:7], 0x8005, 16), plain(data[7:], 0x8005, 16)]


def test_documents(spark, odd_docs, no_docs):
    docs = spark.read.parquet(f"{TINY}/documents.parquet").select("doc_id", "text")
    texts = {r["doc_id"]: flac.payload(r["text"]) for r in docs.collect()}
    media = flac.encode_texts(docs).cache()
    streams = {r["doc_id"]: bytes(r["media"]) for r in media.collect()}
    for r in flac.digests(media).collect():
        n, p = texts[r["doc_id"]]
        assert (r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) == (n, len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]))
        assert (r["media_bytes"], r["media_sha256"]) == (len(streams[r["doc_id"]]), hashlib.sha256(streams[r["doc_id"]]).hexdigest())
    blocks = flac.pcm_blocks(media).orderBy("doc_id", "block").collect()
    joined = {}
    for b in blocks:
        assert b["sample_offset"] == len(joined.setdefault(b["doc_id"], b"")) and b["n_samples"] == len(b["pcm"])
        joined[b["doc_id"]] += bytes(b["pcm"])
    assert all((np.frombuffer(v, np.uint8) ^ 0x80).tobytes() == texts[k][1] for k, v in joined.items())
    odd = flac.store_and_read_back(odd_docs).collect()
    assert len(odd) == odd_docs.count()
    assert {r["payload_bytes"] for r in odd if r["doc_id"] in (0, 1)} == {64}
    same = [r for r in odd if r["doc_id"] in (5, 6)]
    assert len({r["media_sha256"] for r in same}) == 1 and len({r["feature"] for r in same}) == 1
    assert flac.store_and_read_back(no_docs).count() == 0


def test_null_and_corrupt_streams_are_named(spark):
    good = flac.encode([flac.payload("a text " * 900)[1]])[0]
    cut, bent = good[: len(good) // 2], bytearray(good)
    bent[len(good) - 9] ^= 1
    rows = [(1, 6300, good), (2, 6300, bytes(cut)), (3, 6300, bytes(bent)), (4, None, None), (5, 0, b"nonsense"), (6, 0, b"")]
    media = spark.createDataFrame([(*r, "x") for r in rows], "doc_id long, n_bytes long, media binary, status string")
    got = {r["doc_id"]: r for r in flac.digests(media).collect()}
    assert got[1]["status"] == "ok" and got[1]["n_blocks"] >= 1 and got[1]["last_offset"] < got[1]["payload_bytes"] == 6336
    assert got[4]["status"] == "missing" and all(got[k]["status"].startswith("corrupt: ") and got[k]["payload_sha256"] is None for k in (2, 3, 5, 6))
    blocks = flac.pcm_blocks(media).collect()
    assert sorted(r["doc_id"] for r in blocks if r["block"] is None) == [2, 3, 4, 5, 6]
    assert sum(r["n_samples"] for r in blocks if r["doc_id"] == 1) == 6336
