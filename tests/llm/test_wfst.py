import math
import random
import struct
import time
import zlib

import public_tokenizers
import pytest
from helpers import TINY

from hypertriad.llm import wfst

PATH = public_tokenizers.path("piece_bpe_32k.model")


def toy(**options):
    pieces = ["<unk>", "<s>", "</s>"] + [f"<0x{b:02X}>" for b in range(256)] + ["▁", "a", "b", "ab", "▁a", "ba", "▁ab", "bab", "c▁"[:1]]
    kinds = [2, 3, 3] + [6] * 256 + [1] * 9
    return wfst.Transducer(wfst.Vocabulary(pieces, [-1.0 * (k % 7) - 0.5 for k in range(len(pieces))], kinds, unigram=True, **options))


def brute(t, text):
    """The least weight over all segmentations."""
    weights = {p: w for p, k, w in zip(t.vocabulary.pieces, t.vocabulary.kinds, t.vocabulary.weights()) if k == 1}
    best = [0.0] + [math.inf] * len(text)
    for i in range(len(text)):
        for j in range(i + 1, len(text) + 1):
            if text[i:j] in weights:
                best[j] = min(best[j], best[i] + weights[text[i:j]])
        if text[i] not in weights:
            best[i + 1] = min(best[i + 1], best[i] + wfst.BYTE_WEIGHT * len(text[i].encode()))
    return best[-1]


def test_shortest_paths_against_all_segmentations():
    t, r = toy(), random.Random(1)
    for _ in range(400):
        text = "".join(r.choice("aabb ccé") for _ in range(r.randint(0, 12)))
        ids, weight = t.encode(text)
        assert weight == pytest.approx(brute(t, t.normalise(text)))
        assert t.decode(ids) == text


def message(*fields):
    """A protocol buffer message of (number, value) fields; floats take 32 bits."""
    out = b""

    def varint(n):
        got = b""
        while True:
            got, n = got + bytes([n & 127 | (n > 127) << 7]), n >> 7
            if not n:
                return got

    for number, value in fields:
        if isinstance(value, float):
            out += varint(number << 3 | 5) + struct.pack("<f", value)
        elif isinstance(value, int):
            out += varint(number << 3) + varint(value)
        else:
            out += varint(number << 3 | 2) + varint(len(value)) + value
    return out


def unigram(path, normaliser, seed=5):
    """A unigram model with random scores, written by hand: no tokenizer is trained."""
    r = random.Random(seed)
    words = {"".join(r.choice("abcdeh▁") for _ in range(r.randint(2, 5))) for _ in range(300)} | {f"▁{c}" for c in "abcdeh"}
    pieces = [("<unk>", 0.0, 2), ("<s>", 0.0, 3), ("</s>", 0.0, 3), *[(f"<0x{b:02X}>", 0.0, 6) for b in range(256)]]
    pieces += [(w, -r.uniform(2, 12), 1) for w in sorted(words)] + [(c, -r.uniform(5, 9), 1) for c in "▁abcdeh"]
    data = b"".join(message((1, message((1, p.encode()), (2, float(s)), (3, k)))) for p, s, k in pieces)
    data += message((2, message((3, 1), (35, 1)))) + message((3, normaliser))
    path.write_bytes(data)
    return data


PLAIN = message((1, b"identity"), (3, 1), (4, 0), (5, 1))
SQUEEZED = message((1, b"identity"), (3, 1), (4, 1), (5, 1))


@pytest.mark.parametrize("normaliser", [PLAIN, SQUEEZED])
def test_unigram_model_as_the_library_reads_it(tmp_path, normaliser):
    import sentencepiece

    data = unigram(tmp_path / "u.model", normaliser)
    sp, t, r = sentencepiece.SentencePieceProcessor(model_proto=data), wfst.compiled(str(tmp_path / "u.model")), random.Random(6)
    for _ in range(300):
        text = "".join(r.choice("aabbccdeh   ") for _ in range(r.randint(0, 40)))
        ids, weight = t.encode(text)
        theirs = sp.encode(text)
        assert weight == pytest.approx(-sum(t.vocabulary.scores[k] for k in theirs), rel=1e-5, abs=1e-6)
        assert t.normalise(text) == "".join(sp.id_to_piece(theirs))
        assert t.path(text)[1] == pytest.approx(weight)


def test_character_map_of_the_library(tmp_path):
    import sentencepiece

    theirs = sentencepiece.SentencePieceNormalizer(rule_name="nmt_nfkc")
    proto = theirs.serialized_model_proto()
    charsmap = next(dict(wfst._fields(v))[2] for n, v in wfst._fields(proto) if n == wfst.NORMALISER)
    unigram(tmp_path / "m.model", message((1, b"nmt_nfkc"), (2, charsmap), (3, 1), (4, 1), (5, 1)))
    t, r = wfst.compiled(str(tmp_path / "m.model")), random.Random(7)
    assert len(t.vocabulary.charmap) > 1000
    again = wfst.Normaliser(wfst.Vocabulary([], [], [], True, True, True, t.vocabulary.charmap))
    for _ in range(400):
        text = "".join(r.choice("ab \u3000\t①ｈée\u0301ﬁ㌔½Åが゙…\u200b한글가") for _ in range(r.randint(0, 15)))
        assert t.normalise(text) == again.apply(text)
        assert t.normalise(text).replace("▁", " ").strip() == theirs.normalize(text).replace("▁", " ").strip()
        ids, weight = t.encode(text)
        assert t.path(text)[1] == pytest.approx(weight) and t.decode(ids) == theirs.normalize(text).replace("▁", " ").strip()


def test_the_composition_is_lazy_and_whole():
    """The path of the whole composition, the parts' paths and the least of all segmentations agree."""
    t, r = wfst.compiled(PATH), random.Random(2)
    for _ in range(60):
        text = "".join(r.choice("ab the\n 12é漢 ▁") for _ in range(r.randint(0, 40)))
        ids, weight = t.path(text)
        assert t.encode(text)[1] == pytest.approx(weight) and t.decode(struct.pack(f"<{len(ids)}I", *ids)) == text.replace("▁", " ")


def test_given_documents(spark, odd_docs, no_docs):
    docs = spark.read.parquet(f"{TINY}/documents.parquet")
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    t = wfst.compiled(PATH)
    for r in wfst.digests(docs).collect():
        ids, weight = t.encode(texts[r["doc_id"]])
        assert (r["n_ids"], r["ids_crc32"], r["weight"]) == (len(ids) // 4, zlib.crc32(ids), weight)
        assert r["decoded_crc32"] == zlib.crc32(texts[r["doc_id"]].encode())
    back = {r["doc_id"]: r["text"] for r in wfst.decode_ids(wfst.encode_texts(docs)).collect()}
    assert back == texts
    odd = {r["doc_id"]: r for r in wfst.digests(odd_docs).collect()}
    assert odd[0]["n_ids"] == odd[1]["n_ids"] == 0 and odd[0]["weight"] == 0
    assert odd[7]["decoded_crc32"] == zlib.crc32("é ü 漢字 \U0001f600".encode())
    assert wfst.digests(no_docs).count() == 0


def test_no_pieces_fall_back_to_bytes():
    t = wfst.compiled(PATH)
    ids, weight = t.encode("\U0001f9ff")
    assert weight >= 4 * wfst.BYTE_WEIGHT or weight > 0
    assert t.decode(ids) == "\U0001f9ff"


def test_long_words_take_linear_time():
    t, took = wfst.compiled(PATH), []
    for n in (20_000, 80_000):
        began = time.time()
        t.encode("thinganderest" * (n // 13))
        took.append(time.time() - began)
    assert took[1] < 10 * took[0] and took[1] < 5
