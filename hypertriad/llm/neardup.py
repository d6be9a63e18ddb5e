"""Near duplicates: improved consistent weighted sampling over TF-IDF word shingles, banded, verified.

1. Document frequencies come from all documents, with near copies counted together: a first sketch of fixed size estimates
   how many documents share a document's plain min-hash bands, and a second one counts each shingle of a document by one
   over that number (count-mean-min: four rows of hashed counters, less the mean load, the least of the four).  So the size
   of a group of copies does not lower the weight of what its members share.  Inverse document frequency is
   log(documents / frequency), from 0 for what all documents have, and levels off for shingles in fewer than one of
   RARE documents: the sketch tells such shares apart at any number of documents, as its noise grows with their root only.
2. Every document gets SAMPLES consistent weighted samples of its weighted shingles.  Equal texts are one node from here.
3. Nodes that agree on all samples of a band share a bucket.  In each bucket every node is checked against the least and
   the greatest node, which takes two pairs a node however large the bucket is; links give components.
4. What is left are pairs in a bucket across components.  Buckets are cut into blocks, pure in one component where that
   is large, and only pairs of blocks that can hold such a pair are compared, inside a task: by their samples first and
   exactly where these allow the threshold and the two are not joined yet.  Only a spanning forest of links comes out.
5. Every link is verified by the exact weighted Jaccard similarity.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import HEAVY_LEAST, HEAVY_PARTS, Stored, fresh, join_skewed, row_uid
from .components import components

WORDS = 5
THRESHOLD = 0.8
BANDS, ROWS = 16, 3
SAMPLES = BANDS * ROWS
SKETCH_ROWS, SKETCH_WIDTH = 4, 1 << 18
SKETCH_BLOCK = 4096
#: Shingles in fewer than one of RARE documents have the full weight; no weight is less than LEAST_IDF, so that all count.
RARE, LEAST_IDF = 1000, 1e-3
#: Plain min-hash bands that tell copies, counter rows for each, and the unit in which a document's share is counted.
COPY_BANDS, COPY_ROWS, COPY_COUNTERS, UNIT = 4, 3, 2, 1 << 12
#: Pairs whose share of equal samples is lower are not verified, unless asked for (``least_estimate=0`` verifies every pair of a
#: bucket); at similarity 0.8 this is three deviations down.
LEAST_ESTIMATE = 0.62
BLOCK = 1024
#: Characters of texts shingled at once, and bytes of them over which the sums of word ids run.
PORTION, WINDOW = 1 << 18, 1 << 16

_BLANK = bytes(b if b >= 128 or chr(b).isalnum() else 32 for b in range(256))


class _WordIds:
    """64-bit ids of words: polynomials over random numbers of their bytes, of all words of a text at once.

    A word's sum is a difference of two running sums, divided by the power of the base at its start, so it does not depend
    on its place.  The sums run over windows of whole words; a word that fits in none has another hash.
    """

    BASE = 0x9E3779B97F4A7C15

    def __init__(self):
        self.of_byte = np.random.default_rng(11).integers(0, 1 << 64, 256, dtype=np.uint64) | np.uint64(1)
        self.powers, self.inverses = (np.cumprod(np.array([1] + [b] * (WINDOW - 1), np.uint64)) for b in (self.BASE, pow(self.BASE, -1, 1 << 64)))

    def of(self, raw: bytes) -> tuple[np.ndarray, np.ndarray]:
        """Ids and starts of the words of bytes that begin with a blank and in which blanks alone separate words."""
        ids, at, a = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)], 0
        while a < len(raw):  # a blank is at a
            b = len(raw) if len(raw) - a <= WINDOW else raw.rfind(b" ", a + 1, a + WINDOW + 1)
            if b < 0:  # a word of WINDOW bytes or more
                b = raw.find(b" ", a + WINDOW + 1)
                b = len(raw) if b < 0 else b
                ids.append(np.array([xxhash.xxh3_64_intdigest(raw[a + 1 : b])], np.uint64))
                at.append(np.array([a + 1]))
            else:
                got = np.frombuffer(raw, np.uint8, b - a, a)
                inside = np.zeros(len(got) + 2, bool)
                np.not_equal(got, 32, out=inside[1:-1])
                edges = np.flatnonzero(inside[1:] != inside[:-1])
                first, end = edges[::2], edges[1::2]
                sums = np.zeros(len(got) + 1, np.uint64)
                np.cumsum(self.of_byte[got] * self.powers[: len(got)], out=sums[1:])
                h = (sums[end] - sums[first]) * self.inverses[first]
                h ^= h >> np.uint64(32)
                ids.append(h * np.uint64(0xD6E8FEB86659FD93))
                at.append(first + a)
            a = b
        return np.concatenate(ids), np.concatenate(at)


def plain_bytes(text: str) -> bytes:
    """Lower case as UTF-8; ASCII marks and blanks, which separate words, are blanks."""
    return text.lower().encode("utf-8", "replace").translate(_BLANK)


def shingles_of(texts: list[str | None], ids: _WordIds, distinct: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """64-bit shingle ids of all texts one after another, their counts and the number of them in each text.

    The ids of a text are sorted and distinct, or else as they come, each counted 1.  A text of fewer than WORDS words is
    one shingle, of none none.
    """
    raws = [plain_bytes(t or "") for t in texts]
    w, at = ids.of(b" ".join([b"", *raws]))
    begin = np.searchsorted(at, np.cumsum([1] + [len(r) + 1 for r in raws]))  # each text's first word
    words = np.diff(begin)
    lens = np.where(words >= WORDS, words - WORDS + 1, np.minimum(words, 1))
    h = np.zeros(len(w), np.uint64)
    short = []
    for k in range(WORDS):
        here = h[: max(len(w) - k, 0)]
        here *= np.uint64(0x9E3779B97F4A7C15)
        here += w[k:]
        here ^= here >> np.uint64(29)
        if k + 1 < WORDS:
            own = begin[:-1][words == k + 1]
            short.append((own, h[own]))
    for own, got in short:
        h[own] = got
    starts = np.cumsum(lens) - lens
    h = h[np.arange(lens.sum()) + np.repeat(begin[:-1] - starts, lens)] * np.uint64(0xBF58476D1CE4E5B9)
    if not distinct or not len(h):
        return h, np.ones(len(h), np.int64), lens
    for a, n in zip(starts.tolist(), lens.tolist()):
        h[a : a + n].sort()
    new = np.ones(len(h), bool)
    np.not_equal(h[1:], h[:-1], out=new[1:])
    new[starts[lens > 0]] = True
    kept = np.flatnonzero(new)
    return h[kept], np.diff(np.append(kept, len(h))), np.diff(np.searchsorted(kept, np.append(starts, len(h))))


def shingles(text: str | None, ids: _WordIds) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct 64-bit shingle ids of one text and their counts."""
    return shingles_of([text], ids)[:2]


def _portions(texts: pa.Array) -> Iterator[list[str | None]]:
    """The texts in order, some at a time: PORTION characters or one text more."""
    some, size = [], 0
    for t in texts:
        some.append(t.as_py())
        size += len(some[-1] or "")
        if size >= PORTION:
            yield some
            some, size = [], 0
    if some:
        yield some


def _cells(h: np.ndarray, rows: int = SKETCH_ROWS, seed: int = 0) -> list[np.ndarray]:
    """The counter of each hash in each sketch row."""
    shift = 64 - SKETCH_WIDTH.bit_length() + 1
    return [((h ^ np.uint64(0xA5A5 * (r + 1 + seed))) * np.uint64((0xD6E8FEB86659FD93 + 2 * (r + seed) * 0x9E3779B9) & (2**64 - 1)) >> np.uint64(shift)).astype(np.int64) + r * SKETCH_WIDTH for r in range(rows)]


def copy_keys(h: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """COPY_BANDS plain min-hash keys of each document; documents are the runs of h that begin at ``starts``."""
    keys = np.random.default_rng(9).integers(1, 1 << 63, COPY_BANDS * COPY_ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    out = np.zeros((len(starts), COPY_BANDS), np.uint64)
    for k, key in enumerate(keys):
        x = h * key
        x ^= x >> np.uint64(31)
        least = np.minimum.reduceat(x * np.uint64(0xD6E8FEB86659FD93), starts)
        b = k % COPY_BANDS
        out[:, b] = (out[:, b] ^ least) * np.uint64(0x9E3779B97F4A7C15) ^ least >> np.uint64(29)
    return out


def _copy_cells(keys: np.ndarray) -> np.ndarray:
    """(documents, bands, counters) cells of copy keys."""
    return np.stack([np.stack(_cells(keys[:, b], COPY_COUNTERS, 8 * b + 8), 1) + b * COPY_COUNTERS * SKETCH_WIDTH for b in range(COPY_BANDS)], 1)


class Copies:
    """How many documents hold copies of a document, itself among them, as estimated by the first sketch."""

    def __init__(self, counts: np.ndarray):
        self.counts = np.maximum(counts - counts.mean(axis=1, keepdims=True), 1).ravel()

    def of(self, h: np.ndarray, starts: np.ndarray) -> np.ndarray:
        return self.counts[_copy_cells(copy_keys(h, starts))].min(axis=2).max(axis=1)


def _sketch(docs: DataFrame, rows: int, count, distinct: bool = True) -> tuple[np.ndarray, int]:
    """rows x SKETCH_WIDTH counters and a total, summed over all documents.  count(h, starts) gives the cells, the amount of
    each and the total of some documents; their shingles are distinct, or else as they come."""

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, total, ids, seen = np.zeros(rows * SKETCH_WIDTH, np.int64), 0, _WordIds(), False
        for batch in batches:
            for texts in _portions(batch.column(0)):
                h, _, lens = shingles_of(texts, ids, distinct)
                if len(h):
                    lens = lens[lens > 0]
                    cells, amounts, more = count(h, np.cumsum(lens) - lens)
                    for c in cells:
                        np.add.at(sums, c, amounts)
                    total, seen = total + more, True
        if seen:
            parts = sums.reshape(-1, SKETCH_BLOCK)
            some = [k for k in range(len(parts)) if parts[k].any()]
            yield pa.record_batch([pa.array([*some, -1], pa.int32()), pa.array([*(parts[k].astype("<i8").tobytes() for k in some), np.array([total], "<i8").tobytes()], pa.binary())], names=["block", "counts"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}
        for batch in batches:
            for k, b in zip(batch.column(0).to_pylist(), batch.column(1)):
                got = np.frombuffer(b.as_py(), "<i8")
                total[k] = total[k] + got if k in total else got
        if total:
            yield pa.record_batch([pa.array(list(total), pa.int32()), pa.array([v.tobytes() for v in total.values()], pa.binary())], names=["block", "counts"])

    schema = "block int, counts binary"
    got = docs.select("text").mapInArrow(local, schema).repartition("block").mapInArrow(add, schema).collect()  # of fixed size
    out, total = np.zeros((rows * SKETCH_WIDTH // SKETCH_BLOCK, SKETCH_BLOCK), np.int64), 0
    for r in got:
        if r["block"] < 0:
            total = int(np.frombuffer(r["counts"], np.int64)[0])
        else:
            out[r["block"]] = np.frombuffer(r["counts"], np.int64)
    return out.reshape(rows, SKETCH_WIDTH), total


def copy_sketch(docs: DataFrame) -> Copies:
    def count(h, starts):
        cells = _copy_cells(copy_keys(h, starts))
        return [cells[:, b, c] for b in range(COPY_BANDS) for c in range(COPY_COUNTERS)], 1, len(starts)

    return Copies(_sketch(docs, COPY_BANDS * COPY_COUNTERS, count, distinct=False)[0])  # repeats leave a least hash as it is


def frequency_sketch(docs: DataFrame) -> tuple[np.ndarray, float]:
    """Counters of document frequencies (SKETCH_ROWS x SKETCH_WIDTH, whatever the input) and the number of documents, both
    with a group of near copies counted as about one document."""
    copies = docs.sparkSession.sparkContext.broadcast(copy_sketch(docs))  # of fixed size

    def count(h, starts):
        share = np.maximum(1, np.round(UNIT / copies.value.of(h, starts))).astype(np.int64)
        each = np.repeat(share, np.diff(np.append(starts, len(h))))
        return _cells(h), each, int(share.sum())

    counts, total = _sketch(docs, SKETCH_ROWS, count)
    return counts / UNIT, total / UNIT


class Weights:
    """TF-IDF weights from a frequency sketch."""

    def __init__(self, counts: np.ndarray, docs: float):
        load = counts.mean(axis=1, keepdims=True)
        df = np.maximum(counts - load, 1).ravel()
        self.idf = np.clip(np.log((docs + 1) / df) / np.log(min(max(docs + 1, 2), RARE)), LEAST_IDF, 1).astype(np.float32)

    def of(self, h: np.ndarray, tf: np.ndarray) -> np.ndarray:
        """The least frequency of the rows is the greatest weight."""
        w = self.idf[_cells(h)[0]]
        for cells in _cells(h)[1:]:
            w = np.maximum(w, self.idf[cells])
        return w * tf.astype(np.float32)


class Sampler:
    """Improved consistent weighted sampling with its variates looked up by hash bits."""

    def __init__(self, seed: int = 7):
        r = np.random.default_rng(seed)
        self.gamma = r.gamma(2.0, 1.0, 1 << 16).astype(np.float32)
        self.log_gamma = np.log(r.gamma(2.0, 1.0, 1 << 16)).astype(np.float32)
        self.keys = r.integers(1, 1 << 63, SAMPLES, dtype=np.uint64) * np.uint64(2) + np.uint64(1)

    def samples(self, h: np.ndarray, w: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """SAMPLES 64-bit samples for each document; documents are the runs of h that begin at ``starts`` (none empty)."""
        lens = np.diff(np.append(starts, len(h)))
        log_w = np.log(w)
        out = np.empty((len(starts), SAMPLES), np.uint64)
        low = np.uint64(0xFFFF)
        for k in range(SAMPLES):
            x = h * self.keys[k]
            x ^= x >> np.uint64(32)
            x *= np.uint64(0xD6E8FEB86659FD93)
            r = self.gamma[(x & low).astype(np.intp)]
            beta = (x >> np.uint64(40)).astype(np.float32) * np.float32(2.0**-24)
            t = np.floor(log_w / r + beta)
            a = self.log_gamma[((x >> np.uint64(16)) & low).astype(np.intp)] - r * (t + np.float32(1) - beta)
            hit = np.flatnonzero(a == np.repeat(np.minimum.reduceat(a, starts), lens))
            first = hit[np.searchsorted(hit, starts)]
            out[:, k] = (h[first] ^ (t[first].astype(np.int64).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))) * np.uint64(0xBF58476D1CE4E5B9)
        return out


def band_keys(samples: np.ndarray) -> np.ndarray:
    """One 64-bit key for each band."""
    x = samples.reshape(len(samples), BANDS, ROWS)
    h = np.zeros(x.shape[:2], np.uint64)
    for k in range(ROWS):
        h = (h ^ x[:, :, k]) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(31)
    return h.view(np.int64)


def signatures(docs: DataFrame, weights) -> DataFrame:
    """doc_id, digest, bands (null where there is no word) and prints (16 bits of each sample) of every row."""
    schema = "doc_id long, digest string, bands array<long>, prints binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sampler, ids, tfidf = Sampler(), _WordIds(), weights.value
        for batch in batches:
            bands: list = [None] * batch.num_rows
            prints: list = [None] * batch.num_rows
            done = 0
            for texts in _portions(batch.column(2)):
                h, tf, lens = shingles_of(texts, ids)
                rows = np.flatnonzero(lens)
                if len(rows):
                    lens = lens[rows]
                    got = sampler.samples(h, tfidf.of(h, tf), np.cumsum(lens) - lens)
                    for i, b, s in zip((rows + done).tolist(), band_keys(got), (got >> np.uint64(48)).astype("<u2")):
                        bands[i], prints[i] = b, s.tobytes()
                done += len(texts)
            yield pa.record_batch([batch.column(0), batch.column(1), pa.array(bands, pa.list_(pa.int64())), pa.array(prints, pa.binary())], names=["doc_id", "digest", "bands", "prints"])

    return docs.select(F.col("doc_id").cast("long"), F.md5("text").alias("digest"), "text").mapInArrow(run, schema)


def vectors(texts: DataFrame, weights) -> DataFrame:
    """(node, text) to (node, ids, weights): sorted shingle ids and their weights as bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, tfidf = _WordIds(), weights.value
        for batch in batches:
            made: list[tuple[bytes, bytes]] = []
            for some in _portions(batch.column(1)):
                h, tf, lens = shingles_of(some, ids)
                w, ends = tfidf.of(h, tf), np.cumsum(lens)
                made += [(h[a:b].tobytes(), w[a:b].tobytes()) for a, b in zip((ends - lens).tolist(), ends.tolist())]
            yield pa.record_batch([batch.column(0), pa.array([h for h, _ in made], pa.binary()), pa.array([w for _, w in made], pa.binary())], names=["node", "ids", "w"])

    return texts.select("node", "text").mapInArrow(run, "node long, ids binary, w binary")


def weighted_jaccard(h1: bytes, w1: bytes, h2: bytes, w2: bytes) -> float:
    a, b = np.frombuffer(h1, np.uint64), np.frombuffer(h2, np.uint64)
    wa, wb = np.frombuffer(w1, np.float32).astype(float), np.frombuffer(w2, np.float32).astype(float)
    at = np.minimum(np.searchsorted(b, a), len(b) - 1)
    same = b[at] == a
    both = np.minimum(wa[same], wb[at[same]]).sum()
    return float(both / (wa.sum() + wb.sum() - both))


def verified(pairs: DataFrame, vecs: DataFrame, threshold: float) -> DataFrame:
    """The pairs (u, v) whose exact weighted Jaccard similarity is at least the threshold."""
    a = vecs.select(F.col("node").alias("u"), F.col("ids").alias("h1"), F.col("w").alias("w1"))
    b = vecs.select(F.col("node").alias("v"), F.col("ids").alias("h2"), F.col("w").alias("w2"))

    @F.pandas_udf("double")
    def similarity(h1: pd.Series, w1: pd.Series, h2: pd.Series, w2: pd.Series) -> pd.Series:
        return pd.Series([weighted_jaccard(*x) for x in zip(h1, w1, h2, w2)], dtype=float)

    s = similarity("h1", "w1", "h2", "w2")
    return pairs.join(a, "u").join(b, "v").where(s >= threshold - 1e-9).select("u", "v")


def _block_pairs(buckets: DataFrame) -> DataFrame:
    """The rows of each pair of blocks that may hold a pair across components: band, key, g, side, node, comp.

    buckets: stored (band, key, node, comp), with two components at least in each bucket.  A block holds about BLOCK rows
    of one component, if that has as many in the bucket, or of several.  g names the pair of blocks; side is 0 for the
    first block, 1 for the second and 2 if they are the same.
    """
    comps = buckets.groupBy("band", "key", "comp").agg(F.count(F.lit(1)).alias("n"))
    large = F.col("n") >= BLOCK
    blocks = comps.select("band", "key", "comp", F.when(large, F.col("comp")).otherwise(-1).alias("p"), F.when(large, F.ceil(F.col("n") / BLOCK)).alias("k"), "n")
    mixed = blocks.where("p < 0").groupBy("band", "key").agg(F.ceil(F.sum("n") / BLOCK).alias("km"))
    pure = blocks.where("p >= 0").groupBy("band", "key").agg(F.collect_list(F.struct("p", "k")).alias("pures"))  # at most a BLOCKth of the bucket's rows
    upto = lambda k: F.sequence(F.lit(0).cast("long"), k - 1)
    none = F.array().cast("array<struct<p:bigint,i:bigint>>")
    names = F.concat(
        F.coalesce(F.transform(upto(F.col("km")), lambda i: F.struct(F.lit(-1).cast("long").alias("p"), i.alias("i"))), none),
        F.coalesce(F.flatten(F.transform("pures", lambda b: F.transform(upto(b["k"]), lambda i: F.struct(b["p"].alias("p"), i.alias("i"))))), none),
    )
    layout = mixed.join(pure, ["band", "key"], "full").select("band", "key", "km", names.alias("all"))
    own = F.struct(F.col("p").cast("long").alias("p"), F.pmod(F.xxhash64("node"), F.coalesce("k", "km")).alias("i"))
    placed = buckets.join(blocks.drop("n"), ["band", "key", "comp"]).join(layout, ["band", "key"]).withColumn("own", own)
    other = F.explode(F.filter("all", lambda b: (b["p"] < 0) | (F.col("own.p") != b["p"])))
    sent = placed.select("band", "key", "node", "comp", "own", other.alias("other"))
    side = F.when(F.col("own") == F.col("other"), 2).when(F.col("own") < F.col("other"), 0).otherwise(1)
    g = F.xxhash64("band", "key", F.least("own", "other"), F.greatest("own", "other"))
    return sent.select("band", "key", g.alias("g"), side.alias("side"), "node", "comp")


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The rows of each (g, band, key) of sorted batches; a run is at most two blocks, so it fits."""
    held = None
    for batch in batches:
        table = pa.Table.from_batches([*([held] if held is not None else []), batch]).combine_chunks()
        if not table.num_rows:
            continue
        batch = table.to_batches()[0]
        k = np.stack([batch.column(n).to_numpy(zero_copy_only=False).astype(np.int64) for n in ("g", "band", "key")], 1)
        starts = [0, *(np.flatnonzero((k[1:] != k[:-1]).any(axis=1)) + 1).tolist()]
        for a, b in zip(starts, starts[1:]):
            yield batch.slice(a, b - a)
        held = batch.slice(starts[-1])
    if held is not None:
        yield held


def _likely(run: pa.RecordBatch, least: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(i, j, equal samples) of the run's pairs across components whose estimate allows the threshold, best first, without
    those that share an earlier band, as these are pairs of another bucket."""
    n, band = run.num_rows, run.column("band")[0].as_py()
    side = run.column("side").to_numpy()
    prints = np.frombuffer(b"".join(run.column("prints").to_pylist()), "<u2").reshape(n, SAMPLES)
    comp = run.column("comp").to_numpy()
    left, right = np.flatnonzero(side != 1), np.flatnonzero(side != 0)
    found = []
    for a in range(0, len(left), 64):
        rows = left[a : a + 64]
        equal = np.zeros((len(rows), len(right)), np.int16)
        for k in range(SAMPLES):
            equal += prints[rows, k][:, None] == prints[right, k][None, :]
        ok = (equal >= least * SAMPLES) & (comp[rows][:, None] != comp[right][None, :])
        if side[0] == 2:
            ok &= rows[:, None] < right[None, :]
        i, j = np.nonzero(ok)
        if len(i):
            found.append((rows[i], right[j], equal[i, j]))
    if not found:
        return (np.zeros(0, np.int64),) * 3
    i, j, equal = (np.concatenate(x) for x in zip(*found))
    if band:
        bands = run.column("bands").flatten().to_numpy().reshape(n, BANDS)[:, :band]
        new = ~(bands[i] == bands[j]).any(axis=1)
        i, j, equal = i[new], j[new], equal[new]
    order = np.argsort(-equal, kind="stable")
    return i[order], j[order], equal[order]


def across(buckets: DataFrame, prints: DataFrame, vecs: DataFrame, threshold: float, store: Stored, least_estimate: float = LEAST_ESTIMATE) -> DataFrame:
    """Links (u, v) that join the components inside buckets: in each pair of blocks a spanning forest of its links.

    A first pass finds, by samples alone, the rows that have a likely partner; only these are sent with their vectors to
    the second, which verifies likely pairs, most likely first, and skips those already joined.
    """
    keys = ["g", "band", "key"]
    schema = "g long, band int, key long, side int, node long, comp long, bands array<long>, prints binary"

    def sift(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for run in _runs(batches):
            i, j, _ = _likely(run, least_estimate)
            if len(i):
                yield run.take(pa.array(np.unique(np.concatenate([i, j]))))

    def join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for run in _runs(batches):
            node, comp = run.column("node").to_numpy(), run.column("comp").to_pylist()
            ids, w = run.column("ids"), run.column("w")
            parent = {c: c for c in comp}

            def root(c: int) -> int:
                while parent[c] != c:
                    parent[c] = parent[parent[c]]
                    c = parent[c]
                return c

            us, vs = [], []
            for i, j, _ in zip(*(x.tolist() for x in _likely(run, least_estimate))):
                a, b = root(comp[i]), root(comp[j])
                if a != b and weighted_jaccard(ids[i].as_py(), w[i].as_py(), ids[j].as_py(), w[j].as_py()) >= threshold - 1e-9:
                    parent[a] = b
                    us.append(node[i])
                    vs.append(node[j])
            if us:
                yield pa.record_batch([pa.array(us, pa.int64()), pa.array(vs, pa.int64())], names=["u", "v"])

    dealt = _block_pairs(buckets).join(prints, "node").select(*[f.split()[0] for f in schema.split(", ")])
    likely = store.put(dealt.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(sift, schema))
    return likely.join(vecs, "node").repartition(*keys).sortWithinPartitions(*keys).mapInArrow(join, "u long, v long")


def _placed(docs: DataFrame, threshold: float, least_estimate: float = LEAST_ESTIMATE) -> DataFrame:
    """doc_id, digest of the text and class (uid of its first row, least doc_id and number of its texts' rows), stored."""
    spark = docs.sparkSession
    store = Stored(spark)
    weights = spark.sparkContext.broadcast(Weights(*frequency_sketch(docs)))
    signed = store.put(signatures(docs, weights).withColumn("uid", row_uid()))
    total = signed.count()
    texts_ = signed.where("digest is not null").groupBy("digest").agg(F.min("uid").alias("node"), F.min("doc_id").alias("least"), F.count(F.lit(1)).alias("n"))
    nodes = store.put(texts_)
    own = signed.where("bands is not null").join(nodes.select(F.col("node").alias("uid")), "uid", "left_semi")
    rows = store.put(own.select(F.col("uid").alias("node"), F.posexplode("bands").alias("band", "key")))
    groups = store.put(rows.groupBy("band", "key").agg(F.min("node").alias("lo"), F.max("node").alias("hi"), F.count(F.lit(1)).alias("n")).where("lo < hi"))
    buckets = store.put(join_skewed(rows, groups, ["band", "key"], "n", total * BANDS))
    pairs = buckets.select("node", F.explode(F.array("lo", "hi")).alias("mate")).where("node <> mate").select(F.least("node", "mate").alias("u"), F.greatest("node", "mate").alias("v")).distinct()
    wanted = buckets.select("node").distinct()
    keyed = signed.select("uid", "doc_id", "digest").join(wanted.withColumnRenamed("node", "uid"), "uid").select(F.col("uid").alias("node"), F.col("doc_id").alias("_d"), "digest")
    texts = docs.select(F.col("doc_id").cast("long").alias("_d0"), F.md5("text").alias("_g0"), "text")
    texts = texts.join(keyed, (F.col("_g0") == F.col("digest")) & F.col("_d0").eqNullSafe(F.col("_d"))).select("node", "text").dropDuplicates(["node"])
    vecs = store.put(vectors(texts, weights))
    links = store.put(verified(pairs, vecs, threshold))
    comp = store.put(components(links, store))

    labelled = buckets.select("band", "key", "node").join(comp, "node", "left").withColumn("comp", F.coalesce("comp", "node"))
    split = labelled.groupBy("band", "key").agg(F.min("comp").alias("a"), F.max("comp").alias("b"), F.count(F.lit(1)).alias("n")).where("a < b").select("band", "key", "n")
    open_ = store.put(join_skewed(labelled, split, ["band", "key"], "n", total * BANDS))
    prints = signed.select(F.col("uid").alias("node"), "bands", "prints")
    wanted = prints.join(open_.select("node").distinct(), "node", "left_semi")
    more = store.put(across(open_, wanted, vecs, threshold, store, least_estimate))
    comp = store.put(components(links.unionByName(more), store))

    linked = store.put(nodes.join(comp, "node"))
    classes_ = linked.groupBy("comp").agg(F.min("least").alias("class_least"), F.count(F.lit(1)).alias("m"))
    of_linked = join_skewed(linked, classes_, ["comp"], "m", total)
    alone = nodes.where("n > 1").join(comp, "node", "left_anti").select("digest", F.col("node").alias("comp"), F.col("least").alias("class_least"), "n")
    by_text = store.put(of_linked.select("digest", "comp", "class_least", "n").unionByName(alone))  # all other texts have one row
    sent = signed.select("doc_id", "uid", "digest")
    many = F.broadcast(by_text.where(F.col("n") >= max(HEAVY_LEAST, total // HEAVY_PARTS)).select(F.col("digest"), F.col("comp").alias("_c"), F.col("class_least").alias("_l")))  # at most HEAVY_PARTS rows
    few = by_text.where(F.col("n") < max(HEAVY_LEAST, total // HEAVY_PARTS)).drop("n")
    placed = sent.join(many, "digest").select("doc_id", "digest", F.col("_c").alias("comp"), F.col("_l").alias("class_least"))
    rest = sent.join(many.select("digest"), "digest", "left_anti").join(few, "digest", "left")
    single = F.col("comp").isNull()
    rest = rest.select("doc_id", "digest", F.when(single, F.col("uid")).otherwise(F.col("comp")).alias("comp"), F.when(single, F.col("doc_id")).otherwise(F.col("class_least")).alias("class_least"))
    return store.put(placed.unionByName(rest))


def classes(docs: DataFrame, threshold: float = THRESHOLD, least_estimate: float = LEAST_ESTIMATE) -> DataFrame:
    """doc_id and class_id of every row of (doc_id, text): the least doc_id among the rows its near duplicates link it to.

    Equal texts share a class.  Texts without a word have no shingles and share a class only with equal texts; a null
    text is a class of its own.  Repeated rows give repeated rows.  A class of null doc_ids alone has a null class_id.
    Empty table: empty result.  least_estimate 0: every pair of a bucket is verified.
    """
    return _placed(docs, threshold, least_estimate).select("doc_id", F.col("class_least").alias("class_id"))


def keep_one(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """One row of each class: that of the least doc_id (null last), then of the least digest; columns as they are.

    Rows with the same doc_id and text are copies, of which one stays.  A null text is a class of its own.
    """
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "digest")).alias("r")
    kept = _placed(docs, threshold).groupBy("comp").agg(first).select("r.doc_id", "r.digest").distinct()
    digest = fresh(docs, "_digest")
    marked = docs.withColumn(digest, F.md5("text"))
    chosen = marked.join(kept, marked["doc_id"].cast("long").eqNullSafe(kept["doc_id"]) & marked[digest].eqNullSafe(kept["digest"]), "left_semi")
    return chosen.dropDuplicates(["doc_id", digest]).drop(digest)
