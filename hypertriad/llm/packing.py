"""Best-fit packing of token sequences, planned on the histogram of lengths.

Documents are tokenised and only those above the capacity are cut.  A packing depends on how many pieces there are of
each length, so the plan is made on at most ``capacity`` counts, whatever the number of pieces: large items (above a
third of the capacity; at most two fit a bin) are paired greedily, longest with the longest that fits, then smaller ones
go, longest first, each into the bin with the least sufficient gap.  Bins with equal contents are one group with a
count, so plan and work stay bounded by the capacity.  The pieces of a length are numbered without gaps, and a piece's
number says, by the plan, which bin of which group it goes to and where.
"""

from __future__ import annotations

import base64
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import public_tokenizers
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Stored, gapless, row_uid

CAPACITY = 1024
END_ID = 2
BATCH_CHARS = 4_000_000


class Tokens:
    """ids of a text under byte_bpe_50k; the rank form of the vocabulary is read, as it encodes four times as fast."""

    def __init__(self, vocabulary: str, pattern: str):
        import tiktoken

        with open(vocabulary, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self._encoding = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})

    def ids(self, text: str) -> list[int]:
        return self._encoding.encode_ordinary(text)


def cut(n: int, capacity: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of a sequence of n ids: full pieces, and a shorter first one if need be."""
    first = n % capacity
    return ([(0, first)] if first else []) + [(s, capacity) for s in range(first, n, capacity)]


def pieces(docs: DataFrame, capacity: int = CAPACITY, keep_ids: bool = True, vocabulary: str | None = None) -> DataFrame:
    """Tokenise (doc_id, text) and cut: doc_id, piece, start, length, ids_crc32 and, if asked for, ids.

    Null text counts as empty and gives one piece with the end id alone.  Other columns of ``docs`` are not read.
    """
    vocabulary = vocabulary or public_tokenizers.path("byte_bpe_50k.tiktoken")
    pattern = public_tokenizers.PATTERN
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids array<int>" * keep_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens = Tokens(vocabulary, pattern)
        for batch in batches:
            rows: list[tuple] = []
            held = 0
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                ids = np.array([*tokens.ids(text.as_py() or ""), END_ID], dtype="<u4")
                for k, (s, n) in enumerate(cut(len(ids), capacity)):
                    part = ids[s : s + n]
                    rows.append((doc_id, k, s, n, zlib.crc32(part.tobytes()), *([part.astype("i4")] if keep_ids else [])))
                held += len(ids)
                if held > BATCH_CHARS:
                    yield _batch(rows, keep_ids)
                    rows, held = [], 0
            yield _batch(rows, keep_ids)

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, schema)


def _batch(rows: list[tuple], keep_ids: bool) -> pa.RecordBatch:
    kinds = [("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64())] + [("ids", pa.list_(pa.int32()))] * keep_ids
    cols = list(zip(*rows)) or [()] * len(kinds)
    return pa.record_batch([pa.array(list(c), t) for c, (_, t) in zip(cols, kinds)], names=[n for n, _ in kinds])


class Plan:
    """Which ranks of each length go to which sequence and offset; a few numbers for each group of equal bins."""

    def __init__(self, counts: dict[int, int], capacity: int):
        self.capacity = capacity
        self.groups = [(n, items) for n, items in _groups({k: v for k, v in counts.items() if v}, capacity)]
        used: dict[int, int] = {}
        key, first, offset, sequence = [], [], [], 0
        for n, items in self.groups:
            at = 0
            for length in items:
                start = used.get(length, 0)
                key.append((length << 48) + start)
                first.append(sequence - start)
                offset.append(at)
                used[length] = start + n
                at += length
            sequence += n
        self.sequences = sequence
        order = np.argsort(np.array(key, dtype=np.int64), kind="stable")
        self.key, self.shift, self.offset = (np.array(x, dtype=np.int64)[order] for x in (key, first, offset))

    def place(self, length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at = np.searchsorted(self.key, (length << 48) + rank, side="right") - 1
        return self.shift[at] + rank, self.offset[at]


def _groups(counts: dict[int, int], capacity: int) -> list[tuple[int, list[int]]]:
    """(number of bins, lengths in each) for every group of equal bins."""
    left = dict(counts)
    bins: dict[int, list[tuple[int, list[int]]]] = {}  # gap -> groups

    def add(n: int, items: list[int]) -> None:
        bins.setdefault(capacity - sum(items), []).append((n, items))

    large = [x for x in sorted(left, reverse=True) if 3 * x > capacity]
    for x in large:
        while left[x]:
            mate = next((y for y in large if y <= capacity - x and y <= x and left[y] - (y == x) > 0), None)
            if mate is None:
                add(left[x], [x])
                left[x] = 0
            elif mate == x:
                add(left[x] // 2, [x, x])
                left[x] %= 2
            else:
                n = min(left[x], left[mate])
                add(n, [x, mate])
                left[x] -= n
                left[mate] -= n
    for x in sorted((x for x in left if 3 * x <= capacity), reverse=True):
        small = sorted(g for g in bins if g >= x)
        while left[x] and small:
            gap = small.pop(0)
            per = gap // x  # best fit refills the bin it has just narrowed
            rest: list[tuple[int, list[int]]] = []
            for n, items in bins.pop(gap):
                full = min(n, left[x] // per)
                part = left[x] - full * per if full < n else 0
                part = min(part, per - 1) if full < n else 0
                if full:
                    bins.setdefault(gap - per * x, []).append((full, items + [x] * per))
                if part:
                    bins.setdefault(gap - part * x, []).append((1, items + [x] * part))
                left[x] -= full * per + part
                if n - full - bool(part):
                    rest.append((n - full - bool(part), items))
            if rest:
                bins.setdefault(gap, []).extend(rest)
        if left[x]:
            per = capacity // x
            if left[x] // per:
                add(left[x] // per, [x] * per)
            if left[x] % per:
                add(1, [x] * (left[x] % per))
            left[x] = 0
    return [g for gap in sorted(bins) for g in bins[gap]]


def pack(docs: DataFrame, capacity: int = CAPACITY, keep_ids: bool = True, vocabulary: str | None = None) -> DataFrame:
    """Best-fit packing of (doc_id, text): the columns of ``pieces`` with sequence_id and offset.

    Each sequence is filled from offset 0 without gaps up to at most ``capacity`` ids.  Empty table: empty result.
    Repeated rows are pieces of their own.  Nothing is cut that fits a sequence.
    """
    store = Stored(docs.sparkSession)
    made = store.put(pieces(docs, capacity, keep_ids, vocabulary).withColumn("_uid", row_uid()))
    counts = {r["length"]: r["n"] for r in made.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most ``capacity`` rows
    plan = docs.sparkSession.sparkContext.broadcast(Plan(counts, capacity))
    ranked = gapless(made.select("_uid", "length"), ["length"], "_uid", "_rank", sum(counts.values())) if keep_ids else gapless(made, ["length"], "_uid", "_rank", sum(counts.values()))

    @F.pandas_udf("sequence_id long, offset long")
    def place(length, rank):

        seq, off = plan.value.place(length.to_numpy(np.int64), rank.to_numpy(np.int64))
        return pd.DataFrame({"sequence_id": seq, "offset": off})

    placed = ranked.withColumn("_p", place("length", "_rank"))
    if keep_ids:  # the ids stay out of the numbering's shuffles
        placed = made.join(placed.select("_uid", "_p"), "_uid")
    return placed.select("doc_id", "piece", "start", "length", "ids_crc32", *(["ids"] if keep_ids else []), "_p.sequence_id", "_p.offset")


def sequences(packed: DataFrame) -> DataFrame:
    """The packed rows of a training set: sequence_id and its ids in order (at most the capacity), with piece bounds."""
    parts = F.sort_array(F.collect_list(F.struct("offset", "doc_id", "piece", "ids")))
    return packed.groupBy("sequence_id").agg(parts.alias("p")).select("sequence_id", F.flatten("p.ids").alias("ids"), F.col("p.offset").alias("bounds"), F.col("p.doc_id").alias("doc_ids"))


def ids_bytes(ids: list[int]) -> bytes:
    """ids as unsigned little-endian 32-bit numbers, the form that ids_crc32 is taken of."""
    return struct.pack(f"<{len(ids)}I", *ids)
