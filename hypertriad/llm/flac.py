"""FLAC as a media column: lossless 8-bit mono streams, checked and decoded to PCM blocks with sample offsets.

Frames of many rows are coded together: Rice codes, residuals and checksums are numpy operations over up to FRAMES frames
at once, one sample position of all frames at a time where a code's place depends on the one before.  The decoder reads
constant, verbatim, fixed and linear-prediction subframes with partitioned Rice residuals, verifies CRC-8, CRC-16 and
MD5, and takes what the batched path does not know (other partitions, wasted bits) through a bit reader.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCK = 4096
FRAMES = 384
RATE = 8000
BATCH_BYTES = 2_000_000
PAD = 64


class Corrupt(ValueError):
    """A stream that fails a checksum or cannot be parsed."""


# --- checksums ------------------------------------------------------------------------------------------------------


def _table(poly: int, bits: int) -> np.ndarray:
    out = np.arange(256, dtype=np.int64) << (bits - 8)
    for _ in range(8):
        out = np.where(out >> (bits - 1) & 1, out << 1 ^ poly, out << 1) & ((1 << bits) - 1)
    return out


@lru_cache(maxsize=1)
def _crc8_table() -> list[int]:
    return _table(0x07, 8).tolist()


def crc8(data: bytes) -> int:
    c, t = 0, _crc8_table()
    for b in data:
        c = t[c ^ b]
    return c


@lru_cache(maxsize=1)
def _crc16_places() -> np.ndarray:
    """[d, b]: what byte b adds to the CRC-16 when d bytes follow it."""
    first = _table(0x8005, 16)
    out, row = np.empty((2 * BLOCK, 256), np.uint16), first
    for d in range(len(out)):
        out[d] = row
        row = (row << 8 & 0xFFFF) ^ first[row >> 8]
    return out


def crc16(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """CRC-16 of the adjoining byte ranges [start, end) of buf; a checksum is linear, so it is an exclusive or of places."""
    lens = ends - starts
    table = _crc16_places()
    if lens.max(initial=0) > len(table):
        return np.array([_crc16_long(buf[a:b]) for a, b in zip(starts, ends)])
    follow = np.repeat(ends, lens) - 1 - np.arange(starts[0], ends[-1])
    return np.bitwise_xor.reduceat(table[follow, buf[starts[0] : ends[-1]]], starts - starts[0])


def _crc16_long(part: np.ndarray) -> int:
    c, first = 0, _table(0x8005, 16).tolist()
    for b in part.tolist():
        c = (c << 8 & 0xFFFF) ^ first[c >> 8 ^ b]
    return c


# --- encoding -------------------------------------------------------------------------------------------------------


def _coded_number(n: int) -> bytes:
    """A frame number in the extended UTF-8 form."""
    if n < 0x80:
        return bytes([n])
    extra = 1
    while n >= 1 << (5 * extra + 6):
        extra += 1
    lead = (0xFF00 >> (extra + 1)) & 0xFF
    return bytes([lead | n >> 6 * extra, *(0x80 | n >> 6 * k & 0x3F for k in range(extra - 1, -1, -1))])


def frame_header(number: int, samples: int) -> bytes:
    """Fixed block size, explicit 16-bit length, rate as in the stream, mono, 8 bits."""
    head = b"\xff\xf8\x70\x02" + _coded_number(number) + struct.pack(">H", samples - 1)
    return head + bytes([crc8(head)])


def encode_frames(blocks: list[np.ndarray], numbers: list[int]) -> list[bytes]:
    """Frames of int8 blocks: the best of fixed orders 0 to 2 with one Rice partition, or constant or verbatim."""
    n = np.array([len(b) for b in blocks])
    x = np.zeros((len(blocks), n.max()), np.int32)
    for i, b in enumerate(blocks):
        x[i, : len(b)] = b
    inside = np.arange(x.shape[1]) < n[:, None]
    folded, cost = [], []
    for order in range(3):
        r = np.diff(x, n=order, axis=1)
        u = (r << 1) ^ (r >> 31)
        u[~inside[:, order:]] = 0
        folded.append(u)
        cost.append(u.sum(axis=1))
    order = np.argmin(cost, axis=0)
    order[n <= 2] = 0
    count = n - order
    mean = np.min(cost, axis=0) / np.maximum(count, 1)
    k = np.clip(np.floor(np.log2(mean * 0.7 + 1e-9)), 0, 14).astype(np.int64)
    parts = [folded[o][i, : count[i]] for i, o in enumerate(order)]
    u = np.concatenate(parts).astype(np.int64)
    kk = np.repeat(k, count)
    q = u >> kk
    size = q + 1 + kk
    first = np.cumsum(count) - count
    bits = np.add.reduceat(size, first)
    constant = (x == x[:, :1]).astype(bool) | ~inside
    constant = constant.all(axis=1)
    verbatim = ~constant & (bits + 10 + 8 * order >= 8 * n)
    heads = [frame_header(number, int(s)) for number, s in zip(numbers, n)]
    body = np.where(constant, 2, np.where(verbatim, 1 + n, 1 + order + (10 + bits + 7) // 8))
    length = np.array([len(h) for h in heads]) + body + 2
    start = np.cumsum(length) - length
    rice_at = (start + [len(h) for h in heads] + 1 + order) * 8 + 10
    coded = ~(constant | verbatim)
    on = np.repeat(coded, count)
    begin = np.cumsum(size) - size
    at = (begin - np.repeat(begin[first], count) + np.repeat(rice_at, count))[on]
    q, kk, u = q[on], kk[on], u[on]
    flat = np.zeros(int(length.sum()) * 8, np.uint8)
    stop = at + q
    flat[stop] = 1
    for b in range(int(kk.max(initial=0))):
        has = kk > b
        flat[(stop + kk - b)[has]] = (u[has] >> b) & 1
    for b in range(4):
        flat[rice_at[coded] - 1 - b] = (k[coded] >> b) & 1
    out = np.packbits(flat)
    for i, h in enumerate(heads):
        s = int(start[i])
        out[s : s + len(h)] = np.frombuffer(h, np.uint8)
        s += len(h)
        raw = blocks[i].view(np.uint8)
        if constant[i]:
            out[s : s + 2] = (0, raw[0])
        elif verbatim[i]:
            out[s] = 0x02
            out[s + 1 : s + 1 + len(raw)] = raw
        else:
            out[s] = (8 + order[i]) << 1
            out[s + 1 : s + 1 + order[i]] = raw[: order[i]]
    ends = start + length
    # the two bytes of the checksum are zero here; ranges adjoin, so sum over all and take them out by their length
    sums = crc16_of(out, start, ends - 2)
    out[ends - 2], out[ends - 1] = sums >> 8, sums & 0xFF
    return [out[a:b].tobytes() for a, b in zip(start, ends)]


def crc16_of(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """CRC-16 of byte ranges that need not adjoin."""
    lens = ends - starts
    at = np.arange(lens.sum()) + np.repeat(starts - (np.cumsum(lens) - lens), lens)
    packed_ends = np.cumsum(lens)
    return crc16(buf[at], packed_ends - lens, packed_ends).astype(np.int64)


def lpc_frame(block: np.ndarray, number: int, order: int, precision: int = 12) -> bytes:
    """One frame by linear prediction with quantised least-squares coefficients (for tonal signals; the texts' streams
    do not gain by it).  ``block``: int8, longer than the order."""
    x = block.astype(np.int64)
    past = np.stack([x[order - 1 - j : len(x) - 1 - j] for j in range(order)], axis=1).astype(float)
    coef = np.linalg.lstsq(past, x[order:].astype(float), rcond=None)[0]
    top = np.abs(coef).max(initial=1e-9)
    shift = int(np.clip(precision - 1 - np.ceil(np.log2(top + 1e-9)) - 1, 0, 15))
    qc = np.clip(np.round(coef * 2**shift), -(2 ** (precision - 1)), 2 ** (precision - 1) - 1).astype(np.int64)
    r = x[order:] - ((past.astype(np.int64) @ qc) >> shift)
    u = (r << 1) ^ (r >> 63)
    k = int(np.clip(np.floor(np.log2(u.mean() * 0.7 + 1e-9)), 0, 14))
    bits = f"0{32 + order - 1:06b}0" + "".join(f"{v & 0xFF:08b}" for v in x[:order].tolist()) + f"{precision - 1:04b}{shift:05b}"
    bits += "".join(f"{v & (1 << precision) - 1:0{precision}b}" for v in qc.tolist()) + f"000000{k:04b}"
    bits += "".join("0" * (v >> k) + "1" + (f"{v & (1 << k) - 1:0{k}b}" if k else "") for v in u.tolist())
    bits += "0" * (-len(bits) % 8)
    frame = frame_header(number, len(x)) + int(bits, 2).to_bytes(len(bits) // 8, "big")
    return frame + struct.pack(">H", _crc16_long(np.frombuffer(frame, np.uint8)))


def container(frames: list[bytes], sizes: list[int], md5: bytes) -> bytes:
    """The stream: STREAMINFO, a SEEKTABLE with a point for each frame, and the frames."""
    lens = [len(f) for f in frames]
    info = struct.pack(">HH", BLOCK, BLOCK) + min(lens).to_bytes(3, "big") + max(lens).to_bytes(3, "big")
    info += (RATE << 44 | 0 << 41 | 7 << 36 | sum(sizes)).to_bytes(8, "big") + md5
    points, sample, offset = [], 0, 0
    for n, size in zip(lens, sizes):
        points.append(struct.pack(">QQH", sample, offset, size))
        sample, offset = sample + size, offset + n
    table = b"".join(points)
    return b"fLaC" + b"\x00" + len(info).to_bytes(3, "big") + info + b"\x83" + len(table).to_bytes(3, "big") + table + b"".join(frames)


def encode(payloads: list[bytes]) -> list[bytes]:
    """Streams of non-empty payloads; bytes 0 to 255 are samples -128 to 127."""
    blocks, numbers, owner = [], [], []
    samples = [(np.frombuffer(p, np.uint8) ^ 0x80).view(np.int8) for p in payloads]
    for i, x in enumerate(samples):
        for k in range(0, len(x), BLOCK):
            blocks.append(x[k : k + BLOCK])
            numbers.append(k // BLOCK)
            owner.append(i)
    frames: list[bytes] = []
    for a in range(0, len(blocks), FRAMES):
        frames += encode_frames(blocks[a : a + FRAMES], numbers[a : a + FRAMES])
    of: list[list[int]] = [[] for _ in payloads]
    for j, i in enumerate(owner):
        of[i].append(j)
    return [container([frames[j] for j in js], [len(blocks[j]) for j in js], hashlib.md5(samples[i].tobytes()).digest()) for i, js in enumerate(of)]


# --- decoding -------------------------------------------------------------------------------------------------------


@dataclass
class Header:
    number: int
    samples: int
    body: int  # where the subframe begins


def read_header(data: bytes, at: int) -> Header | None:
    """The frame header at a place, if there is one with a right CRC-8: mono, 8 bits, fixed block size."""
    if data[at : at + 2] != b"\xff\xf8" or len(data) < at + 6:
        return None
    code, rate, channels, depth = data[at + 2] >> 4, data[at + 2] & 15, data[at + 3] >> 4, data[at + 3] >> 1 & 7
    p, lead = at + 4, data[at + 4]
    extra = 0
    if lead >= 0x80:
        ones = 8 - (lead ^ 0xFF).bit_length()
        if ones < 2 or ones > 7:
            return None
        extra, number = ones - 1, lead & (0x7F >> ones)
        for b in data[p + 1 : p + 1 + extra]:
            number = number << 6 | b & 0x3F
    else:
        number = lead
    p += 1 + extra
    if code == 6:
        samples, p = data[p] + 1, p + 1
    elif code == 7:
        samples, p = int.from_bytes(data[p : p + 2], "big") + 1, p + 2
    else:
        samples = 192 if code == 1 else 576 << code - 2 if 2 <= code <= 5 else 256 << code - 8 if code >= 8 else 0
    p += {12: 1, 13: 2, 14: 2}.get(rate, 0)
    if not samples or channels or depth not in (0, 1) or p >= len(data) or crc8(data[at:p]) != data[p]:
        return None
    return Header(number, samples, p + 1)


@dataclass
class Stream:
    frames: list[tuple[int, int, Header]]  # begin, end, header
    md5: bytes
    total: int


def parse(data: bytes) -> Stream:
    """Metadata and frame bounds.  A frame ends where a valid header with the next number begins and its CRC-16 holds."""
    if data[:4] != b"fLaC":
        raise Corrupt("no stream marker")
    at, last, md5, total = 4, False, b"", 0
    while not last:
        if at + 4 > len(data):
            raise Corrupt("metadata cut short")
        last, kind, size = data[at] >> 7, data[at] & 0x7F, int.from_bytes(data[at + 1 : at + 4], "big")
        if kind == 0:
            total = int.from_bytes(data[at + 14 : at + 22], "big") & (1 << 36) - 1
            md5 = data[at + 22 : at + 38]
        at += 4 + size
    frames, begin, head = [], at, read_header(data, at)
    while begin < len(data):
        if head is None:
            raise Corrupt(f"no frame header at byte {begin}")
        nxt, follows = data.find(b"\xff\xf8", head.body + 1), None
        while nxt >= 0:
            follows = read_header(data, nxt)
            if follows and follows.number == head.number + 1 and _crc16_long_ok(data, begin, nxt):
                break
            nxt = data.find(b"\xff\xf8", nxt + 1)
        end = nxt if nxt >= 0 else len(data)
        frames.append((begin, end, head))
        begin, head = end, follows
    return Stream(frames, md5, total)


def _crc16_long_ok(data: bytes, begin: int, end: int) -> bool:
    part = np.frombuffer(data, np.uint8, end - begin, begin)
    return len(part) > 2 and int(crc16(part, np.array([0]), np.array([len(part)]))[0]) == 0


class Bits:
    """A bit reader for the frames that the batched path leaves."""

    def __init__(self, data: bytes, at: int):
        self.data, self.at = data, at * 8

    def take(self, n: int) -> int:
        if self.at + n > 8 * len(self.data):
            raise Corrupt("frame cut short")
        first, last = self.at >> 3, self.at + n + 7 >> 3
        v = int.from_bytes(self.data[first:last], "big") >> (8 * last - self.at - n) & (1 << n) - 1
        self.at += n
        return v

    def signed(self, n: int) -> int:
        v = self.take(n)
        return v - (1 << n) if n and v >> n - 1 else v

    def zeros(self) -> int:
        n = 0
        while not self.take(1):
            n += 1
        return n


def read_subframe(data: bytes, head: Header, depth: int = 8) -> np.ndarray:
    """The samples of any mono subframe, one code at a time."""
    b = Bits(data, head.body)
    kind = b.take(8) >> 1
    wasted = 0
    if data[head.body] & 1:
        wasted = b.zeros() + 1
        depth -= wasted
    n = head.samples
    if kind == 0:
        out = [b.signed(depth)] * n
    elif kind == 1:
        out = [b.signed(depth) for _ in range(n)]
    elif 8 <= kind <= 12 or kind >= 32:
        order = kind - 8 if kind < 32 else kind - 31
        out = [b.signed(depth) for _ in range(order)]
        coef, shift = ((), (1,), (2, -1), (3, -3, 1), (4, -6, 4, -1))[order] if kind < 32 else None, 0
        if coef is None:
            precision = b.take(4) + 1
            shift = b.signed(5)
            coef = tuple(b.signed(precision) for _ in range(order))
        for r in _residual(b, n, order):
            out.append(r + (sum(c * out[-1 - j] for j, c in enumerate(coef)) >> shift))
    else:
        raise Corrupt(f"reserved subframe kind {kind}")
    return np.array(out, np.int64) << wasted


def _residual(b: Bits, n: int, order: int) -> Iterator[int]:
    method, parts = b.take(2), 1 << b.take(4)
    if method > 1:
        raise Corrupt("reserved residual coding")
    width = 5 if method else 4
    for p in range(parts):
        k = b.take(width)
        raw = b.take(5) if k == (1 << width) - 1 else None
        for _ in range(n // parts - (order if p == 0 else 0)):
            if raw is not None:
                yield b.signed(raw)
            else:
                u = b.zeros() << k
                u |= b.take(k) if k else 0
                yield u >> 1 ^ -(u & 1)


def decode_frames(datas: list[bytes], frames: list[tuple[int, int, int, Header]]) -> list[np.ndarray]:
    """Samples of (stream, begin, end, header) frames, CRC-16 verified; fixed subframes with one partition go together."""
    cut = [datas[i][a:b] for i, a, b, _ in frames]
    lens = np.array([len(c) for c in cut])
    ends = np.cumsum(lens)
    starts = ends - lens
    buf = np.frombuffer(b"".join(cut) + bytes(8), np.uint8)
    wrong = np.flatnonzero(crc16(buf, starts, ends))  # a message with its checksum behind it sums to 0
    if len(wrong):
        raise Corrupt(f"frame checksum of frame {frames[wrong[0]][3].number}")
    out: list = [None] * len(frames)
    fast, info = [], []
    for i, (s, a, _, h) in enumerate(frames):
        d, p = datas[s], h.body
        kind = d[p]
        order = (kind >> 1) - 8
        q = p + 1 + order
        if not kind & 1 and 0 <= order <= 4 and d[q] & 0xFC == 0 and h.samples > order and (k := (d[q] & 3) << 2 | d[q + 1] >> 6) < 15:
            fast.append(i)
            info.append((h.samples - order, order, k, (int(starts[i]) + q - a) * 8 + 10, h.samples))
        elif kind == 2:
            out[i] = np.frombuffer(d, np.int8, h.samples, p + 1)
        else:
            out[i] = read_subframe(d, h).astype(np.int8)
    if fast:
        for i, x in zip(fast, _rice_together(buf, np.array(info, np.int64), [cut[i] for i in fast], [frames[i] for i in fast])):
            out[i] = x
    return out


def _rice_together(buf: np.ndarray, info: np.ndarray, cut: list[bytes], frames: list) -> list[np.ndarray]:
    by = np.argsort(-info[:, 0], kind="stable")
    count, order, k, pos, samples = info[by].T
    bits = np.unpackbits(buf)
    n = len(bits)
    nxt = np.where(bits, np.arange(n, dtype=np.int32), np.int32(n - 1))
    nxt = np.minimum.accumulate(nxt[::-1])[::-1]
    b = buf.astype(np.int32)
    word = np.zeros(len(b), np.int32)
    word[:-2] = b[:-2] << 16 | b[1:-1] << 8 | b[2:]
    u = np.zeros((int(count[0]), len(by)), np.int32)
    active = np.searchsorted(-count, -np.arange(int(count[0])), side="left")  # frames with more than i codes
    pos, k32, step, mask = pos.astype(np.int32), k.astype(np.int32), (k + 1).astype(np.int32), ((1 << k) - 1).astype(np.int32)
    room = (24 - k).astype(np.int32)
    last = n - 1
    for i in range(int(count[0])):
        m = active[i]
        p = pos[:m]
        stop = nxt[p]
        low = stop + 1
        v = word[low >> 3] >> (room[:m] - (low & 7)) & mask[:m]
        u[i, :m] = (stop - p) << k32[:m] | v
        pos[:m] = np.minimum(stop + step[:m], last)
    r = (u >> 1) ^ -(u & 1)
    found: list = [None] * len(by)
    for f, c in enumerate(by):
        o, h = int(order[f]), frames[c][3]
        x = r[: count[f], f].astype(np.int64)
        first = np.frombuffer(cut[c], np.int8, o, h.body - frames[c][1] + 1).astype(np.int64)
        for j in range(o, 0, -1):  # undo one difference at a time
            lead = np.diff(first, n=j - 1)[-1]
            x = lead + np.cumsum(x)
        found[c] = np.concatenate([first, x]).astype(np.int8)
    return found


def decode(datas: list[bytes]) -> list[list[np.ndarray]]:
    """PCM blocks (int8) of whole streams; sample count and MD5 are verified."""
    streams = [parse(d) for d in datas]
    todo = [(i, a, b, h) for i, s in enumerate(streams) for a, b, h in s.frames]
    blocks: list[list[np.ndarray]] = [[] for _ in datas]
    for at in range(0, len(todo), FRAMES):
        part = todo[at : at + FRAMES]
        for (i, *_), x in zip(part, decode_frames(datas, part)):
            blocks[i].append(x)
    for s, xs in zip(streams, blocks):
        if s.total and sum(map(len, xs)) != s.total:
            raise Corrupt("sample count")
        if any(s.md5) and hashlib.md5(b"".join(x.tobytes() for x in xs)).digest() != s.md5:
            raise Corrupt("MD5 of the samples")
    return blocks


def decode_each(datas: list[bytes | None]) -> list[tuple[list[np.ndarray], str]]:
    """PCM blocks and status of every stream: ``ok``, ``missing`` (null) or ``corrupt: `` and the fault, which leaves the
    others as they are."""
    able = [d for d in datas if d is not None]
    try:
        good = iter([(b, "ok") for b in decode(able)])
    except (Corrupt, IndexError, ValueError):
        good = iter([_decode_one(d) for d in able])
    return [([], "missing") if d is None else next(good) for d in datas]


def _decode_one(data: bytes) -> tuple[list[np.ndarray], str]:
    try:
        return decode([data])[0], "ok"
    except (Corrupt, IndexError, ValueError) as fault:
        return [], f"corrupt: {fault}"


# --- Spark ----------------------------------------------------------------------------------------------------------


def payload(text: str | None) -> tuple[int, bytes]:
    """(unpadded length, UTF-8 with zero bytes up to a positive multiple of 64)."""
    b = (text or "").encode("utf-8")
    return len(b), b + bytes(-len(b) % PAD or (0 if b else PAD))


def _grouped(items: Iterator, size) -> Iterator[list]:
    """Runs of items of about BATCH_BYTES; one larger item is a run of its own."""
    held: list = []
    total = 0
    for x in items:
        held.append(x)
        total += size(x)
        if total >= BATCH_BYTES:
            yield held
            held, total = [], 0
    if held:
        yield held


def encode_texts(docs: DataFrame) -> DataFrame:
    """(doc_id, text) to doc_id, n_bytes and media, the FLAC stream of the whole text; null text counts as empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in _grouped(zip(batch.column(0).to_pylist(), batch.column(1)), lambda x: len(x[1].as_py() or "")):
                made = [payload(t.as_py()) for _, t in part]
                yield pa.record_batch([pa.array([d for d, _ in part], pa.int64()), pa.array([n for n, _ in made], pa.int64()), pa.array(encode([p for _, p in made]), pa.binary())], names=["doc_id", "n_bytes", "media"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, n_bytes long, media binary")


def pcm_blocks(media: DataFrame) -> DataFrame:
    """(doc_id, media) to PCM blocks: doc_id, block, sample_offset (for seeking), n_samples, pcm and status.

    A null or corrupt stream gives one row without a block, its status being ``missing`` or ``corrupt: `` and the fault.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in _grouped(zip(batch.column(0).to_pylist(), batch.column(1)), lambda x: len(x[1].as_py() or b"")):
                rows = []
                for (d, _), (xs, status) in zip(part, decode_each([m.as_py() for _, m in part])):
                    at = 0
                    for k, x in enumerate(xs):
                        rows.append((d, k, at, len(x), x.tobytes(), status))
                        at += len(x)
                    if not xs:
                        rows.append((d, None, None, None, None, status))
                cols = list(zip(*rows)) or [()] * 6
                kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.binary(), pa.string())
                yield pa.record_batch([pa.array(list(c), t) for c, t in zip(cols, kinds)], names=["doc_id", "block", "sample_offset", "n_samples", "pcm", "status"])

    return media.select("doc_id", "media").mapInArrow(run, "doc_id long, block int, sample_offset long, n_samples int, pcm binary, status string")


def features(x: np.ndarray) -> str:
    """Samples, energy, sign changes and peak of a signal, as one string of integers."""
    v = x.astype(np.int64)
    return f"{len(v)}:{int((v * v).sum())}:{int(((v[1:] < 0) != (v[:-1] < 0)).sum())}:{int(np.abs(v).max(initial=0))}"


def digests(media: DataFrame) -> DataFrame:
    """What is read back from each stream: hashes of payload, tail and stored form, features, the number of PCM blocks, the
    sample offset of the last one, and the status (as in ``pcm_blocks``; what cannot be read back is null)."""
    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, n_blocks int, last_offset long, status string"
    kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int32(), pa.int64(), pa.string())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in _grouped(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)), lambda x: len(x[2].as_py() or b"")):
                datas = [m.as_py() for _, _, m in part]
                rows = []
                for (d, n, _), m, (xs, status) in zip(part, datas, decode_each(datas)):
                    stored = (None, None) if m is None else (len(m), hashlib.sha256(m).hexdigest())
                    if not xs:
                        rows.append((d, n, None, None, None, *stored, None, None, None, status))
                        continue
                    x = np.concatenate(xs)
                    back = (x.view(np.uint8) ^ 0x80).tobytes()
                    rows.append((d, n, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-PAD:]), *stored, features(x), len(xs), len(x) - len(xs[-1]), status))
                cols = list(zip(*rows))
                yield pa.record_batch([pa.array(list(c), t) for c, t in zip(cols, kinds)], names=[f.split()[0] for f in schema.split(", ")])

    return media.select("doc_id", "n_bytes", "media").mapInArrow(run, schema)


def store_and_read_back(docs: DataFrame) -> DataFrame:
    """The media contract for ``documents``: every whole text stored as FLAC and described from what is read back.

    Null text counts as empty.  A row for each row; equal texts give equal values.  Other columns are not read.  Empty table:
    empty result.
    """
    return digests(encode_texts(docs))
