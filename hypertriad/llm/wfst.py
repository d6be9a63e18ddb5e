"""SentencePiece encoding and decoding by weighted finite-state transducers.

The vocabulary is compiled once into two transducers.  The normaliser rewrites characters (blanks to marks, a leading mark,
squeezed blanks and the model's own character map, whichever the model asks for).  The piece transducer is a trie from whose
final states an arc without input writes a piece, at its weight, and returns to the root; at the root, a character that is no
piece writes its bytes.  An input is composed with both lazily, state by state, and the path of least weight in the tropical
semiring is taken in one pass over the states alive.  Where no piece spans a place, composition and shortest path split there
exactly; the parts recur (they are words, mostly) and their paths are kept in a bounded table.
"""

from __future__ import annotations

import math
import re
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pandas as pd
import public_tokenizers
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MARK = "▁"
#: Weight of one byte-fallback arc: above any sum of pieces of one character.
BYTE_WEIGHT = 1_000.0
KEPT_PATHS = 300_000

# Field numbers and kinds of the public SentencePiece model format.
PIECES, TRAINER, NORMALISER = 1, 2, 3
UNKNOWN, CONTROL, UNUSED, BYTE = 2, 3, 5, 6
UNIGRAM = 1


def _fields(data: bytes) -> Iterator[tuple[int, bytes | int]]:
    """(number, value) of a protocol buffer message."""
    at = 0

    def varint() -> int:
        nonlocal at
        out = shift = 0
        while True:
            b = data[at]
            at += 1
            out |= (b & 0x7F) << shift
            shift += 7
            if b < 0x80:
                return out

    while at < len(data):
        tag = varint()
        kind = tag & 7
        if kind == 0:
            yield tag >> 3, varint()
        else:
            n = varint() if kind == 2 else 8 if kind == 1 else 4
            yield tag >> 3, data[at : at + n]
            at += n


def character_map(blob: bytes) -> dict[str, str]:
    """The rules of a model's character map: a double-array trie of 32-bit units, behind their length in bytes, whose leaves
    name places among zero-ended replacements."""
    if not blob:
        return {}
    size = struct.unpack_from("<I", blob)[0]
    units, texts = np.frombuffer(blob, "<u4", size // 4, 4).tolist(), blob[4 + size :]
    reach = lambda u: (u >> 10) << ((u & 512) >> 6)
    out: dict[str, str] = {}
    todo = [(reach(units[0]), b"")]
    while todo:
        node, key = todo.pop()
        for c in range(1, 256):
            at = node ^ c
            if at < len(units) and units[at] & 0x800000FF == c:
                child = at ^ reach(units[at])
                if units[at] >> 8 & 1:
                    place = units[child] & 0x7FFFFFFF
                    out[(key + bytes([c])).decode("utf-8", "surrogateescape")] = texts[place : texts.index(b"\0", place)].decode()
                todo.append((child, key + bytes([c])))
    return out


@dataclass
class Vocabulary:
    pieces: list[str]
    scores: list[float]
    kinds: list[int]
    unigram: bool
    dummy_prefix: bool = True
    squeeze: bool = False
    charmap: dict[str, str] = field(default_factory=dict)
    escape: bool = True

    @staticmethod
    def read(path: str) -> Vocabulary:
        with open(path, "rb") as f:
            data = f.read()
        pieces, scores, kinds, model, prefix, squeeze, escape, charmap = [], [], [], UNIGRAM, True, True, True, {}
        for n, v in _fields(data):
            if n == PIECES:
                own = dict(_fields(v))
                pieces.append(own.get(1, b"").decode())
                scores.append(struct.unpack("<f", own[2])[0] if 2 in own else 0.0)
                kinds.append(own.get(3, 1))
            elif n == TRAINER:
                model = dict(_fields(v)).get(3, UNIGRAM)
            elif n == NORMALISER:
                own = dict(_fields(v))
                prefix, squeeze, escape, charmap = bool(own.get(3, 1)), bool(own.get(4, 1)), bool(own.get(5, 1)), character_map(own.get(2, b""))
        return Vocabulary(pieces, scores, kinds, model == UNIGRAM, prefix, squeeze, charmap, escape)

    def weights(self) -> list[float]:
        """-log probability of each piece: the score of a unigram model; for merge ranks, Zipf's law over the ranks."""
        if self.unigram:
            return [-s for s in self.scores]
        total = math.log(sum(1 / (2 - s) for s, k in zip(self.scores, self.kinds) if k not in (UNKNOWN, CONTROL, BYTE)))
        return [math.log(2 - s) + total for s in self.scores]


class Normaliser:
    """A sequential transducer over characters.  A state is (what stands before, characters of a rule not yet decided);
    ``step`` gives the output and the next state, ``finish`` the output at the end of the input."""

    START, BODY, GAP = 0, 1, 2

    def __init__(self, v: Vocabulary):
        self.prefix, self.squeeze, self.rules = v.dummy_prefix, v.squeeze, v.charmap
        self.blank = MARK if v.escape else " "
        self.begun = {key[:n] for key in v.charmap for n in range(1, len(key) + 1)}
        self.plain = not v.squeeze and not v.charmap
        self.start = (self.START, "")

    def _write(self, mode: int, text: str) -> tuple[str, int]:
        out = []
        for c in text:
            if c == " " and self.squeeze:
                mode = mode if mode == self.START else self.GAP
                continue
            if mode == self.START and self.prefix or mode == self.GAP:
                out.append(self.blank)
            out.append(self.blank if c == " " else c)
            mode = self.BODY
        return "".join(out), mode

    def _decided(self, mode: int, held: str, end: bool) -> tuple[str, tuple[int, str]]:
        """Applies the longest rule at the front of ``held`` as long as no longer one can follow."""
        out = ""
        while held and (end or held not in self.begun):
            n = next((n for n in range(len(held), 0, -1) if held[:n] in self.rules), 0)
            text, mode = self._write(mode, self.rules[held[:n]] if n else held[0])
            out, held = out + text, held[n or 1 :]
        return out, (mode, held)

    def step(self, state: tuple[int, str], c: str) -> tuple[str, tuple[int, str]]:
        if not self.rules:
            text, mode = self._write(state[0], c)
            return text, (mode, "")
        return self._decided(state[0], state[1] + c, False)

    def finish(self, state: tuple[int, str]) -> str:
        return self._decided(*state, True)[0]

    def apply(self, text: str, state: tuple[int, str] = (START, "")) -> str:
        """The output from a state on.  Without rules and squeezing every character has one arc, so whole strings go at once."""
        if self.plain:
            return (self.blank if self.prefix and text and state[0] == self.START else "") + text.replace(" ", self.blank)
        out = []
        for c in text:
            piece, state = self.step(state, c)
            out.append(piece)
        return "".join(out) + self.finish(state)


class Pieces:
    """The piece transducer.  arcs: for each state the arcs that read a character and write nothing; final: for each state
    the (piece, weight) of its arc that reads nothing, writes the piece and returns to the root, or None.  State 0 is the
    root, the start and the only accepting state; there, a character that is no piece writes its bytes (``fallback``)."""

    def __init__(self, v: Vocabulary):
        self.arcs: list[dict[str, int]] = [{}]
        self.final: list[tuple[int, float] | None] = [None]
        self.byte = {int(p[3:5], 16): i for i, (p, k) in enumerate(zip(v.pieces, v.kinds)) if k == BYTE}
        self.unknown = next((i for i, k in enumerate(v.kinds) if k == UNKNOWN), 0)
        for i, (p, k, w) in enumerate(zip(v.pieces, v.kinds, v.weights())):
            if k in (UNKNOWN, CONTROL, UNUSED, BYTE) or not p:
                continue
            state = 0
            for c in p:
                if c not in self.arcs[state]:
                    self.arcs[state][c] = len(self.arcs)
                    self.arcs.append({})
                    self.final.append(None)
                state = self.arcs[state][c]
            if self.final[state] is None or w < self.final[state][1]:
                self.final[state] = (i, w)

    def fallback(self, c: str) -> tuple[list[int], float]:
        ids = [self.byte[b] for b in c.encode("utf-8", "replace")] if self.byte else [self.unknown]
        return ids, BYTE_WEIGHT * len(ids)


class Composition:
    """The normaliser and the piece transducer as one machine.  The normaliser is sequential, so for one input its output is
    one chain of states, and a composed state is a place in that chain and a state of the pieces, made when it is reached."""

    def __init__(self, first: Normaliser | None, second: Pieces):
        self.first, self.second = first, second

    def chain(self, text: str, state: tuple[int, str] | None = None) -> str:
        """What the pieces read: the normaliser's output from one of its states on."""
        return text if self.first is None else self.first.apply(text, state or self.first.start)

    def shortest(self, text: str, start: tuple[int, str] | None = None) -> tuple[list[int], float]:
        """The tropical shortest path of an input; of equal ones, that whose last piece is longest.  Places are an order of
        the composed states in which every arc leads on, so each state at the root is expanded once, at its least weight."""
        read, arcs, final = self.chain(text, start), self.second.arcs, self.second.final
        n, root = len(read), self.second.arcs[0]
        best, back = [0.0] + [math.inf] * n, [None] * (n + 1)
        for i in range(n):
            here, j, alone = best[i], i, False
            state = root.get(read[i])
            while state is not None:
                j += 1
                got = final[state]
                if got is not None:
                    if j == i + 1:
                        alone = True
                    w = here + got[1]
                    if w < best[j]:
                        best[j], back[j] = w, (i, got[0])
                if j == n:
                    break
                state = arcs[state].get(read[j])
            if not alone:
                ids, w = self.second.fallback(read[i])
                if here + w < best[i + 1]:
                    best[i + 1], back[i + 1] = here + w, (i, ids)
        out: list[int] = []
        at = n
        while at:
            at, ids = back[at]
            if isinstance(ids, int):
                out.append(ids)
            else:
                out += ids[::-1]
        return out[::-1], best[n]


class _Kept(dict):
    """Packed ids and weight of parts, made when asked for; forgets all when it is full."""

    def __init__(self, make):
        super().__init__()
        self.make = make

    def __missing__(self, part: str) -> tuple[bytes, float]:
        ids, weight = self.make(part)
        got = (struct.pack(f"<{len(ids)}I", *ids), weight)
        if len(part) <= 64:
            if len(self) >= KEPT_PATHS:
                self.clear()
            self[part] = got
        return got


class Transducer:
    """The compiled vocabulary: encodes whole texts by shortest paths and decodes ids."""

    def __init__(self, vocabulary: Vocabulary):
        v = self.vocabulary = vocabulary
        self.normaliser, self.pieces = Normaliser(v), Pieces(v)
        self.surface = [bytes([int(p[3:5], 16)]) if k == BYTE else b"" if k in (UNKNOWN, CONTROL) else p.replace(MARK, " ").encode() for p, k in zip(v.pieces, v.kinds)]
        real = [p for p, k in zip(v.pieces, v.kinds) if k not in (UNKNOWN, CONTROL, UNUSED, BYTE)]
        joined = {c for p in real if len(p) > 1 for c in p}
        # parts between which no piece spans: a run of marks with the word after it; characters in no longer piece alone
        alone = re.escape("".join(c for c in map(chr, range(128)) if c not in joined and c != " "))
        self.whole = any(re.search(f"[^{MARK}]{MARK}", p) for p in real) or not v.escape
        marks = f"[{MARK} ]"
        self.parts = re.compile(f"[{alone}]|{marks}*[^{MARK} {alone}]+|{marks}+" if alone else f"{marks}*[^{MARK} ]+|{marks}+", re.S)
        self._ready()

    def _ready(self) -> None:
        """A plain normaliser is composed with the pieces part by part; any other is applied first, as its rules may span
        parts, and the pieces are composed with its output."""
        plain = self.normaliser.plain
        machine = Composition(self.normaliser if plain else None, self.pieces)
        inside = (Normaliser.BODY, "") if plain else None
        self._first, self._inner = _Kept(machine.shortest), _Kept(lambda part: machine.shortest(part, inside))

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k not in ("_first", "_inner")}

    def __setstate__(self, state: dict) -> None:
        self.__dict__ |= state
        self._ready()

    def normalise(self, text: str) -> str:
        return self.normaliser.apply(text)

    def path(self, text: str) -> tuple[list[int], float]:
        """The shortest path of a whole text through the composition of both transducers, in one piece."""
        return Composition(self.normaliser, self.pieces).shortest(text)

    def encode(self, text: str | None) -> tuple[bytes, float]:
        """ids of the whole text as little-endian unsigned 32-bit numbers, and the weight of the path."""
        text = text or ""
        if not self.normaliser.plain:
            text = self.normaliser.apply(text)
        parts = [text] if self.whole and text else self.parts.findall(text)
        if not parts:
            return b"", 0.0
        inner = self._inner
        got = [self._first[parts[0]] if self.normaliser.plain else inner[parts[0]], *[inner[p] for p in parts[1:]]]
        return b"".join([g[0] for g in got]), math.fsum([g[1] for g in got])

    def decode(self, ids: bytes) -> str:
        """The text of ids; the leading blank that the normaliser added goes."""
        surface = self.surface
        raw = b"".join([surface[k] for k in np.frombuffer(ids, "<u4").tolist()])
        text = raw.decode("utf-8", "replace")
        return text[1:] if self.vocabulary.dummy_prefix and text.startswith(" ") else text


@lru_cache(maxsize=2)
def compiled(path: str) -> Transducer:
    return Transducer(Vocabulary.read(path))


def encode_texts(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, ids (array) and weight of every whole text; null text: no ids and weight 0."""
    path = path or public_tokenizers.path("piece_bpe_32k.model")

    @F.pandas_udf("ids array<int>, weight double")
    def run(s: pd.Series) -> pd.DataFrame:
        t = compiled(path)
        got = [t.encode(x if isinstance(x, str) else None) for x in s]
        return pd.DataFrame({"ids": [np.frombuffer(b, "<i4") for b, _ in got], "weight": [w for _, w in got]})

    return docs.select("doc_id", run("text").alias("_r")).select("doc_id", "_r.ids", "_r.weight")


def decode_ids(encoded: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id and text of ids; null ids give a null text."""
    path = path or public_tokenizers.path("piece_bpe_32k.model")

    @F.pandas_udf("string")
    def run(s: pd.Series) -> pd.Series:
        t = compiled(path)
        return pd.Series([None if x is None else t.decode(np.asarray(x, "<u4").tobytes()) for x in s], dtype=object)

    return encoded.select("doc_id", run("ids").alias("text"))


def digests(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, n_ids, ids_crc32 (as in packing), weight of the path, and decoded_crc32 of the decoded text, for every row.

    Null and empty texts: no ids, weight 0.  Repeated rows give repeated rows; other columns are not read.  Empty table: empty
    result.
    """
    path = path or public_tokenizers.path("piece_bpe_32k.model")

    @F.pandas_udf("n_ids long, ids_crc32 long, weight double, decoded_crc32 long")
    def run(s: pd.Series) -> pd.DataFrame:
        t = compiled(path)
        got = [t.encode(x if isinstance(x, str) else None) for x in s]
        return pd.DataFrame({"n_ids": [len(b) // 4 for b, _ in got], "ids_crc32": [zlib.crc32(b) for b, _ in got], "weight": [w for _, w in got], "decoded_crc32": [zlib.crc32(t.decode(b).encode()) for b, _ in got]})

    return docs.select("doc_id", run("text").alias("_r")).select("doc_id", "_r.*")
