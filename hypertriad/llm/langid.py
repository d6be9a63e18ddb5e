"""Language identification by string kernels: Nystroem landmarks and one-versus-rest kernel ridge regression.

The kernel of two texts is the cosine of their presence sets of byte n-grams (n = 2, 3, 4; the blended spectrum), hashed
to a fixed number of columns.  Landmarks drawn from a bounded training sample give Nystroem features; kernel ridge
regression on them gives one score for each language.  As the kernel is a product of presence rows, landmark and ridge
matrices fold into one (columns x languages) matrix, so a batch of whole texts is scored by one matrix product.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import fresh

ORDERS = (2, 3, 4)
COLUMNS = 1 << 15
#: Training rows for each language and for all together, at most (but one for each language at least); their texts are at most
#: MAX_TRAIN_CHARS long.
TRAIN_PER_LANGUAGE, TRAIN_ROWS = 400, 40_000
MAX_TRAIN_CHARS = 50_000
#: Landmarks for each language and for all together, likewise.
LANDMARKS_PER_LANGUAGE, LANDMARKS = 40, 2_000
RIDGE = 1e-2
SHARPNESS = 6.0
UNDETERMINED = "und"

#: ASCII bytes that are not letters become blanks; all other bytes stay.
_BLANK = bytes(b if b >= 128 or chr(b).isalpha() else 32 for b in range(256))
_LETTER = re.compile(r"[^\W\d_]")


def has_letter(text: str | None) -> bool:
    return bool(text) and _LETTER.search(text) is not None


def columns_of(text: str) -> np.ndarray:
    """The hashed column of every n-gram occurrence of the whole text (with repeats)."""
    b = np.frombuffer(b" " + text.lower().encode("utf-8", "replace").translate(_BLANK) + b" ", dtype=np.uint8).astype(np.uint32)
    out, code = [], b
    for n in range(2, max(ORDERS) + 1):
        code = (code[:-1] << np.uint32(8)) | b[n - 1 :]
        if len(code) == 0:
            break
        if n in ORDERS:
            h = (code ^ np.uint32(n * 0x9E3779B1 & 0xFFFFFFFF)) * np.uint32(0x85EBCA6B)
            out.append((h ^ (h >> np.uint32(15))) & np.uint32(COLUMNS - 1))
    return np.concatenate(out) if out else np.zeros(0, np.uint32)


def presence(texts: list[str]) -> np.ndarray:
    """Rows of presence over the hashed columns, scaled to length 1 (no n-gram: zeros)."""
    m = np.zeros((len(texts), COLUMNS), dtype=np.float32)
    for i, t in enumerate(texts):
        m[i, columns_of(t)] = 1
    m /= np.sqrt(np.maximum(m.sum(axis=1, keepdims=True), 1))
    return m


@dataclass
class Model:
    languages: list[str]
    fold: np.ndarray  # columns x languages

    def predict(self, texts: list[str | None], block: int = 64) -> tuple[list[str], np.ndarray]:
        """Language and score (0 to 1) of each whole text; ``und`` and 0 where there is no letter or no model."""
        lang, score = [UNDETERMINED] * len(texts), np.zeros(len(texts))
        if not self.languages:
            return lang, score
        todo = [i for i, t in enumerate(texts) if has_letter(t)]
        for at in range(0, len(todo), block):
            part = todo[at : at + block]
            raw = (presence([texts[i] for i in part]) @ self.fold).astype(np.float64) * SHARPNESS
            e = np.exp(raw - raw.max(axis=1, keepdims=True))
            p = e / e.sum(axis=1, keepdims=True)
            for i, k, s in zip(part, p.argmax(axis=1), p.max(axis=1)):
                lang[i], score[i] = self.languages[k], float(s)
        return lang, score


def fit(rows: list[tuple[str, str]]) -> Model:
    """(text, language) rows to a model; languages are in sorted order, so ties go to the first."""
    rows = [r for r in rows if has_letter(r[0])]
    languages = sorted({r[1] for r in rows})
    if not languages:
        return Model([], np.zeros((COLUMNS, 0), np.float32))
    of: dict[str, list[str]] = {g: [] for g in languages}
    for text, g in rows:
        of[g].append(text)
    each = max(1, min(LANDMARKS_PER_LANGUAGE, LANDMARKS // len(languages)))
    marks = [t for g in languages for t in of[g][:each]]
    z = presence(marks)
    values, vectors = np.linalg.eigh((z @ z.T).astype(np.float64))
    ok = values > 1e-6 * values.max()
    root = vectors[:, ok] / np.sqrt(values[ok])  # K_mm to the power -1/2, on its range
    gram, target = np.zeros((ok.sum() + 1,) * 2), np.zeros((ok.sum() + 1, len(languages)))
    for at in range(0, len(rows), 256):
        part = rows[at : at + 256]
        phi = np.hstack([(presence([t for t, _ in part]) @ z.T).astype(np.float64) @ root, np.ones((len(part), 1))])
        y = np.array([[1.0 if g == h else -1.0 for h in languages] for _, g in part])
        share = np.array([1 / len(of[g]) for _, g in part])[:, None]  # each language weighs the same
        gram += phi.T @ (phi * share)
        target += phi.T @ (y * share)
    w = np.linalg.solve(gram + RIDGE / len(languages) * np.eye(len(gram)), target)
    return Model(languages, (z.T @ (root @ w[:-1])).astype(np.float32))  # a common bias would not change the order


def held_out(doc_id: Column) -> Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2


def training_rows(docs: DataFrame) -> list[tuple[str, str]]:
    """A bounded sample of labelled rows, equally large for each language, drawn by a hash of doc_id and text.

    At most TRAIN_PER_LANGUAGE rows a language, and TRAIN_ROWS in all, reach the driver, however often a doc_id or a row
    repeats; every label that has a usable row has one here.
    """
    able = docs.where(F.col("lang").isNotNull() & ~held_out(F.col("doc_id")) & (F.length("text") <= MAX_TRAIN_CHARS)).select("text", "lang", F.xxhash64("doc_id", "text").alias("h"))
    counts = {r["lang"]: r["n"] for r in able.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}  # a row for each label
    if not counts:
        return []
    each = max(1, min(TRAIN_PER_LANGUAGE, TRAIN_ROWS // len(counts)))
    first = Window.partitionBy("lang").orderBy("h", "text")  # the limit is taken on each partition before the exchange

    def drawn(rows: DataFrame) -> list:
        return rows.withColumn("r", F.row_number().over(first)).where(F.col("r") <= each).collect()

    keep = F.element_at(F.create_map(*[F.lit(x) for g, n in counts.items() for x in (g, min(1.0, 1.5 * each / n))]), F.col("lang"))
    rows = drawn(able.where(F.pmod("h", F.lit(1_000_003)) < keep * 1_000_003))  # about 600 rows a language go on
    if missing := sorted(set(counts) - {r["lang"] for r in rows}):
        rows += drawn(able.where(F.col("lang").isin(missing)))
    return [(r["text"], r["lang"]) for r in sorted(rows, key=lambda r: (r["lang"], r["r"]))]


def identify(docs: DataFrame, model: Model, out: str = "_language") -> DataFrame:
    """``docs`` with a struct column ``out`` (lang_pred, score) for every whole text; all other columns stay."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("lang_pred string, score double")
    def predict(s: pd.Series) -> pd.DataFrame:
        lang, score = sent.value.predict([t if isinstance(t, str) else None for t in s])
        return pd.DataFrame({"lang_pred": lang, "score": score})

    return docs.withColumn(out, predict("text"))


def predict_documents(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred and score for every document; see the module's limits on what is learned from.

    Null texts and texts without a letter are ``und`` with score 0, and so are all without a label to learn from.  A row for
    each row, repeated ones too; other columns are not read.  Empty table: empty result.
    """
    model = fit(training_rows(docs))
    return identify(docs.select("doc_id", "text"), model).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "_language.lang_pred", "_language.score")


def keep_identified(docs: DataFrame, least: float = 0.3) -> DataFrame:
    """The documents whose language is determined with a score of at least ``least``; columns as they are, whatever their names.

    Null texts and texts without a letter go; empty table: empty result.
    """
    out = fresh(docs, "_language")
    found = identify(docs, fit(training_rows(docs)), out)
    return found.where((F.col(f"{out}.lang_pred") != UNDETERMINED) & (F.col(f"{out}.score") >= least)).drop(out)
