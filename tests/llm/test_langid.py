import zlib

import numpy as np
from helpers import SMALL

from hypertriad.llm import langid


def test_presence_kernel_against_sets():
    texts = ["Abc abd", "abd!", "ünï"]

    def grams(t):
        b = b" " + t.lower().encode().translate(langid._BLANK) + b" "
        return {b[i : i + n] for n in langid.ORDERS for i in range(len(b) - n + 1)}

    k = langid.presence(texts) @ langid.presence(texts).T
    for i, a in enumerate(texts):
        for j, b in enumerate(texts):
            want = len(grams(a) & grams(b)) / (len(grams(a)) * len(grams(b))) ** 0.5
            assert abs(k[i, j] - want) < 0.03
    assert langid.presence([""]).sum() >= 0


def test_held_out_accuracy(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    lang = {r["doc_id"]: r["lang"] for r in docs.collect()}
    got = langid.predict_documents(docs).collect()
    assert len(got) == len(lang)
    held = [r for r in got if r["held_out"]]
    assert {r["doc_id"] for r in held} == {d for d in lang if zlib.crc32(str(d).encode()) % 4 == 2}
    assert np.mean([r["lang_pred"] == lang[r["doc_id"]] for r in held]) > 0.98
    assert all(0 <= r["score"] <= 1 for r in got)


def test_labels_and_ids_are_no_inputs(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").limit(300).cache()
    model = langid.fit(langid.training_rows(docs))
    a = langid.identify(docs, model).select("doc_id", "_language").collect()
    b = langid.identify(docs.selectExpr("doc_id", "text", "'xx' AS lang", "'y' AS source"), model).select("doc_id", "_language").collect()
    assert sorted(a) == sorted(b)


def test_odd_documents(spark, odd_docs, no_docs):
    got = {r["doc_id"]: r for r in langid.predict_documents(odd_docs).collect() if r["doc_id"] is not None}
    assert {got[k]["lang_pred"] for k in (0, 1, 2, 3, 8)} == {"und"} and got[0]["score"] == 0
    assert langid.predict_documents(no_docs).count() == 0
    unlabelled = odd_docs.withColumn("lang", odd_docs["lang"].substr(9, 1)).selectExpr("doc_id", "text", "CAST(NULL AS STRING) AS lang")
    assert {r["lang_pred"] for r in langid.predict_documents(unlabelled).collect()} == {"und"}


def test_stage_keeps_clean_documents(spark, odd_docs):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    kept = langid.keep_identified(docs)
    assert kept.columns == docs.columns and kept.count() == docs.count()
    assert {r["text"] for r in langid.keep_identified(odd_docs).select("text").collect()} & {None, "", "!!! $$$ 123"} == set()


def test_training_rows_are_bounded(spark, monkeypatch):
    monkeypatch.setattr(langid, "TRAIN_PER_LANGUAGE", 5)
    own = next(k for k in range(9) if zlib.crc32(str(k).encode()) % 4 != 2)
    docs = spark.range(400).selectExpr(f"{own} AS doc_id", "concat('text ', id) AS text", "'en' AS lang")  # one doc_id has all rows
    assert len(langid.training_rows(docs)) == 5
    docs = spark.range(400).selectExpr(f"{own} AS doc_id", "'one text' AS text", "'en' AS lang")  # one row, repeated
    assert len(langid.training_rows(docs)) == 5
    docs = spark.range(400).selectExpr("id AS doc_id", "concat('text ', id) AS text", "if(id % 2 = 0, 'en', 'de') AS lang")
    rows = langid.training_rows(docs)
    assert 0 < len(rows) <= 10 and rows == langid.training_rows(docs.repartition(7))


def test_stage_keeps_columns_of_its_own_names(spark):
    docs = spark.sql("SELECT 1L AS doc_id, 'ein kurzer Text' AS text, 'de' AS lang, 'a' AS _language, 'b' AS _LANGUAGE_")
    assert langid.keep_identified(docs).collect() == docs.collect()


def test_every_label_can_be_learned(spark):
    docs = spark.range(900).selectExpr("id AS doc_id", "repeat(concat(char(97 + id % 26), char(97 + (id div 26) % 26), ' '), 20) AS text", "concat('l', id % 300) AS lang")
    got = {r["lang"] for r in spark.createDataFrame(langid.training_rows(docs), "text string, lang string").select("lang").distinct().collect()}
    assert got == {f"l{k % 300}" for k in range(900) if zlib.crc32(str(k).encode()) % 4 != 2}
    assert langid.fit([(f"{w} text", w) for w in (f"w{k}" for k in range(250))]).fold.shape[1] == 250
