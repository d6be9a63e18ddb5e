from helpers import SMALL
from test_neardup import brute

import corpus_pipeline
from hypertriad.llm import langid, neardup, packing, pii


def test_stages_against_brute_force(spark):
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language_id", "near_dedup", "pii", "packing"]
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    kept = [r for r in docs.orderBy("doc_id").collect() if langid.has_letter(r["text"])]
    weights = neardup.Weights(*neardup.frequency_sketch(spark.createDataFrame(kept, docs.schema)))
    first = [r for k, (r, c) in enumerate(zip(kept, brute([r["text"] for r in kept], weights))) if c == k]
    field, want = pii.trained(), {}
    tokens = packing.Tokens(__import__("public_tokenizers").path("byte_bpe_50k.tiktoken"), __import__("public_tokenizers").PATTERN)
    for r in first:
        n = len(tokens.ids(pii.redacted(r["text"], pii.find(r["text"], field)[1]))) + 1
        want[r["doc_id"]] = [x for _, x in packing.cut(n, 1024)]
    got = {}
    for r in corpus_pipeline.run(spark, SMALL).collect():
        got.setdefault(r["doc_id"], {})[r["piece"]] = r["length"]
    assert {k: [v[p] for p in sorted(v)] for k, v in got.items()} == want


def test_stages_on_odd_and_empty(spark, odd_docs, no_docs):
    for docs in (odd_docs, no_docs):
        for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
            out = stage(spark, docs, SMALL)
            assert k == 3 or out.columns == docs.columns
            out.count()
