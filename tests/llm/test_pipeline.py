"""The pipeline against a plain version of each stage on the stage's own input."""

import numpy as np

import corpus_pipeline
from starwatch.llm import tokens

SF = "/root/testdata/sf0.001"


def test_stages_in_order_and_columns(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language_id", "line_dedup", "near_copies", "decontamination", "packing"]
    before = docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, SF).cache()
        assert docs.columns == list(corpus_pipeline.COLUMNS), name
        now = docs.count()
        assert 0 < now <= before
        before = now
    shingles = {r.doc_id: {tuple(w[i : i + 5]) for w in [r.text.lower().split()] for i in range(max(1, len(w) - 4))} for r in docs.collect() if r.text and r.text.split()}
    ids = list(shingles)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            x, y = shingles[a], shingles[b]
            assert 100 * len(x & y) < 80 * len(x | y)
    lib = tokens.library(tokens.vocabulary_path())
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, SF).collect()
    want = {r.doc_id: len(lib.encode(r.text or "", add_special_tokens=False).ids) + 1 for r in docs.collect()}
    got = {}
    for r in packed:
        got[r.doc_id] = got.get(r.doc_id, 0) + r.length
    assert got == want
    assert np.isclose(sum(got.values()), sum(want.values()))
