"""The pipeline on awkward documents, and its parts held against their own rules."""

from collections import Counter

import corpus_pipeline
from cardsketch.llm import jaccard, secrets


def test_stages(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    x = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = {r["doc_id"]: r for r in x.collect()}
        y = stage(spark, x, sf_dir)
        assert y.columns == docs.columns
        rows = y.collect()
        after = {r["doc_id"]: r for r in rows}
        assert len(rows) == len(after) and set(after) <= set(before)
        if name == "near_dedup":
            cls = {r["id"]: r["component_id"] for r in jaccard.classes(x).collect()}
            assert set(after) == set(cls.values()) and all(r["text"] == before[i]["text"] for i, r in after.items())
        if name in ("secrets", "mixing"):
            assert set(after) == set(before)
        if name == "secrets":
            assert not any(secrets.base_spans(r["text"]) for r in rows)
        if name == "mixing":
            assert after == before
        x = spark.createDataFrame(rows, docs.schema)
    pieces = corpus_pipeline.STAGES[-1][1](spark, x, sf_dir).collect()
    assert {r["doc_id"] for r in pieces} == {r["doc_id"] for r in rows}
    whole = corpus_pipeline.run(spark, sf_dir).collect()
    assert Counter(tuple(r)[:5] for r in whole) == Counter(tuple(r)[:5] for r in pieces)


def test_odd_documents(spark, sf_dir):
    rows = [(1, None, None, None, None, "k"), (1, None, None, None, None, "k"), (2, "", "en", "a", 0, "k"), (None, "some words", "en", None, 10, "k"), (3, "token = abcdefgh12 " * 3000, "en", "a", 9, None)]
    x = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, slot string")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        y = stage(spark, x, sf_dir)
        assert y.columns == x.columns
        x = spark.createDataFrame(y.collect(), x.schema)
    assert {r["doc_id"] for r in x.collect()} == {1, 3, None}
    empty = spark.createDataFrame([], x.schema)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty, sf_dir).count() == 0
