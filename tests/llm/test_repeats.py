"""Repeated byte strings and passages of words against a count of every window."""

import re
from collections import Counter

import numpy as np
import pytest

from cardsketch.llm import pfp

WORDS = 50


def slow_left(rows, length, words):
    """(passages, words in them, what is left) of each text."""
    data = [(t or "").encode() for _, t in rows]
    at = [[m.span() for m in re.finditer(rb"[^\x20\x09-\x0D]+", b)] for b in data]
    word = [[b[x:y].lower() for x, y in p] for b, p in zip(data, at)]
    by_bytes, by_words = Counter(), Counter()
    for b, w in zip(data, word):
        by_bytes.update(b[p:p + length] for p in range(len(b) - length + 1))
        by_words.update(tuple(w[p:p + words]) for p in range(len(w) - words + 1))
    out = []
    for b, w, p in zip(data, word, at):
        gone, cut = np.zeros(len(b), bool), np.zeros(len(w), bool)
        for k in range(len(b) - length + 1):
            if by_bytes[b[k:k + length]] > 1:
                gone[k:k + length] = True
        for k in range(len(w) - words + 1):
            if by_words[tuple(w[k:k + words])] > 1:
                cut[k:k + words] = True
        runs = np.flatnonzero(np.diff(np.concatenate(([0], cut.astype(int), [0])))).reshape(-1, 2)
        for x, y in runs:
            gone[p[x][0]:p[y - 1][1]] = True
        out.append((len(runs), int(cut.sum()), bytes(np.frombuffer(b, np.uint8)[~gone]).decode("utf-8", "replace")))
    return out


def test_passages_of_words(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    want = dict(zip((i for i, _ in rows), slow_left(rows, 400, WORDS)))
    got = {r["doc_id"]: (r["n_passages"], r["passage_words"], r["text"]) for r in pfp.remove_repeats(docs, words=WORDS, with_text=True).collect()}
    assert got == want


@pytest.mark.parametrize("n", [51, 58, 66, 80])
def test_planted_passages_short_of_400_bytes(spark, n):
    """Two documents share a passage of n words, of about six bytes each, and are otherwise unlike."""
    rng = np.random.default_rng(n)
    text = lambda k: " ".join("".join(rng.choice(list("abcdefghijklmnop"), rng.integers(2, 9))) for _ in range(k))
    shared, rows = text(n), []
    for i in range(6):
        a, b = text(70), text(90)
        rows.append((i, f"{a} {shared} {b}" if i < 2 else f"{a} {b}", "x", 1))
    rows += [(6, None, None, 2), (7, "", None, 3), (8, shared.upper(), None, 4)]
    got = {r["doc_id"]: r for r in pfp.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string, th string, law int"), words=WORDS, with_text=True).collect()}
    long = len(shared.encode()) >= 400
    for i in (0, 1):
        assert shared not in got[i]["text"] and (got[i]["n_passages"], got[i]["passage_words"]) == (1, n)
        assert (got[i]["n_removed"] >= 400) == long
    assert got[8]["n_passages"] == 1 and got[8]["n_removed"] == 0 and got[8]["text"] == ""
    for i in range(2, 6):
        assert got[i]["text"] == rows[i][1] and got[i]["n_passages"] == got[i]["n_removed"] == 0
    assert got[6]["text"] == got[7]["text"] == ""


def test_many_cut_texts_move_by_key(spark, sf_dir, monkeypatch):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    a = sorted(map(tuple, pfp.remove_repeats(docs, words=WORDS, with_text=True).collect()))
    monkeypatch.setattr(pfp, "SENT", 0)
    assert a == sorted(map(tuple, pfp.remove_repeats(docs, words=WORDS, with_text=True).collect()))


def test_ranges_are_short_rows_and_need_no_sort_to_be_counted(spark, sf_dir, monkeypatch):
    """Tables with a row a range hold longs only, seven at most, and are aggregated by hash."""
    seen, store = [], pfp.stored
    monkeypatch.setattr(pfp, "stored", lambda df: seen.append((df.columns, df._jdf.queryExecution().executedPlan().toString())) or store(df))
    pfp.remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet"), words=WORDS)
    tables = [x for x in seen if "s" in x[0]]
    assert len(tables) >= 6
    for columns, plan in tables:
        assert len(columns) <= 7 and "law" not in columns and "SortAggregate" not in plan


@pytest.mark.parametrize("span", [256, 40])
def test_packed_ranges(span):
    rng = np.random.default_rng(span)
    law, t = rng.integers(0, 2, 1000), rng.integers(span, 1 << 31, 1000)
    hi = t - rng.integers(0, span, 1000)
    lo = np.maximum(hi - rng.integers(0, span, 1000), t - span + 1)
    for a, b in zip((law, t, lo, hi), pfp.unpacked(pfp.packed(law, t, lo, hi))):
        assert (a == b).all()
