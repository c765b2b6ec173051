"""The pipeline's near copies against brute force over sets of five-word shingles."""

import math
from collections import Counter, defaultdict

import numpy as np
import pytest

import corpus_pipeline
from cardsketch.llm import common, jaccard, simhash
from cardsketch.llm.common import text_hash
from cardsketch.llm.components import components

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def shingle_sets(rows):
    out = []
    for i, t in rows:
        w = (t or "").encode().lower().split()
        out.append((i, frozenset(zip(*(w[k:] for k in range(5)))) if len(w) > 5 else frozenset([tuple(w)] if w else [])))
    return out


def near_pairs(rows):
    """Places of rows with likeness 0.8 or more, by counting common shingles of all pairs that have one."""
    sets, at, both = shingle_sets(rows), defaultdict(list), defaultdict(int)
    for p, (_, s) in enumerate(sets):
        for x in s:
            at[x].append(p)
    for places in at.values():
        for j, q in enumerate(places):
            for p in places[:j]:
                both[p, q] += 1
    empty = [p for p, (_, s) in enumerate(sets) if not s]
    return [k for k, n in both.items() if 5 * n >= 4 * (len(sets[k[0]][1]) + len(sets[k[1]][1]) - n)] + list(zip(empty, empty[1:]))


def kept_of(rows, root=None):
    """(id, text) of the rows that stay: of each group that of the least id, if there are several that of the least hash."""
    root, out = joined(rows) if root is None else root, Counter()
    th = dict(zip((t for _, t in rows), hashes([t for _, t in rows])))
    for r in set(root):
        group = [rows[p] for p in range(len(rows)) if root[p] == r]
        ids = [i for i, _ in group if i is not None]
        first = min(ids) if ids else None
        _, i, t = min((th[t], i, t or "") for i, t in group if i == first) if first is not None else min(((th[t], None, t) for i, t in group), key=lambda x: x[0])
        out[i, next(b for a, b in group if a == i and (b or "") == (t or ""))] += 1
    return out


def hashes(texts):
    from pyspark.sql import SparkSession

    x = SparkSession.getActiveSession().createDataFrame([(i, t) for i, t in enumerate(texts)], "i int, text string")
    return [r["h"] for r in x.select("i", text_hash("text").alias("h")).orderBy("i").collect()]


def joined(rows):
    root = list(range(len(rows)))

    def find(p):
        while root[p] != p:
            p = root[p]
        return p

    for p, q in near_pairs(rows):
        root[find(p)] = find(q)
    return [find(p) for p in range(len(rows))]


def brute(rows):
    root = joined(rows)
    find = lambda p: root[p]
    least = defaultdict(lambda: math.inf)
    for p, (i, _) in enumerate(rows):
        if i is not None:
            least[find(p)] = min(least[find(p)], i)
    return [(i, None if least[find(p)] == math.inf else least[find(p)]) for p, (i, _) in enumerate(rows)]


def planted():
    """Texts of 30 to 400 words and copies in which single words are changed, up to a likeness around 0.8."""
    rng, rows = np.random.default_rng(3), []
    for _ in range(60):
        n = int(rng.integers(30, 400))
        w = [f"w{x}" for x in rng.integers(0, 50_000, n)]
        rows.append(" ".join(w))
        for _ in range(3):
            c = list(w)
            for k in rng.choice(n, max(1, int(n * rng.uniform(0, 0.035))), replace=False):
                c[k] = "changed" + str(rng.integers(0, 9999))
            rows.append(" ".join(c))
    rows += [None, "", "  ", "one", "One", "a b c d e", "a b c d e f", "a b c d e"]
    return [(i, t) for i, t in enumerate(rows)]


none_last = lambda x: tuple((v is None, v if v is not None else 0) for v in x)


@pytest.mark.parametrize("name", ["given", "planted", "odd"])
def test_stage_keeps_one_of_each_group(spark, sf_dir, name):
    rows = planted()
    if name == "given":
        rows = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()]
    if name == "odd":
        rows = [*rows[:8], (None, rows[0][1]), (None, "no id"), (None, "no id"), (3, rows[0][1]), (3, "other text under an old id")]
    docs = spark.createDataFrame([(i, t, "en", "a", 1) for i, t in rows], SCHEMA).repartition(3)
    want = brute(rows)
    assert sorted(map(tuple, jaccard.classes(docs).collect()), key=none_last) == sorted(want, key=none_last)
    kept = corpus_pipeline.drop_near_copies(spark, docs, sf_dir)
    assert kept.columns == docs.columns
    assert Counter((r["doc_id"], r["text"]) for r in kept.collect()) == kept_of(rows)


def test_no_ids_are_sent(spark, sf_dir, monkeypatch):
    monkeypatch.setattr(common, "SENT", 0)
    test_stage_keeps_one_of_each_group(spark, sf_dir, "planted")


@pytest.mark.parametrize("name", ["planted", "given"])
def test_large_groups_are_compared_in_blocks(spark, sf_dir, monkeypatch, name):
    monkeypatch.setattr(jaccard, "BLOCK", 2)
    test_stage_keeps_one_of_each_group(spark, sf_dir, name)


def test_recall_near_the_bound():
    """Of pairs with likeness 0.8 to 0.85, those that meet in a band and lie within the sketch's radius."""
    rng, met = np.random.default_rng(4), 0
    for _ in range(1500):
        n = int(rng.integers(20, 300))
        both = math.ceil(n * rng.uniform(0.8, 0.85))
        x = rng.integers(0, 1 << 63, n, dtype=np.uint64)
        a, b = x[: both + (n - both) // 2], np.concatenate((x[:both], x[both + (n - both) // 2:]))
        (ka, sa), (kb, sb) = (jaccard.signature(np.unique(v)) for v in (a, b))
        met += any(p == q for p, q in zip(ka, kb)) and int(np.bitwise_count(sa ^ sb).sum()) <= jaccard.SKETCH_RADIUS
    assert met >= 1495


def test_chance_meetings_are_not_links():
    x = [np.arange(0, 100, dtype=np.uint64), np.arange(12, 112, dtype=np.uint64), np.arange(11, 111, dtype=np.uint64), np.arange(22, 122, dtype=np.uint64)]
    assert jaccard.groups(x).tolist() == [0, 0, 0, 0]  # by way of each other
    assert jaccard.groups([x[0], x[1]]).tolist() == [0, 1] and jaccard.groups([x[0], x[2]]).tolist() == [0, 0]
    assert jaccard.groups([np.array([], np.uint64)] * 2 + [x[0]]).tolist() == [0, 0, 2]


def test_simhash_finds_its_links(spark, sf_dir, monkeypatch):
    """Fingerprints within 3 bits are one component of the candidates, and the stage joins near copies by them alone."""
    rows = planted()[:80]
    h = {int(jaccard.name_of(x)): x for x in (jaccard.shingles(t) for _, t in rows)}
    f = {s: simhash.majority(x) for s, x in h.items()}
    wrap = lambda v: v - (1 << 64) if v >> 63 else v
    nodes = spark.createDataFrame([(wrap(s), wrap(v)) for s, v in f.items()], "s long, f long")
    got = {r["node"]: r["root"] for r in components(jaccard._by_simhash(nodes)).collect()}
    near = [(p, q) for p in f for q in f if p < q and (f[p] ^ f[q]).bit_count() <= 3]
    assert near and all(got[wrap(p)] == got[wrap(q)] for p, q in near)
    assert set(got) == {wrap(s) for pair in near for s in pair}
    monkeypatch.setattr(jaccard, "_by_bands", lambda nodes, partitions: nodes.select("s", "s").toDF("a", "b").limit(0))
    docs = spark.createDataFrame([(i, t, "en", "a", 1) for i, t in rows], SCHEMA).repartition(3)
    cls, at = dict(map(tuple, jaccard.classes(docs).collect())), {int(jaccard.name_of(jaccard.shingles(t))): i for i, t in rows}
    like = [(at[p], at[q]) for p, q in near if len(np.intersect1d(h[p], h[q])) >= 0.8 * len(np.union1d(h[p], h[q]))]
    assert like and all(cls[i] == cls[j] for i, j in like)
