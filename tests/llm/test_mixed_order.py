"""The order that mixing writes is that in which packing numbers sequences."""

from collections import defaultdict

import corpus_pipeline
from cardsketch.llm import mixing, packing
from cardsketch.llm.common import stored
from cardsketch.llm.queries import tokenizer_path


def sources(spark):
    rows = [(i, " ".join(f"word{(i * 7 + k) % 97}" for k in range(3 + i % 5)), "en", "a" if i % 4 else "b", 1) for i in range(600)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").repartition(5)


def test_place_is_the_written_order(spark, sf_dir):
    docs = sources(spark)
    slot = {r["doc_id"]: (r["slot"], r["place"]) for r in mixing.mix(docs).collect()}
    x = stored(corpus_pipeline.mix_sources(spark, docs, sf_dir))
    got = [r["doc_id"] for r in sorted(packing.with_place(x).collect(), key=lambda r: r["place"])]
    assert got == sorted(slot, key=slot.get)
    assert packing.with_place(x).columns == [*docs.columns, "place"]


def test_sequences_come_in_mixed_order(spark, sf_dir):
    docs = sources(spark)
    slot = {r["doc_id"]: (r["slot"], r["place"]) for r in mixing.mix(docs).collect()}
    x = stored(corpus_pipeline.mix_sources(spark, docs, sf_dir))
    rows = packing.pack(x, tokenizer_path(), capacity=64, in_order=True).collect()
    first = {r["sequence_id"]: r["doc_id"] for r in rows if r["offset"] == 0}
    order = [slot[first[s]] for s in sorted(first)]
    assert sorted(first) == list(range(len(first))) and order == sorted(order)
    like = defaultdict(list)
    for r in rows:
        like[r["length"]].append((r["doc_id"], r["sequence_id"]))
    assert {r["doc_id"] for r in rows} == set(slot)


def test_taking_mixing_out_changes_the_sequences(spark, sf_dir):
    docs = stored(sources(spark))
    with_it = corpus_pipeline.pack_sequences(spark, stored(corpus_pipeline.mix_sources(spark, docs, sf_dir)), sf_dir)
    without = corpus_pipeline.pack_sequences(spark, docs, sf_dir)
    assert sorted(map(tuple, with_it.collect())) != sorted(map(tuple, without.collect()))


def test_no_switch_by_size():
    """Over 2**20 blocks each block keeps its own window and each source stays within a block of its target weight."""
    w, blocks = {"a": 1.0, "b": 2.0**0.5, "c": 0.001}, {"a": 500_000, "b": 700_000, "c": 600}
    plan = mixing.schedule(blocks, w)
    assert [(r["source"], r["phase"], r["period"], len(r["slots"]), len(r["release"])) for r in plan] == [(s, 0, 0, n, n) for s, n in blocks.items()]
    (a, b, c), total = ([*r["slots"]] for r in plan), sum(w.values())
    ends = min(blocks[s] / w[s] for s in w) * total  # until a source runs out
    for s, slots in zip("abc", (a, b, c)):
        for k, t in enumerate(slots):
            if t >= ends - 1:
                break
            assert abs(k - t * w[s] / total) < 1 + 1e-6 and abs(k + 1 - (t + 1) * w[s] / total) < 1 + 1e-6


def test_windows_come_in_parts(spark, sf_dir, monkeypatch):
    docs = stored(sources(spark))
    rows = lambda: sorted(map(tuple, mixing.mix(docs, block_rows=2).collect()))
    order = lambda: [r["doc_id"] for r in mixing.mixed(docs, block_rows=2).collect()]
    whole, as_mixed = rows(), order()
    monkeypatch.setattr(mixing, "PART", 7)
    assert rows() == whole and order() == as_mixed
    plan = mixing.schedule({"a": 225, "b": 75}, mixing.target_weights({"a": 450, "b": 150}))
    want = {(r["source"], r["first"] + k): r["slots"][k] for r in plan for k in range(len(r["slots"]))}
    assert {(r["source"], r["block"]): r["slot"] for r in mixing.mix(docs, block_rows=2).collect()} == want
