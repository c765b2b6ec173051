"""Near copies by the likeness of their sets of five-word shingles.

Candidates are, first, texts whose SimHash fingerprints, over these shingles, differ in at most 3 bits, found by
simhash.py's deletion variants.  A likeness of 0.8 is 4 to 15 bits, out of reach of any variants, so for the rest of the
links candidates are also texts that share one of BANDS keys, each of ROWS MinHash values, and whose sketches, a bit
of each of 128 MinHash values, differ in at most SKETCH_RADIUS bits.  Texts with likeness 0.8 miss every
band with a chance of 5e-5 and the sketch's radius with 2e-5.  Within a key's bucket only a spanning forest's
links are emitted, so rows never grow with the square of a bucket.  The sets of a component of these
links are then compared themselves, a pair of bounded blocks in a task, of which again only a forest's links go on.

Equal sets are one node from the start.  Texts of fewer words are one shingle; null and blank texts
have the empty set and are alike.  Words are those of simhash.fingerprint.
"""

from __future__ import annotations

from itertools import accumulate

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import simhash
from .common import discard, keep_least, sent, stored, text_hash
from .components import components

WORDS, LEAST = 5, 0.8
#: Texts whose sets a task holds at once.
PART = 256
#: Sets of a block.
BLOCK = 256
BANDS, ROWS, VALUES, SKETCH_RADIUS = 25, 5, 128, 27
_rng = np.random.default_rng(20)
_A = _rng.integers(0, 1 << 64, VALUES, dtype=np.uint64) | np.uint64(1)
_B = _rng.integers(0, 1 << 64, VALUES, dtype=np.uint64)


def shingles(text: str | None, words: int = WORDS) -> np.ndarray:
    """The distinct hashes of runs of `words` words, sorted."""
    w = (text or "").encode().lower().split()
    if not w:
        return np.array([], np.uint64)
    joined, x = b" ".join(w), xxhash.xxh64_intdigest
    if len(w) <= words:
        return np.array([x(joined, 42)], np.uint64)
    ends = list(accumulate(map(len, w), lambda a, b: a + b + 1))
    starts = [0, *(e + 1 for e in ends[: len(w) - words])]
    return np.unique(np.array([x(joined[a:b], 42) for a, b in zip(starts, ends[words - 1:])], np.uint64))


def name_of(h: np.ndarray) -> int:
    """A number that equal sets share."""
    return xxhash.xxh64_intdigest(h.tobytes(), 1)


def min_hashes(h: np.ndarray) -> np.ndarray:
    least = np.full(VALUES, np.iinfo(np.uint64).max, np.uint64)
    for i in range(0, len(h), 512):
        np.minimum(least, (h[i:i + 512, None] * _A + _B).min(axis=0), out=least)
    return least


def signature(h: np.ndarray) -> tuple[list[int], np.ndarray]:
    """The keys of all bands, and the sketch as two numbers."""
    m = min_hashes(h)
    keys = [xxhash.xxh64_intdigest(m[k * ROWS:(k + 1) * ROWS].tobytes(), k) for k in range(BANDS)]
    bits = ((m ^ (m >> np.uint64(29))) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(63)
    return keys, np.packbits(bits.astype(np.uint8), bitorder="little").view(np.uint64)


def _signatures(batches):
    for batch in batches:
        s, f, keys, sketch = [], [], [], []
        for t in batch["text"]:
            h = shingles(t.as_py())
            k, b = signature(h)
            s.append(name_of(h))
            f.append(simhash.majority(h))
            keys.append(np.array(k, np.uint64).view(np.int64))
            sketch.append(b)
        two = np.array(sketch, np.uint64).reshape(-1, 2).view(np.int64)
        yield pa.RecordBatch.from_arrays([batch["id"], batch["th"], pa.array(np.array(s, np.uint64).view(np.int64)), pa.array(np.array(f, np.uint64).view(np.int64)), pa.array(two[:, 0]), pa.array(two[:, 1]), pa.array(keys, pa.list_(pa.int64()))], names=["id", "th", "s", "f", "s1", "s2", "keys"])


def _runs(batches, key: str):
    """Whole runs of equal keys, as lists of arrays, from batches sorted by key; runs may go over batches."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        k = batch[key].to_numpy()
        if held and held[-1][key][0].as_py() != k[0]:
            yield pa.Table.from_batches(held)
            held = []
        last = int(np.searchsorted(k, k[-1]))
        if last:
            yield pa.Table.from_batches([*held, batch.slice(0, last)])
            held = []
        held.append(batch.slice(last))
    if held:
        yield pa.Table.from_batches(held)


def _bounds(k: np.ndarray) -> np.ndarray:
    return np.flatnonzero(np.concatenate(([True], k[1:] != k[:-1], [True])))


def forest(sketch: np.ndarray, radius: int = SKETCH_RADIUS) -> list[tuple[int, int]]:
    """Links (places) of a spanning forest of the graph on sketches with links up to radius."""
    out, rest = [], np.arange(len(sketch))
    while len(rest) > 1:
        front, rest = [rest[0]], rest[1:]
        while front and len(rest):
            p = front.pop()
            near = np.bitwise_count(sketch[rest] ^ sketch[p]).sum(axis=1) <= radius
            if near.any():
                hit, rest = rest[near], rest[~near]
                out += [(int(p), int(q)) for q in hit]
                front += hit.tolist()
    return out


def _links(batches):
    """From (key, s, s1, s2) sorted by key: (a, b)."""
    for t in _runs(batches, "key"):
        k, s = t["key"].to_numpy(), t["s"].to_numpy()
        sketch = np.stack([t["s1"].to_numpy(), t["s2"].to_numpy()], axis=1).view(np.uint64)
        at = _bounds(k)
        size = np.diff(at)
        two = at[:-1][size == 2]
        two = two[np.bitwise_count(sketch[two] ^ sketch[two + 1]).sum(axis=1) <= SKETCH_RADIUS]
        more = [(i + p, i + q) for i, n in zip(at[:-1][size > 2], size[size > 2]) for p, q in forest(sketch[i:i + n])]
        m = np.array(more, np.int64).reshape(-1, 2)
        a, b = s[np.concatenate([two, m[:, 0]])], s[np.concatenate([two + 1, m[:, 1]])]
        if len(a):
            yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])


def groups(sets: list[np.ndarray], least: float = LEAST) -> np.ndarray:
    """For each set, the place of the first of its component in the graph with links of likeness `least` or more."""
    size = np.array([len(x) for x in sets])
    out, todo = np.arange(len(sets)), np.ones(len(sets), bool)
    _, word = np.unique(np.concatenate(sets), return_inverse=True)
    ends = np.concatenate(([0], np.cumsum(size)))
    mark = np.zeros(word.max(initial=-1) + 1, bool)
    for first in range(len(sets)):
        if not todo[first]:
            continue
        todo[first], front = False, [first]
        while front:
            p = front.pop()
            own = word[ends[p]:ends[p + 1]]
            rest = np.flatnonzero(todo & (np.minimum(size, size[p]) >= least * np.maximum(size, size[p]) - 1e-9))
            if not len(rest):
                continue
            mark[own] = True
            both = np.array([np.count_nonzero(mark[word[ends[q]:ends[q + 1]]]) for q in rest])
            mark[own] = False
            hit = rest[both >= least * (size[rest] + size[p] - both) - 1e-9]
            out[hit], todo[hit] = first, False
            front += hit.tolist()
    return out


def _sets(batches):
    """(root, n, s, h) from (s, root, n, text), h as bytes, PART texts at a time."""
    for whole in batches:
        for batch in (whole.slice(k, PART) for k in range(0, whole.num_rows, PART)):
            h = [shingles(t.as_py()).tobytes() for t in batch["text"]]
            yield pa.RecordBatch.from_arrays([batch["root"], batch["n"], batch["s"], pa.array(h, pa.binary())], names=["root", "n", "s", "h"])


def _exact(least: float):
    """From (key, n, s, h) sorted by key: (n, s, c), c the same within a group of a key's sets."""
    def run(batches):
        for t in _runs(batches, "key"):
            at, s, c = _bounds(t["key"].to_numpy()), t["s"].to_numpy(), []
            for i, j in zip(at, at[1:]):
                g = groups([np.frombuffer(x, np.uint64) for x in t["h"].slice(i, j - i).to_pylist()], least)
                c.append(s[i:j][g])
            yield pa.RecordBatch.from_arrays([pa.array(t["n"].to_numpy()), pa.array(s), pa.array(np.concatenate(c))], names=["n", "s", "c"])
    return run


def _grouped(sets: DataFrame, least: float, partitions: int) -> DataFrame:
    """(s, c) from (root, n, s, h), n being the blocks of the component: c is the same within a group.

    A component's sets are dealt over blocks of about BLOCK.  Each pair of blocks is compared in a task of its own, which
    gives a spanning forest of the links there; the forests of all pairs of blocks join what all links join.  So no
    component is in one task, and links are never more than its sets times its blocks."""
    own = F.pmod(F.xxhash64(F.lit(13), "s"), F.col("n")).cast("int")
    x = sets.withColumn("b", own).withColumn("j", F.explode(F.sequence(F.lit(0), F.col("n") - 1)))
    x = x.select(F.xxhash64("root", F.least("b", "j"), F.greatest("b", "j")).alias("key"), "n", "s", "h")
    x = x.repartition(partitions, "key").sortWithinPartitions("key", "s").mapInArrow(_exact(least), "n int, s long, c long")
    x = stored(x.where("n = 1 or s <> c").distinct())
    alone, links = x.where("n = 1").select("s", "c"), x.where("n > 1").select(F.col("s").alias("a"), F.col("c").alias("b"))
    return alone.union(components(links).select(F.col("node").alias("s"), F.col("root").alias("c"))) if links.head(1) else alone


def _texts(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("id"), text_hash(text_col).alias("th"), F.col(text_col).cast("string").alias("text"))


def _by_simhash(nodes: DataFrame) -> DataFrame:
    """(a, b): links that join all sets (s, f) whose fingerprints f differ in at most 3 bits."""
    lead = stored(nodes.groupBy("f").agg(F.min("s").alias("lead")))
    same = nodes.select("s", "f").join(lead, "f").where("s <> lead").select(F.col("s").alias("a"), F.col("lead").alias("b"))
    x = stored(simhash.links(lead.select("f")).distinct())
    for c in ("a", "b"):
        x = x.join(lead.select(F.col("f").alias(c), F.col("lead").alias(f"{c}1")), c).drop(c)
    return same.union(x.select("a1", "b1"))


def _by_bands(nodes: DataFrame, partitions: int) -> DataFrame:
    """(a, b): links of the sets (s, s1, s2, keys) that share a band's key and have like sketches."""
    x = nodes.select(F.explode("keys").alias("key"), "s", "s1", "s2")
    return x.repartition(partitions, "key").sortWithinPartitions("key", "s").mapInArrow(_links, "a long, b long")


def _members(docs: DataFrame, id_col: str, text_col: str, least: float) -> DataFrame:
    """(id, th, root, component_id) for each row: root names the group that links of likeness `least` or more join."""
    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    made = stored(_texts(docs, id_col, text_col).mapInArrow(_signatures, "id long, th long, s long, f long, s1 long, s2 long, keys array<long>"))
    # of rows of one set, that of the least (id, th) stands for all
    node = F.min(F.struct("id", "th")).alias("row")
    nodes = stored(made.groupBy("s").agg(F.min("id").alias("least"), node, F.first("f").alias("f"), F.first("s1").alias("s1"), F.first("s2").alias("s2"), F.first("keys").alias("keys")))
    x = stored(_by_simhash(nodes))  # one Python stage at a time
    roots = stored(components(x.union(stored(_by_bands(nodes, n)))).select(F.col("node").alias("s"), "root"))
    blocks = stored(roots.groupBy("root").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("n")))
    want = roots.join(blocks, "root").join(nodes.select("s", "row"), "s")
    want = stored(want.select("s", "root", "n", F.col("row.id").alias("i"), F.col("row.th").alias("h")))
    on = F.col("id").eqNullSafe(F.col("i")) & (F.col("th") == F.col("h"))
    # each wanted set comes from one text, which alone moves
    texts = _texts(docs, id_col, text_col).join(sent(want), on).groupBy("s", "root", "n").agg(F.first("text").alias("text"))
    sets = stored(texts.mapInArrow(_sets, "root long, n int, s long, h binary"))
    group = stored(_grouped(sets, least, n))
    discard(sets)
    x = nodes.select("s", "least").join(group, "s", "left").select("s", "least", F.coalesce("c", "s").alias("root"))
    best = x.groupBy("root").agg(F.min("least").alias("component_id"))
    return made.select("id", "th", "s").join(x.join(best, "root").select("s", "root", "component_id"), "s").select("id", "th", "root", "component_id")


def classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: float = LEAST) -> DataFrame:
    """(id, component_id) for each row: the least id that links of likeness `least` or more reach."""
    return _members(docs, id_col, text_col, least).select("id", "component_id")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: float = LEAST) -> DataFrame:
    """The rows of docs, all columns, of which one stays of each group (keep_least says which)."""
    return keep_least(docs, _members(docs, id_col, text_col, least), id_col, text_col)
