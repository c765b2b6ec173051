"""SimHash near-duplicates by deletion-variant signatures.

Fingerprints that differ in at most `radius` = 3 bits are cut into 2 segments: one of them differs in
at most one bit.  Each segment of 32 bits is indexed under its 32 one-wildcard variants (that bit
cleared, its place kept), so linked fingerprints meet under an equal variant; those that meet are
verified.  Within a variant's bucket only the links of a spanning forest are emitted, so rows never
grow with the square of a bucket; buckets over LARGE are cut by the bytes of the other segment, of
which links must share one.

Null or blank text has fingerprint zero and is linked like any other.  Repeated rows share a class.
"""

from __future__ import annotations

from itertools import accumulate

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import keep_least, stored, text_hash
from .components import components

LARGE, SMALL = 4096, 8


def fingerprint(text: str | None, words: int = 3, seed: int = 42) -> int:
    w = (text or "").encode().lower().split()
    if not w:
        return 0
    joined = b" ".join(w)
    if len(w) <= words:
        h = np.array([xxhash.xxh64_intdigest(joined, seed)], np.uint64)
    else:
        ends = list(accumulate(map(len, w), lambda a, b: a + b + 1))
        starts = [0, *(e + 1 for e in ends[: len(w) - words])]
        x = xxhash.xxh64_intdigest
        h = np.array([x(joined[a:b], seed) for a, b in zip(starts, ends[words - 1:])], np.uint64)
    return majority(h)


def majority(h: np.ndarray) -> int:
    """A bit is 1 if it is in over half of h."""
    n, ones = len(h), np.zeros(64, np.int64)
    for i in range(0, n, 65536):
        ones += np.unpackbits(h[i:i + 65536].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > n, bitorder="little").view(np.uint64)[0])


def _fingerprints(name: str, text_col: str):
    def run(batches):
        for batch in batches:
            f = np.array([fingerprint(x.as_py()) for x in batch[text_col]], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([*(c for c, k in zip(batch.columns, batch.schema.names) if k != text_col), pa.array(f)], names=[*(k for k in batch.schema.names if k != text_col), name])
    return run


def with_fingerprint(ids: DataFrame, id_col: str, text_col: str, name: str) -> DataFrame:
    """(id, name): the fingerprint as a long, for each row."""
    return ids.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_fingerprints(name, "text"), f"id long, {name} long")


def forest(x: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """Links of a spanning forest of the graph on x (unsigned, distinct) with links up to radius."""
    out, rest = [], x
    while len(rest) > 1:
        front, rest = [rest[0]], rest[1:]
        while front and len(rest):
            p = front.pop()
            near = np.bitwise_count(rest ^ p) <= radius
            if near.any():
                hit = rest[near]
                rest = rest[~near]
                out += [(int(p), int(q)) for q in hit]
                front += list(hit)
    return out


def _bucket(x: np.ndarray, other: np.uint64, radius: int) -> list[tuple[int, int]]:
    x = np.unique(x)
    if len(x) <= LARGE:
        return forest(x, radius)
    out = []
    for k in range(4):
        byte = (x >> (other + np.uint64(8 * k))) & np.uint64(255)
        for v in np.unique(byte):
            out += forest(x[byte == v], radius)
    return out


def _verify(radius: int):
    """From (key, f) sorted by key: links.  Buckets may run over batches."""
    def pairs(key: np.ndarray, f: np.ndarray):
        first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
        size = np.diff(np.concatenate((first, [len(key)])))
        small = np.repeat(size <= SMALL, size)
        a, b = [], []
        for lag in range(1, SMALL):
            ok = (key[lag:] == key[:-lag]) & small[lag:]
            if not ok.any():
                break
            p, q = f[:-lag][ok], f[lag:][ok]
            near = np.bitwise_count(p ^ q) <= radius
            a.append(p[near])
            b.append(q[near])
        more = []
        for i in np.flatnonzero(size > SMALL):
            other = np.uint64(32 if (int(key[first[i]]) >> 32) < 32 else 0)
            more += _bucket(f[first[i]:first[i] + size[i]], other, radius)
        m = np.array(more, np.uint64).reshape(-1, 2)
        return np.concatenate([*a, m[:, 0]]).view(np.int64), np.concatenate([*b, m[:, 1]]).view(np.int64)

    def run(batches):
        keys, fs = [], []
        for batch in batches:
            k, f = batch["key"].to_numpy(), batch["f"].to_numpy().view(np.uint64)
            if not len(k):
                continue
            last = np.searchsorted(k, k[-1])
            if last:  # the buckets before the last one are whole
                p, q = pairs(np.concatenate([*keys, k[:last]]), np.concatenate([*fs, f[:last]]))
                keys, fs = [], []
                if len(p):
                    yield pa.RecordBatch.from_arrays([pa.array(p), pa.array(q)], names=["a", "b"])
            elif keys and keys[0][0] != k[0]:
                p, q = pairs(np.concatenate(keys), np.concatenate(fs))
                keys, fs = [], []
                if len(p):
                    yield pa.RecordBatch.from_arrays([pa.array(p), pa.array(q)], names=["a", "b"])
            keys.append(k[last:])
            fs.append(f[last:])
        if keys:
            p, q = pairs(np.concatenate(keys), np.concatenate(fs))
            if len(p):
                yield pa.RecordBatch.from_arrays([pa.array(p), pa.array(q)], names=["a", "b"])
    return run


def links(prints: DataFrame, radius: int = 3) -> DataFrame:
    """(a, b): links that join all distinct fingerprints (column f) within radius of each other."""
    if radius > 3:
        raise ValueError("two segments with one wildcard cover 3 differing bits")
    v = F.explode(F.sequence(F.lit(0), F.lit(63)))
    x = prints.select("f", v.alias("v"))
    seg = F.when(F.col("v") < 32, F.col("f").bitwiseAND(F.lit(0xFFFFFFFF))).otherwise(F.shiftrightunsigned("f", 32))
    hole = F.expr("shiftleft(1L, v % 32)")
    x = x.select((F.shiftleft(F.col("v").cast("long"), 32) + seg.bitwiseAND(F.bitwise_not(hole))).alias("key"), "f")
    n = int(prints.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return x.repartition(n, "key").sortWithinPartitions("key").mapInArrow(_verify(radius), "a long, b long")


def _rooted(prints: DataFrame, radius: int) -> DataFrame:
    """(f, root, component_id) for each distinct f of prints (id, f): the least id that links reach."""
    least = stored(prints.groupBy("f").agg(F.min("id").alias("least")))
    roots = components(links(least.select("f"), radius))
    x = least.join(roots.withColumnRenamed("node", "f"), "f", "left").select("f", "least", F.coalesce("root", "f").alias("root"))
    best = x.groupBy("root").agg(F.min("least").alias("component_id"))
    return x.join(best, "root").select("f", "root", "component_id")


def classes(prints: DataFrame, radius: int = 3) -> DataFrame:
    """(f, component_id) for each distinct f of prints (id, f)."""
    return _rooted(prints, radius).drop("root")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = 3) -> DataFrame:
    """(id, fingerprint, component_id) for each row."""
    prints = stored(with_fingerprint(docs, id_col, text_col, "f"))
    return prints.join(classes(prints, radius), "f").select(F.col("id").alias(id_col), F.lower(F.lpad(F.hex("f"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = 3) -> DataFrame:
    """The rows of docs, all columns, of which one stays of each group (keep_least says which)."""
    x = docs.select(F.col(id_col).cast("long").alias("id"), text_hash(text_col).alias("th"), F.col(text_col).cast("string").alias("text"))
    prints = stored(x.mapInArrow(_fingerprints("f", "text"), "id long, th long, f long"))
    return keep_least(docs, prints.join(_rooted(prints, radius), "f").select("id", "th", "root", "component_id"), id_col, text_col)
