"""Removal of long repeated strings by window-minimum anchors and fingerprints of ranges of windows.

A text is a sequence of units: its bytes, or the hashes of its words (runs between ASCII white space, A-Z
lower-cased).  A window is `length` units.  Each unit has a hash of the few units there; a unit is a
trigger if its hash is the least among the next `span` units of some window.  So each window has one
trigger that its content alone decides, and equal windows, wherever they are, see it at the same
place.  There is no dictionary, parse or order of suffixes: only equal windows must come together,
and fingerprints of the units around the trigger do that.

Windows of one trigger are handled as one range.  First only ranges are kept whose key, the units that
all windows of that trigger share, occurs again; only their texts move.  Then, at each of three
levels (the widths of a Law), a range has two keys: the units that all its windows share, and those
that any of them covers.  If no other range has the first, none of its windows is repeated; if another
has the second (128 bits), all are; the rest goes to the next level.  Rows are ranges, never units or pairs.

Null text is empty.  Texts shorter than a window lose nothing.  Repeated rows repeat each other, and so do equal
strings of one text.  Only the id and text columns are read, whatever other columns are called.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, stored

#: Windows handled at once, which bounds the memory for very long texts.
CHUNK = 1 << 20
#: Stands for a null id inside the operator.
NO_ID = -(1 << 63)
#: Most ids of cut texts that are sent to all tasks, so that the other texts need not move.
SENT = 1 << 20
ANCHORS = "id long, th long, at long, s long"
RANGES = ANCHORS + ", b1 long, b2 long"
#: Bits of the distances, in units, from a range's windows to its trigger, which are less than a law's span.
NEAR = 9


@dataclass(frozen=True)
class Law:
    """What windows are made of: bytes a unit, units a window and a trigger's search, widths of the levels."""

    unit: int
    length: int
    span: int
    widths: tuple[int, int, int]

    def units(self, buf: bytes) -> bytes:
        if self.unit == 1:
            return buf
        words = buf.lower().split()
        return np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words)).tobytes()


def by_bytes(length: int) -> Law:
    if length < 272:
        raise ValueError("length must be 272 bytes at least")
    return Law(1, length, 256, (256, 16, 1))


def by_words(length: int) -> Law:
    if length < 44:
        raise ValueError("length must be 44 words at least")
    return Law(8, length, 40, (40, 8, 1))


def _place_hashes(data: np.ndarray, law: Law, n: int) -> np.ndarray:
    """A hash of 16 bytes or 4 words at each of the first n units."""
    if law.unit == 1:
        x = np.ndarray((n + 8,), "<u8", data, 0, (1,))
        h = x[:n] * np.uint64(0x9E3779B97F4A7C15) + x[8:] * np.uint64(0xC2B2AE3D27D4EB4F)
    else:
        x = data.view("<u8")
        h = x[:n] * np.uint64(0x9E3779B97F4A7C15)
        for k, c in ((1, 0xC2B2AE3D27D4EB4F), (2, 0x165667B19E3779F9), (3, 0xD6E8FEB86659FD93)):
            h += x[k:n + k] * np.uint64(c)
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    return h


def triggers(data: np.ndarray, windows: int, law: Law) -> np.ndarray:
    """For each of the first `windows` starts, the trigger among the next law.span units."""
    n = windows + law.span - 1
    h = _place_hashes(data, law, n)
    h &= np.uint64(0xFFFFFFFF00000000)
    h |= np.uint64(0xFFFFFFFF) - np.arange(n, dtype=np.uint64)
    step = 1
    while 2 * step <= law.span:
        h = np.minimum(h[:-step], h[step:])
        step *= 2
    if step < law.span:
        h = np.minimum(h[:step - law.span], h[law.span - step:])
    return (np.uint64(0xFFFFFFFF) - (h[:windows] & np.uint64(0xFFFFFFFF))).astype(np.int64)


def anchors(buf: bytes, law: Law):
    """(t, lo, hi, s) arrays: the ranges of windows of a text, by trigger, a chunk at a time."""
    total = len(buf) // law.unit - law.length + 1
    whole, shared = np.frombuffer(buf, np.uint8), (law.length - law.span + 1) * law.unit
    for base in range(0, max(0, total), CHUNK):
        windows = min(CHUNK, total - base)
        at = triggers(whole[base * law.unit:], windows, law) + base
        cut = np.flatnonzero(np.diff(at)) + 1
        lo, hi = np.concatenate(([0], cut)) + base, np.concatenate((cut, [windows])) - 1 + base
        t = at[lo - base]
        x, seed = xxhash.xxh3_64_digest, law.unit
        s = np.frombuffer(b"".join([x(buf[a:a + shared], seed) for a in (t * law.unit).tolist()]), ">u8")
        yield t, lo, hi, s.astype(np.uint64).view(np.int64)


def pieces(law: np.ndarray, t: np.ndarray, lo: np.ndarray, hi: np.ndarray, width: np.ndarray) -> tuple[np.ndarray, ...]:
    """(place, near, lo, hi): ranges cut at multiples of their width from their triggers; near is the least of them
    that a piece has."""
    first, last = (t - hi) // width, (t - lo) // width
    n = last - first + 1
    at = np.repeat(np.arange(len(t)), n)
    near = (np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + first[at]) * width[at]
    return at, near, np.maximum(lo[at], t[at] - near - width[at] + 1), np.minimum(hi[at], t[at] - near)


def packed(law: np.ndarray | int, t: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """Ranges as one long each, so that rows of the large tables are short."""
    return ((t << NEAR | t - lo) << NEAR | t - hi) << 1 | law


def unpacked(at: np.ndarray) -> tuple[np.ndarray, ...]:
    """(law, t, lo, hi)"""
    near, t = (1 << NEAR) - 1, at >> (2 * NEAR + 1)
    return at & 1, t, t - (at >> (NEAR + 1) & near), t - (at >> 1 & near)


def _keys(buf: bytes, law: Law, width: int, t: list[int], near: list[int], lo: list[int], hi: list[int]) -> tuple[bytes, bytes]:
    """Keys of pieces of ranges, joined: of the units shared by any `width` windows aligned to the trigger (8 bytes),
    and of all units covered (16)."""
    u, word, shared = law.unit, law.unit > 1, law.length - width + 1
    x, y = xxhash.xxh3_64_digest, xxhash.xxh3_128_digest
    s = b"".join([x(buf[(a - n) * u:(a - n + shared) * u], 2 * n + word) for a, n in zip(t, near)])
    b = b"".join([y(buf[p * u:(q + law.length) * u], 2 * (a - p) + word) for a, p, q in zip(t, lo, hi)])
    return s, b


def _parse(laws: list[Law]):
    """From (id, th, text): the anchors of each text under each law."""
    names = [x.split()[0] for x in ANCHORS.split(", ")]

    def table(held) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*held)], names=names)

    def run(batches):
        for batch in batches:
            held, n = [], 0
            for i, th, text in zip(batch["id"].to_pylist(), batch["th"].to_pylist(), batch["text"]):
                raw = (text.as_py() or "").encode()
                for k, law in enumerate(laws):
                    for t, lo, hi, s in anchors(law.units(raw), law):
                        held.append((np.full(len(t), i, np.int64), np.full(len(t), th, np.int64), packed(k, t, lo, hi), s))
                        n += len(t)
                if n > 50_000:
                    yield table(held)
                    held, n = [], 0
            if held:
                yield table(held)
    return run


def _flat(column: pa.Array) -> tuple[np.ndarray, ...]:
    """(row, law, t, lo, hi) of a column of lists of packed ranges, null being empty."""
    size = column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
    return (np.repeat(np.arange(len(column)), size), *unpacked(column.flatten().to_numpy(zero_copy_only=False).astype(np.int64)))


def _refine(laws: list[Law], level: int):
    """From (id, th, text, ranges): the ranges cut at multiples of the level's width from their triggers."""
    names = [x.split()[0] for x in RANGES.split(", ")]
    widths = np.array([x.widths[level] for x in laws], np.int64)

    def run(batches):
        for batch in batches:
            row, law, t, lo, hi = _flat(batch["ranges"])
            o = np.lexsort((law, row))
            row, law, t, lo, hi = (x[o] for x in (row, law, t, lo, hi))
            at, near, lo, hi = pieces(law, t, lo, hi, widths[law])
            row, law, t = row[at], law[at], t[at]
            cut = np.flatnonzero(np.concatenate(([True], (np.diff(row) != 0) | (np.diff(law) != 0), [True]))) if len(row) else np.zeros(1, int)
            ids, ths, held, first = batch["id"].to_numpy(), batch["th"].to_numpy(), [], 0
            for i, (a, b) in enumerate(zip(cut, cut[1:])):
                k = laws[law[a]]
                units = k.units((batch["text"][int(row[a])].as_py() or "").encode())
                held.append(_keys(units, k, k.widths[level], *(x[a:b].tolist() for x in (t, near, lo, hi))))
                if b - first > 50_000 or i == len(cut) - 2:
                    part = slice(first, b)
                    s, two = (np.frombuffer(b"".join(x), ">u8").astype(np.uint64).view(np.int64) for x in zip(*held))
                    r = row[part]
                    columns = [pa.array(ids[r]), pa.array(ths[r]), pa.array(packed(*(x[part] for x in (law, t, lo, hi)))), pa.array(s), pa.array(two[::2]), pa.array(two[1::2])]
                    yield pa.RecordBatch.from_arrays(columns, names=names)
                    held, first = [], b
    return run


def _seen_again(rows: DataFrame) -> DataFrame:
    """The rows whose key s another row has, too."""
    # counts are written first: the join then has plain exchanges on both sides and can be split where a key is hot
    again = stored(rows.groupBy("s").agg(F.count("*").alias("n")).where("n > 1").select("s"))
    found = stored(rows.join(again, "s", "left_semi"))
    discard(again)
    return found


def _resolve(ranges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(repeated, open): ranges all of whose windows are repeated, and those that the next level must see: of
    each two or more unlike ranges with a common first key, one range a kind."""
    # any range of a kind will do; first of longs needs no sort, min of a struct would
    kinds = stored(ranges.groupBy("s", "b1", "b2").agg(F.count("*").alias("n"), *[F.first(c).alias(c) for c in ("id", "th", "at")]))
    whole = stored(ranges.join(kinds.where("n > 1").select("s", "b1", "b2"), ["s", "b1", "b2"], "left_semi").select("id", "th", "at"))
    several = stored(kinds.groupBy("s").agg(F.count("*").alias("k")).where("k > 1").select("s"))
    left = stored(kinds.join(several, "s", "left_semi").select("id", "th", "at"))
    for x in (kinds, several):
        discard(x)
    return whole, left


def runs(group: np.ndarray, lo: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(group, start, end): the unions of half-open spans of each group, as maximal runs in order; runs that touch are one."""
    o = np.lexsort((lo, group))
    base = group[o] << 40  # no text is so long
    a, b = lo[o] + base, end[o] + base
    far = np.maximum.accumulate(b) if len(b) else b
    new = np.concatenate(([True], a[1:] > far[:-1])) if len(a) else np.zeros(0, bool)
    last = np.concatenate((np.flatnonzero(new)[1:] - 1, [len(a) - 1])) if len(a) else np.zeros(0, int)
    g = group[o][new]
    return g, a[new] - (g << 40), far[last] - (g << 40)


def _without(buf: bytes, cut: list[tuple[int, int]]) -> bytes:
    ends = [0, *(b for _, b in cut)]
    return b"".join([buf[a:b] for a, b in zip(ends, [*(a for a, _ in cut), len(buf)])])


def _word_places(buf: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the words of a text, in bytes."""
    x = np.frombuffer(buf, np.uint8)
    edge = np.flatnonzero(np.diff(np.concatenate(([0], ((x != 32) & ((x < 9) | (x > 13))).view(np.int8), [0]))))
    return edge[::2], edge[1::2]


def _cut(laws: list[Law], with_text: bool):
    """From (id, th, text, spans): what is removed from each text, and what is left of it."""
    lengths = np.array([x.length for x in laws], np.int64)

    def run(batches):
        for batch in batches:
            row, law, _, lo, hi = _flat(batch["spans"])
            g, a, b = runs(row * 2 + law, lo, hi + lengths[law])
            at = np.searchsorted(g, np.arange(2 * batch.num_rows + 1))
            rows = []
            for i, text in enumerate(batch["text"]):
                buf = (text.as_py() or "").encode()
                p, q, r = at[2 * i:2 * i + 3].tolist()
                own, words = list(zip(a[p:q].tolist(), b[p:q].tolist())), list(zip(a[q:r].tolist(), b[q:r].tolist()))
                kept, left = _without(buf, own), None
                if with_text and words:
                    start, end = _word_places(buf)
                    x = np.array([*own, *((start[c], end[d - 1]) for c, d in words)], np.int64)
                    _, c, d = runs(np.zeros(len(x), np.int64), x[:, 0], x[:, 1])
                    left = _without(buf, list(zip(c.tolist(), d.tolist()))).decode("utf-8", "replace")
                elif with_text:
                    left = kept.decode("utf-8", "replace")
                rows.append((sum(y - x for x, y in own), len(own), hashlib.sha256(kept).hexdigest(), len(words), sum(y - x for x, y in words), left))
            cols = list(zip(*rows)) or [[]] * 6
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string())
            yield pa.RecordBatch.from_arrays([batch["id"], batch["th"], *(pa.array(c, k) for c, k in zip(cols, kinds))], names=["id", "th", *CUT])
    return run


CUT = ("n_removed", "n_spans", "kept_sha256", "n_passages", "passage_words", "text")


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = 400, words: int | None = None, with_text: bool = False) -> DataFrame:
    """(id, n_bytes, n_removed, n_spans, kept_sha256[, n_passages, passage_words][, text]) for each row of docs.

    The first five tell of strings of `length` bytes.  With `words`, n_passages and passage_words count the maximal
    runs, and the words in them, of strings of that many words that also start elsewhere.  text is what is left
    of a text without either; where a cut falls inside a character, that becomes U+FFFD."""
    laws = [by_bytes(length), *([by_words(words)] if words else [])]
    source = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    whole = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)).alias("id"), F.xxhash64(source).alias("th"), source.alias("text"))
    key = ["id", "th"]
    least = min(length, 2 * words - 1) if words else length
    parse = stored(whole.where(F.octet_length("text") >= least).mapInArrow(_parse(laws), ANCHORS))
    found = _seen_again(parse)
    discard(parse)
    # the texts that a level or the result needs, with their open ranges
    listed = lambda x: x.groupBy(*key).agg(F.collect_list("at").alias("ranges"))
    texts = stored(whole.join(listed(found), key).dropDuplicates(key))
    discard(found)
    asked, spans = texts, None
    for level in range(3):
        ranges = stored(asked.mapInArrow(_refine(laws, level), RANGES))
        more, left = _resolve(ranges)
        discard(ranges)
        spans = more if spans is None else spans.union(more)
        asked = texts.drop("ranges").join(listed(left), key)
    spans = spans.groupBy(*key).agg(F.collect_list("at").alias("spans"))
    cut = stored(texts.drop("ranges").join(spans, key).mapInArrow(_cut(laws, with_text), "id long, th long, n_removed long, n_spans long, kept_sha256 string, n_passages long, passage_words long, text string"))
    discard(texts)
    sizes = [*key, F.octet_length("text").cast("long").alias("n_bytes")]
    own = [F.lit(0).cast("long").alias("n_removed"), F.lit(0).cast("long").alias("n_spans"), F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"), *[F.lit(0).cast("long").alias(c) for c in CUT[3:5]], F.col("text")]
    touched = whole.select(*sizes).join(cut, key).select(*key, "n_bytes", *CUT)
    keys = cut.select(*key)
    others = whole.join(F.broadcast(keys) if keys.count() <= SENT else keys, key, "left_anti").select(*sizes, *own)
    out = ["n_bytes", *CUT[:3], *(CUT[3:5] if words else ()), *([CUT[5]] if with_text else [])]
    return others.unionByName(touched).select(F.nullif("id", F.lit(NO_ID)).alias(id_col), *out)
