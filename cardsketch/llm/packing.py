"""Best-fit-decreasing packing of token pieces into sequences.

Pieces of one length are alike, so best-fit decreasing is carried out on the histogram of lengths, of
`capacity` rows at most whatever the corpus: a segment tree over remaining capacities gives the
tightest open capacity that takes a length, and one plan row places a run of like pieces into a run
of like bins.  Pieces find their place by their rank within their length.  The result is that of
best-fit decreasing piece by piece, over all pieces at once.

Where rows have a place, an order to keep, it ranks the pieces of a length, and sequences are numbered by the place
of their first piece.  Null and empty texts are one closing token.  Repeated rows are packed like any others.
"""

from __future__ import annotations

import codecs
import json
import re
import sys
import zlib
from array import array
from types import ModuleType

import numpy as np
import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import ranked, spread_for, stored

CAPACITY, CLOSE = 4096, 1
#: Words whose ids a worker keeps; results don't depend on it.
CACHED_WORDS = 150_000


class OpenCapacities:
    """Segment tree over remaining capacities 0..capacity: which of them some open bin has."""

    def __init__(self, capacity: int):
        self.size = 1 << capacity.bit_length()
        self.any = bytearray(2 * self.size)

    def set(self, r: int, there: bool) -> None:
        i = r + self.size
        self.any[i] = there
        while i > 1:
            i //= 2
            self.any[i] = self.any[2 * i] or self.any[2 * i + 1]

    def tightest(self, least: int) -> int:
        """The smallest open capacity of `least` or more, -1 if there is none."""
        i = least + self.size
        if self.any[i]:
            return least
        while i > 1:
            if i % 2 == 0 and self.any[i + 1]:
                i += 1
                while i < self.size:
                    i = 2 * i if self.any[2 * i] else 2 * i + 1
                return i - self.size
            i //= 2
        return -1


def best_fit_plan(lengths: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int, int]]:
    """From counts by length: rows (length, first rank, pieces, first bin, pieces a bin, offset)."""
    tree, runs, plan, bins = OpenCapacities(capacity), {}, [], 0

    def put(r: int, first: int, n: int) -> None:
        if r and n:
            runs.setdefault(r, []).append((first, n))
            tree.set(r, True)

    for length in sorted(lengths, reverse=True):
        rank, left = 0, lengths[length]
        while left:
            r = tree.tightest(length)
            if r < 0:
                r = capacity
                each = r // length
                first, n = bins, -(-left // each)
                bins += n
            else:
                each = r // length
                first, n = runs[r].pop()
                if not runs[r]:
                    del runs[r]
                    tree.set(r, False)
            full = min(n, left // each)
            placed, used = full * each, full
            if placed < left and full < n:  # one more bin takes fewer than it could
                placed, used = left, full + 1
                put(r - (left - full * each) * length, first + full, 1)
            put(r - each * length, first, full)
            put(r, first + used, n - used)
            plan.append((length, rank, placed, first, each, capacity - r))
            rank, left = rank + placed, left - placed
    return plan


def _byte_letters() -> dict[int, str]:
    """The letters by which byte-level vocabularies write bytes: printable ones stand for themselves,
    the others follow from 256 on."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in own]
    return {b: chr(b) for b in own} | {b: chr(256 + i) for i, b in enumerate(rest)}


# fixed values: the settings of the vocabulary on which word_ids rests
NORMALISER = [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": "\\s+"}, "content": " "}, {"type": "Lowercase"}]
SPLITTER = [
    {"type": "Split", "pattern": {"Regex": "'s|'t|'re|'ve|'m|'ll|'d|[\\p{L}]+|[\\p{N}]|[^\\s\\p{L}\\p{N}]+"}, "behavior": "Removed", "invert": True},
    {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False},
]


def splits_at_spaces(path: str) -> bool:
    """Whether a vocabulary file has those settings; texts go through any other as they are."""
    with open(path, encoding="utf-8") as f:
        d = json.load(f)
    n, p, m = d.get("normalizer") or {}, d.get("pre_tokenizer") or {}, d.get("model") or {}
    return n.get("normalizers") == NORMALISER and p.get("pretokenizers") == SPLITTER and m.get("type") == "BPE" and m.get("dropout") is None and not m.get("ignore_merges")


def _shelf() -> dict:
    """What a worker keeps from task to task: functions come pickled by value, so no variable of this module lasts."""
    return sys.modules.setdefault("cardsketch_worker", ModuleType("cardsketch_worker")).__dict__.setdefault("shelf", {})


#: ASCII punctuation, whose runs are units to the splitter.
MARKS = bytes(b for b in range(33, 127) if not chr(b).isalnum())


def _latin(text: str) -> bool:
    """Whether all characters are below U+0100."""
    if text.isascii():
        return True
    try:
        text.encode("latin-1")
    except UnicodeEncodeError:
        return False
    return True


def word_ids(path: str):
    """A function from text to its ids as unsigned 32-bit little-endian bytes.

    The vocabulary's normaliser and splitter never join characters across ASCII white space, and
    drop the latter; so ids are those of the words between, which a worker keeps from task to task.
    Words of Latin letters, which are one unit to the splitter, go straight to the merge rules; so
    do they before a run of ASCII punctuation, which is a unit of its own.  All others take the whole
    way, in one string at a time.  Texts of Latin letters alone are composed already, so A-Z may be lower-cased
    before words are looked up, unless that would write or unwrite one of the vocabulary's added tokens.
    """
    from tokenizers import Tokenizer

    shelf = _shelf()
    if path not in shelf:
        shelf[path] = Tokenizer.from_file(path), {}, splits_at_spaces(path)
    whole, cache, short = shelf[path]
    if not short:
        return lambda text: np.array(whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
    merge, pack, decode = whole.model.tokenize, np.array, codecs.charmap_decode
    table = "".join(v for _, v in sorted(_byte_letters().items()))
    added = [t.content.encode().lower() for t in whole.get_added_tokens_decoder().values()]
    runs: dict[bytes, bytes] = {}

    def many(words: list[str]) -> None:
        e = whole.encode(" ".join(words), add_special_tokens=False)
        ends = np.cumsum([len(w) + 1 for w in words])
        at = np.searchsorted(ends, [a for a, _ in e.offsets], "right")
        cut = np.searchsorted(at, np.arange(len(words) + 1))
        ids = pack(e.ids, "<u4")
        for w, a, b in zip(words, cut, cut[1:]):
            cache[w.encode()] = ids[a:b].tobytes()

    def run_ids(run: bytes) -> bytes:
        if run not in runs:
            if len(runs) >= 1000:
                runs.clear()
            runs[run] = pack(whole.encode(run.decode(), add_special_tokens=False).ids, "<u4").tobytes()
        return runs[run]

    def fill(missing: set[bytes]) -> None:
        other, known = [], cache.get
        for raw in missing:
            core = raw.rstrip(MARKS)
            if core.isalpha():
                low = core.lower()
                got = None if low is raw else known(low)
                if got is None:
                    got = array("I", [t.id for t in merge(low.decode())]).tobytes()
            elif core and max(core) < 0xC4 and (w := core.decode()).isalpha():  # U+00FF is written C3 BF
                got = known(core)
                if got is None:
                    got = array("I", [t.id for t in merge(decode(w.lower().encode(), "strict", table)[0])]).tobytes()
            else:
                other.append(raw.decode())
                continue
            cache[raw] = got if len(core) == len(raw) else got + run_ids(raw[len(core):])
        for i in range(0, len(other), 500):
            many(other[i:i + 500])

    def ids(text: str) -> bytes:
        out, raw = [], text.encode()
        if _latin(text):
            low = raw.lower()
            if not any(a in low for a in added):
                raw = low
        words = raw.split()
        for i in range(0, len(words), 50_000):
            part = words[i:i + 50_000]
            got = list(map(cache.get, part))
            if None in got:
                missing = {w for w, g in zip(part, got) if g is None}
                if len(cache) + len(missing) > CACHED_WORDS:
                    cache.clear()
                    missing = set(part)
                fill(missing)
                got = map(cache.__getitem__, part)
            out.append(b"".join(got))
        return b"".join(out)

    return ids


#: Rows of a file or partition whose pieces are ranked in one group, as bits.
CELL_BITS = 13


def with_place(docs: DataFrame, name: str = "place", columns: list[Column] | None = None) -> DataFrame:
    """docs, or columns of it, with a long that rises with the order in which its rows were written: by file, as numbered
    by the task that wrote it, then by the row's number in its file.  Reading deals files and their
    parts out in an order of its own, which this doesn't depend on.  Rows of other DataFrames have the order of their partitions."""
    own = [F.col(f"`{c}`") for c in docs.columns] if columns is None else columns
    mine = [f"v{i}" for i in range(len(own))]
    try:
        x = docs.select(*[c.alias(m) for c, m in zip(own, mine)], F.col("_metadata.file_path").alias("at_file"), F.col("_metadata.row_index").alias("at_row"))
        names = docs.inputFiles()
    except AnalysisException:
        names = []
    if not names:
        return docs.select(*own, F.monotonically_increasing_id().alias(name))
    files = sorted((f.rsplit("/", 1)[-1] for f in names), key=lambda f: (int((re.match(r"part-(\d+)", f) or [0, 0])[1]), f))
    number = F.map_from_arrays(*[F.from_json(F.lit(json.dumps(v)), f"array<{t}>") for v, t in ((files, "string"), (list(range(len(files))), "long"))])
    at = F.broadcast(docs.sparkSession.range(1).select(F.explode(number).alias("at_name", "at_number")))
    x = x.join(at, F.substring_index("at_file", "/", -1) == F.col("at_name"), "left")
    # a file that is none of them comes last
    number = F.coalesce("at_number", F.lit(len(files)).cast("long"))
    return x.select(*[F.col(m).alias(c) for m, c in zip(mine, docs.select(*own).columns)], (F.shiftleft(number, 33) + F.col("at_row")).alias(name))


def _pieces(path: str, capacity: int, close: int):
    def run(batches):
        ids, end = word_ids(path), np.array([close], "<u4").tobytes()
        for batch in batches:
            rows = []
            for i, place, text in zip(batch["id"].to_pylist(), batch["place"].to_pylist(), batch["text"]):
                b = ids(text.as_py() or "") + end
                for k in range(0, len(b), 4 * capacity):
                    p = b[k:k + 4 * capacity]
                    rows.append((i, k // (4 * capacity), k // 4, len(p) // 4, zlib.crc32(p), place))
            cols = list(zip(*rows)) or [[]] * 6
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64()))], names=["id", "piece", "start", "length", "ids_crc32", "place"])
    return run


def _place(plan: np.ndarray):
    """plan: rows of best_fit_plan, sorted by (length, first rank)."""
    def run(batches):
        key = plan[:, 0] * (1 << 48) + plan[:, 1]
        for batch in batches:
            n, rank = batch["length"].to_numpy(), batch["rank"].to_numpy()
            p = plan[np.searchsorted(key, n * (1 << 48) + rank, "right") - 1]
            k = rank - p[:, 1]
            yield pa.RecordBatch.from_arrays([*(batch[c] for c in ("id", "piece", "start", "length", "ids_crc32", "place")), pa.array(p[:, 3] + k // p[:, 4]), pa.array(p[:, 5] + k % p[:, 4] * n)], names=["id", "piece", "start", "length", "ids_crc32", "place", "sequence_id", "offset"])
    return run


def _numbered(x: DataFrame) -> DataFrame:
    """Sequences numbered anew, by the place of the piece each begins with."""
    heads = x.where("offset = 0").select(F.col("sequence_id").alias("__old"), "place", "piece", F.shiftright("place", CELL_BITS).alias("__cell"))
    counts = heads.groupBy("__cell").agg(F.count("*").alias("n"))
    first = counts.select(F.col("__cell").alias("__c"), (F.sum("n").over(Window.orderBy("__cell")) - F.col("n")).alias("__first"))
    heads = heads.withColumn("__at", F.row_number().over(Window.partitionBy("__cell").orderBy("place", "piece")))
    heads = heads.join(first, F.col("__cell") == F.col("__c")).select("__old", (F.col("__first") + F.col("__at") - 1).alias("__new"))
    return x.join(heads, F.col("sequence_id") == F.col("__old")).withColumn("sequence_id", F.col("__new"))


def pack(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, close: int = CLOSE, in_order: bool = False) -> DataFrame:
    """(id, piece, start, length, ids_crc32, sequence_id, offset): the place of each piece.
    With in_order, the order in which docs was written ranks like pieces and numbers sequences."""
    own = [F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")]
    made = with_place(docs, columns=own) if in_order else docs.select(*own, F.lit(0).cast("long").alias("place"))
    made = stored(made.mapInArrow(_pieces(tokenizer_path, capacity, close), "id long, piece int, start long, length long, ids_crc32 long, place long"))
    counts = {r["length"]: r["n"] for r in made.groupBy("length").agg(F.count("*").alias("n")).collect()}  # capacity rows at most
    plan = np.array(sorted(best_fit_plan(counts, capacity)), np.int64).reshape(-1, 6)
    order = ([F.col("place")] if in_order else [F.col("id")]) + [F.col("piece"), F.col("ids_crc32")]
    x = ranked(made, ["length"], order, "rank", spread_for(sum(counts.values())), F.shiftright("place", CELL_BITS) if in_order else None)
    x = x.select("id", "piece", "start", "length", "ids_crc32", "place", "rank")
    out = x.mapInArrow(_place(plan), "id long, piece int, start long, length long, ids_crc32 long, place long, sequence_id long, offset long")
    if in_order:
        out = _numbered(stored(out))
    return out.select(F.col("id").alias(id_col), "piece", "start", "length", "ids_crc32", "sequence_id", "offset")
