"""Document fingerprints by one-permutation MinHash, with built-in expressions only.

Each five-word shingle is hashed once; the top bits choose one of BINS bins, which keeps its least hash.
An empty bin takes the value of the non-empty bin that comes first in a keyed order of its own: TRIES
drawn bins, then all by a keyed hash (optimal densification).  The fingerprint is the low byte of each bin,
packed as hex; chance matches of bytes, 1 in 256, are taken out of the likeness.

Texts of fewer words are one shingle; null, empty and blank texts have a fingerprint of their own.
Words are those between white space, in lower case.  Equal texts have equal fingerprints.  Other columns
are not read.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

BINS, WORDS, BITS, TRIES = 128, 5, 8, 8
#: Rows of a range of ids, and most ranges, whose bounds travel with the plan.
RANGE_ROWS, RANGES = 20_000, 1 << 16


def _bin(h: Column) -> Column:
    return F.call_function("shiftrightunsigned", h, F.lit(64 - BINS.bit_length() + 1)).cast("int")


def _drawn() -> Column:
    """For each bin the bins that are tried first if it is empty, as array<array<int>>."""
    bins = np.random.default_rng(5).integers(0, BINS, (BINS, TRIES)).tolist()
    return F.from_json(F.lit(str(bins)), "array<array<int>>")


def with_bins(df: DataFrame, text: Column, name: str, words: int = WORDS) -> DataFrame:
    """df with `name`: the low bytes of all bins, as an array of smallint."""
    t = f"__{name}"
    split = F.filter(F.split(F.lower(text), "[ \\t\\n\\x0B\\f\\r]+"), lambda w: w != "")
    df = df.withColumn(f"{t}_w", F.transform(split, lambda w: F.xxhash64(w)))
    w = F.col(f"{t}_w")
    whole = F.when(F.size(w) > 0, F.array(F.xxhash64(w))).otherwise(F.array().cast("array<long>"))
    rolling = F.transform(F.sequence(F.lit(0), F.size(w) - words), lambda i: F.xxhash64(*[F.get(w, i + k) for k in range(words)]))
    df = df.withColumn(f"{t}_h", F.sort_array(F.when(F.size(w) >= words, rolling).otherwise(whole)))
    h = F.col(f"{t}_h")
    # sorted: a bin's hashes follow each other, least first
    df = df.withColumn(f"{t}_m", F.filter(h, lambda x, i: (i == 0) | (_bin(x) != _bin(F.get(h, F.greatest(i - 1, F.lit(0)))))))
    df = df.withColumn(f"{t}_b", F.transform(f"{t}_m", _bin))
    m, b = F.col(f"{t}_m"), F.col(f"{t}_b")
    every = F.sequence(F.lit(0), F.lit(BINS - 1))
    df = df.withColumn(f"{t}_p", F.transform(every, lambda i: F.array_position(b, i).cast("int")))  # place in m, 0 if empty
    p, drawn = F.col(f"{t}_p"), _drawn()

    def tried(i: Column) -> Column:
        return F.aggregate(F.get(drawn, i), F.lit(0), lambda at, c: F.when(at > 0, at).otherwise(F.get(p, c)))

    def last(i: Column) -> Column:
        return F.array_min(F.transform(m, lambda v: F.struct(F.xxhash64(F.lit(5), i, _bin(v)).alias("order"), v.alias("v"))))["v"]

    def value(i: Column) -> Column:
        place = F.when(F.get(p, i) > 0, F.get(p, i)).otherwise(tried(i))
        return F.get(F.transform(F.array(place), lambda at: F.when(at > 0, F.get(m, at - 1)).otherwise(last(i))), F.lit(0))

    low = F.transform(every, lambda i: value(i).bitwiseAND(F.lit(255)).cast("smallint"))
    blank = F.transform(every, lambda i: (i * 37 % 256).cast("smallint"))
    return df.withColumn(name, F.when(F.size(m) == 0, blank).otherwise(low)).drop(*[f"{t}_{c}" for c in "whmbp"])


def packed(low: Column) -> Column:
    return F.array_join(F.transform(low, lambda v: F.lower(F.lpad(F.hex(v), 2, "0"))), "")


def likeness(a: Column, b: Column) -> Column:
    """The share of shingles in common, from matching bytes less those that match by chance."""
    same = F.size(F.filter(F.zip_with(a, b, lambda x, y: x == y), lambda x: x)) / F.lit(float(BINS))
    chance = 1.0 / (1 << BITS)
    return F.greatest(F.lit(0.0), (same - chance) / (1 - chance))


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fingerprint) for each row."""
    x = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    return with_bins(x, F.col("text"), "low").select(F.col("id").alias(id_col), packed(F.col("low")).alias("fingerprint"))


def bounds_of(cuts: list[int]) -> list[tuple[int, int]]:
    """Bounds (order, hash) from sorted cuts of the order: where cuts fall together, as one value has the rows
    of several ranges, its rows are cut by their hashes."""
    out = []
    for v in sorted(set(cuts)):
        n = cuts.count(v)
        out += [(v, (1 << 64) * j // n - (1 << 63) - 1) for j in range(1, n + 1)]
    return out


def _longs(values: list[int]) -> Column:
    return F.from_json(F.lit(str(values)), "array<long>")


def _cell(o: Column, h: Column, bounds: list[tuple[int, int]]) -> Column:
    """How many of bounds lie under (o, h), by bisection."""
    size = 1
    while size <= len(bounds):
        size *= 2
    most = (1 << 63) - 1
    full = [*bounds, *[(most, most)] * (size - len(bounds))]
    orders, hashes = _longs([a for a, _ in full]), _longs([b for _, b in full])
    steps = F.array(*[F.lit(size >> k) for k in range(1, size.bit_length())])

    def under(i: Column) -> Column:
        return (F.get(orders, i) < o) | ((F.get(orders, i) == o) & (F.get(hashes, i) < h))
    return F.aggregate(steps, F.lit(0), lambda at, s: F.when(under(at + s - 1), at + s).otherwise(at))


def compare_edited(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", cells: int | None = None) -> DataFrame:
    """(id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next) for each row.

    The edited text has its last floor(n_chars / 3) characters replaced by the first of the next text
    by descending id (null ids last, ties by descending xxhash64 of the text; after the last the first).  Texts
    move once, dealt over ranges of (id, hash); the first row of each range is also sent to the range before it, so that
    no range waits for another.  Only rows equal in id and text can't be parted.  Bounds, a pair a range, are
    literals of the plan."""
    spark = docs.sparkSession
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    x = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(id_col).cast("long"), F.lit(-(1 << 63))).alias("order"), F.xxhash64(text).alias("hash"), text.alias("text"))
    if not cells:
        cells = min(RANGES, max(2 * int(spark.conf.get("spark.sql.shuffle.partitions")), x.count() // RANGE_ROWS))
    cuts = x.agg(F.percentile_approx("order", [i / cells for i in range(1, cells)], max(10_000, 4 * cells))).first()[0] if cells > 1 else []
    bounds = bounds_of(list(cuts or []))
    x = x.withColumn("cell", _cell(F.col("order"), F.col("hash"), bounds))
    firsts = {r["cell"]: r["m"] for r in x.groupBy("cell").agg(F.max(F.struct("order", "hash")).alias("m")).collect()}  # `cells` rows and a few
    full = sorted(firsts)
    before = {c: full[(i + 1) % len(full)] for i, c in enumerate(full)}  # the range that ends where c begins
    n = len(bounds) + 1
    first = (F.col("order") == F.get(_longs([firsts[c]["order"] if c in firsts else 0 for c in range(n)]), F.col("cell"))) & (F.col("hash") == F.get(_longs([firsts[c]["hash"] if c in firsts else 0 for c in range(n)]), F.col("cell")))
    sent_to = F.get(_longs([before.get(c, 0) for c in range(n)]), F.col("cell")).cast("int")
    own = F.struct(F.col("cell").alias("to"), F.lit(False).alias("guest"))
    guest = F.struct(sent_to.alias("to"), F.lit(True).alias("guest"))
    x = x.withColumn("at", F.explode(F.when(first, F.array(own, guest)).otherwise(F.array(own)))).select("id", "order", "hash", "text", "at.to", "at.guest")
    x = with_bins(x.repartitionById(n, "to"), F.col("text"), "low")
    by = Window.partitionBy("to").orderBy("guest", F.col("order").desc(), F.col("hash").desc(), "text")
    x = x.withColumn("next", F.lead(F.struct("text", "low")).over(by)).where("not guest")
    x = x.withColumn("n_chars", F.length("text").cast("long"))
    cut = F.floor(F.col("n_chars") / 3).cast("int")
    x = x.withColumn("edited", F.concat(F.substr("text", F.lit(1), F.col("n_chars").cast("int") - cut), F.substr("next.text", F.lit(1), cut)))
    x = with_bins(x, F.col("edited"), "low2")
    return x.select(
        F.col("id").alias(id_col), "n_chars", F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"), packed(F.col("low")).alias("fingerprint"), packed(F.col("low2")).alias("edited_fingerprint"),
        likeness(F.col("low"), F.col("low2")).alias("near_edited"), likeness(F.col("low"), F.col("next.low")).alias("near_next"))
