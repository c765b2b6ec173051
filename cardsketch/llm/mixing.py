"""Mixing sources to target weights by Pfair scheduling.

Rows of a source are cut into blocks of `block_rows`.  A fluid that serves all sources at once, in proportion to their
weights, and those that remain at the same ratio when a source has run out, would serve block k of a source
between two moments: the block may not be taken before the slot of the first and must be taken before the
end of the slot of the last.  Earliest deadline first among the released blocks keeps every such window, and so
each source within one block of its target at every slot.  Weights are integers out of 2**40, windows are worked
out in integers.

The driver walks over all blocks once, whatever their number, and writes their slots and windows PART at a time to a
table, which is joined to the rows by source and block; it holds PART windows and a row a source.  By
default that is so for a corpus of any size.  Whoever wants plans of bounded length can set EXACT: a corpus of more blocks then
begins with phases, which end when a source runs out and repeat a period of PATTERN slots over all phases, in
which weights are rounded to whole blocks, and with more than SOURCES sources gets larger blocks.

Every row is emitted once.  A null source is a source of its own.  Repeated rows are rows like any others; ties go
by id and source.  Texts are not read, whatever their length.  Sources without a weight get the mean of those that have one.
"""

from __future__ import annotations

import heapq
import json
from bisect import bisect_right
from collections.abc import Iterator
from fractions import Fraction
from itertools import islice

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import aliased, named, ranked, scratch, spread_for, stored

BLOCK_ROWS, PERIOD = 16, 1000
#: Blocks up to which each has its own window, None: any number; beyond, slots of all periods together and sources up to which there are periods.
EXACT: int | None = None
PATTERN, SOURCES = 1 << 21, 1024
#: Windows that the driver holds at once.
PART = 1 << 18
UNIT = 1 << 40
#: Most starts of ranges, over all sources, that are broadcast.
STARTS = 500_000


def quotas(weights: dict[str, float], period: int) -> dict[str, int]:
    """Integers in proportion to weights, 1 at least, that add up to `period` (or to their number)."""
    period, big, total, q = max(period, len(weights)), dict(weights), sum(weights.values()), {}
    while True:  # those with less than 1 get 1, the others share the rest
        free = period - len(q)
        small = [s for s, w in big.items() if free * w < total]
        if not small:
            break
        for s in small:
            q[s] = 1
            total -= big.pop(s)
        total = sum(big.values())
    exact = {s: free * w / total for s, w in big.items()}
    q |= {s: int(x) for s, x in exact.items()}
    rest = period - sum(q.values())
    for s in sorted(exact, key=lambda s: (q[s] - exact[s], s))[:rest]:
        q[s] += 1
    return q


class Fluid:
    """How far the fluid is when it has served a source k blocks, in slots: k q / q(source), less as sources run out.

    q: weights; blocks: of each source, or none if they never run out."""

    def __init__(self, q: dict[str, int], blocks: dict[str, int]):
        self.q = q
        ends = sorted((Fraction(n, q[s]), s) for s, n in blocks.items())
        self.turn, self.rate, self.done = [Fraction(0)], [sum(q.values())], [0]
        for v, s in ends:
            if v != self.turn[-1]:
                self.turn.append(v)
                self.rate.append(self.rate[-1])
                self.done.append(self.done[-1])
            self.rate[-1] -= q[s]
            self.done[-1] += blocks[s]
        self.near = [float(v) for v in self.turn]

    def at(self, s: str, k: int) -> tuple[int, int]:
        """Numerator and denominator of the moment at which source s has k blocks."""
        q = self.q[s]
        j = max(0, bisect_right(self.near, k / q) - 1)
        while j + 1 < len(self.turn) and self.turn[j + 1].numerator * q <= k * self.turn[j + 1].denominator:
            j += 1
        while j and self.turn[j].numerator * q > k * self.turn[j].denominator:
            j -= 1
        return self.done[j] * q + self.rate[j] * k, q


def walk(q: dict[str, int], slots: int, blocks: dict[str, int]) -> Iterator[tuple[int, str, int, int, int]]:
    """(slot, source, block, release, deadline) in order of slots: earliest deadline first among released blocks."""
    fluid, due, ready = Fluid(q, blocks), dict.fromkeys(q, 0), []
    after = {}  # when the block after the released one is released

    def release(s: str, r: int) -> None:
        n, d = fluid.at(s, due[s] + 1)
        after[s] = n // d
        heapq.heappush(ready, (-(-n // d), s, r))

    for s in q:
        if blocks.get(s, 1):
            release(s, 0)
    coming: list[tuple[int, str]] = []
    for t in range(slots):
        while coming and coming[0][0] <= t:
            r, s = heapq.heappop(coming)
            release(s, r)
        d, s, r = heapq.heappop(ready)
        if d <= t:
            raise AssertionError("a deadline is missed")
        yield t, s, due[s], r, d
        due[s] += 1
        if due[s] != blocks.get(s):
            heapq.heappush(coming, (after[s], s))


def placed(q: dict[str, int], slots: int, blocks: dict[str, int]) -> dict[str, list[tuple[int, int, int]]]:
    """(slot, release, deadline) of each source's blocks in `slots` slots."""
    out: dict[str, list[tuple[int, int, int]]] = {s: [] for s in q}
    for t, s, _, r, d in walk(q, slots, blocks):
        out[s].append((t, r, d))
    return out


def schedule(blocks: dict[str, int], weights: dict[str, float], period: int = PERIOD) -> list[dict]:
    """A row (source, phase, first, last, start, quota, period, slots, release, deadline) a phase and source: blocks
    first..last of the source, counted from the phase's first, lie at start + slots[k] in the last phase, whose windows
    are start + release[k] and start + deadline[k], and at start + period * (k // quota) + slots[k % quota] in others."""
    left, done, start, phase, out = {s: n for s, n in blocks.items() if n}, dict.fromkeys(blocks, 0), 0, 0, []
    long = max(period, PATTERN // max(1, len(left)))
    while left:
        w, total = {s: weights[s] for s in left}, sum(left.values())
        exact = EXACT is None or total <= max(EXACT, period)
        if exact:
            q, end, p = quotas(w, UNIT), total, 0
            made = placed(q, total, left)
            n_of = left
        else:
            q = quotas(w, long)
            p = sum(q.values())
            made = placed(q, p, {})
            end = min((n - 1) // q[s] * p + made[s][(n - 1) % q[s]][0] + 1 for s, n in left.items())
            n_of = {s: end // p * q[s] + sum(x[0] < end % p for x in made[s]) for s in left}
        for s in sorted(left):
            if n_of[s]:
                slots, release, deadline = ([x[i] for x in made[s]] for i in range(3))
                out.append({"source": s, "phase": phase, "first": done[s], "last": done[s] + n_of[s] - 1, "start": start, "quota": q[s], "period": p, "slots": slots, "release": release if exact else [], "deadline": deadline if exact else []})
        for s, n in n_of.items():
            done[s] += n
        left = {s: n - n_of[s] for s, n in left.items() if n > n_of[s]}
        start, phase = start + end, phase + 1
    return out


def target_weights(counts: dict[str, int], given: dict[str, float] | None = None, power: float = 0.5) -> dict[str, float]:
    """The weights given, or the counts to a power under 1, which evens sources out."""
    if given:
        mean = sum(given.values()) / len(given)
        return {s: given.get(s, mean) for s in counts}
    return {s: max(1, n) ** power for s, n in counts.items()}


NONE = "\u0000none"


def _keyed(id_col: str, source_col: str) -> list[Column]:
    """id, source, the source's key, and a hash of the id of 63 bits."""
    i, s = F.col(id_col).cast("long"), F.col(source_col).cast("string")
    return [i.alias("id"), s.alias("source"), F.coalesce(s, F.lit(NONE)).alias("key"), F.shiftrightunsigned(F.xxhash64(F.lit(7), i), 1).alias("hash")]


def _windows(spark: SparkSession, blocks: dict[str, int], weights: dict[str, float]) -> DataFrame:
    """(k2, block, release, deadline, slot) of all blocks, as the driver walks over them, PART at a time."""
    kind = "k2 string, b2 long, release long, deadline long, slot long"
    path, x = scratch(spark), walk(quotas(weights, UNIT) if blocks else {}, sum(blocks.values()), blocks)
    spark.createDataFrame([], kind).write.parquet(path)
    while part := list(islice(x, PART)):
        slot, k2, block, release, deadline = zip(*part)
        whole = pa.table({"k2": pa.array(k2, pa.string()), "b2": block, "release": release, "deadline": deadline, "slot": slot})
        spark.createDataFrame(whole).write.mode("append").parquet(path)
    return spark.read.schema(kind).parquet(path)


def _planned(x: DataFrame, weights: dict[str, float] | None, block_rows: int, period: int) -> tuple[DataFrame, int, int]:
    """The schedule, the rows of the largest source, and those of a block.  The schedule has a row a block (k2, b2,
    release, deadline, slot) or, beyond EXACT blocks, a row a source (k2, phases)."""
    counts = {r["key"]: r["n"] for r in x.groupBy("key").agg(F.count("*").alias("n")).collect()}  # a row a source
    if EXACT is not None and len(counts) > SOURCES:  # the last block of a source may be short
        block_rows = max(block_rows, -(-sum(counts.values()) // max(1, EXACT - len(counts))))
    blocks, target, most = {s: -(-n // block_rows) for s, n in counts.items()}, target_weights(counts, weights), max(counts.values(), default=1)
    if EXACT is None or sum(blocks.values()) <= max(EXACT, period):
        return _windows(x.sparkSession, blocks, target), most, block_rows
    per: dict[str, list] = {s: [] for s in counts}
    for r in schedule(blocks, target, period):
        per[r.pop("source")].append(r)
    kind = "array<struct<source:string,phases:array<struct<phase:int,first:long,last:long,start:long,quota:long,period:long,slots:array<long>,release:array<long>,deadline:array<long>>>>>"
    table = x.sparkSession.range(1).select(F.explode(F.from_json(F.lit(json.dumps([{"source": s, "phases": p} for s, p in per.items()])), kind)).alias("x")).select(F.col("x.source").alias("k2"), "x.phases")
    return table, most, block_rows


def _slotted(x: DataFrame, table: DataFrame, block_rows: int) -> DataFrame:
    """Adds block, phase, release, deadline, slot and place to rows with key and rank."""
    x = x.withColumn("block", F.floor(F.col("rank") / block_rows)).withColumn("place", (F.col("rank") % block_rows).cast("int"))
    if "phases" not in table.columns:
        x = x.join(table, (F.col("key") == F.col("k2")) & (F.col("block") == F.col("b2")))
        return x.withColumn("phase", F.lit(0)).drop("k2", "b2")
    x = x.join(F.broadcast(table), F.col("key") == F.col("k2"))
    x = x.withColumn("p", F.get(F.filter("phases", lambda p: (p["first"] <= F.col("block")) & (F.col("block") <= p["last"])), F.lit(0)))
    x = x.withColumn("k", (F.col("block") - F.col("p.first")).cast("int"))
    k, own = F.col("block") - F.col("p.first"), F.col("p.period") == 0

    def of(name: str, formula: str) -> Column:
        return F.col("p.start") + F.when(own, F.get(f"p.{name}", F.col("k"))).otherwise(F.expr(formula))

    x = x.withColumn("n", k)
    return x.withColumns({
        "block": F.col("block").cast("long"),
        "phase": F.col("p.phase"),
        "release": of("release", "n * p.period div p.quota"),
        "deadline": of("deadline", "((n + 1) * p.period + p.quota - 1) div p.quota"),
        "slot": of("slots", "n div p.quota * p.period + get(p.slots, cast(n % p.quota as int))"),
    }).drop("k2", "phases", "p", "k", "n")


def _ranks(x: DataFrame, most: int) -> DataFrame:
    """Ranks within a source, which rise with (hash, id)."""
    spread = spread_for(most, 4000)
    return ranked(x, ["key"], [F.col("hash"), F.col("id")], "rank", spread, F.floor(F.col("hash") / F.lit(-(-(1 << 63) // spread))).cast("int"))


def mix(docs: DataFrame, weights: dict[str, float] | None = None, id_col: str = "doc_id", source_col: str = "source", block_rows: int = BLOCK_ROWS, period: int = PERIOD) -> DataFrame:
    """(id, source, block, phase, release, deadline, slot, place): block is the source's block, slot its
    place among all blocks, release and deadline the slots it had to lie between, place the row's
    place in its block."""
    x = docs.select(*_keyed(id_col, source_col))
    table, most, block_rows = _planned(x, weights, block_rows, period)
    x = _slotted(_ranks(x, most), table, block_rows)
    return x.select(F.col("id").alias(id_col), F.col("source").alias(source_col), "block", "phase", "release", "deadline", "slot", "place")


def _bisected(h: Column, i: Column, n: int) -> Column:
    """The last of the sorted array `starts`, of up to n entries, that is at or before (h, i)."""
    def step(at: Column, jump: Column) -> Column:
        e = F.get("starts", at + jump)
        return F.when((at + jump < F.size("starts")) & ((e["hash"] < h) | (e["hash"] == h) & (e["id"] <= i)), at + jump).otherwise(at)

    jumps = F.array(*[F.lit(1 << b) for b in reversed(range(max(1, n).bit_length()))])
    return F.get("starts", F.aggregate(jumps, F.lit(0), step))


def mixed(docs: DataFrame, weights: dict[str, float] | None = None, id_col: str = "doc_id", source_col: str = "source", block_rows: int = BLOCK_ROWS, period: int = PERIOD) -> DataFrame:
    """The rows of docs, all columns, in mixed order.

    Slots rise with (hash, id) within a source.  So one row a source and range of slots, where that
    range starts, tells each row's range from its own columns, and texts move once, to their range, with a row a
    block that brings its slot and sorts before the block's first row.  Only where some (id, source) is repeated or
    an id is null, or there are over STARTS rows of ranges, are places joined to rows, and texts move twice."""
    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    x = docs.select(*_keyed(id_col, source_col))
    table, most, block_rows = _planned(x, weights, block_rows, period)
    place = stored(_slotted(_ranks(x, most), table, block_rows).select("id", "source", "key", "hash", "slot", "place"))
    sources, slots = place.agg(F.count_distinct("key"), F.coalesce(F.max("slot"), F.lit(0)) + 1).first()
    odd = place.where("id is null").head(1) or place.groupBy("id", "key").agg(F.count("*").alias("n")).where("n > 1").head(1)
    if odd or sources * n > STARTS:
        return _joined(docs, place, id_col, source_col)
    lead = place.where("place = 0").withColumn("range", F.expr(f"cast(slot div {-(-slots // n)} as int)"))
    start = lead.groupBy("key", "range").agg(F.min(F.struct("hash", "id")).alias("s"))
    start = start.groupBy(F.col("key").alias("k1")).agg(F.array_sort(F.collect_list(F.struct("s.hash", "s.id", "range"))).alias("starts"))
    start = stored(start)  # sources * n entries, STARTS at most
    i, _, key, h = _keyed(id_col, source_col)
    y = aliased(docs, i.alias("__id"), key.alias("key"), h.alias("__hash"))
    own = [F.lit(None).cast(f.dataType).alias(f.name) for f in y.schema if f.name not in ("__id", "key", "__hash")]
    y = y.join(F.broadcast(start), F.col("key") == F.col("k1")).withColumn("__range", _bisected(F.col("__hash"), F.col("__id"), n)["range"]).drop("k1", "starts")
    y = y.withColumn("__slot", F.lit(None).cast("long"))
    y = y.union(lead.select(*own, F.col("id"), "key", "hash", "range", "slot")).repartitionById(n, "__range")
    inside = Window.partitionBy("__range", "key").orderBy("__hash", "__id", F.col("__slot").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, 0)
    y = y.withColumn("slot", F.last("__slot", True).over(inside)).where("__slot is null").sortWithinPartitions("slot", "__hash", "__id")
    return named(y, docs)


def _joined(docs: DataFrame, place: DataFrame, id_col: str, source_col: str) -> DataFrame:
    """Rows put in order by joining their places; equal (id, source) are told apart by their number."""
    place = place.select(F.col("id").alias("__i"), F.col("source").alias("__s"), F.col("slot").alias("__slot"), F.col("place").alias("__place"))
    same = lambda i, s: Window.partitionBy(i, s)
    place = place.withColumn("__n", F.row_number().over(same("__i", "__s").orderBy("__slot", "__place")))
    x = aliased(docs, F.col(id_col).cast("long").alias("__i1"), F.col(source_col).cast("string").alias("__s1"))
    x = x.withColumn("__n1", F.row_number().over(same("__i1", "__s1").orderBy(F.lit(1))))
    on = F.col("__i1").eqNullSafe(F.col("__i")) & F.col("__s1").eqNullSafe(F.col("__s")) & (F.col("__n1") == F.col("__n"))
    return named(x.join(place, on).orderBy("__slot", "__place"), docs)
