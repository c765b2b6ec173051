"""Sharding by a consistent-hash ring with virtual nodes and bounded loads.

A row's key hashes to one of `cells` points of a ring; each shard owns the arcs that end at its virtual
nodes.  A shard takes rows up to its capacity, and what is over goes on clockwise to the next shard
with room.  Capacities add up to the number of rows and differ by one at most, so the law that holds
is `rows`: counts are at most one apart.  Only the cells' counts come to the driver, which walks the
ring on them; rows find their shard by their rank within their cell.

Null text has size 8.  Repeated rows are rows of their own.  The key is the id; null is a key too.
"""

from __future__ import annotations

import json
from bisect import bisect_left
from collections import deque
from hashlib import blake2b

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ranked, spread_for

CELLS, VIRTUAL = 8192, 64


def ring(shards: int, virtual: int = VIRTUAL, cells: int = CELLS) -> list[int]:
    """The shard that owns each cell: that of the first virtual node from the cell on, clockwise."""
    nodes: dict[int, tuple[bytes, int]] = {}
    for s in range(shards):
        for v in range(virtual):
            h = blake2b(f"{s}/{v}".encode(), digest_size=16).digest()
            at = int.from_bytes(h[:8]) % cells
            nodes[at] = min(nodes.get(at, (h, s)), (h, s))
    points = sorted(nodes)
    return [nodes[points[bisect_left(points, c) % len(points)]][1] for c in range(cells)]


def bounded_loads(counts: dict[int, int], owners: list[int], shards: int) -> list[tuple[int, int, int, int, int]]:
    """Rows (cell, first rank, rows, shard, first slot): a shard takes its own cells' rows in ring order
    until it is full; the rest is carried clockwise, first come first served."""
    total = sum(counts.values())
    room = [total // shards + (s < total % shards) for s in range(shards)]
    used, out, over = [0] * shards, [], {}

    def give(cell: int, first: int, n: int, s: int) -> int:
        m = min(n, room[s] - used[s])
        if m:
            out.append((cell, first, m, s, used[s]))
            used[s] += m
        return m

    for c in sorted(counts):
        m = give(c, 0, counts[c], owners[c])
        if m < counts[c]:
            over[c] = (m, counts[c] - m)
    carried: deque[list[int]] = deque()
    for lap in range(2):
        for c, s in enumerate(owners):
            if not lap and c in over:
                carried.append([c, *over[c]])
            while carried and used[s] < room[s]:
                x = carried[0]
                m = give(x[0], x[1], x[2], s)
                x[1], x[2] = x[1] + m, x[2] - m
                if not x[2]:
                    carried.popleft()
    return out


def _table(spark: SparkSession, rows: list[tuple[int, ...]], names: list[str]) -> DataFrame:
    kind = "array<array<long>>"
    x = spark.range(1).select(F.explode(F.from_json(F.lit(json.dumps(rows)), kind)).alias("x"))
    return x.select(*[F.get("x", F.lit(i)).alias(n) for i, n in enumerate(names)])


def shard(docs: DataFrame, shards: int = 24, id_col: str = "doc_id", text_col: str = "text", cells: int = CELLS, virtual: int = VIRTUAL) -> DataFrame:
    """(id, size, text_crc32, law, shard, slot, grown_shard) for each row."""
    spark = docs.sparkSession
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    x = docs.select(F.col(id_col).cast("long").alias("id"), (F.octet_length(text) + 8).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"))
    x = x.withColumn("cell", F.pmod(F.xxhash64(F.lit(11), "id"), F.lit(cells)).cast("int"))
    counts = {r["cell"]: r["n"] for r in x.groupBy("cell").agg(F.count("*").alias("n")).collect()}  # `cells` rows at most
    plan = bounded_loads(counts, ring(shards, virtual, cells), shards)  # cells + shards rows and a few
    x = ranked(x, ["cell"], [F.col("id"), F.col("text_crc32"), F.col("size")], "rank", spread_for(max(counts.values(), default=1), 20_000, 1))
    table = _table(spark, plan, ["c2", "first", "n", "shard", "slot0"])
    on = (F.col("cell") == F.col("c2")) & (F.col("rank") >= F.col("first")) & (F.col("rank") < F.col("first") + F.col("n"))
    x = x.join(F.broadcast(table), on)
    return x.select(F.col("id").alias(id_col), "size", "text_crc32", F.lit("rows").alias("law"), F.col("shard").cast("int").alias("shard"), (F.col("slot0") + F.col("rank") - F.col("first")).alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
