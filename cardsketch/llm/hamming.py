"""Exact top-k search in Hamming space by incremental multi-index hashing.

Vectors become 64-bit codes (the signs of their coordinates; with fewer than 64 the other bits are
zero, and coordinates from 64 on are folded in by XOR, which does not keep nearness).  Codes are
cut into SEGMENTS segments, each with a table from its value to codes.  A query probes all values within
radius 0, 1, 2, ... of its own, segment by segment, and verifies what it finds; once radius r is done
on the first j segments and r - 1 on the others, every code within SEGMENTS * r + j - 1 has been
seen.  A query ends when its k-th verified distance is no more than that.

Equal codes are one entry with its k least ids: no more can be among the k nearest, ties going to the
lesser id.  Entries and queries are dealt over blocks of bounded size, and a task searches one block of
entries for one block of queries, all queries of a radius and segment at once.  Each query first searches one
block; its k-th distance there bounds the search of all others, which end at that radius.  A
query's k best of all blocks are merged.  A query's own row is among its neighbours.  Null vectors, and those
of no coordinates, are left out.  Rows repeated under an id count once.  Other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import stored

SEGMENTS, WIDTH = 8, 8
ENTRIES, QUERIES = 16_384, 16_384
#: Pairs of a query and an entry that are verified at once, which bounds a task's memory.
AT_ONCE = 1 << 20
FAR = 65


class SegmentIndex:
    def __init__(self, codes: np.ndarray):
        self.codes, self.order, self.first = codes, [], []
        for s in range(SEGMENTS):
            v = segment(codes, s)
            self.order.append(np.argsort(v, kind="stable"))
            self.first.append(np.searchsorted(v[self.order[-1]], np.arange(257)))

    def bucket(self, s: int, value: int) -> np.ndarray:
        return self.order[s][self.first[s][value]:self.first[s][value + 1]]


def segment(codes: np.ndarray, s: int) -> np.ndarray:
    return ((codes >> np.uint64(WIDTH * s)) & np.uint64(255)).astype(np.int64)


def verified(q: np.ndarray, e: np.ndarray, r: int, s: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query, entry, distance) of the pairs that no earlier step, by radius and segment, has met."""
    parts = np.bitwise_count((q[:, None] ^ e[None, :]).view(np.uint8).reshape(len(q), len(e), SEGMENTS))
    a, b = np.nonzero(parts.argmin(axis=2) == s)  # the first segment of least distance is where a pair meets
    return a, b, parts[a, b].sum(axis=1, dtype=np.int64)


def nearest(index: SegmentIndex, queries: np.ndarray, limit: np.ndarray, weight: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query, entry, distance) among which are, for each query, the rows among its k nearest that lie within its
    limit; weight: rows of each entry."""
    within = np.zeros((len(queries), FAR), np.int64)
    bound = np.minimum(limit, FAR - 1).astype(np.int64)  # no row beyond it is wanted
    live, found = np.arange(len(queries)), []
    value = [segment(queries, s) for s in range(SEGMENTS)]
    for r in range(WIDTH + 1):
        for s in range(SEGMENTS):
            own = value[s][live]
            for v in range(256):
                e = index.bucket(s, v)
                if not len(e):
                    continue
                asking = live[np.bitwise_count((own ^ v).astype(np.uint64)) == r]
                step = max(1, AT_ONCE // len(e))
                for at in range(0, len(asking), step):
                    q = asking[at:at + step]
                    a, b, d = verified(queries[q], index.codes[e], r, s)
                    near = d <= bound[q[a]]
                    a, b, d = q[a[near]], e[b[near]], d[near]
                    np.add.at(within, (a, d), weight[b])
                    found.append((a.astype(np.int32), b.astype(np.int32), d.astype(np.int8)))
            enough = np.cumsum(within[live], axis=1) >= k
            bound[live] = np.where(enough.any(axis=1), np.minimum(bound[live], enough.argmax(axis=1)), bound[live])
            live = live[bound[live] > SEGMENTS * r + s]  # those whose bound is not covered yet
            if not len(live):
                break
        if not len(live):
            break
        found = [tuple(x[keep] for x in f) for f in found for keep in [f[2] <= bound[f[0]]]]
    if not found:
        return (np.zeros(0, np.int64),) * 3
    a, b, d = (np.concatenate(x).astype(np.int64) for x in zip(*found))
    keep = d <= bound[a]
    return a[keep], b[keep], d[keep]


def _search(k: int):
    """From the queries (code, limit) and entries (code, ids) of a pair of blocks: each query's rows among its k nearest."""
    def run(q: pd.DataFrame, e: pd.DataFrame) -> pd.DataFrame:
        out = pd.DataFrame({"query": np.zeros(0, np.int64), "id": np.zeros(0, np.int64), "distance": np.zeros(0, np.int32)})
        if not len(q) or not len(e):
            return out
        codes, queries = (x["code"].to_numpy().view(np.uint64) for x in (e, q))
        size = e["ids"].str.len().to_numpy()
        ids, first = np.concatenate(e["ids"].to_list()), np.concatenate(([0], np.cumsum(size)))
        a, b, d = nearest(SegmentIndex(codes), queries, q["limit"].to_numpy(), size, k)
        n = size[b]
        a, d = np.repeat(a, n), np.repeat(d, n)
        i = ids[np.repeat(first[b], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)]
        o = np.lexsort((i, d, a))
        a, d, i = a[o], d[o], i[o]
        rank = np.arange(len(a)) - np.searchsorted(a, a)
        keep = rank < k
        return pd.DataFrame({"query": queries[a[keep]].view(np.int64), "id": i[keep], "distance": d[keep].astype(np.int32)})
    return run


def code_column(vectors: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """(id, code): the sign of coordinate i is bit i; coordinates from 64 on are folded in by XOR."""
    bit = F.aggregate(
        F.transform(F.col(vector_col), lambda x, i: F.when(x > 0, F.call_function("shiftleft", F.lit(1).cast("long"), i % 64)).otherwise(F.lit(0).cast("long"))),
        F.lit(0).cast("long"), lambda a, b: a.bitwiseXOR(b))
    x = vectors.where(F.col(id_col).isNotNull() & (F.size(vector_col) > 0))
    return x.select(F.col(id_col).cast("long").alias("id"), bit.alias("code"))


def top_k(vectors: DataFrame, k: int = 10, every: int = 20, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(id, rank, neighbour, distance): for each row whose id is divisible by `every`, its k nearest rows."""
    spark = vectors.sparkSession
    rows = stored(code_column(vectors, id_col, vector_col).distinct())
    best = Window.partitionBy("code").orderBy("id")
    entries = rows.withColumn("n", F.row_number().over(best)).where(F.col("n") <= k).groupBy("code").agg(F.collect_list("id").alias("ids"))
    entries = stored(entries)
    asked = stored(rows.where(F.col("id") % every == 0))
    codes = stored(asked.select("code").distinct())
    parallel = max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    nb, most = max(1, -(-entries.count() // ENTRIES)), codes.count()
    # blocks of queries: as few as fit, for each copies the entries, but enough to keep all cores busy
    nq = max(1, -(-most // QUERIES), min(-(-parallel // nb), most // 64))
    block = lambda n, seed: F.pmod(F.xxhash64(F.lit(seed), "code"), F.lit(n)).cast("int")
    dealt = entries.select("code", "ids", block(nb, 3).alias("eb"))

    def searched(q: DataFrame, e: DataFrame) -> DataFrame:
        """One task's unit is a pair of blocks, in partitions of its own number, which are not merged."""
        n = min(nb * nq, 16 * parallel)
        pair = (F.col("eb") * nq + F.col("qb")).cast("int").alias("pair")
        q, e = q.select("code", "limit", pair).repartition(n, "pair"), e.select("code", "ids", pair).repartition(n, "pair")
        return q.groupBy("pair").cogroup(e.groupBy("pair")).applyInPandas(_search(k), "query long, id long, distance int")

    q = codes.select("code", F.lit(FAR).alias("limit"), block(nq, 5).alias("qb")).withColumn("eb", F.col("qb") % nb)
    spread = lambda e, keep: e.withColumn("qb", F.explode(F.sequence(F.lit(0), F.lit(nq - 1)))).where(keep)
    home = F.col("qb") % nb == F.col("eb")
    found = searched(q, spread(dealt, home))
    if nb > 1:
        found = stored(found)
        limit = found.groupBy("query").agg(F.when(F.count("*") >= k, F.max("distance")).otherwise(FAR).alias("far"))
        q = q.drop("limit", "eb").join(limit, F.col("code") == F.col("query"), "left").withColumn("limit", F.coalesce("far", F.lit(FAR)))
        q = stored(q.select("code", "limit", "qb")).withColumn("eb", F.explode(F.sequence(F.lit(0), F.lit(nb - 1)))).where(~home)
        found = found.union(searched(q, spread(dealt, ~home)))
    order = Window.partitionBy("query").orderBy("distance", "id")
    found = found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)
    found = stored(found)  # a join of two written tables can be split where a code is hot
    return asked.join(found.withColumnRenamed("id", "neighbour"), F.col("code") == F.col("query")).select(F.col("id").alias(id_col), "rank", "neighbour", "distance")
