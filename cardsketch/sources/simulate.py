"""Simulated streams: literal ones, and the race of bits for their cells.

In the race, the first arrival of bit k in a cell is exponential with rate 2**-k / m per element, which
is exact when elements arrive as a Poisson process; a stream then costs about 40 m draws, not n.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import SketchConfig
from ..functions.constants import LOGLOG, PHI, alpha, gamma, martingale_variance, variance
from ..functions.hashing import low_bit
from ..operators.entropy import solve
from ..operators.tailcut import TailCut

#: methods of each plot: (method, cells over 2**b as a ratio)
PLOTS = {"a": (("nb", 1.0), ("hll", 7 / 6)), "b": (("mart_nb", 1.0), ("mart_hll", 7 / 6)), "c": (("tc_nb", 1.0), ("tc_hll", 5 / 4))}


def literal(spark: SparkSession, streams: int, n: int, cfg: SketchConfig) -> DataFrame:
    """(stream_id, bucket, bit): n distinct elements in each of `streams` streams."""
    x = spark.range(streams * n).select((F.col("id") / n).cast("int").alias("stream_id"), (F.col("id") % n).alias("e"))
    cell = F.pmod(F.xxhash64(F.lit(1), "stream_id", "e"), F.lit(cfg.m).cast("long")).cast("int")
    return x.select("stream_id", cell.alias("bucket"), low_bit(F.shiftrightunsigned(F.xxhash64(F.lit(2), "stream_id", "e"), 4), cfg.rho_bits).alias("bit"))


def _terms(kind: str, bits: np.ndarray) -> np.ndarray:
    """Terms of cells from their bitmaps."""
    top = np.zeros(bits.shape, np.int64)
    some = bits > 0
    top[some] = np.floor(np.log2(bits[some].astype(np.float64))).astype(np.int64) + 1
    out = 2.0**-top
    if kind == "nb":
        unseen = (top >= 2) & ((bits >> np.maximum(top - 2, 0)) & 1 == 0)
        out = np.where(unseen, 3 * out, out)
    return out


def _far_arrivals(rng: np.random.Generator, m: int, n: float, cut: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(time, cell, rank) of all arrivals of ranks over `cut` up to n, in order of time."""
    size = rng.poisson(n * 2.0**-cut)
    return np.sort(rng.uniform(0, n, size)), rng.integers(0, m, size), cut + rng.geometric(0.5, size)


def _base_before(t: np.ndarray, times: np.ndarray) -> np.ndarray:
    """The least register, of first-arrival times t of ranks 1, 2, ... in each cell, just before each of `times`."""
    rank = np.arange(1, t.shape[1] + 1)
    return np.array([np.where(t < x, rank, 0).max(axis=1).min() for x in times], np.int64)


def tail_cut_cells(t: np.ndarray, far: tuple[np.ndarray, np.ndarray, np.ndarray], at: float, cut: int) -> tuple[np.ndarray, np.ndarray]:
    """(top, nbr) of a sequential tail-cut sketch at a moment.

    t: first arrivals of ranks 1..cut, which no offset cuts, by cell.  Only cells with arrivals beyond
    the cut differ from a lossless sketch: they are replayed.  The base they are cut by is the least register of a
    lossless sketch, as long as that is under the cut, which for 4 bits it is up to some 2**16 elements a cell."""
    rank = np.arange(1, cut + 1)
    seen = t <= at
    top = np.where(seen, rank, 0).max(axis=1)
    under = np.take_along_axis(np.concatenate((np.ones((len(t), 2), bool), seen), axis=1), top[:, None], axis=1)[:, 0]
    nbr = np.where(top < 2, 1, under.astype(np.int64))
    times, cells, ks = far
    live = times <= at
    if not live.any():
        return top, nbr
    times, cells, ks = times[live], cells[live], ks[live]
    base = _base_before(t, times)
    for c in np.unique(cells):
        events = [(x, k, 0) for x, k in zip(t[c], rank) if x <= at] + [(x, k, b + cut) for x, k, b in zip(times[cells == c], ks[cells == c], base[cells == c])]
        a, b = 0, 1
        for _, k, most in sorted(events):
            k = min(k, most) if most else k
            if k > a:
                a, b = k, 1 if k == 1 or (k == a + 1 and a > 0) else 0
            elif k == a - 1:
                b = 1
        top[c], nbr[c] = a, b
    return top, nbr


def _replayed(rng: np.random.Generator, m: int, at: np.ndarray, width: int, kind: str):
    """The sketch at each checkpoint, element by element; for offsets of 2 or 3 bits, by which a cut cell can fall
    behind all others.  An uncut rank counts at its first arrival only."""
    from ..operators.tailcut import TailCut

    n = int(at[-1])
    cell, k = rng.integers(0, m, n), rng.geometric(0.5, n)
    keep = k >= (1 << width)
    keep[np.unique(cell * 64 + np.minimum(k, 63), return_index=True)[1]] = True
    t, i, places = TailCut(m, width, kind), 0, np.flatnonzero(keep)
    for x in at:
        while i < len(places) and places[i] < x:
            t.add(int(cell[places[i]]), int(k[places[i]]))
            i += 1
        yield t


def run_stream(rng: np.random.Generator, method: str, m: int, at: np.ndarray, width: int = 4, depth: int = 44) -> np.ndarray:
    """Estimates of one stream at the checkpoints; for mart_ methods, the retrospective variances after them."""
    kind = method.split("_")[-1]
    c = {"nb": gamma, "hll": alpha}[kind](m) * m * m if kind in ("nb", "hll") else 0.0
    if method.startswith("tc"):
        cut = (1 << width) - 1
        if width < 4:
            return np.array([c / (2.0**-t.tops() * ((3 - 2 * t.nbr) if kind == "nb" else 1)).sum() for t in _replayed(rng, m, at, width, kind)])
        t = rng.exponential(1, (m, cut)) * m * 2.0 ** np.arange(1, cut + 1)
        far, out = _far_arrivals(rng, m, at[-1], cut), []
        for x in at:
            top, nbr = tail_cut_cells(t, far, x, cut)
            out.append(c / (2.0**-top * ((3 - 2 * nbr) if kind == "nb" else 1)).sum())
        return np.array(out)
    k = np.arange(1, depth + 1)
    t = rng.exponential(1, (m, depth)) * m * 2.0**k
    if not method.startswith("mart"):
        out = []
        for x in at:
            bits = ((t <= x) << (k - 1)).sum(axis=1)
            if kind in ("loglog", "pcsa"):
                some = np.where(t <= x, k, 0).max(axis=1) if kind == "loglog" else np.where(t > x, k, depth + 1).min(axis=1) - 1
                out.append((LOGLOG * m if kind == "loglog" else m / PHI) * 2.0 ** some.mean())
                continue
            s, empty = _terms(kind, bits).sum(), int((bits == 0).sum())
            e = c / s
            out.append(m * np.log(m / empty) if e < 2.5 * m and empty else e)
        return np.array(out)
    live = t <= at[-1]
    cell, j = np.nonzero(live)
    times = t[cell, j]
    o = np.lexsort((times, cell))
    cell, j, times = cell[o], j[o], times[o]
    first = np.concatenate(([True], cell[1:] != cell[:-1]))
    bits = np.int64(1) << j
    # the bitmap of a cell after each arrival: bits are distinct, so sums are ORs
    run = np.cumsum(bits.astype(np.uint64))
    start = np.maximum.accumulate(np.where(first, np.arange(len(cell)), 0))
    after = (run - (run[start] - bits[start].astype(np.uint64))).astype(np.int64)
    terms = _terms(kind, after)
    delta = terms - np.where(first, 1.0, np.concatenate(([1.0], terms[:-1])))
    o = np.argsort(times)
    times, delta = times[o], delta[o]
    keep = delta != 0
    times, delta = times[keep], delta[keep]
    before = 1 + np.concatenate(([0.0], np.cumsum(delta)[:-1])) / m
    total = np.concatenate(([0.0], np.cumsum(1 / before)))
    own = np.concatenate(([0.0], np.cumsum((1 - before) / before**2)))
    i = np.searchsorted(times, at, "right")
    return np.concatenate((total[i], own[i]))


def streams_of(spark: SparkSession, methods: list[tuple[str, int]], streams: int, at: np.ndarray, seed: int = 1, width: int = 4) -> DataFrame:
    """(stream_id, method, m, checkpoint, estimate, own_variance): simulated streams of each (method, cells)."""
    cols = "stream_id long, method string, m int, checkpoint double, estimate double, own_variance double"

    def run(batches):
        for pdf in batches:
            out = []
            for i in pdf["id"]:
                for j, (name, m) in enumerate(methods):
                    e = run_stream(np.random.default_rng((seed, int(i), j)), name, m, at, width)
                    own = e[len(at):] if len(e) > len(at) else np.full(len(at), np.nan)
                    out.append(pd.DataFrame({"stream_id": int(i), "method": name, "m": m, "checkpoint": at, "estimate": e[:len(at)], "own_variance": own}))
            if out:
                yield pd.concat(out)

    return spark.range(0, streams, 1, min(streams, max(8, streams // 25))).mapInPandas(run, cols)


def plot(spark: SparkSession, which: str, streams: int = 200, cells: int = 64, n: float = 1e5, checkpoints: int = 10, seed: int = 1, width: int = 4) -> DataFrame:
    """(stream_id, method, m, checkpoint, estimate): the two methods of a plot at equal memory."""
    at = n * np.arange(1, checkpoints + 1) / checkpoints
    methods = [(name, -(-int(round(cells * ratio * 1000)) // 1000)) for name, ratio in PLOTS[which]]
    return streams_of(spark, methods, streams, at, seed, width).drop("own_variance")


def plot_errors(spark: SparkSession, which: str, **options) -> DataFrame:
    """(method, m, checkpoint, runs, bias, rel_mse, rel_mse_se, m_mse): rel_mse_se is the standard error of rel_mse."""
    e = F.pow(F.col("estimate") / F.col("checkpoint") - 1, F.lit(2.0))
    x = plot(spark, which, **options).groupBy("method", "m", "checkpoint")
    x = x.agg(F.count("*").alias("runs"), (F.avg(F.col("estimate") / F.col("checkpoint")) - 1).alias("bias"), F.avg(e).alias("rel_mse"), (F.stddev_samp(e) / F.sqrt(F.count("*"))).alias("rel_mse_se"))
    return x.withColumn("m_mse", F.col("m") * F.col("rel_mse"))


def plot_ratio(spark: SparkSession, which: str, **options) -> DataFrame:
    """(better, worse, checkpoint, runs, ratio, ratio_se, predicted): relative errors of a plot's two methods, first over
    second, at equal memory; predicted is the same from the variance constants."""
    a, b = (name for name, _ in PLOTS[which])
    x = plot_errors(spark, which, **options).groupBy("checkpoint").agg(
        F.max("runs").alias("runs"), *[F.max(F.when(F.col("method") == k, F.col(c))).alias(f"{c}_{i}") for i, k in enumerate((a, b)) for c in ("rel_mse", "rel_mse_se", "m")])
    ratio = F.col("rel_mse_0") / F.col("rel_mse_1")
    se = ratio * F.sqrt(F.pow(F.col("rel_mse_se_0") / F.col("rel_mse_0"), F.lit(2.0)) + F.pow(F.col("rel_mse_se_1") / F.col("rel_mse_1"), F.lit(2.0)))
    of = lambda name: martingale_variance(name[5:]) if name.startswith("mart") else variance(name.split("_")[-1], None)
    return x.select(F.lit(a).alias("better"), F.lit(b).alias("worse"), "checkpoint", "runs", ratio.alias("ratio"), se.alias("ratio_se"), (F.lit(of(a) / of(b)) * F.col("m_1") / F.col("m_0")).alias("predicted"))


def measured_products(spark: SparkSession, streams: int = 2000, m: int = 256, n: float = 2e5) -> DataFrame:
    """(method, bits_a_cell, m_var, measured, published): measured memory-variance products for 64-bit hashes; the
    entropy-coded bitmap's is the ideal code length of its streams times the spread of its likelihood estimates."""
    bits = {"pcsa": 64, "loglog": 6, "hll": 6, "nb": 7, "mart_hll": 6, "mart_nb": 7}
    published = {"pcsa": 38.9, "loglog": 10.11, "hll": 6.48, "nb": 5.46, "mart_hll": 6 * 0.69, "mart_nb": 7 * 0.52}
    x = streams_of(spark, [(k, m) for k in bits], streams, np.array([n])).groupBy("method").agg((F.var_samp(F.col("estimate") / n) * m).alias("m_var"))
    pick = lambda d: F.create_map(*[F.lit(v) for kv in d.items() for v in kv])[F.col("method")]
    x = x.select("method", pick({k: float(v) for k, v in bits.items()}).alias("bits_a_cell"), "m_var").withColumn("published", pick(published))

    def entropy(batches):
        for pdf in batches:
            est, size = [], []
            for i in pdf["id"]:
                rng = np.random.default_rng((7, int(i)))
                s = {k: int(rng.binomial(m, -np.expm1(-n / (m * 2.0**k)))) for k in range(1, 45)}
                e, b = solve(s, m)
                est.append(e / n)
                size.append(b / m)
            yield pd.DataFrame({"estimate": est, "bits": size})

    few = spark.range(0, min(streams, 500), 1, 8).mapInPandas(entropy, "estimate double, bits double")
    e = few.agg(F.lit("entropy").alias("method"), F.avg("bits").alias("bits_a_cell"), (F.var_samp("estimate") * m).alias("m_var"), F.lit(1.98).alias("published"))
    return x.unionByName(e).select("method", "bits_a_cell", "m_var", (F.col("bits_a_cell") * F.col("m_var")).alias("measured"), "published")


def own_variances(spark: SparkSession, streams: int = 2000, m: int = 64, n: float = 2e4) -> DataFrame:
    """(method, runs, true, own): the spread of sequential estimates, and the mean of the variances that they state of themselves."""
    x = streams_of(spark, [("mart_nb", m), ("mart_hll", m)], streams, np.array([n]))
    return x.groupBy("method").agg(F.count("*").alias("runs"), (F.var_samp("estimate") / n**2).alias("true"), (F.avg("own_variance") / n**2).alias("own"))


def differences(cell: np.ndarray, k: np.ndarray, other: np.ndarray, m: int, width: int) -> tuple[bool, bool]:
    """Whether the tail-cut sketch of a stream differs in another order, and when its two halves are merged."""
    far = k >= (1 << width)

    # an uncut rank counts at its first arrival only
    def state(order: np.ndarray) -> TailCut:
        t, c, r = TailCut(m, width), cell[order], k[order]
        _, first = np.unique(c * 64 + r, return_index=True)
        keep = far[order]
        keep[first] = True
        for a, b in zip(c[keep].tolist(), r[keep].tolist()):
            t.add(a, b)
        return t

    one, half = np.arange(len(cell)), len(cell) // 2
    a, b = state(one), state(other)
    c = state(one[:half]).merged(state(one[half:]))
    same = lambda x, y: bool((x.tops() == y.tops()).all() and (x.nbr == y.nbr).all())
    return not same(a, b), not same(a, c)


def order_share(spark: SparkSession, streams: int = 300, m: int = 64, n: int = 20_000, widths: tuple[int, ...] = (2, 3, 4)) -> DataFrame:
    """(width, runs, by_order, by_merge): the share of streams whose tail-cut sketch differs when the same elements come
    in another order, or are counted as two halves that are merged."""
    def run(batches):
        for pdf in batches:
            out = []
            for i in pdf["id"]:
                rng = np.random.default_rng((11, int(i)))
                cell, k = rng.integers(0, m, n), rng.geometric(0.5, n)
                for w in widths:
                    out.append((w, *differences(cell, k, rng.permutation(n), m, w)))
            if out:
                yield pd.DataFrame(out, columns=["width", "o", "g"]).astype({"width": "int32"})

    x = spark.range(0, streams, 1, min(streams, 32)).mapInPandas(run, "width int, o boolean, g boolean")
    return x.groupBy("width").agg(F.count("*").alias("runs"), F.avg(F.col("o").cast("double")).alias("by_order"), F.avg(F.col("g").cast("double")).alias("by_merge"))
