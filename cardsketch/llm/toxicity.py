"""Toxicity scores: FTRL-proximal logistic regression over hashed word n-grams and skip-grams.

Features are the words of a text, its neighbouring pairs and its pairs one word apart, each hashed to
one of 2**BITS coordinates and counted once a text.  FTRL-proximal keeps a learning rate a
coordinate; its L1 term leaves few weights, which travel with the scoring function.  It learns from
a bounded sample of labelled rows (`rows`, by least hash of the id); every row is scored.

Null and empty texts get the score of the bias alone.  A row of labels with a null is not used; an id
labelled more than once is toxic if any label says so.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BITS = 20
CUT = 0.3
_P = np.uint64(0x100000001B3)
_P_INV = np.uint64(pow(0x100000001B3, -1, 1 << 64))


def _powers(base: np.uint64, n: int) -> np.ndarray:
    x = np.full(n, base, np.uint64)
    x[:1] = 1
    return np.multiply.accumulate(x)


def features(texts: list[str], bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """(text, coordinate) of each word, pair and spaced pair, repeats included."""
    raw = [t.lower().encode() for t in texts]
    data = np.frombuffer(b" ".join([*raw, b" "]), np.uint8)
    ends_of = np.cumsum([len(r) + 1 for r in raw]) if raw else np.zeros(0, np.int64)
    word = ((data >= 97) & (data <= 122)) | ((data >= 48) & (data <= 57)) | (data >= 128)
    edge = np.flatnonzero(np.diff(np.concatenate(([0], word.view(np.int8), [0]))))
    s, e = edge[::2], edge[1::2]
    if not len(s):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    up, down = _powers(_P, len(data) + 1), _powers(_P_INV, len(data) + 1)
    acc = np.concatenate((np.zeros(1, np.uint64), np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[:-1])))
    h = (acc[e] - acc[s]) * down[s]
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    doc = np.searchsorted(ends_of, s, "right")

    def mix(x: np.ndarray) -> np.ndarray:
        x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
        return (x >> np.uint64(64 - bits)).astype(np.int64)

    at, out = [doc], [mix(h)]
    for gap, c in ((1, np.uint64(0x94D049BB133111EB)), (2, np.uint64(0xD6E8FEB86659FD93))):
        if len(h) > gap:
            same = doc[gap:] == doc[:-gap]
            at.append(doc[gap:][same])
            out.append(mix(h[:-gap] * c + h[gap:] * np.uint64(0xA0761D6478BD642F))[same])
    return np.concatenate(at), np.concatenate(out)


def split_texts(texts: list[str], most: int = 1 << 18):
    """Consecutive texts of about `most` characters together, as (first, texts)."""
    first, size = 0, 0
    for i, t in enumerate(texts):
        if size and size + len(t) > most:
            yield first, texts[first:i]
            first, size = i, 0
        size += len(t)
    if texts:
        yield first, texts[first:]


class Ftrl:
    """FTRL-proximal for logistic loss with binary features."""

    def __init__(self, bits: int = BITS, alpha: float = 1.0, beta: float = 1.0, l1: float = 4.0, l2: float = 0.1):
        self.z, self.n = np.zeros(1 << bits), np.zeros(1 << bits)
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2
        self.bias_z = self.bias_n = self.prior = 0.0

    def weights(self, i: np.ndarray) -> np.ndarray:
        z = self.z[i]
        return np.where(np.abs(z) <= self.l1, 0.0, -(z - np.sign(z) * self.l1) / ((self.beta + np.sqrt(self.n[i])) / self.alpha + self.l2))

    def bias(self) -> float:
        return self.prior - self.bias_z / ((self.beta + self.bias_n ** 0.5) / self.alpha)

    def learn(self, i: np.ndarray, y: int) -> None:
        w, b = self.weights(i), self.bias()
        g = 1 / (1 + np.exp(-np.clip(w.sum() + b, -30, 30))) - y
        old = self.n[i]
        self.z[i] += g - (np.sqrt(old + g * g) - np.sqrt(old)) / self.alpha * w
        self.n[i] = old + g * g
        self.bias_z += g - ((self.bias_n + g * g) ** 0.5 - self.bias_n ** 0.5) / self.alpha * (b - self.prior)
        self.bias_n += g * g


def fit(texts: list[str], labels: list[int], passes: int = 3, least: int = 3, **options) -> tuple[np.ndarray, np.ndarray, float]:
    """(coordinates, weights, bias): those that are not zero.

    Coordinates in fewer than `least` texts are left out.  The last fifth of the texts is not learnt
    from but calibrates the margins (Platt's scaling), which L1 makes too small."""
    model, sets, seen = Ftrl(**options), [], np.zeros(1 << BITS, np.int32)
    for first, part in split_texts(texts):
        d, f = features(part)
        key = np.unique(d * (1 << BITS) + f)
        d, f = key >> BITS, key & ((1 << BITS) - 1)
        seen += np.bincount(f, minlength=1 << BITS).astype(np.int32)
        cut = np.searchsorted(d, np.arange(len(part) + 1))
        sets += [f[a:b].astype(np.int32) for a, b in zip(cut, cut[1:])]
    sets = [x[seen[x] >= least] for x in sets]
    learnt = len(sets) - len(sets) // 5
    model.prior = float(np.log((sum(labels) + 0.5) / (len(labels) - sum(labels) + 9.5)))  # few rows: mostly clean
    for _ in range(passes):
        for x, y in zip(sets[:learnt], labels):
            model.learn(x, y)
    w = model.weights(np.arange(1 << BITS))
    margin = np.array([w[x].sum() + model.bias() for x in sets[learnt:]])
    a, b = platt(margin, np.array(labels[learnt:], float))
    at = np.flatnonzero(w)
    return at.astype(np.int32), (a * w[at]).astype(np.float32), float(a * model.bias() + b)


def platt(margin: np.ndarray, y: np.ndarray, steps: int = 50) -> tuple[float, float]:
    """Slope and shift of a logistic fit of labels on margins, by damped Newton steps; the slope
    stays positive.  Without both labels it leaves margins as they are."""
    if len(set(y)) < 2:
        return 1.0, 0.0
    t = np.where(y == 1, (y.sum() + 1) / (y.sum() + 2), 1 / (len(y) - y.sum() + 2))
    a, b = 1.0, 0.0
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(a * margin + b, -30, 30)))
        v = p * (1 - p)
        g = np.array([((p - t) * margin).sum(), (p - t).sum()])
        h = np.array([[(v * margin * margin).sum(), (v * margin).sum()], [(v * margin).sum(), v.sum()]]) + np.eye(2) * 1e-3
        step = np.clip(np.linalg.solve(h, g), -1, 1)
        a, b = max(0.1, a - step[0]), b - step[1]
    return float(a), float(b)


def scores(texts: list[str], model: tuple[np.ndarray, np.ndarray, float]) -> np.ndarray:
    dense = np.zeros(1 << BITS, np.float32)
    dense[model[0]] = model[1]
    return _scores(texts, dense, model[2])


def _scores(texts: list[str], dense: np.ndarray, bias: float) -> np.ndarray:
    out = np.full(len(texts), bias)
    for first, part in split_texts(texts):
        d, f = features(part)
        hit = dense[f] != 0
        key = np.unique(d[hit] * (1 << BITS) + f[hit])
        np.add.at(out, first + (key >> BITS), dense[key & ((1 << BITS) - 1)])
    return 1 / (1 + np.exp(-np.clip(out, -30, 30)))


def held_out(id_col: str):
    return F.pmod(F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")), F.lit(4)) == 2


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", rows: int = 12_000, skip_held_out: bool = True) -> tuple[np.ndarray, np.ndarray, float]:
    """Fits on at most `rows` labelled rows, in one task."""
    y = labels.select(F.col(id_col).cast("long").alias("id"), F.col(label_col).cast("int").alias("y")).dropna().groupBy("id").agg(F.max("y").alias("y"))
    if skip_held_out:
        y = y.where(~held_out("id"))
    y = y.orderBy(F.xxhash64("id"), "id").limit(rows)
    x = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).join(F.broadcast(y), "id")  # y has `rows` rows at most
    x = x.orderBy(F.xxhash64("id"), "id", F.xxhash64("text")).limit(rows)

    def run(batches):
        texts, ys = [], []
        for b in batches:
            texts += [t or "" for t in b["text"].to_pylist()]
            ys += b["y"].to_pylist()
        at, w, bias = fit(texts, ys)
        yield pa.RecordBatch.from_arrays([pa.array([at.tobytes()]), pa.array([w.tobytes()]), pa.array([bias])], names=["at", "w", "bias"])

    r = x.coalesce(1).mapInArrow(run, "at binary, w binary, bias double").first()
    return np.frombuffer(r["at"], np.int32), np.frombuffer(r["w"], np.float32), r["bias"]


def score(docs: DataFrame, model, id_col: str = "doc_id", text_col: str = "text", cut: float = CUT) -> DataFrame:
    """(id, held_out, score, predicted) for each row."""
    def run(batches):
        dense = np.zeros(1 << BITS, np.float32)
        dense[model[0]] = model[1]
        for b in batches:
            s = _scores([t or "" for t in b["text"].to_pylist()], dense, model[2])
            yield pa.RecordBatch.from_arrays([b["id"], b["held_out"], pa.array(s), pa.array((s >= cut).astype(np.int32))], names=["id", "held_out", "score", "predicted"])

    x = docs.select(F.col(id_col).cast("long").alias("id"), held_out(id_col).alias("held_out"), F.col(text_col).cast("string").alias("text"))
    return x.mapInArrow(run, "id long, held_out boolean, score double, predicted int").withColumnRenamed("id", id_col)


def keep_clean(docs: DataFrame, model, text_col: str = "text", cut: float = CUT) -> DataFrame:
    """The rows of docs, all columns, that score under cut."""
    def run(batches):
        dense = np.zeros(1 << BITS, np.float32)
        dense[model[0]] = model[1]
        for b in batches:
            s = _scores([t or "" for t in b[text_col].to_pylist()], dense, model[2])
            yield b.filter(pa.array(s < cut))

    return docs.mapInArrow(run, docs.schema)
