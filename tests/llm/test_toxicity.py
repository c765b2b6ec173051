"""The learner and its features against plain versions, one text and one coordinate at a time."""

import math
import re

import numpy as np

from cardsketch.llm import toxicity

M = (1 << 64) - 1


def slow_features(text, bits=toxicity.BITS):
    """Coordinates of words, pairs and spaced pairs: words are runs of a-z, 0-9 and bytes from 128 on."""
    hashes = []
    for w in re.findall(rb"[a-z0-9\x80-\xff]+", text.lower().encode()):
        h = sum((b + 1) * pow(0x100000001B3, i, 1 << 64) for i, b in enumerate(w)) & M
        hashes.append((h ^ (h >> 31)) * 0x9E3779B97F4A7C15 & M)

    def mix(x):
        return ((x ^ (x >> 29)) * 0xBF58476D1CE4E5B9 & M) >> (64 - bits)

    out = [mix(h) for h in hashes]
    for gap, c in ((1, 0x94D049BB133111EB), (2, 0xD6E8FEB86659FD93)):
        out += [mix((a * c + b * 0xA0761D6478BD642F) & M) for a, b in zip(hashes, hashes[gap:])]
    return sorted(out)


def test_features(spark, sf_dir):
    texts = [r["text"] or "" for r in spark.read.parquet(f"{sf_dir}/documents.parquet").limit(30).collect()] + ["", "one", "Zwölf, BOXKÄMPFER!  x-y 3.5", "a b a b", "日本 語"]
    d, f = toxicity.features(texts)
    for i, t in enumerate(texts):
        assert sorted(f[d == i].tolist()) == slow_features(t)


class SlowFtrl:
    """The update rule as it is stated: a coordinate's weight is closed-form in its sums of gradients and their squares."""

    def __init__(self, alpha, beta, l1, l2):
        self.p, self.z, self.n = (alpha, beta, l1, l2), {}, {}

    def weight(self, i):
        alpha, beta, l1, l2 = self.p
        z = self.z.get(i, 0.0)
        return 0.0 if abs(z) <= l1 else -(z - math.copysign(l1, z)) / ((beta + math.sqrt(self.n.get(i, 0.0))) / alpha + l2)

    def learn(self, coordinates, margin, y):
        g = 1 / (1 + math.exp(-margin)) - y
        for i in coordinates:
            w, n = self.weight(i), self.n.get(i, 0.0)
            sigma = (math.sqrt(n + g * g) - math.sqrt(n)) / self.p[0]
            self.z[i] = self.z.get(i, 0.0) + g - sigma * w
            self.n[i] = n + g * g


def test_updates():
    rng = np.random.default_rng(1)
    fast, slow, bias = toxicity.Ftrl(bits=8, l1=0.3), SlowFtrl(1.0, 1.0, 0.3, 0.1), SlowFtrl(1.0, 1.0, 0.0, 0.0)
    for _ in range(400):
        x = np.unique(rng.integers(0, 60, 9))
        y = int(rng.random() < (0.9 if 7 in x else 0.2))
        margin = sum(slow.weight(int(i)) for i in x) + bias.weight(0)
        assert abs(fast.weights(x).sum() + fast.bias() - margin) < 1e-9
        slow.learn([int(i) for i in x], margin, y)
        bias.learn([0], margin, y)
        fast.learn(x, y)
    w = fast.weights(np.arange(256))
    assert all(abs(w[i] - slow.weight(i)) < 1e-9 for i in range(256)) and (w == 0).sum() > 190 and w[7] > 0


def test_scores_do_not_depend_on_the_batch():
    rng = np.random.default_rng(2)
    model = (np.unique(rng.integers(0, 1 << toxicity.BITS, 5000)).astype(np.int32), None, 0.1)
    model = (model[0], rng.normal(size=len(model[0])).astype(np.float32), 0.1)
    texts = ["some words here " * n for n in (0, 1, 50, 30_000)] + ["", "others"]
    whole = toxicity.scores(texts, model)
    assert np.allclose(whole, [toxicity.scores([t], model)[0] for t in texts], atol=1e-6) and ((0 < whole) & (whole < 1)).all()
