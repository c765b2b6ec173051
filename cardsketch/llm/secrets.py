"""Secrets: fixed patterns, and strings whose letters look drawn at random.

A candidate is a run of LEAST encoding letters or more, or what base spans leave of one.  Its encoding is the
narrowest alphabet that has its letters; three statistics are taken of the letters' ranks in it: chi-squared of
counts against uniformity, the runs above and below the middle of the alphabet, and the serial correlation of
neighbours.  All three are near 0 for letters drawn at random.  What they are in ordinary writing is
learnt from the corpus itself: the words of every text, joined and cut into windows of four lengths, give their
means and covariance for each alphabet and length class.  A candidate's evidence is the linear combination
that tells random letters best from writing; the covariance gives it a known spread for writing though the
three depend on each other.  What random letters themselves vary by is added to it, as some statistics hardly
vary in writing but for rare windows: so writing spreads less than the standard normal by which it is judged.  Tails of the whole corpus's candidates go through
Benjamini-Hochberg, with the rate shared out by length class, so that short strings need stronger evidence.

Where a corpus has few windows, the means and covariances PROSE count as FEW windows beside them.  Null and empty
texts have no span.  Repeated rows get equal spans; rows of one id and text share them.  Of spans that
begin together all are reported.  Only the id and text columns are read.
"""

from __future__ import annotations

import hashlib
import math
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import aliased, named, sent, stored, text_hash
from .toxicity import split_texts

KINDS = ("assign", "access", "hex", "random")
# fixed patterns
PATTERNS = {
    "assign": (r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    "access": (r"AKIA[A-Z0-9]+", 0, 20),
    "hex": (r"[0-9a-f]+", 0, 24),
}
LEAST = 20
CANDIDATE = rf"[A-Za-z0-9+/_=-]{{{LEAST},}}"
#: Alphabets in the order in which they are tried; letters of one case count as lower-case ones in the first three.
ALPHABETS = {"digits": "0123456789", "hex": "0123456789abcdef", "alpha": "abcdefghijklmnopqrstuvwxyz", "base32": "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567", "base64": "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz+/"}
NAMES = tuple(ALPHABETS)
#: Letters of a window of each length class; a class begins at CLASS_FROM letters.
WINDOWS, CLASS_FROM = (24, 34, 52, 80), (0, 28, 40, 64)
CYCLE = sum(WINDOWS)
SHARES = (0.1, 0.2, 0.3, 0.4)
#: Evidence is counted in bins of this width, up to BINS of them.
BIN, BINS = 0.05, 800
FEW = 200
# fixed values, measured: means of the three statistics of 24 letters of writing, then their covariance, row by row
PROSE = {
    "digits": (0.14, -0.03, 0.01, 0.29, -0.005, 0.014, 0.0115, -0.018, 0.048),
    "hex": (2.11, -0.499, 1.275, 0.079, -0.001, 0.029, 0.0005, 0.0, 0.055),
    "alpha": (0.815, 0.04, 0.024, 0.089, 0.001, 0.001, 0.0144, -0.018, 0.0426),
    "base32": (0.887, -0.077, 0.276, 0.077, 0.0, 0.003, 0.0169, -0.02, 0.0436),
    "base64": (0.992, -0.464, 0.588, 0.062, -0.001, -0.002, 0.0039, -0.0045, 0.0215),
}


def _ranks() -> np.ndarray:
    """The rank of each byte in each alphabet, 255 where it has none."""
    out = np.full((len(NAMES), 256), 255, np.uint8)
    for k, (name, letters) in enumerate(ALPHABETS.items()):
        for i, c in enumerate(letters):
            out[k, ord(c)] = i
            if name in ("hex", "alpha"):
                out[k, ord(c.upper())] = i
            if name == "base32":
                out[k, ord(c.lower())] = i
    out[NAMES.index("base64"), [ord("-"), ord("_")]] = 62, 63
    return out


RANKS = _ranks()
SIZES = np.array([len(x) for x in ALPHABETS.values()])


def encoding(token: str) -> int:
    """The place in NAMES of the narrowest alphabet that has the token's letters."""
    used = set(token)
    one_case = token.lower() == token or token.upper() == token
    if used <= set(ALPHABETS["digits"]):
        return 0
    if one_case and {c.lower() for c in used} <= set(ALPHABETS["hex"]):
        return 1
    if one_case and {c.lower() for c in used} <= set(ALPHABETS["alpha"]):
        return 2
    return 3 if used <= set(ALPHABETS["base32"]) else 4


def length_class(n: int) -> int:
    return sum(n >= m for m in CLASS_FROM) - 1


def statistics(v: np.ndarray, k: int) -> np.ndarray:
    """(windows, 3) from ranks (windows, letters) in an alphabet of k: chi-squared, runs and serial correlation, each
    near 0 for letters drawn at random.  The first is the logarithm of chi-squared over its expectation, as its excess
    over that would make it in a window of the length class."""
    w, n = v.shape
    counts = np.bincount((v + np.arange(w)[:, None] * k).ravel(), minlength=w * k).reshape(w, k)
    excess = ((counts * counts).sum(axis=1) * k / n - n) / (k - 1) - 1
    chi = np.log(np.maximum(0.05, 1 + excess * WINDOWS[length_class(n)] / n))
    high = v >= k / 2
    runs = (high[:, 1:] != high[:, :-1]).mean(axis=1) - 0.5
    x = v - (k - 1) / 2
    serial = (x[:, 1:] * x[:, :-1]).mean(axis=1) / ((k * k - 1) / 12)
    return np.stack([chi, runs, serial], axis=1)


def prose(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, text): the letters and digits of words that are shorter than a candidate, and the text each is from."""
    data = np.frombuffer("\n".join([*texts, ""]).encode(), np.uint8)
    letter = RANKS[-1][data] < 62
    edge = np.flatnonzero(np.diff(np.concatenate(([0], letter.view(np.int8), [0]))))
    size = edge[1::2] - edge[::2]
    keep = np.repeat(size < LEAST, size)
    at = np.flatnonzero(letter)[keep]
    ends = np.cumsum([len(t.encode()) + 1 for t in texts])
    return data[at], np.searchsorted(ends, at, "right")


def sums_of(texts: list[str]) -> np.ndarray:
    """For each alphabet and length class the number of windows, the sums of their statistics and of their products."""
    out = np.zeros((len(NAMES), len(WINDOWS), 10))
    for _, part in split_texts(texts):
        data, of = prose(part)
        for a in range(len(NAMES)):
            r = RANKS[a][data]
            there = r < SIZES[a]
            v, n = r[there].astype(np.int64), np.bincount(of[there], minlength=len(part))
            base = np.cumsum(n) - n
            for c, length in enumerate(WINDOWS):
                offset = sum(WINDOWS[:c])
                each = n // CYCLE + (n % CYCLE >= offset + length)
                if not each.any():
                    continue
                i = np.arange(each.sum()) - np.repeat(np.cumsum(each) - each, each)
                start = np.repeat(base + offset, each) + i * CYCLE
                f = statistics(v[start[:, None] + np.arange(length)], int(SIZES[a]))
                out[a, c, 0] += len(f)
                out[a, c, 1:4] += f.sum(axis=0)
                out[a, c, 4:] += (f[:, _I] * f[:, _J]).sum(axis=0)
    return out


_I, _J = np.triu_indices(3)


def laws(sums: np.ndarray) -> np.ndarray:
    """(alphabets, classes, 4): weights of the three statistics and a shift, that make of them a number with mean 0 and a
    deviation of 1 at most for windows of the corpus's writing, and larger the more random the letters are."""
    out = np.zeros((len(NAMES), len(WINDOWS), 4))
    for a, name in enumerate(NAMES):
        for c, length in enumerate(WINDOWS):
            own = np.array(PROSE[name])
            own[0] = math.log(1 + (math.exp(own[0]) - 1) * length / WINDOWS[0])
            s = sums[a, c] + FEW * np.concatenate(([1], own[:3], own[3:] * np.where(_I == 0, 1, WINDOWS[0] / length) + own[_I] * own[_J]))
            mean = s[1:4] / s[0]
            cov = np.zeros((3, 3))
            cov[_I, _J] = s[4:] / s[0] - mean[_I] * mean[_J]
            k = int(SIZES[a])
            cov += np.triu(cov, 1).T + np.diag([2 / (k - 1), 0.25 / (length - 1), 1 / (length - 1)])
            w = np.linalg.solve(cov, -mean)
            scale = math.sqrt(max(1e-12, float(-mean @ w)))
            out[a, c] = [*(w / scale), float(-mean @ w) / scale]
    return out


def evidence(law: np.ndarray, a: int, n: int, f) -> float:
    """How far a candidate of n letters is from writing, in deviations; lengths beside a window's scale it."""
    c = length_class(n)
    x = law[a, c]
    return float((x[0] * f[0] + x[1] * f[1] + x[2] * f[2] + x[3]) * math.sqrt(n / WINDOWS[c]))


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the fixed patterns, by start, then kind."""
    out = []
    for m in _ASSIGN.finditer(text):
        if len(m[2]) >= 6:
            out.append((m.start(), m.end(), "assign"))
    if "AKIA" in text:
        out += [(m.start(), m.end(), "access") for m in re.finditer(r"AKIA[A-Z0-9]{16,}", text)]
    out += [(m.start(), m.end(), "hex") for m in re.finditer(r"[0-9a-f]{24,}", text)]
    return sorted(out, key=lambda x: (x[0], KINDS.index(x[2])))


_ASSIGN = re.compile(PATTERNS["assign"][0], re.I | re.A)
_CAND = re.compile(CANDIDATE)


def candidates(text: str, base: list[tuple[int, int, str]]) -> list[tuple[int, int, int, int, float, float, float]]:
    """(start, end, alphabet, letters, chi, runs, serial) of the parts of long encoding runs that lie outside base spans."""
    out = []
    for m in _CAND.finditer(text):
        at, parts = m.start(), []
        for a, b, _ in base:
            if b > at and a < m.end():
                parts.append((at, a))
                at = max(at, b)
        parts.append((at, m.end()))
        for a, b in parts:
            body = text[a:b].rstrip("=")
            if len(body) < LEAST:
                continue
            k = encoding(body)
            v = RANKS[k][np.frombuffer(body.encode(), np.uint8)]
            v = v[v < SIZES[k]].astype(np.int64)  # an equals sign within has no rank
            if len(v) >= LEAST:
                out.append((a, b, k, len(v), *statistics(v[None, :], int(SIZES[k]))[0].tolist()))
    return out


def thresholds(counts: list[tuple[int, int, int]], rate: float) -> list[float]:
    """From (length class, bin, tests): by class, the least evidence that Benjamini-Hochberg rejects."""
    total, out = sum(n for _, _, n in counts), [math.inf] * len(WINDOWS)
    for c in range(len(WINDOWS)):
        above = 0
        for b, n in sorted(((b, n) for k, b, n in counts if k == c), reverse=True):
            above += n
            if b > 0 and 0.5 * math.erfc(b * BIN / math.sqrt(2)) * total <= rate * SHARES[c] * above:
                out[c] = b * BIN
    return out


def _joined(spans) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in spans)


def _runs(spans) -> list[dict]:
    """The union of spans as disjoint runs in order."""
    out: list[dict] = []
    for a, b, _ in sorted(spans):
        if out and a < out[-1]["b"]:
            out[-1]["b"] = max(b, out[-1]["b"])
        else:
            out.append({"a": a, "b": b})
    return out


_BASE = pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64()), ("k", pa.string())]))
_CANDS = pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64()), ("law", pa.int32()), ("n", pa.int32()), ("f", pa.list_(pa.float64()))]))
SCANNED = "id long, th long, base array<struct<a:long,b:long,k:string>>, cand array<struct<a:long,b:long,law:int,n:int,f:array<double>>>, sums array<double>"


def _scan(batches):
    """Spans, candidates, and beside the first row of a batch the sums of its writing."""
    for batch in batches:
        if not batch.num_rows:
            continue
        base, cand, texts = [], [], [x.as_py() or "" for x in batch["text"]]
        for t in texts:
            b = base_spans(t)
            base.append([{"a": x, "b": y, "k": k} for x, y, k in b])
            cand.append([{"a": x[0], "b": x[1], "law": x[2], "n": x[3], "f": list(x[4:])} for x in candidates(t, b)])
        sums = [sums_of(texts).ravel().tolist(), *[None] * (len(texts) - 1)]
        del texts
        yield pa.RecordBatch.from_arrays([batch["id"], batch["th"], pa.array(base, _BASE), pa.array(cand, _CANDS), pa.array(sums, pa.list_(pa.float64()))], names=["id", "th", "base", "cand", "sums"])


def _scanned(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return stored(docs.select(F.col(id_col).cast("long").alias("id"), text_hash(text_col).alias("th"), F.col(text_col).cast("string").alias("text")).mapInArrow(_scan, SCANNED))


def corpus_laws(scanned: DataFrame) -> np.ndarray:
    """What writing looks like: 200 sums over all texts."""
    shape = (len(NAMES), len(WINDOWS), 10)
    total = np.zeros(math.prod(shape))
    for i, x in scanned.where("sums is not null").select(F.posexplode("sums").alias("i", "x")).groupBy("i").agg(F.sum("x")).collect():
        total[i] = x
    return laws(total.reshape(shape))


def corpus_thresholds(scanned: DataFrame, law: np.ndarray, rate: float) -> list[float]:
    """Counts by class and bin, some 3,200 rows at most, decide for the whole corpus."""
    c = scanned.select(F.explode("cand").alias("c")).select("c.*")
    k = sum(((F.col("n") >= m).cast("int") for m in CLASS_FROM[1:]), F.lit(0)).alias("k")
    x = c.select("law", "n", "f", k)
    lit = lambda v: F.from_json(F.lit(str(v)), "array<double>")
    w = [F.get(lit(law[:, :, j].ravel().tolist()), F.col("law") * len(WINDOWS) + F.col("k")) for j in range(4)]
    t = (w[0] * F.get("f", F.lit(0)) + w[1] * F.get("f", F.lit(1)) + w[2] * F.get("f", F.lit(2)) + w[3]) * F.sqrt(F.col("n") / F.get(lit(list(map(float, WINDOWS))), F.col("k")))
    x = x.select("k", F.greatest(F.lit(0), F.least(F.floor(t / BIN), F.lit(BINS))).cast("int").alias("bin"))
    return thresholds([tuple(r) for r in x.groupBy("k", "bin").agg(F.count("*").alias("n")).collect()], rate)


def chosen(base: list[dict], cand: list[dict], law: np.ndarray, limits: list[float]) -> list[tuple[int, int, str]]:
    out = [(x["a"], x["b"], x["k"]) for x in base]
    out += [(x["a"], x["b"], "random") for x in cand if min(BINS * BIN, evidence(law, x["law"], x["n"], x["f"])) >= limits[length_class(x["n"])]]
    return sorted(out, key=lambda x: (x[0], KINDS.index(x[2])))


def _report(law: np.ndarray, limits: list[float]):
    def run(batches):
        for batch in batches:
            rows = []
            for base, cand in zip(*(batch[c].to_pylist() for c in ("base", "cand"))):
                own = [(x["a"], x["b"], x["k"]) for x in base]
                n = [sum(k == kind for _, _, k in own) for kind in KINDS[:3]]
                spans = chosen(base, cand, law, limits)
                rows.append((*n, hashlib.sha256(_joined(own).encode()).hexdigest(), _joined(spans), len(spans) - len(own), _runs(spans)))
            cols = list(zip(*rows)) or [[]] * 7
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())])))
            yield pa.RecordBatch.from_arrays([batch["id"], batch["th"], *(pa.array(c, t) for c, t in zip(cols, kinds))], names=["id", "th", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_random", "runs"])
    return run


def _found(docs: DataFrame, id_col: str, text_col: str, rate: float) -> DataFrame:
    s = _scanned(docs, id_col, text_col)
    law = corpus_laws(s)
    return s.mapInArrow(_report(law, corpus_thresholds(s, law, rate)), "id long, th long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_random long, runs array<struct<a:long,b:long>>")


def find_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rate: float = 0.01) -> DataFrame:
    """(id, n_assign, n_access, n_hex, base_sha256, spans, n_random) for each row."""
    return _found(docs, id_col, text_col, rate).drop("th", "runs").withColumnRenamed("id", id_col)


def masked(text: Column, runs: Column) -> Column:
    """text with each run replaced by a mark."""
    ends = F.concat(F.array(F.lit(0).cast("long")), F.transform(runs, lambda r: r["b"]))
    cut = F.transform(runs, lambda r, i: F.concat(F.substr(text, (F.get(ends, i) + 1).cast("int"), (r["a"] - F.get(ends, i)).cast("int")), F.lit("[SECRET]")))
    last = F.element_at(ends, -1)
    return F.concat(F.array_join(cut, ""), F.substr(text, (last + 1).cast("int"), F.length(text)))


def redact(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", chars_col: str = "n_chars", rate: float = 0.01) -> DataFrame:
    """docs, all rows and columns, with each span of a text replaced by a mark; a changed text's
    chars_col, if there is one, counts its new characters.  Texts are scanned once."""
    hit = _found(docs, id_col, text_col, rate).where(F.size("runs") > 0)
    hit = stored(hit.select(F.col("id").alias("k_id"), F.col("th").alias("k_th"), "runs").dropDuplicates(["k_id", "k_th"]))
    x = aliased(docs, F.col(id_col).cast("long").alias("k_i"), text_hash(text_col).alias("k_h"))
    x = x.join(sent(hit), F.col("k_i").eqNullSafe(F.col("k_id")) & (F.col("k_h") == F.col("k_th")), "left")
    at, kinds = f"c{docs.columns.index(text_col)}", dict(docs.dtypes)
    x = x.withColumn(at, F.when(F.col("runs").isNull(), F.col(at)).otherwise(masked(F.col(at).cast("string"), F.col("runs")).cast(kinds[text_col])))
    if chars_col in docs.columns:
        n = f"c{docs.columns.index(chars_col)}"
        x = x.withColumn(n, F.when(F.col("runs").isNull() | F.col(n).isNull(), F.col(n)).otherwise(F.length(F.col(at).cast("string")).cast(kinds[chars_col])))
    return named(x, docs)
