"""Sketches at rest: fixed-width packed bits in one binary per group, and back.

Tail-cut sketches have their base in a byte before the offsets."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WIDTHS = {"hll": (6,), "nb": (6, 1), "pcsa": (64,), "tc_hll": (4,), "tc_nb": (4, 1)}
#: The columns that a kind keeps of a cell.
COLUMNS = {"hll": ["top"], "nb": ["top", "nbr"], "pcsa": ["bitmap"], "tc_hll": ["top"], "tc_nb": ["top", "nbr"]}


def _bits(x: np.ndarray, width: int) -> np.ndarray:
    return ((x[:, None] >> np.arange(width)) & 1).astype(np.uint8)


def pack_cells(kind: str, columns: list[np.ndarray]) -> bytes:
    """One row of values a cell, all m cells in order.  Offsets of a tail-cut sketch that don't fit are cut."""
    head, columns = b"", [c.astype(np.int64) for c in columns]
    if kind.startswith("tc"):
        base = int(columns[0].min())
        head, columns = bytes([base]), [np.minimum(columns[0] - base, 15), *columns[1:]]
    return head + np.packbits(np.concatenate([_bits(c, w) for c, w in zip(columns, WIDTHS[kind])], axis=1).ravel()).tobytes()


def unpack_cells(kind: str, payload: bytes, m: int) -> list[np.ndarray]:
    widths, base = WIDTHS[kind], 0
    if kind.startswith("tc"):
        base, payload = payload[0], payload[1:]
    flat = np.unpackbits(np.frombuffer(payload, np.uint8))[: m * sum(widths)].reshape(m, -1).astype(np.int64)
    out, at = [], 0
    for w in widths:
        out.append((flat[:, at:at + w] << np.arange(w)).sum(axis=1))
        at += w
    return [out[0] + base, *out[1:]]


def payload_bytes(kind: str, m: int) -> int:
    return -(-m * sum(WIDTHS[kind]) // 8) + kind.startswith("tc")


def blobs(rows: DataFrame, m: int, kind: str = "nb", by: list[str] = ()) -> DataFrame:
    """(by..., kind, m, payload) from (by..., bucket, top, nbr), or bitmap for pcsa: m rows a group at most.
    Only groups and their cells are in Python."""
    by = list(by)
    cols = COLUMNS[kind]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        full = [np.ones(m, np.int64) if c == "nbr" else np.zeros(m, np.int64) for c in cols]
        for f, c in zip(full, cols):
            f[pdf["bucket"].to_numpy()] = pdf[c].to_numpy()
        return pd.DataFrame({**{c: [pdf[c].iloc[0]] for c in by}, "kind": [kind], "m": [m], "payload": [pack_cells(kind, full)]})

    kinds = "".join(f"{c} {dict(rows.dtypes)[c]}, " for c in by)
    return rows.select(*by, "bucket", *cols, F.lit(0).alias("__g")).groupBy("__g", *by).applyInPandas(run, f"{kinds}kind string, m int, payload binary")


def cells(blob: DataFrame, by: list[str] = ()) -> DataFrame:
    """(by..., bucket, top, nbr, bitmap) of the filled cells; what a kind doesn't keep is 1 for nbr, null for bitmap,
    and top and nbr of a bitmap are read from it."""
    by = list(by)

    def run(batches):
        for pdf in batches:
            out = []
            for r in pdf.itertuples():
                v = unpack_cells(r.kind, r.payload, r.m)
                if r.kind == "pcsa":
                    top = np.array([int(b).bit_length() for b in v[0]])
                    nbr = np.where(top < 2, 1, (v[0] >> np.maximum(top - 2, 0)) & 1)
                else:
                    top, nbr = v[0], v[1] if len(v) > 1 else np.ones(r.m, int)
                x = pd.DataFrame({"bucket": np.arange(r.m, dtype=np.int32), "top": top.astype(np.int8), "nbr": nbr.astype(np.int8), "bitmap": pd.array(v[0], "Int64") if r.kind == "pcsa" else pd.array([None] * r.m, "Int64")})
                for c in by:
                    x[c] = getattr(r, c)
                out.append(x[x["top"] > 0][[*by, "bucket", "top", "nbr", "bitmap"]])
            if out:
                yield pd.concat(out)

    kinds = "".join(f"{c} {dict(blob.dtypes)[c]}, " for c in by)
    return blob.select(*by, "kind", "m", "payload").mapInPandas(run, f"{kinds}bucket int, top tinyint, nbr tinyint, bitmap long")
