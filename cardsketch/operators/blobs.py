"""Functions over packed sketches for SQL: estimate, merge, explain.

register() makes nb_card(payload, m), the merging aggregate nb_merge(payload, m), and the table function
nb_explain(payload, m).  They run over one row a stored sketch; sketches are built natively.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..functions.constants import alpha, gamma
from .codec import pack_cells, unpack_cells


def card(payload: bytes, m: int, kind: str = "nb", threshold: float = 2.5) -> float:
    """The estimate from a packed sketch, with linear counting for few elements."""
    v = unpack_cells(kind, payload, m)
    nb = kind.endswith("nb")
    terms = 2.0 ** -v[0] * ((3 - 2 * v[1]) if nb else 1)
    raw, empty = (gamma(m) if nb else alpha(m)) * m * m / terms.sum(), int((v[0] == 0).sum())
    if empty == m:
        return 0.0
    return float(m * np.log(m / empty)) if raw < threshold * m and empty else float(raw)


def merged(payloads, m: int) -> bytes:
    """The packed neighbour-bit sketch of the union of streams."""
    mask = np.zeros(m, np.int64)
    for p in payloads:
        top, nbr = unpack_cells("nb", p, m)
        mask |= np.where(top > 0, np.int64(1) << np.maximum(top - 1, 0), 0) | np.where((top > 1) & (nbr == 1), np.int64(1) << np.maximum(top - 2, 0), 0)
    top = np.array([int(x).bit_length() for x in mask])
    nbr = np.where(top < 2, 1, (mask >> np.maximum(top - 2, 0)) & 1)
    return pack_cells("nb", [top, nbr])


def nb_card():
    @F.pandas_udf("double")
    def f(payload: pd.Series, m: pd.Series) -> pd.Series:
        return pd.Series([None if p is None else card(p, int(k)) for p, k in zip(payload, m)])
    return f


def nb_merge():
    @F.pandas_udf("binary")
    def f(payload: pd.Series, m: pd.Series) -> bytes:
        return merged([p for p in payload if p is not None], int(m.iloc[0]))
    return f


def nb_explain():
    @F.udtf(returnType="bucket int, top int, nbr int")
    class Explain:
        def eval(self, payload: bytes, m: int):
            if payload is not None:
                top, nbr = unpack_cells("nb", bytes(payload), m)
                for i in np.flatnonzero(top).tolist():
                    yield i, int(top[i]), int(nbr[i])
    return Explain


def register(spark: SparkSession) -> None:
    spark.udf.register("nb_card", nb_card())
    spark.udf.register("nb_merge", nb_merge())
    spark.udtf.register("nb_explain", nb_explain())
