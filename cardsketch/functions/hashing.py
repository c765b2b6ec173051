"""From an element to its cell and its geometric draw, in built-in expressions.

The draw is kept as the lowest set bit itself (`bit`), so that OR over rows is the union of what was
seen.  A sentinel at position rho_bits keeps the draw defined and every value under 2**61, where
negation cannot overflow.  Cell and draw come from separate hash words, so any number of cells works
and a sketch can be folded to a divisor of it; with layout "top" both come from one word, the cell from its
first bits.  Rows with a null in any element column are dropped, as COUNT(DISTINCT ...) does, unless nulls are kept.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import SketchConfig


def element(df: DataFrame, cols: list[str], strings: str = "exact") -> list[Column]:
    """The columns as hashable ones: maps become sorted entries, negative zero becomes zero, all NaN one, and
    strings lose outer spaces and case if they are to be folded."""
    kinds = dict(df.dtypes)
    out = []
    for c in cols:
        x, kind = F.col(c), kinds.get(c, "")
        if kind.startswith("map"):
            x = F.array_sort(F.map_entries(x))
        elif kind in ("double", "float"):
            x = F.when(F.isnan(x), F.lit(float("nan")).cast(kind)).otherwise(x + F.lit(0.0).cast(kind))
        elif kind == "string" and strings == "folded":
            x = F.lower(F.trim(x))
        out.append(x)
    return out


def digest(xs: list[Column], seed: int | Column, keep_nulls: bool = False) -> Column:
    """Hex digits; a seed other than 0 goes before the text.  Parts of a composite element come after their lengths,
    so that no two elements have one text; null, if kept, is n."""
    texts = [x.cast("string") for x in xs]
    parts = [F.concat(F.length(t).cast("string"), F.lit(":"), t) for t in texts] if len(xs) > 1 or keep_nulls else texts
    text = F.concat(*[F.coalesce(t, F.lit("n")) for t in parts]) if keep_nulls else F.concat(*parts)
    if isinstance(seed, Column):
        text = F.concat(seed.cast("string"), F.lit(":"), text)
    elif seed:
        text = F.concat(F.lit(f"{seed}:"), text)
    return F.md5(text.cast("binary"))


def low_bit(y: Column, rho_bits: int) -> Column:
    y = y.bitwiseOR(F.lit(1 << rho_bits).cast("long"))
    return y.bitwiseAND(-y)


def split(df: DataFrame, cols: str | list[str], cfg: SketchConfig, by: list[str] = (), keep: list[Column] = (), seed: Column | None = None) -> DataFrame:
    """(by..., keep..., bucket, bit) of each row whose element is not null.  seed, a column, goes before cfg.seed."""
    cols = [cols] if isinstance(cols, str) else list(cols)
    xs, rows, keeps = element(df, cols, cfg.strings), df, cfg.nulls == "keep"
    if not keeps:
        live = xs[0].isNotNull()
        for x in xs[1:]:
            live = live & x.isNotNull()
        rows = df.where(live)
    b = cfg.cell_bits
    if cfg.family == "md5":
        rows = rows.withColumn("__d", digest(xs, cfg.seed if seed is None else seed, keeps))
        word = F.conv(F.substring("__d", 1, 8), 16, 10).cast("long")
        cell = bucket_pow2(F.call_function("shiftleft", word, F.lit(32)), b) if cfg.layout == "top" else word % cfg.m
        draw = F.conv(F.substring("__d", 18, 15), 16, 10).cast("long")
        return rows.select(*by, *keep, cell.cast("int").alias("bucket"), low_bit(draw, cfg.rho_bits).alias("bit"))
    parts = [y for x in xs for y in (x.isNull(), x)] if keeps else xs  # the hash passes over nulls
    hashed = lambda k: F.xxhash64(F.lit(2 * cfg.seed + k), *([] if seed is None else [seed]), *parts)
    if cfg.layout == "top":
        rows = rows.withColumn("__h", hashed(0))
        rest = F.col("__h").bitwiseAND(F.lit((1 << (64 - b)) - 1 if b else -1).cast("long"))
        return rows.select(*by, *keep, bucket_pow2(F.col("__h"), b).alias("bucket"), low_bit(rest, min(cfg.rho_bits, 64 - b)).alias("bit"))
    cell = F.pmod(hashed(1), F.lit(cfg.m).cast("long"))
    draw = F.shiftrightunsigned(hashed(0), 4)
    return rows.select(*by, *keep, cell.cast("int").alias("bucket"), low_bit(draw, cfg.rho_bits).alias("bit"))


def bucket_pow2(h: Column, b: int) -> Column:
    """The cell as the top b bits of a hash word; 0 if there are none."""
    return F.shiftrightunsigned(h, 64 - b).cast("int") if b else F.lit(0)


def rho(bit: Column) -> Column:
    """The rank, from 1, of an isolated bit; the length of any other non-negative long."""
    return F.when(bit == 0, 0).otherwise(F.length(F.bin(bit)))
