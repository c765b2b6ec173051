"""What fixes a sketch: cells, hash family, seed, and the width of the geometric draw."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class SketchConfig:
    m: int = 1024
    family: str = "xxhash64"  # or "md5", whose values DuckDB gets too
    seed: int = 42
    rho_bits: int = 60
    small_range: bool = True
    threshold: float = 2.5  # linear counting below threshold * m
    layout: str = "words"  # cell and draw from two hash words, any m; or "top": m = 2**b, the first b bits of one word
    nulls: str = "drop"  # as COUNT(DISTINCT) does; or "keep": null is a value like any other
    strings: str = "exact"  # or "folded": without spaces around, in lower case

    def __post_init__(self) -> None:
        bad = self.m < 1 or self.family not in ("xxhash64", "md5") or not 1 <= self.rho_bits <= 60
        bad = bad or self.layout not in ("words", "top") or self.nulls not in ("drop", "keep") or self.strings not in ("exact", "folded")
        if bad or self.layout == "top" and self.m & (self.m - 1):
            raise ValueError(f"no such sketch: {self}")

    @property
    def cell_bits(self) -> int:
        return self.m.bit_length() - 1


#: For queries that DuckDB repeats.
def portable(m: int, seed: int = 0, **kw) -> SketchConfig:
    return SketchConfig(m=m, family="md5", seed=seed, **kw)
