"""t-wise independent hash families: polynomials with random coefficients modulo a prime."""

from __future__ import annotations

import math
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

from . import rng

#: Products of two residues fit a long below the first prime, a decimal below the second.
PRIME, WIDE_PRIME = 2**31 - 1, 2**61 - 1


@dataclass(frozen=True)
class PolyHash:
    """``h(v, j)`` in ``0 .. buckets-1`` of vertex number ``v`` (from 0) and index ``j`` (1..k)."""

    coeffs: tuple[int, ...]
    buckets: int
    k: int
    prime: int = PRIME

    def column(self, v: Column, j: Column) -> Column:
        wide = self.prime != PRIME
        kind, p = ("decimal(19,0)" if wide else "bigint"), F.lit(self.prime)
        p = p.cast(kind) if wide else p
        at = F.pmod(v.cast(kind), p) * F.lit(self.k).cast("decimal(10,0)" if wide else "bigint")
        x = F.pmod(at + (j - 1).cast(kind), p).cast(kind)
        step = lambda h, c: F.pmod((h * x).cast("decimal(38,0)") + c if wide else h * x + c, p).cast(kind)
        coeffs = [F.lit(c).cast(kind) for c in reversed(self.coeffs)]
        if len(coeffs) <= 16:  # nested, so compiled; deeper nesting overflows the planner's stack
            h = F.lit(0).cast(kind)
            for c in coeffs:
                h = step(h, c)
        else:
            h = F.aggregate(F.array(*coeffs), F.lit(0).cast(kind), step)
        return F.pmod(h, F.lit(self.buckets).cast(kind)).cast("bigint")

    def sql(self, v: str, j: str) -> str:
        x = f"((({v})::HUGEINT * {self.k} + ({j}) - 1) % {self.prime})"
        h = "0::HUGEINT"
        for c in reversed(self.coeffs):
            h = f"(({h}) * {x} + {c}) % {self.prime}"
        return f"(({h}) % {self.buckets})::BIGINT"

    def pandas(self, v: pd.Series, j: pd.Series) -> pd.Series:
        x = ((v.astype(object) * self.k + j - 1) % self.prime).astype(object)
        h = x * 0
        for c in reversed(self.coeffs):
            h = (h * x + c) % self.prime
        return (h % self.buckets).astype("int64")


def independence(n: int, c: float = 1.0) -> int:
    """t = ceil(8 c log2 n)."""
    return max(2, math.ceil(8 * c * math.log2(max(n, 2))))


def poly_family(t: int, n: int, k: int, seed: int) -> PolyHash:
    """A member of the family, its ``t`` coefficients drawn from the seed; the prime is above n * k,
    as independence of all (vertex number, index) needs."""
    prime = PRIME if n * k < PRIME else WIDE_PRIME
    return PolyHash(tuple((rng.py_bits(seed, "coeff", i) if prime == PRIME else rng.py_bits(seed, "coeff", i) << 9 | rng.py_bits(seed, "low", i) % 512) % prime for i in range(t)), n, k, prime)
