"""Transition matrices and their powers in fixed point.

An entry is a long ``floor(x * 2**bits)``.  Rounding is always down, sums are exact and do not
depend on order, and a row sums to at most one, so products of two entries and sums of such
products stay under ``2**(2*bits)``: ``bits`` up to 31 fits a long, up to ``FINE`` a decimal.  Long powers
need the latter: a row loses mass at every squaring, and ``lost_mass`` says how much.

Matrices of up to ``TILE`` vertices (checked by a count) are also raised in one task, to the same
bits: numpy multiplies limbs of 20 bits, whose sums doubles hold exactly.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..ckpt import cut

BITS, FINE, TILE = 30, 60, 256


def transition(arcs: DataFrame, bits: int = BITS) -> DataFrame:
    """``(i, j, x)``: weight of the arc over the weight at ``i``, rounded down."""
    total = arcs.groupBy("i").agg(F.sum("w").alias("total"))
    return arcs.join(total, "i").select("i", "j", scaled("w", "total", bits).alias("x"))


def scaled(part: str, whole: str, bits: int) -> F.Column:
    """``floor(part * 2**bits / whole)`` of long columns."""
    if bits <= 31:
        return F.expr(f"({part} * {1 << bits}L) div {whole}")
    return F.expr(f"(cast({part} as decimal(19,0)) * cast('{1 << bits}' as decimal(19,0))) div cast({whole} as decimal(38,0))")


def product(a: str, b: str, bits: int) -> F.Column:
    """Exact product of two entries, as long or as decimal."""
    if bits <= 31:
        return F.col(a) * F.col(b)
    return F.col(a).cast("decimal(19,0)") * F.col(b).cast("decimal(19,0)")


def shifted(x: str, bits: int, wide: bool) -> F.Column:
    """``floor(x / 2**bits)`` as a long."""
    return F.expr(f"{x} div cast('{1 << bits}' as decimal(38,0))" if wide else f"{x} div {1 << bits}L")


def matmul_floor(a: DataFrame, b: DataFrame, bits: int = BITS) -> DataFrame:
    """Product of sparse matrices, rounded down; zero entries are left out."""
    right = b.select(F.col("i").alias("k"), F.col("j").alias("j2"), F.col("x").alias("y"))
    return (
        a.join(right, a["j"] == right["k"])
        .groupBy("i", F.col("j2").alias("j"))
        .agg(F.sum(product("x", "y", bits)).alias("s"))
        .select("i", "j", shifted("s", bits, bits > 31).alias("x"))
        .where("x > 0")
    )


def exact_product(x: np.ndarray, y: np.ndarray, bits: int) -> np.ndarray:
    """``matmul_floor`` of dense long matrices, for ``bits`` up to 31 or ``FINE``."""
    if bits <= 31:
        return (x @ y) >> bits
    if bits != FINE:
        raise ValueError(f"dense products are made for up to 31 bits and for {FINE}")
    limbs = lambda m: [(m & 0xFFFFF).astype(float), (m >> 20 & 0xFFFFF).astype(float), (m >> 40).astype(float)]
    p, q, sums = limbs(x), limbs(y), [np.zeros((len(x), y.shape[1]), np.int64) for _ in range(5)]
    for a in range(3):
        for b in range(3):
            sums[a + b] += (p[a] @ q[b]).astype(np.int64)
    carry = sums[3] + ((sums[2] + ((sums[1] + (sums[0] >> 20)) >> 20)) >> 20)
    return (sums[4] << 20) + carry


def lost_mass(power: DataFrame, n: int, bits: int) -> float:
    """Largest share that rounding has taken from a row of an ``n``-vertex matrix; 1.0 if a row is gone."""
    r = power.groupBy("i").agg(F.sum("x").alias("s")).agg(F.count(F.lit(1)).alias("n"), F.min("s").alias("least")).first()
    return 1.0 if r.n < n else 1 - r.least / float(1 << bits)


def matmul_tiles(a: DataFrame, b: DataFrame, n: int, bits: int = BITS, side: int = 256) -> DataFrame:
    """The same product for dense matrices on ids 0..n-1: tiles meet by inner index and numpy
    multiplies them; three-way replication spreads the work over (n / side)**3 tasks."""
    blocks = -(-n // side)

    def tiles(m: DataFrame, row: str, col: str) -> DataFrame:
        put = m.withColumn("bi", F.floor(F.col("i") / side).cast("int")).withColumn("bj", F.floor(F.col("j") / side).cast("int"))
        return put.withColumn("r", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).select(F.col("bi" if row == "bi" else "r").cast("int").alias("bi"), F.col(col).cast("int").alias("bk"), F.col("r" if row == "bi" else "bj").cast("int").alias("bj"), "i", "j", "x")

    left, right = tiles(a, "bi", "bj"), tiles(b, "r", "bi")

    def multiply(key, p: pd.DataFrame, q: pd.DataFrame) -> pd.DataFrame:
        x, y = np.zeros((side, side), np.int64), np.zeros((side, side), np.int64)
        x[p.i % side, p.j % side] = p.x
        y[q.i % side, q.j % side] = q.x
        z = x @ y
        i, j = np.nonzero(z)
        return pd.DataFrame({"i": i + key[0] * side, "j": j + key[2] * side, "s": z[i, j]})

    part = left.groupBy("bi", "bk", "bj").cogroup(right.groupBy("bi", "bk", "bj")).applyInPandas(multiply, "i long, j long, s long")
    return part.groupBy("i", "j").agg(F.sum("s").alias("s")).select("i", "j", F.expr(f"s div {1 << bits}L").alias("x")).where("x > 0")


def power_ladder(a: DataFrame, levels: int, bits: int = BITS, n: int | None = None) -> list[DataFrame]:
    """A, A^2, A^4, ... A^(2^levels) by squaring; each level is written once and read by all later
    steps.  With the number of vertices ``n`` up to ``TILE`` all of it is one task's work."""
    if n is not None and n <= TILE and (bits <= 31 or bits == FINE):
        every = cut(_in_task(a, levels, bits), "powers")
        return [every.where(F.col("t") == t).select("i", "j", "x") for t in range(levels + 1)]
    ladder = [cut(a, "power")]
    for _ in range(levels):
        ladder.append(cut(matmul_floor(ladder[-1], ladder[-1], bits), "power"))
    return ladder


def _in_task(a: DataFrame, levels: int, bits: int) -> DataFrame:
    def raise_all(pdf: pd.DataFrame) -> pd.DataFrame:
        ids, at = np.unique(np.concatenate([pdf.i, pdf.j]), return_inverse=True)
        m = np.zeros((len(ids), len(ids)), np.int64)
        m[at[: len(pdf)], at[len(pdf) :]] = pdf.x
        out = []
        for t in range(levels + 1):
            if t:
                m = exact_product(m, m, bits)
            i, j = np.nonzero(m)
            out.append(pd.DataFrame({"t": t, "i": ids[i], "j": ids[j], "x": m[i, j]}))
        return pd.concat(out)

    return a.groupBy().applyInPandas(raise_all, "t int, i long, j long, x long")


def stacked(ladder: list[DataFrame]) -> DataFrame:
    """All levels as ``(t, i, j, x)``."""
    out = None
    for t, m in enumerate(ladder):
        part = m.select(F.lit(t).alias("t"), "i", "j", "x")
        out = part if out is None else out.unionByName(part)
    return out


def colocate(entry: DataFrame, n: int) -> tuple[DataFrame, DataFrame]:
    """The matrix dealt out by row and, a second copy, by column."""
    return entry.repartition(n, "i"), entry.repartition(n, "j")


def submatrix(entry: DataFrame, keep: DataFrame) -> DataFrame:
    """Entries whose row and column are in ``keep (vertex)``."""
    rows, cols = keep.withColumnRenamed("vertex", "i"), keep.withColumnRenamed("vertex", "j")
    return entry.join(rows, "i", "left_semi").join(cols, "j", "left_semi").select(*entry.columns)


def laplacian(edges: DataFrame) -> DataFrame:
    """Entries ``(i, j, x)`` of the Laplacian, integers."""
    both = edges.select(F.col("u").alias("i"), F.col("v").alias("j"), "w").union(edges.select("v", "u", "w"))
    diagonal = both.groupBy("i").agg(F.sum("w").alias("x")).select("i", F.col("i").alias("j"), "x")
    return both.select("i", "j", (-F.col("w")).alias("x")).union(diagonal)


def dense(entry: DataFrame, order: list[int], scale: float = 1.0) -> np.ndarray:
    """Entries as a numpy matrix in the given order of ids; for small cores only."""
    at = {v: k for k, v in enumerate(order)}
    m = np.zeros((len(order), len(order)))
    for r in entry.select("i", "j", "x").collect():  # the caller has checked the size of the core
        m[at[r.i], at[r.j]] = r.x / scale
    return m
