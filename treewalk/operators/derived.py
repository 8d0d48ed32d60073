"""Derived graphs: the Schur complement and the shortcut graph over a kept vertex set."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..ckpt import cut
from . import linalg, pairs

OTHER = 1 << 50  # offset of the second copy of every vertex


def active_set(vertices: DataFrame, visited: DataFrame, end: int) -> DataFrame:
    """Unvisited vertices and the walk's present end."""
    rest = vertices.join(visited, "vertex", "left_anti")
    here = vertices.where(F.col("vertex") == end)
    return rest.union(here).distinct()


def enter_matrix(arcs: DataFrame, keep: DataFrame, bits: int = linalg.BITS) -> DataFrame:
    """Step from any vertex into the kept set, by weight; vertices without such a step stay."""
    into = arcs.join(keep.withColumnRenamed("vertex", "j"), "j", "left_semi").select("i", "j", "w")
    r = linalg.transition(into, bits)
    stay = arcs.select("i").distinct().join(into.select("i").distinct(), "i", "left_anti").select("i", F.col("i").alias("j"), F.lit(1 << bits).cast("long").alias("x"))
    return r.union(stay)


def schur_bipartite(edges: DataFrame, keep_left: bool = True, bits: int = 20) -> DataFrame:
    """Schur complement of a bipartite view onto its left side (``u``): the other side is
    independent, so meetings in it give all: ``(u, v, x)``, weights in fixed point."""
    kept, gone = ("u", "v") if keep_left else ("v", "u")
    e = edges.select(F.col(kept).alias("i"), F.col(gone).alias("k"), F.col("w").cast("long").alias("a"))
    d = e.groupBy("k").agg(F.sum("a").alias("extra"))
    right = e.select("k", F.col("i").alias("j"), F.col("a").alias("b")).join(d, "k")
    return pairs.sums(e, right, type("Fixed", (pairs.Ratio,), {"bits": bits}), ["u", "v", "x"], above=True)


eliminate_independent = schur_bipartite


def eliminate_vertex(edges: DataFrame, c: int, bits: int = 20) -> DataFrame:
    """One Gaussian step in fixed point ``(u, v, x)``: neighbours a, b of ``c`` gain w(a,c) w(c,b) / d(c)."""
    near = edges.where((F.col("u") == c) | (F.col("v") == c)).select(F.when(F.col("u") == c, F.col("v")).otherwise(F.col("u")).alias("a"), "w")
    d = near.agg(F.sum("w").alias("d"))
    right = near.select(F.col("a").alias("b"), F.col("w").alias("w2"))
    # pairs of neighbours of one vertex: an equi-join on the constant vertex
    fill = near.withColumn("c", F.lit(c)).join(right.withColumn("c", F.lit(c)), "c").where("a < b").join(d.withColumn("c", F.lit(c)), "c").select("a", "b", F.expr(f"(w * w2 * {1 << bits}L) div d").alias("x"))
    rest = edges.where((F.col("u") != c) & (F.col("v") != c)).select("u", "v", (F.col("w") * (1 << bits)).alias("x"))
    return rest.union(fill).groupBy("u", "v").agg(F.sum("x").alias("x"))


def absorbing_chain(a: DataFrame, keep: DataFrame) -> DataFrame:
    """Two copies of every vertex: the walking one steps on while outside the kept set; a step
    into it ends at the second copy of the vertex just before."""
    flag = a.join(keep.select(F.col("vertex").alias("j"), F.lit(True).alias("kept")), "j", "left")
    walking = flag.where("kept IS NULL").select("i", "j", "x")
    ending = flag.where("kept").groupBy("i").agg(F.sum("x").alias("x")).select("i", (F.col("i") + OTHER).alias("j"), "x")
    return walking.union(ending)


def shortcut_absorbing(a: DataFrame, keep: DataFrame, bits: int = linalg.BITS, delta: float = 1e-6, max_levels: int = 60, n: int | None = None) -> tuple[DataFrame, int]:
    """Shortcut matrix ``(i, j, x)``: from ``i``, the vertex just before the kept set is next entered.
    Squares the doubled chain until at most ``delta`` is still walking.  Also the squarings used.
    With a number of vertices ``n`` whose doubled chain fits a tile all of it is one task's work."""
    one = 1 << bits
    if n is not None and 2 * n <= linalg.TILE and (bits <= 31 or bits == linalg.FINE):
        done = cut(_absorbed_in_task(absorbing_chain(a, keep), bits, delta, max_levels), "absorb")
        level = done.agg(F.max("level")).first()[0] or 0
        return done.select("i", "j", "x"), level
    done = a.select("i").distinct().select((F.col("i") + OTHER).alias("i"), (F.col("i") + OTHER).alias("j"), F.lit(one).cast("long").alias("x"))
    m = cut(absorbing_chain(a, keep).union(done), "absorb")
    for level in range(max_levels):
        left = m.where((F.col("i") < OTHER) & (F.col("j") < OTHER)).groupBy("i").agg(F.sum("x").alias("s")).agg(F.max("s")).first()[0] or 0
        if left <= delta * one:
            break
        m = cut(linalg.matmul_floor(m, m, bits), "absorb")
    q = m.where((F.col("i") < OTHER) & (F.col("j") >= OTHER)).select("i", (F.col("j") - OTHER).alias("j"), "x")
    return q, level


def _absorbed_in_task(chain: DataFrame, bits: int, delta: float, max_levels: int) -> DataFrame:
    def run(pdf):
        import pandas as pd

        ids = np.unique(pdf.i)
        n, at = len(ids), {v: k for k, v in enumerate(ids.tolist())}
        m = np.zeros((2 * n, 2 * n), np.int64)
        m[np.arange(n, 2 * n), np.arange(n, 2 * n)] = 1 << bits
        m[[at[v] for v in pdf.i], [at[v] if v < OTHER else n + at[v - OTHER] for v in pdf.j]] = pdf.x
        for level in range(max_levels):
            if m[:n, :n].sum(1).max() <= delta * 2.0**bits:
                break
            m = linalg.exact_product(m, m, bits)
        i, j = np.nonzero(m[:n, n:])
        return pd.DataFrame({"i": ids[i], "j": ids[j], "x": m[:n, n:][i, j], "level": level})

    return chain.groupBy().applyInPandas(run, "i long, j long, x long, level int")


def self_return(shortcut: DataFrame, enter: DataFrame, keep: DataFrame, bits: int = linalg.BITS) -> DataFrame:
    """``(i, x)``: chance of the first kept vertex being ``i`` again."""
    x = linalg.matmul_floor(shortcut.join(keep.withColumnRenamed("vertex", "i"), "i", "left_semi").select("i", "j", "x"), enter, bits)
    return x.where("i = j").select("i", "x")


def schur_transition(shortcut: DataFrame, enter: DataFrame, keep: DataFrame, bits: int = linalg.BITS) -> DataFrame:
    """Walk on the kept set: the first other kept vertex reached; zero diagonal, rows of sum one."""
    own = shortcut.join(keep.withColumnRenamed("vertex", "i"), "i", "left_semi").select("i", "j", "x")
    x = linalg.matmul_floor(own, enter, bits).where("i <> j")
    total = x.groupBy("i").agg(F.sum("x").alias("total"))
    return x.join(total, "i").select("i", "j", linalg.scaled("x", "total", bits).alias("x"))


def schur_dense(w: np.ndarray, keep: list[int]) -> np.ndarray:
    """Schur complement of the Laplacian of weights ``w`` onto ``keep``, as weights."""
    lap = np.diag(w.sum(1)) - w
    out = [i for i in range(len(w)) if i not in set(keep)]
    s = lap[np.ix_(keep, keep)]
    if out:
        s = s - lap[np.ix_(keep, out)] @ np.linalg.solve(lap[np.ix_(out, out)], lap[np.ix_(out, keep)])
    s = -s
    np.fill_diagonal(s, 0)
    return np.maximum(s, 0)


def shortcut_dense(w: np.ndarray, keep: list[int]) -> np.ndarray:
    """Shortcut matrix by a linear solve, for every start."""
    p = w / w.sum(1, keepdims=True)
    kept = np.zeros(len(w), bool)
    kept[keep] = True
    return np.linalg.solve(np.eye(len(w)) - p * ~kept, np.diag(p[:, kept].sum(1)))
