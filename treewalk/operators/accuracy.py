"""How close samples are to the law wanted, and how exact the arithmetic is."""

from __future__ import annotations

import itertools
import math
from fractions import Fraction

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graph import components
from .trees import tree_key


def tree_count(edges: list[tuple[int, int, int]]) -> int:
    """Weighted number of spanning trees: a principal minor of the Laplacian, in exact integers."""
    ids = sorted({a for a, _, _ in edges} | {b for _, b, _ in edges})
    at, n = {v: i for i, v in enumerate(ids)}, len(ids)
    m = [[0] * n for _ in range(n)]
    for a, b, w in edges:
        i, j = at[a], at[b]
        m[i][i] += w
        m[j][j] += w
        m[i][j] -= w
        m[j][i] -= w
    m = [row[1:] for row in m[1:]]
    size, sign, last = n - 1, 1, 1
    for k in range(size):  # division stays exact at every step
        if m[k][k] == 0:
            swap = next((i for i in range(k + 1, size) if m[i][k]), None)
            if swap is None:
                return 0
            m[k], m[swap], sign = m[swap], m[k], -sign
        for i in range(k + 1, size):
            for j in range(k + 1, size):
                m[i][j] = (m[i][j] * m[k][k] - m[i][k] * m[k][j]) // last
        last = m[k][k]
    return sign * last if size else 1


def enumerate_trees(edges: list[tuple[int, int, int]]) -> dict[str, Fraction]:
    """Every spanning tree of a small graph with its exact probability."""
    ids = {a for a, _, _ in edges} | {b for _, b, _ in edges}
    found = {}
    for pick in itertools.combinations(edges, len(ids) - 1):
        label = {v: v for v in ids}
        ok = True
        for a, b, _ in pick:
            x, y = label[a], label[b]
            if x == y:
                ok = False
                break
            label = {v: y if c == x else c for v, c in label.items()}
        if ok:
            found[",".join(sorted(f"{min(a, b)}-{max(a, b)}" for a, b, _ in pick))] = math.prod(w for _, _, w in pick)
    total = sum(found.values())
    return {k: Fraction(v, total) for k, v in found.items()}


def truth_frame(spark, edges: list[tuple[int, int, int]]) -> DataFrame:
    return spark.createDataFrame([(k, float(v)) for k, v in enumerate_trees(edges).items()], "tree string, chance double")


def tv(trees: DataFrame, truth: DataFrame) -> DataFrame:
    """One row ``(samples, tv, chi2, df)``: total variation distance and chi-square of sampled trees
    against ``truth (tree, chance)``."""
    seen = tree_key(trees).groupBy("tree").agg(F.count(F.lit(1)).alias("n"))
    both = seen.join(truth, "tree", "full_outer").select(F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("chance", F.lit(0.0)).alias("p"))
    total = both.agg(F.sum("n").alias("samples"))
    return both.crossJoin(F.broadcast(total)).agg(F.max("samples").alias("samples"), (F.sum(F.abs(F.col("n") / F.col("samples") - F.col("p"))) / 2).alias("tv"), F.sum(F.when(F.col("p") > 0, F.pow(F.col("n") - F.col("samples") * F.col("p"), F.lit(2.0)) / (F.col("samples") * F.col("p")))).alias("chi2"), (F.count_if(F.col("p") > 0) - 1).alias("df"))


def chi2_p(x: float, df: int) -> float:
    """Upper tail of chi-square, by the series of the incomplete gamma function."""
    a, z = df / 2, x / 2
    if z <= 0:
        return 1.0
    term = total = 1 / a
    k = a
    while abs(term) > abs(total) * 1e-14 and k < a + 10_000:
        k += 1
        term *= z / k
        total += term
    return max(0.0, 1 - total * math.exp(-z + a * math.log(z) - math.lgamma(a)))


def resistance_marginals(w: np.ndarray) -> dict[tuple[int, int], float]:
    """Chance of each edge in a weighted uniform tree: weight times effective resistance."""
    inv = np.linalg.pinv(np.diag(w.sum(1)) - w)
    a, b = np.nonzero(np.triu(w, 1))
    return {(int(i), int(j)): float(w[i, j] * (inv[i, i] + inv[j, j] - 2 * inv[i, j])) for i, j in zip(a, b)}


def marginals(trees: DataFrame, samples: int) -> DataFrame:
    """``(u, v, share)`` of each edge over the samples."""
    return trees.groupBy("u", "v").agg((F.count(F.lit(1)) / samples).alias("share"))


def validate_tree(tree: DataFrame, edges: DataFrame) -> DataFrame:
    """One row of checks: edges, vertices, edges outside the graph, components of the tree and of
    the graph, and whether it is a spanning forest."""
    t = tree.select("u", "v").distinct()
    n_v = edges.select(F.col("u").alias("x")).union(edges.select("v")).distinct().agg(F.count(F.lit(1)).alias("n_vertices"))
    outside = t.join(edges.select("u", "v"), ["u", "v"], "left_anti").agg(F.count(F.lit(1)).alias("n_outside"))
    n_e = t.agg(F.count(F.lit(1)).alias("n_edges"))
    vertices = edges.select(F.col("u").alias("vertex")).union(edges.select("v")).distinct()
    ct = components(t, vertices).agg(F.count_distinct("component").alias("n_tree_components"))
    cg = components(edges, vertices).agg(F.count_distinct("component").alias("n_components"))
    row = n_e.crossJoin(n_v).crossJoin(outside).crossJoin(ct).crossJoin(cg)  # one row each
    ok = (F.col("n_outside") == 0) & (F.col("n_tree_components") == F.col("n_components")) & (F.col("n_edges") == F.col("n_vertices") - F.col("n_components"))
    return row.withColumn("ok", ok)


def subtractive_error(exact: np.ndarray, entry: DataFrame, order: list[int], bits: int) -> dict[str, float]:
    """Largest entry error and largest row mass lost of a rounded power, against doubles."""
    from .linalg import dense

    e = exact - dense(entry, order, float(1 << bits))
    return {"max_entry": float(e.max()), "min_entry": float(e.min()), "max_row_mass": float(e.sum(1).max())}


def error_bound(n: int, k: int, delta: float) -> float:
    """Bound of the entry error of the k-th power (k a power of two): E(1) = delta, E(k) = (n+1) E(k/2) + delta."""
    e = delta
    while k > 1:
        e, k = (n + 1) * e + delta, k // 2
    return e


def row_mass_bound(n: int, k: int, delta: float) -> float:
    """Tighter bound on a row's lost mass: n delta (2k - 1)."""
    return n * delta * (2 * k - 1)


def midpoint_tv(exact_half: np.ndarray, rounded_half: np.ndarray) -> np.ndarray:
    """Total variation of the middle's law for every pair of ends; nan where either law is empty."""
    a = exact_half[:, None, :] * exact_half.T[None, :, :]
    b = rounded_half[:, None, :] * rounded_half.T[None, :, :]
    with np.errstate(invalid="ignore", divide="ignore"):
        return np.abs(a / a.sum(2, keepdims=True) - b / b.sum(2, keepdims=True)).sum(2) / 2


def midpoint_bound(n: int, beta: float, c: float) -> float:
    """2 beta n^(c+1), for pairs whose two-step weight is above n^-c."""
    return 2 * beta * n ** (c + 1)


def same_counts(counts: DataFrame, law: DataFrame, least: float = 5.0) -> DataFrame:
    """One row ``(cells, chi2, same)``: whether ``counts (i, j, n)`` of moves fit ``law (i, j, share)``; cells
    that expect under ``least`` moves are left out."""
    total = counts.groupBy("i").agg(F.sum("n").alias("total"))
    both = law.join(total, "i").join(counts, ["i", "j"], "left").withColumn("e", F.col("share") * F.col("total")).where(F.col("e") >= least)
    r = both.agg(F.count(F.lit(1)).alias("cells"), F.sum(F.pow(F.coalesce("n", F.lit(0)) - F.col("e"), F.lit(2.0)) / F.col("e")).alias("chi2"), F.count_distinct("i").alias("rows"))
    z = (F.col("chi2") - (F.col("cells") - F.col("rows"))) / F.sqrt(2.0 * F.greatest(F.col("cells") - F.col("rows"), F.lit(1)))
    return r.select("cells", "chi2", (z < 5).alias("same"))


def rare_pairs(pairs: DataFrame, power: DataFrame, threshold: int) -> DataFrame:
    """``(pairs, rare)``: how many requested pairs have at most ``threshold`` of (fixed-point) weight."""
    x = power.select(F.col("i").alias("p"), F.col("j").alias("q"), "x")
    j = pairs.join(x, ["p", "q"], "left").select(F.coalesce("x", F.lit(0)).alias("x"))
    return j.agg(F.count(F.lit(1)).alias("pairs"), F.count_if(F.col("x") <= threshold).alias("rare"))


def max_self_return(returns: DataFrame, bits: int) -> DataFrame:
    """Largest factor 1 / (1 - chance of return)."""
    return returns.agg(F.max(F.lit(float(1 << bits)) / (F.lit(1 << bits) - F.col("x"))).alias("factor"))


def twise_tail(t: int, mu: float, a: float) -> float:
    """Tail bound of a sum of t-wise independent indicators: 8 ((t mu + t^2) / a^2)^(t/2)."""
    return 8 * ((t * mu + t * t) / (a * a)) ** (t / 2)
