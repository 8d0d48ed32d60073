"""Placing a multiset of middles into places: weighted perfect matchings.

``w[s, m]`` is the weight of middle ``m`` in place ``s``; a matching's weight is the product over
its places.  Variants: ``exact`` (self-reduction with permanents), ``approx_count`` (self-reduction
with a sampled count), ``swap`` (Metropolis over permutations), ``classes`` (counts by class of
place and vertex, then a shuffle within each), ``auto`` (``classes`` up to ``TABLES`` tables of counts, the
swap chain beyond), ``per_pair`` and ``order``.  A method that cannot serve an input says so.
"""

from __future__ import annotations

import itertools
import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import rng

EXACT_LIMIT, TABLES, MOST_DRAWS = 12, 20_000, 200_000


def permanent(m: np.ndarray) -> float:
    """Inclusion-exclusion over column subsets, in Gray order of the subsets."""
    n = len(m)
    if n == 0:
        return 1.0
    if n > 20:
        raise ValueError("permanents are computed for up to 20 rows")
    total, sums, chosen = 0.0, np.zeros(n), np.zeros(n, bool)
    for g in range(1, 1 << n):
        c = (g & -g).bit_length() - 1
        sums += -m[:, c] if chosen[c] else m[:, c]
        chosen[c] = ~chosen[c]
        total += (-1) ** (n - int(chosen.sum())) * sums.prod()
    return total


def log_weight(match: np.ndarray, w: np.ndarray) -> float:
    x = w[np.arange(len(match)), match]
    return float(np.log(x).sum()) if (x > 0).all() else -math.inf


def exact(w: np.ndarray, r: np.random.Generator) -> np.ndarray:
    """Place by place, each middle by the permanent of what would be left."""
    free, out = list(range(len(w))), []
    for s in range(len(w)):
        p = np.array([w[s, m] * permanent(w[s + 1 :][:, [x for x in free if x != m]]) if w[s, m] > 0 else 0.0 for m in free])
        p = np.maximum(p, 0)
        pick = free[int(r.choice(len(free), p=p / p.sum()))]
        out.append(pick)
        free.remove(pick)
    return np.array(out)


def swap(w: np.ndarray, start: np.ndarray, r: np.random.Generator, sweeps: int = 20) -> np.ndarray:
    """Metropolis over permutations from a valid one; proposals exchange two places."""
    m, n = start.copy(), len(w)
    for _ in range(sweeps * n * max(1, n.bit_length()) if n > 1 else 0):
        a, b = r.integers(n), r.integers(n)
        old, new = w[a, m[a]] * w[b, m[b]], w[a, m[b]] * w[b, m[a]]
        if new >= old or r.random() * old < new:
            m[a], m[b] = m[b], m[a]
    return m


def approx_permanent(w: np.ndarray, r: np.random.Generator, error: float = 0.05) -> float:
    """Unbiased sequential estimate: rows choose by weight among free columns, and the product of what they
    could choose from is averaged.  Draws go on until their standard error is ``error`` of the mean."""
    n = len(w)
    if n == 0:
        return 1.0
    out = np.zeros(0)
    while True:
        free, value = np.ones((500, n), bool), np.ones(500)
        for s in range(n):  # all draws of a batch at once
            open_ = np.cumsum(w[s] * free, axis=1)
            total = open_[:, -1]
            pick = (open_ <= (r.random(500) * total)[:, None]).sum(1).clip(max=n - 1)
            value *= total
            free[np.arange(500), pick] = False
        out = np.concatenate([out, value])
        mean, spread = float(out.mean()), float(out.std()) / math.sqrt(len(out))
        if spread <= error * mean or (mean == 0 and len(out) >= 2000):
            return mean
        if len(out) >= MOST_DRAWS:
            raise ValueError(f"{MOST_DRAWS} draws leave a relative error of {spread / mean:.2g}")


def approx_count(w: np.ndarray, r: np.random.Generator, tv: float = 0.05) -> np.ndarray:
    """Self-reduction with sampled counts in place of permanents.  Each of the n choices uses counts with a
    standard error of ``tv`` / n of their value, so that all choices together stay near ``tv``."""
    error = tv / max(1, len(w))
    free, out = list(range(len(w))), []
    for s in range(len(w)):
        p = np.array([w[s, m] * approx_permanent(w[s + 1 :][:, [x for x in free if x != m]], r, error) if w[s, m] > 0 else 0.0 for m in free])
        if p.sum() <= 0:
            p = np.array([float(w[s, m] > 0) for m in free])
        pick = free[int(r.choice(len(free), p=p / p.sum()))]
        out.append(pick)
        free.remove(pick)
    return np.array(out)


def class_tables(rows: list[int], cols: list[int], w: np.ndarray) -> tuple[list[np.ndarray], np.ndarray]:
    """All tables of counts with the given margins, with weight prod w^N / N!."""
    tables: list[np.ndarray] = []

    def fill(k: int, left: list[int], done: list[tuple[int, ...]]) -> None:
        if k == len(rows):
            tables.append(np.array(done))
            return
        for part in itertools.product(*[range(min(c, rows[k]) + 1) for c in left]):
            if sum(part) == rows[k] and (k < len(rows) - 1 or list(part) == left):
                fill(k + 1, [c - p for c, p in zip(left, part)], [*done, part])

    fill(0, list(cols), [])
    weights = np.array([math.prod(w[g, x] ** int(t[g, x]) / math.factorial(int(t[g, x])) for g in range(len(rows)) for x in range(len(cols))) for t in tables])
    return tables, weights


def table_bound(place_class: np.ndarray, vertex: np.ndarray) -> int:
    """Bound on the number of tables of counts."""
    rows, kinds = np.unique(place_class, return_counts=True)[1], len(np.unique(vertex))
    return math.prod(math.comb(int(a) + kinds - 1, kinds - 1) for a in rows[:-1])


def classes(w: np.ndarray, place_class: np.ndarray, vertex: np.ndarray, r: np.random.Generator, limit: int = TABLES) -> np.ndarray:
    """Draw the table of counts, then shuffle inside each class."""
    g, x = np.unique(place_class), np.unique(vertex)
    rows, cols = [int((place_class == k).sum()) for k in g], [int((vertex == k).sum()) for k in x]
    if (n := table_bound(place_class, vertex)) > limit:
        raise ValueError(f"up to {n} tables of counts, over {limit}; use 'swap' or 'auto'")
    small = np.array([[w[np.flatnonzero(place_class == a)[0], np.flatnonzero(vertex == b)[0]] for b in x] for a in g])
    tables, weight = class_tables(rows, cols, small)
    t = tables[int(r.choice(len(tables), p=weight / weight.sum()))]
    pools = {b: list(r.permutation(np.flatnonzero(vertex == b))) for b in x}
    out = np.zeros(len(w), int)
    for i, a in enumerate(g):
        items = [pools[b].pop() for j, b in enumerate(x) for _ in range(int(t[i, j]))]
        out[np.flatnonzero(place_class == a)] = r.permutation(items)
    return out


def draw(w: np.ndarray, method: str, r: np.random.Generator, place_class=None, vertex=None, start=None, tv: float = 0.05) -> np.ndarray:
    """Middle of every place by the named method."""
    if method == "exact":
        if len(w) > EXACT_LIMIT:
            raise ValueError(f"exact matchings are drawn for up to {EXACT_LIMIT} places, not {len(w)}")
        return exact(w, r)
    if method == "auto":
        method = "classes" if table_bound(place_class, vertex) <= TABLES else "swap"
    if method == "approx_count":
        return approx_count(w, r, tv)
    if method == "classes":
        return classes(w, place_class, vertex, r)
    if method != "swap":
        raise ValueError(f"no placement is called {method!r}")
    return swap(w, np.arange(len(w)) if start is None else start, r)


def place(bip: DataFrame, method: str = "auto", seed: int = 0, tv: float = 0.05) -> DataFrame:
    """``bip (sample_id, pos_id, mid_id, place_class, vertex, weight)`` with one row for each place and
    middle, to ``(sample_id, pos_id, mid_id)``: one grouped task a sample."""

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        t = pdf.pivot_table(index="pos_id", columns="mid_id", values="weight", fill_value=0.0)
        c = pdf.drop_duplicates("pos_id").set_index("pos_id")["place_class"].reindex(t.index).to_numpy()
        v = pdf.drop_duplicates("mid_id").set_index("mid_id")["vertex"].reindex(t.columns).to_numpy()
        w = t.to_numpy(float)
        r = np.random.default_rng([seed, int(pdf.sample_id.iloc[0])])
        m = draw(w / max(w.max(), 1e-300), method, r, c, v, tv=tv)
        return pd.DataFrame({"sample_id": pdf.sample_id.iloc[0], "pos_id": t.index, "mid_id": t.columns.to_numpy()[m]})

    return bip.groupBy("sample_id").applyInPandas(one, "sample_id long, pos_id long, mid_id long")


def split_final(mids: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The last middle of each sample, and the multiset of the others ``(sample_id, vertex, c)``."""
    last = mids.groupBy("sample_id").agg(F.max("pos").alias("pos"), F.max_by("vertex", "pos").alias("vertex"))
    rest = mids.join(last.select("sample_id", F.col("pos").alias("final")), "sample_id").where("pos <> final")
    return last, multiset(rest)


def multiset(mids: DataFrame) -> DataFrame:
    return mids.groupBy("sample_id", "vertex").agg(F.count(F.lit(1)).alias("c"))


def per_pair(mids: DataFrame, seed: int, level: int) -> DataFrame:
    """Uniform shuffle of the draws inside each pair: exact, as places of one pair are exchangeable."""
    w = Window.partitionBy("sample_id", "p", "q").orderBy(rng.bits(seed, f"shuffle{level}", "sample_id", "p", "q", "occ"), "occ")
    return mids.select("sample_id", "p", "q", F.row_number().over(w).cast("long").alias("occ"), "vertex")
