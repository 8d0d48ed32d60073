"""Walks and resistances of graphs too large for a dense core: rows of neighbours, a copy of them in every task.

The edges reach the tasks by a shuffle, never by way of the driver; vertices are numbered 0..n-1 first.
"""

from __future__ import annotations

from array import array
from bisect import bisect_right
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..ckpt import cut
from ..sources.graphs import Graph, index_vertices


class Rows:
    """Neighbours of every vertex, in id order, with cumulative weights where they differ."""

    def __init__(self, n: int, u: np.ndarray, v: np.ndarray, w: np.ndarray):
        a, b = np.concatenate([u, v]), np.concatenate([v, u])
        order = np.lexsort((b, a))
        self.n, self.degree = n, np.bincount(a, minlength=n)
        self.ptr = np.concatenate([[0], np.cumsum(self.degree)])
        self.near, self.weight = b[order], np.concatenate([w, w])[order]
        self.even = len(w) == 0 or bool((w == w[0]).all())

    def stepper(self, r: np.random.Generator) -> Callable[[int], int]:
        ptr, near = self.ptr.tolist(), array("i", self.near.astype(np.int32).tobytes())
        uniform = iter(())
        if not self.even:
            total = np.cumsum(self.weight)
            base = np.concatenate([[0], total])[self.ptr]
            high = array("q", total.astype(np.int64).tobytes())
            base = base.astype(np.int64).tolist()

        def draw() -> float:
            nonlocal uniform
            x = next(uniform, None)
            if x is None:
                uniform = iter(r.random(8192).tolist())
                x = next(uniform)
            return x

        if self.even:
            return lambda v: near[ptr[v] + int(draw() * (ptr[v + 1] - ptr[v]))]
        # integer weights: a whole number below the total falls into one neighbour's share
        return lambda v: near[bisect_right(high, base[v] + int(draw() * (base[v + 1] - base[v])), ptr[v], ptr[v + 1])]


def cover_steps(g: Rows, r: np.random.Generator, start: int = 0) -> int:
    """Steps until every vertex is seen."""
    step, seen, left, v, n = g.stepper(r), bytearray(g.n), g.n - 1, start, 0
    seen[v] = 1
    while left:
        v = step(v)
        n += 1
        if not seen[v]:
            seen[v] = 1
            left -= 1
    return n


def loop_erased(g: Rows, r: np.random.Generator, root: int = 0) -> list[tuple[int, int]]:
    """(child, parent).  Vertices of one neighbour are taken off first, over and over: their edges are in every
    tree.  The rest by loop-erased walks."""
    degree, out = g.degree.tolist(), []
    ptr, near, gone = g.ptr.tolist(), g.near, bytearray(g.n)
    leaves = [v for v in range(g.n) if degree[v] == 1 and v != root]
    while leaves:
        v = leaves.pop()
        p = next(x for x in near[ptr[v] : ptr[v + 1]].tolist() if not gone[x])
        gone[v] = 1
        out.append((v, p))
        degree[p] -= 1
        if degree[p] == 1 and p != root:
            leaves.append(p)
    if len(out) == g.n - 1:
        return out
    if any(gone):
        keep = np.frombuffer(gone, np.uint8) == 0
        names = np.flatnonzero(keep)
        at = np.cumsum(keep) - 1
        a = np.repeat(np.arange(g.n), g.degree)
        ok = keep[a] & keep[g.near] & (a < g.near)
        core = Rows(len(names), at[a[ok]], at[g.near[ok]], g.weight[ok])
        return out + [(int(names[c]), int(names[p])) for c, p in loop_erased(core, r, int(at[root]))]
    step, inside, leave = g.stepper(r), bytearray(g.n), [0] * g.n
    inside[root] = 1
    for s in range(g.n):
        v = s
        while not inside[v]:
            x = step(v)
            leave[v] = x
            v = x
        v = s
        while not inside[v]:
            inside[v] = 1
            out.append((v, leave[v]))
            v = leave[v]
    return out


TREES = {"loop_erased": loop_erased}


def in_tasks(g: Graph, items: int | None, work: Callable, names: list[str], schema: str) -> DataFrame:
    """``work(rows, mine)`` in tasks that each hold all edges of a numbered graph; ``mine``: its share of 0..items-1
    (default: the vertices).  ``work`` yields tuples of arrays."""
    edges = cut(g.edges.select(*[F.col(c).cast("long").alias(c) for c in ("u", "v", "w")]), "edges")
    spark = edges.sparkSession
    n = edges.agg(F.max(F.greatest("u", "v"))).first()[0]
    n = 0 if n is None else n + 1
    total = n if items is None else items
    tasks = max(1, min(total, spark.sparkContext.defaultParallelism))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [[c.to_numpy() if k else c[:1].to_numpy() for k, c in enumerate(b.columns)] for b in batches if b.num_rows]
        if not held:
            return
        task = int(held[0][0][0])
        u, v, w = (np.concatenate([h[k] for h in held]) for k in (1, 2, 3))
        held.clear()
        rows = Rows(n, u, v, w)
        del u, v, w
        for cols in work(rows, range(task, total, tasks)):
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=names)

    dealt = edges.select(F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))).alias("task"), "u", "v", "w").repartitionById(tasks, F.col("task"))
    return dealt.mapInArrow(run, schema)


def replicate(g: Graph, n_samples: int, method: str | Callable, seed: int) -> DataFrame:
    """``n_samples`` trees ``(sample_id, child, parent, u, v)``; ``method``: a name, or a function of rows and generator."""
    ids, dense = index_vertices(g)
    ids, tree = cut(ids, "ids"), TREES[method] if isinstance(method, str) else method

    def work(rows, mine):
        for s in mine:
            t = np.array(tree(rows, np.random.default_rng([seed, s])), np.int64).reshape(-1, 2)
            yield np.full(len(t), s, np.int64), t[:, 0].copy(), t[:, 1].copy()

    t = in_tasks(dense, n_samples, work, ["sample_id", "c", "p"], "sample_id long, c long, p long")
    for short, name in (("c", "child"), ("p", "parent")):
        t = t.join(ids.select(F.col("vid").alias(short), F.col("vertex").alias(name)), short).drop(short)
    return t.select("sample_id", "child", "parent", F.least("child", "parent").alias("u"), F.greatest("child", "parent").alias("v"))


def cover_times(g: Graph, reps: int, seed: int) -> DataFrame:
    """``(rep, steps)``."""
    def work(rows, mine):
        for s in mine:
            yield np.array([s], np.int64), np.array([cover_steps(rows, np.random.default_rng([seed, s]))], np.int64)

    return in_tasks(index_vertices(g)[1], reps, work, ["rep", "steps"], "rep long, steps long")


def _solve(rows: Rows, starts: np.ndarray, tol: float = 1e-9) -> np.ndarray:
    """Columns of the Laplacian's pseudo-inverse at ``starts`` (up to a constant each), by conjugate gradients."""
    a, w = np.repeat(np.arange(rows.n), rows.degree), rows.weight.astype(float)
    d = np.bincount(a, w, rows.n)[:, None]
    cuts = np.searchsorted(rows.ptr, np.arange(0, len(rows.near), 1 << 15))  # whole rows, so that products stay in cache
    cuts = np.unique(np.append(cuts[cuts < rows.n], [0, rows.n]))

    def times(x: np.ndarray) -> np.ndarray:
        out = d * x
        for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist()):
            s = slice(rows.ptr[lo], rows.ptr[hi])
            near = x[rows.near[s]]
            out[lo:hi] -= np.add.reduceat(near if rows.even and w[0] == 1 else w[s, None] * near, rows.ptr[lo:hi] - rows.ptr[lo], axis=0)
        return out

    b = np.full((rows.n, len(starts)), -1.0 / rows.n)
    b[starts, np.arange(len(starts))] += 1
    x, r = np.zeros_like(b), b.copy()
    z = r / d
    p, rz = z.copy(), (r * z).sum(0)
    for _ in range(20 * rows.n):
        q = times(p)
        step = rz / np.maximum((p * q).sum(0), 1e-300)
        x += step * p
        r -= step * q
        if np.abs(r).max() <= tol:
            return x
        z = r / d
        new = (r * z).sum(0)
        p = z + (new / np.maximum(rz, 1e-300)) * p
        rz = new
    raise FloatingPointError("resistances did not settle")


def marginals(g: Graph, block: int = 32) -> DataFrame:
    """``(u, v, p)``: chance of each edge in a tree, its weight times its effective resistance."""
    ids, dense = index_vertices(g)
    ids = cut(ids, "ids")

    def work(rows, mine):
        for lo in range(0, len(mine), block):
            at = np.array(mine[lo : lo + block])
            x = _solve(rows, at)
            for k, v in enumerate(at.tolist()):
                s = slice(rows.ptr[v], rows.ptr[v + 1])
                near = rows.near[s].astype(np.int64)
                yield np.minimum(near, v), np.maximum(near, v), rows.weight[s] * (x[v, k] - x[near, k])

    half = in_tasks(dense, None, work, ["a", "b", "p"], "a long, b long, p double").groupBy("a", "b").agg(F.sum("p").alias("p"))
    for short, name in (("a", "u"), ("b", "v")):
        half = half.join(ids.select(F.col("vid").alias(short), F.col("vertex").alias(name)), short).drop(short)
    return half.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), "p")
