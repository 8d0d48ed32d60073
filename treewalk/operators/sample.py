"""Spanning trees: one large draw with DataFrames, or many draws of a small core in tasks."""

from __future__ import annotations

import functools
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..ckpt import cut
from ..functions import rng
from ..sources.graphs import Graph, index_vertices
from . import derived, doubling, graph as graphs, kernels, lazy, linalg, params, sparse, split, topdown, trees

TREE = "sample_id long, child long, parent long, u long, v long"
CORE_LIMIT = 4000  # vertices of a core that is broadcast as a dense matrix


def core(g: Graph, limit: int = CORE_LIMIT) -> tuple[list[int], np.ndarray]:
    """Vertices and weight matrix of a small graph.  Vertices and edges are counted before the edges come
    to the driver, as columns."""
    n, m = g.vertices.count(), g.edges.count()
    if n > limit or m > limit * limit // 2:
        raise ValueError(f"{n} vertices and {m} edges are above the core bound of {limit} vertices; reduce the graph first")
    t = g.edges.select("u", "v", "w").toArrow()
    u, v, x = (t.column(c).to_numpy() for c in ("u", "v", "w"))
    order, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    w = np.zeros((len(order), len(order)))
    w[at[: len(u)], at[len(u) :]] = w[at[len(u) :], at[: len(u)]] = x
    return order.tolist(), w


def split_core(g: Graph) -> tuple[list[int], split.Split] | None:
    """Vertices and classes of a bipartite graph with a side of up to ``split.SMALL`` vertices whose ids all lie on
    one side of the others'; None for other graphs and for those of up to ``linalg.TILE`` vertices."""
    f = g.edges.agg(F.count_distinct("u").alias("a"), F.count_distinct("v").alias("b")).first()
    if f.a + f.b <= linalg.TILE or min(f.a, f.b) > split.SMALL or g.vertices.count() != f.a + f.b:
        return None
    t = g.edges.select("u", "v", "w").toArrow()  # at most SMALL edges a vertex
    u, v, x = (t.column(c).to_numpy() for c in ("u", "v", "w"))
    if f.a < f.b:
        u, v = v, u
    large, at = np.unique(u, return_inverse=True)
    small, to = np.unique(v, return_inverse=True)
    return [*large.tolist(), *small.tolist()], split.Split.of(at, to, x, len(large), len(small))


def replicate(g: Graph, n_samples: int, method: str = "phased", seed: int = 42, tasks: int | None = None, **options) -> DataFrame:
    """``n_samples`` trees of one graph; each task takes a share of the sample ids.  Loop-erased walks need no dense
    core: above its bound the tasks hold rows of neighbours.  Nor does the phased sampler with ``on_short="fail"``, for up
    to ``lazy.LIMIT`` vertices."""
    if method in sparse.TREES and not options and g.vertices.count() > CORE_LIMIT:
        return sparse.replicate(g, n_samples, method, seed)
    sure = method in ("phased", "phased_exact") and set(options) <= {"on_short", "eps", "length"} and options.get("on_short") == "fail"
    found = split_core(g) if sure else None
    if sure and found is None and method == "phased" and CORE_LIMIT < g.vertices.count() <= lazy.LIMIT:
        return sparse.replicate(g, n_samples, functools.partial(lazy.phased, **options), seed)
    order, w = found or core(g)
    spark = g.edges.sparkSession
    shared = spark.sparkContext.broadcast((np.array(order, np.int64), w, method, seed, options))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, w, method, seed, options = shared.value
        draw = kernels.METHODS[method] if isinstance(w, np.ndarray) else functools.partial(split.phased, exact=method == "phased_exact")
        for b in batches:
            for lo in range(0, b.num_rows, 500):
                out = []
                for s in b.column(0).slice(lo, 500).to_pylist():
                    out += [(s, int(ids[c]), int(ids[p])) for c, p in draw(w, np.random.default_rng([seed, s]), **options)]
                s, c, p = (np.array(x, np.int64) for x in zip(*out)) if out else (np.zeros(0, np.int64),) * 3
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in (s, c, p, np.minimum(c, p), np.maximum(c, p))], names=["sample_id", "child", "parent", "u", "v"])

    n = tasks or max(1, min(n_samples, spark.sparkContext.defaultParallelism))
    return spark.range(0, n_samples, 1, n).mapInArrow(run, TREE)


def by_doubling(g: Graph, start: int, tau: int | None = None, seed: int = 42, balance: str = "hash", max_rounds: int = 40) -> DataFrame:
    """Tree of doubled walks of length ``tau`` (default about n log n), joined end to end.  Vertices are
    numbered first: the hash family is independent over numbers below n only."""
    ids, dense = index_vertices(g)
    ids = cut(ids, "ids")
    n = ids.count()
    tau = tau or 1 << int(np.ceil(np.log2(max(2, n * np.log(n + 1)))))
    arcs = cut(dense.arcs, "arcs")
    first = ids.where(F.col("vertex") == start).first()
    if first is None:
        raise ValueError(f"{start} is no vertex")
    start = first.vid
    walk, end, offset = None, start, 0
    for k in range(max_rounds):
        part = doubling.walk_from(arcs, end, tau, seed + 1000 * k, balance)
        part = part.select("sample_id", (F.col("pos") + offset).alias("pos"), "vertex")
        walk = cut(part if walk is None else walk.union(part.where(F.col("pos") > offset)), "walk")
        facts = walk.agg(F.count_distinct("vertex").alias("n"), F.max("pos").alias("last"), F.max_by("vertex", "pos").alias("end")).first()
        if facts.n == n:
            t = trees.first_visit(walk).select("sample_id", "child", "parent")
            for c in ("child", "parent"):
                t = t.join(ids.select(F.col("vid").alias(c), F.col("vertex").alias(f"{c}_id")), c)
            return t.select("sample_id", F.col("child_id").alias("child"), F.col("parent_id").alias("parent"), F.least("child_id", "parent_id").alias("u"), F.greatest("child_id", "parent_id").alias("v"))
        end, offset = facts.end, facts.last
    raise RuntimeError("the graph was not covered; is it connected?")


@dataclass
class Phase:
    """State between phases of the sampler: what is visited, where the walk stands, the edges so far."""

    start: int
    end: int
    visited: DataFrame
    tree: DataFrame | None = None
    number: int = 0
    failed: bool = False


def _pair_facts(walk: DataFrame) -> dict:
    """Distinct pairs of neighbours, and the most of them that one vertex owns."""
    pairs = topdown.requests(walk, 1).groupBy("p").agg(F.count(F.lit(1)).alias("n"))
    r = pairs.agg(F.sum("n").alias("pairs"), F.max("n").alias("load")).first()
    return {"pairs": r.pairs or 0, "pair_load": r.load or 0}


def run_phase(state: Phase, arcs: DataFrame, vertices: DataFrame, a: DataFrame, n: int, goal: int, size: int, seed: int, bits: int, delta: float, place: str = "order", exact: bool = False) -> tuple[Phase, dict]:
    """One phase: the derived graph over what is unvisited, a walk on it to the ``goal``-th vertex, and the
    real edges that enter its new vertices.  ``exact``: further stretches of ``size`` steps until the goal."""
    spark = arcs.sparkSession
    active = cut(derived.active_set(vertices, state.visited, state.end), "active")
    k = active.count()
    shortcut, squarings, t = None, 0, a
    if k < n:
        shortcut, squarings = derived.shortcut_absorbing(a, active, bits, delta, n=n)
        shortcut = cut(shortcut, "shortcut")
        t = cut(derived.schur_transition(shortcut, derived.enter_matrix(arcs, active, bits), active, bits), "schur")
    levels, want, lost = size.bit_length() - 1, min(goal, k), 0.0
    if k == 2:  # one step is all there is; even powers would never leave the start
        walk = cut(doubling.stepwise(t.withColumnRenamed("x", "w"), spark.createDataFrame([(0, state.end)], "sample_id long, vertex long"), 1, seed + state.number), "walk")
    else:
        ladder = linalg.power_ladder(t, levels, bits, k)
        lost = linalg.lost_mass(ladder[-1], k, bits)
        walk, end, offset = None, state.end, 0
        for stretch in range(64 if exact else 1):
            starts = spark.createDataFrame([(0, end)], "sample_id long, vertex long")
            drawn = seed + state.number + 1000 * stretch
            if k <= linalg.TILE and place == "order":
                part = topdown.walks_in_task(ladder, starts, drawn, want, bits)
            else:
                part = topdown.full_walk(ladder, starts, drawn, want, bits=bits, place=place)
            part = part.select("sample_id", (F.col("pos") + offset).alias("pos"), "vertex")
            walk = part if walk is None else cut(topdown.truncate_window(walk.union(part.where(F.col("pos") > offset)), want), "walk")
            reach = walk.agg(F.count_distinct("vertex").alias("n"), F.max("pos").alias("last"), F.max_by("vertex", "pos").alias("end")).first()
            if reach.n >= want:
                break
            end, offset = reach.end, reach.last
    got = walk.agg(F.count_distinct("vertex").alias("n"), F.max("pos").alias("last"), F.max_by("vertex", "pos").alias("end"), F.count(F.lit(1)).alias("rows")).first()
    facts = {"phase": state.number, "active": k, "distinct": got.n, "length": got.last, "rows": got.rows, **_pair_facts(walk), "squarings": squarings, "levels": levels if k > 2 else 0, "lost": lost, "short": got.n < want}
    new = trees.first_visit(walk) if shortcut is None else trees.first_visit_shortcut(walk, shortcut, arcs, active, seed, state.number, bits)
    tree = cut(new if state.tree is None else state.tree.union(new), "tree")
    visited = cut(state.visited.union(walk.select("vertex")).distinct(), "visited")
    return Phase(state.start, got.end, visited, tree, state.number + 1, got.n < want), facts


def phased(g: Graph, start: int, eps: float = 0.01, seed: int = 42, rho: str = "sqrt", length: int = 0, bits: int | None = None, on_short: str = "arbitrary", delta: float | None = None, place: str = "order", exact: bool = False) -> tuple[DataFrame, list[dict]]:
    """The phased sampler with DataFrames: a tree and facts of each phase.

    Length and bits follow ``params`` for an error of ``eps`` and the largest weight, unless given.
    ``place``: see ``topdown.full_walk``.  ``exact``: cube-root phases, shuffles inside pairs, walks that
    go on until the phase's goal.  Rounding that takes more than a third of ``eps`` from a row raises
    FloatingPointError.  A phase that misses its goal sets ``short`` in its facts; then ``on_short`` decides:
    'arbitrary' gives a breadth-first tree, 'fail' raises.  Only scalars come to the driver.
    """
    arcs, vertices = cut(g.arcs, "arcs"), cut(g.vertices, "vertices")
    n, m, w = vertices.count(), *g.edges.agg(F.count(F.lit(1)), F.max("w")).first()
    if exact:
        rho, place = "cbrt", "per_pair"
    goal = params.rho(n, rho)
    size = length or params.target_length(n, m, eps, weight=w or 1)
    bits = bits or params.precision(n, size, eps)
    delta = delta if delta is not None else 2.0 ** -(2 * bits // 3)
    a = cut(linalg.transition(arcs, bits), "transition")
    state = Phase(start, start, arcs.sparkSession.createDataFrame([(start,)], "vertex long"))
    facts: list[dict] = []
    for _ in range(params.phases_bound(n) * 4 + 4):
        if state.visited.count() == n:
            if state.tree is None:
                state.tree = arcs.sparkSession.createDataFrame([], TREE)
            return state.tree, facts
        state, fact = run_phase(state, arcs, vertices, a, n, goal, size, seed, bits, delta, place, exact)
        facts.append(fact)
        if fact["lost"] > eps / 3:
            raise FloatingPointError(f"rounding at {bits} bits takes {fact['lost']:.2g} from a row, more than a third of {eps}")
        if state.failed and on_short == "arbitrary":
            return graphs.bfs_tree(g.edges, start).where("parent IS NOT NULL").select(F.lit(0).cast("long").alias("sample_id"), F.col("vertex").alias("child"), "parent", F.least("vertex", "parent").alias("u"), F.greatest("vertex", "parent").alias("v")), facts
        if state.failed:
            raise RuntimeError(f"phase {fact['phase']} saw {fact['distinct']} vertices in {size} steps")
    raise RuntimeError("phases ran out; is the graph connected?")


def random_weight_mst(edges: DataFrame, seed: int, sample_id: int = 0) -> DataFrame:
    """Minimum spanning forest under hashed weights: each component takes its lightest edge out,
    rounds of joins until none is left.  Not a uniform tree."""
    e = cut(edges.select("u", "v", rng.bits(seed, "mst", F.lit(sample_id), "u", "v").alias("x")), "mst")
    labels = cut(e.select(F.col("u").alias("vertex")).union(e.select("v")).distinct().select("vertex", F.col("vertex").alias("c")), "labels")
    chosen = e.select("u", "v").limit(0)
    for _ in range(64):
        lu, lv = labels.select(F.col("vertex").alias("u"), F.col("c").alias("cu")), labels.select(F.col("vertex").alias("v"), F.col("c").alias("cv"))
        cross = cut(e.join(lu, "u").join(lv, "v").where("cu <> cv"), "cross")
        if cross.isEmpty():
            break
        key = F.struct("x", "u", "v")
        best = cross.select(F.col("cu").alias("c"), key.alias("k")).union(cross.select("cv", key)).groupBy("c").agg(F.min("k").alias("k")).select("k.u", "k.v").distinct()
        chosen = cut(chosen.union(best).distinct(), "chosen")
        labels = cut(graphs.components(chosen, labels.select("vertex")).select("vertex", F.col("component").alias("c")), "labels")
    return chosen.select(F.lit(sample_id).cast("long").alias("sample_id"), "u", "v")


def _take_leaves(edges: DataFrame, rounds: int = 8) -> tuple[DataFrame | None, DataFrame]:
    """Edges at vertices of one neighbour, which are in every tree, as ``(u, v, child, parent)``, round by round,
    and the edges left."""
    tips, rest = None, edges
    for _ in range(rounds):
        leaf = graphs.degrees(rest).where("degree = 1").select("vertex")
        ends = [rest.join(leaf.withColumnRenamed("vertex", c), c, "left_semi").select("u", "v", F.struct(F.col(c).alias("child"), F.col(p).alias("parent")).alias("t")) for c, p in ("uv", "vu")]
        tip = cut(ends[0].union(ends[1]).groupBy("u", "v").agg(F.min("t").alias("t")).select("u", "v", "t.child", "t.parent"), "tip")
        if tip.isEmpty():
            break
        tips = tip if tips is None else tips.union(tip)
        rest = cut(rest.join(tip, ["u", "v"], "left_anti").select("u", "v", "w"), "rest")
    return tips, rest


def forest(g: Graph, seed: int = 42, method: str = "loop_erased", limit: int = CORE_LIMIT) -> DataFrame:
    """One tree for every component: components of up to ``limit`` vertices are each sampled in a grouped task.
    Of larger ones the forced edges are taken off first, in frames; what is left of each is sampled in a grouped
    task too, and above ``limit`` by loop-erased walks on rows of neighbours."""
    comp = cut(graphs.components(g.edges, g.vertices), "components")
    big = cut(comp.groupBy("component").count().where(F.col("count") > limit).select("component"), "big")
    e = g.edges.join(comp.withColumnRenamed("vertex", "u"), "u")

    def one(key, pdf):
        import pandas as pd

        order, at = np.unique(np.concatenate([pdf.u, pdf.v]), return_inverse=True)
        a, b = at[: len(pdf)], at[len(pdf) :]
        r = np.random.default_rng([seed, int(key[0]) % (1 << 32)])
        if len(order) <= limit:
            w = np.zeros((len(order), len(order)))
            w[a, b] = w[b, a] = pdf.w
            t = kernels.METHODS[method](w, r)
        else:
            t = sparse.TREES[method](sparse.Rows(len(order), a, b, pdf.w.to_numpy()), r)
        c, p = order[np.array(t, np.int64).reshape(-1, 2)].T
        return pd.DataFrame({"sample_id": 0, "child": c, "parent": p, "u": np.minimum(c, p), "v": np.maximum(c, p)})

    if big.isEmpty():
        return e.groupBy("component").applyInPandas(one, TREE)
    if method not in sparse.TREES:
        raise ValueError(f"components above {limit} vertices are sampled by {', '.join(sparse.TREES)} only")
    small = e.join(big, "component", "left_anti").groupBy("component").applyInPandas(one, TREE)
    tips, rest = _take_leaves(cut(e.join(big, "component", "left_semi").select("u", "v", "w"), "large"))
    left = rest.join(graphs.components(rest).withColumnRenamed("vertex", "u"), "u").groupBy("component").applyInPandas(one, TREE)
    out = small.union(left)
    return out if tips is None else out.union(tips.select(F.lit(0).cast("long"), "child", "parent", "u", "v"))


def sample_tree(g: Graph, method: str = "phased", eps: float = 0.01, seed: int = 42, samples: int = 1, start: int | None = None, **options) -> DataFrame:
    """Trees by any method: many samples, or a method without a DataFrame form, run on the core."""
    if samples == 1 and method in ("phased_frames", "doubling_frames", "mst_frames"):
        first = start if start is not None else g.vertices.agg(F.min("vertex")).first()[0]
        if method == "phased_frames":
            return phased(g, first, eps, seed, **options)[0]
        if method == "doubling_frames":
            return by_doubling(g, first, seed=seed, **options)
        return random_weight_mst(g.edges, seed)
    return replicate(g, samples, method, seed, **options)


__all__ = ["Phase", "by_doubling", "core", "forest", "phased", "random_weight_mst", "replicate", "run_phase", "sample_tree"]
