"""Random walks built from the ends inwards.

The far end comes from a row of a high power; then, level by level, the middle between
each two neighbours is drawn with weight ``half[p, v] * half[v, q]``.  The law of a middle is
computed once for each distinct pair, whatever its count.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..ckpt import cut
from ..functions import rng
from . import linalg, matching, params
from .draws import bounds, pick


def sample_end(power: DataFrame, starts: DataFrame, length: int, seed: int) -> DataFrame:
    """Walk rows at 0 and ``length`` for ``starts (sample_id, vertex)``."""
    rows = power.join(starts.select(F.col("vertex").alias("i")).distinct(), "i", "left_semi")
    drawn = pick(starts.select("sample_id", F.col("vertex").alias("i")), bounds(rows, ["i"], "j", "x"), ["i"], "j", rng.below("total", seed, "end", "sample_id"))
    ends = drawn.select("sample_id", F.lit(length).cast("long").alias("pos"), F.col("j").alias("vertex"))
    return starts.select("sample_id", F.lit(0).cast("long").alias("pos"), "vertex").union(ends)


def _neighbours(walk: DataFrame, spacing: int) -> DataFrame:
    """Rows ``spacing`` apart, by an equal join on the place: one walk's rows spread over all tasks."""
    after = walk.select("sample_id", (F.col("pos") - spacing).alias("pos"), F.col("vertex").alias("q"))
    return walk.select("sample_id", "pos", F.col("vertex").alias("p")).join(after, ["sample_id", "pos"])


def gaps(walk: DataFrame, spacing: int) -> DataFrame:
    """Neighbouring rows ``(sample_id, pos, p, q, occ)`` of a walk filled every ``spacing`` steps; ``occ``
    counts a pair's places in order."""
    w = Window.partitionBy("sample_id", "p", "q").orderBy("pos")
    return _neighbours(walk, spacing).withColumn("occ", F.row_number().over(w).cast("long"))


def requests(walk: DataFrame, spacing: int) -> DataFrame:
    """Distinct pairs with their counts: ``(sample_id, p, q, c)``."""
    return _neighbours(walk, spacing).groupBy("sample_id", "p", "q").agg(F.count(F.lit(1)).alias("c"))


def midpoint_law(pairs: DataFrame, half: DataFrame, bits: int = linalg.BITS) -> DataFrame:
    """For each distinct pair the middle's weights with cumulative bounds:
    ``(p, q, vertex, weight, lo, hi, total)``."""
    d = pairs.select("p", "q").distinct()
    left = half.select(F.col("i").alias("p"), F.col("j").alias("vertex"), F.col("x").alias("a"))
    right = half.select(F.col("i").alias("vertex"), F.col("j").alias("q"), F.col("x").alias("b"))
    law = d.join(left, "p").join(right, ["vertex", "q"]).withColumn("weight", linalg.product("a", "b", bits))
    if bits > 31:  # keep 62 bits of the product
        law = law.withColumn("weight", linalg.shifted("weight", 2 * bits - 62, True))
    return bounds(law.select("p", "q", "vertex", "weight").where("weight > 0"), ["p", "q"], "vertex", "weight").select("p", "q", "vertex", "weight", "lo", "hi", "total")


def generate_midpoints(pairs: DataFrame, half: DataFrame, seed: int, level: int, bits: int = linalg.BITS) -> DataFrame:
    """``c`` draws for each pair of ``pairs (sample_id, p, q, c)``, in order of ``occ``."""
    law = midpoint_law(pairs, half, bits)
    draws = pairs.select("sample_id", "p", "q", F.explode(F.sequence(F.lit(1).cast("long"), F.col("c"))).alias("occ"))
    r = rng.below("total", seed, f"mid{level}", "sample_id", "p", "q", "occ")
    return pick(draws, law, ["p", "q"], "vertex", r).select("sample_id", "p", "q", "occ", "vertex")


def midpoint_counts(pairs: DataFrame, half: DataFrame, seed: int, level: int) -> DataFrame:
    """Only how often each vertex was drawn for each pair: ``(sample_id, p, q, vertex, c)``."""
    return generate_midpoints(pairs, half, seed, level).groupBy("sample_id", "p", "q", "vertex").agg(F.count(F.lit(1)).alias("c"))


def place_in_order(walk: DataFrame, mids: DataFrame, step: int) -> DataFrame:
    """Put the draws of each pair into its places, in order; ``step``: new spacing."""
    new = gaps(walk, 2 * step).join(mids, ["sample_id", "p", "q", "occ"]).select("sample_id", (F.col("pos") + step).alias("pos"), "vertex")
    return walk.select("sample_id", "pos", "vertex").union(new)


def fill_level(walk: DataFrame, half: DataFrame, step: int, seed: int, level: int, bits: int = linalg.BITS, place: str = "order") -> DataFrame:
    """One level: middles at distance ``step`` after every row; ``half`` is the matrix to that power.

    ``place``: 'per_pair' draws for each pair and shuffles the draws over its places; any other puts them
    there as drawn, and then a place is itself a draw: the same values without request and return.
    """
    if place == "per_pair":
        mids = generate_midpoints(requests(walk, 2 * step), half, seed, level, bits)
        return place_in_order(walk, matching.per_pair(mids, seed, level), step)
    places = gaps(walk, 2 * step)
    r = rng.below("total", seed, f"mid{level}", "sample_id", "p", "q", "occ")
    new = pick(places, midpoint_law(places, half, bits), ["p", "q"], "vertex", r)
    return walk.select("sample_id", "pos", "vertex").union(new.select("sample_id", (F.col("pos") + step).alias("pos"), "vertex"))


def match_level(before: DataFrame, filled: DataFrame, half: DataFrame, step: int, seed: int, method: str, bits: int = linalg.BITS) -> DataFrame:
    """Draw anew which middle stands where: a weighted perfect matching of the level's middles and places.

    ``before``: the walk of the level above; ``filled``: the walk with middles, cut already.  The last
    middle keeps its place.  Only the multiset of middles and the places of each sample meet in a task.
    """
    new = filled.where(F.col("pos") % (2 * step) == step)
    last = new.groupBy("sample_id").agg(F.max("pos").alias("last"))
    free = cut(new.join(last, "sample_id").where("pos < last").select("sample_id", "pos", "vertex"), "middles")
    ends = _neighbours(before, 2 * step).select("sample_id", (F.col("pos") + step).alias("pos"), "p", "q")
    places = free.select("sample_id", "pos").join(ends, ["sample_id", "pos"]).select("sample_id", F.col("pos").alias("pos_id"), "p", "q", F.xxhash64("p", "q").alias("place_class"))
    items = free.select("sample_id", F.col("pos").alias("mid_id"), "vertex")
    a = half.select(F.col("i").alias("p"), F.col("j").alias("vertex"), F.col("x").alias("a"))
    b = half.select(F.col("i").alias("vertex"), F.col("j").alias("q"), F.col("x").alias("b"))
    share = lambda c: F.coalesce(c, F.lit(0)) / F.lit(2.0**bits)
    bip = places.join(items, "sample_id").join(a, ["p", "vertex"], "left").join(b, ["vertex", "q"], "left").select("sample_id", "pos_id", "mid_id", "place_class", "vertex", (share("a") * share("b")).alias("weight"))
    drawn = matching.place(bip, method, seed).join(items, ["sample_id", "mid_id"]).select("sample_id", F.col("pos_id").alias("pos"), "vertex")
    return filled.join(free.select("sample_id", "pos"), ["sample_id", "pos"], "left_anti").select("sample_id", "pos", "vertex").union(drawn)


def truncate_window(walk: DataFrame, rho: int) -> DataFrame:
    """Cut each walk where its ``rho``-th distinct vertex first appears.

    Only first visits are ranked: at most one row per vertex, however long the walk is.
    """
    cuts = cut_position(walk, rho)
    return walk.join(cuts, "sample_id", "left").where("cut IS NULL OR pos <= cut").select("sample_id", "pos", "vertex")


def cut_position(walk: DataFrame, rho: int) -> DataFrame:
    """``(sample_id, cut)`` of the walks that reach ``rho`` distinct vertices."""
    first = walk.groupBy("sample_id", "vertex").agg(F.min("pos").alias("pos"))
    rank = F.row_number().over(Window.partitionBy("sample_id").orderBy("pos"))
    return first.withColumn("k", rank).where(F.col("k") == rho).select("sample_id", F.col("pos").alias("cut"))


def full_walk(ladder: list[DataFrame], starts: DataFrame, seed: int, rho: int | None = None, truncate: str = "level", bits: int = linalg.BITS, place: str = "order") -> DataFrame:
    """A walk of ``2**(len(ladder)-1)`` steps for each start.

    ``truncate``: 'level' cuts at the ``rho``-th distinct vertex after every level (so the rows
    never grow past it), 'end' cuts once at the end (the same law), and without ``rho`` the walk
    is filled in full.  ``place``: 'order', 'per_pair', or a method of ``matching.place``, which draws
    the middles' places anew after each cut.
    """
    top = len(ladder) - 1
    walk = cut(sample_end(ladder[top], starts, 1 << top, seed), "walk")
    for level in range(top, 0, -1):
        before, step = walk, 1 << (level - 1)
        walk = fill_level(before, ladder[level - 1], step, seed, level, bits, place)
        if rho and truncate == "level":
            walk = truncate_window(walk, rho)
        walk = cut(walk, "walk")
        if place not in ("order", "per_pair"):
            walk = cut(match_level(before, walk, ladder[level - 1], step, seed * 64 + level, place, bits), "walk")
    return cut(truncate_window(walk, rho), "walk") if rho and truncate == "end" else walk


def walks_in_task(ladder: list[DataFrame], starts: DataFrame, seed: int, rho: int, bits: int = linalg.BITS) -> DataFrame:
    """``full_walk`` cut after every level, for a core whose vertices were counted to be at most
    ``linalg.TILE``: the powers are broadcast and each start's walk is filled in its task.  Draws are the
    same, so the walks are."""
    top = len(ladder) - 1
    t = linalg.stacked(ladder).toArrow()  # at most TILE squared entries a level
    level, i, j, x = (t.column(c).to_numpy() for c in ("t", "i", "j", "x"))
    ids = np.unique(np.concatenate([i, j]))
    if len(ids) > linalg.TILE:
        raise ValueError(f"{len(ids)} vertices are above the bound of {linalg.TILE}")
    powers = np.zeros((top + 1, len(ids), len(ids)), np.int64)
    powers[level, np.searchsorted(ids, i), np.searchsorted(ids, j)] = x
    shared = starts.sparkSession.sparkContext.broadcast((ids, powers))

    def fill(sample: int, start: int) -> list[tuple[int, int]]:
        ids, powers = shared.value

        def draw(hi: np.ndarray, *keys) -> int:
            total = int(hi[-1])
            r = min(int(rng.py_bits(seed, *keys) / float(rng.SCALE) * float(total)), total - 1)
            return int(np.searchsorted(hi, r, side="right"))

        first = int(np.searchsorted(ids, start))
        walk = [(0, first), (1 << top, draw(np.cumsum(powers[top][first]), "end", sample))]
        for k in range(top, 0, -1):
            half, laws, occ, new, seen = powers[k - 1], {}, {}, [walk[0]], {first}
            for (pos, p), (_, q) in zip(walk, walk[1:]):
                pair = (p, q)
                if pair not in laws:
                    w = half[p] * half[:, q] if bits <= 31 else ((half[p].astype(object) * half[:, q]) >> (2 * bits - 62)).astype(np.int64)
                    laws[pair] = np.cumsum(w)
                occ[pair] = occ.get(pair, 0) + 1
                middle = draw(laws[pair], f"mid{k}", sample, int(ids[p]), int(ids[q]), occ[pair])
                for step in ((pos + (1 << (k - 1)), middle), (pos + (1 << k), q)):
                    if len(seen) < rho:
                        new.append(step)
                        seen.add(step[1])
            walk = new
        return [(pos, int(ids[v])) for pos, v in walk]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for sample, start in zip(*(c.to_pylist() for c in b.columns)):
                pos, vertex = zip(*fill(sample, start))
                yield pa.RecordBatch.from_arrays([pa.array([sample] * len(pos), pa.int64()), pa.array(pos, pa.int64()), pa.array(vertex, pa.int64())], names=["sample_id", "pos", "vertex"])

    return cut(starts.select("sample_id", "vertex").mapInArrow(run, "sample_id long, pos long, vertex long"), "walk")


def truncated_walk(arcs: DataFrame, start: int, rho: int | None = None, length: int = 0, seed: int = 42, bits: int | None = None, eps: float = 0.01, place: str = "order", samples: int = 1) -> DataFrame:
    """Phase one: ``samples`` walks from ``start`` to the first time ``rho`` vertices are seen, or ``length``.

    What is not given follows the rules of ``params`` for an error of ``eps``.
    """
    arcs = cut(arcs.select("i", "j", "w"), "arcs")
    facts = arcs.agg(F.count_distinct("i").alias("n"), (F.count(F.lit(1)) / 2).cast("long").alias("m"), F.max("w").alias("w")).first()
    rho = rho or params.rho(facts.n)
    length = length or params.target_length(facts.n, facts.m, eps, weight=facts.w)
    bits = bits or params.precision(facts.n, length, eps)
    ladder = linalg.power_ladder(linalg.transition(arcs, bits), max(0, length.bit_length() - 1), bits, facts.n)
    starts = arcs.sparkSession.range(samples).select(F.col("id").alias("sample_id"), F.lit(start).cast("long").alias("vertex"))
    return full_walk(ladder, starts, seed, rho, bits=bits, place=place)


def recursive_reference(p: np.ndarray, start: int, length: int, r: np.random.Generator) -> list[int]:
    """A walk of ``length`` (a power of two) steps by plain recursion on dense powers of ``p``: the end, then
    the middle of each half.  For tests on small graphs."""
    powers = {1: p}
    while max(powers) < length:
        powers[2 * max(powers)] = powers[max(powers)] @ powers[max(powers)]
    draw = lambda w: int(r.choice(len(w), p=w / w.sum()))

    def inner(a: int, b: int, size: int) -> list[int]:
        if size == 1:
            return [b]
        half = powers[size // 2]
        middle = draw(half[a] * half[:, b])
        return inner(a, middle, size // 2) + inner(middle, b, size // 2)

    return [start, *inner(start, draw(powers[length][start]), length)]
