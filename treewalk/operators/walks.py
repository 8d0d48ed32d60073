"""Measures of walks."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graphs import Graph
from . import kernels, sparse
from .sample import CORE_LIMIT, core


def length(walk: DataFrame) -> DataFrame:
    """``(sample_id, length, n_distinct)``."""
    return walk.groupBy("sample_id").agg(F.max("pos").alias("length"), F.count_distinct("vertex").alias("n_distinct"))


def _repeat(g: Graph, reps: int, seed: int, measure) -> DataFrame:
    _, w = core(g)
    shared = g.edges.sparkSession.sparkContext.broadcast(w)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            s = b.column(0).to_pylist()
            yield pa.RecordBatch.from_arrays([pa.array(s, pa.int64()), pa.array([measure(shared.value, np.random.default_rng([seed, x])) for x in s], pa.int64())], names=["rep", "steps"])

    spark = g.edges.sparkSession
    return spark.range(0, reps, 1, spark.sparkContext.defaultParallelism).mapInArrow(run, "rep long, steps long")


def cover_time(g: Graph, reps: int, seed: int = 42) -> DataFrame:
    """Steps to see all vertices, ``reps`` times; above the bound of a dense core on rows of neighbours."""
    if g.vertices.count() > CORE_LIMIT:
        return sparse.cover_times(g, reps, seed)
    return _repeat(g, reps, seed, kernels.cover_steps)


def hitting_time(g: Graph, reps: int, start: int, goal: int, seed: int = 42) -> DataFrame:
    """Steps from one vertex (by its place in id order) to another."""
    return _repeat(g, reps, seed, lambda w, r: kernels.hitting_steps(w, r, start, goal))


def steps_to_distinct(g: Graph, reps: int, steps: int, seed: int = 42) -> DataFrame:
    """Distinct vertices (as ``steps``) of walks of a given number of steps."""

    def one(w, r):
        c, v, seen = np.cumsum(w, axis=1), 0, {0}
        for _ in range(steps):
            v = int(np.searchsorted(c[v], r.random() * c[v, -1], side="right"))
            seen.add(v)
        return len(seen)

    return _repeat(g, reps, seed, one)


def power_iteration(arcs: DataFrame, stop: float = 0.15, rounds: int = 20) -> DataFrame:
    """Ranking with restarts by repeated joins: ``(vertex, rank)``; the yardstick for short walks."""
    from ..ckpt import cut

    total = arcs.groupBy("i").agg(F.sum("w").alias("total"))
    p = cut(arcs.join(total, "i").select("i", "j", (F.col("w") / F.col("total")).alias("x")), "rank")
    n = total.count()
    now = total.select(F.col("i").alias("vertex"), F.lit(1.0 / n).alias("rank"))
    for _ in range(rounds):
        flow = now.join(p, now["vertex"] == p["i"]).groupBy(F.col("j").alias("vertex")).agg((F.sum(F.col("rank") * F.col("x")) * (1 - stop) + stop / n).alias("rank"))
        now = cut(flow, "rank")
    return now


def quantiles(times: DataFrame) -> DataFrame:
    return times.agg(F.avg("steps").alias("mean"), F.expr("percentile(steps, 0.5)").alias("median"), F.expr("percentile(steps, 0.95)").alias("p95"), F.max("steps").alias("max"))
