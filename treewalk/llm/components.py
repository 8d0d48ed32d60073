"""Connected components without collecting links anywhere."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut


def forest(n: int, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A star forest (child, root) with the components of the links ``a``-``b`` on 0..n-1."""
    label = np.arange(n)
    if not len(a):
        return label[:0], label[:0]
    while True:
        low = np.minimum(label[a], label[b])
        before = label.copy()
        np.minimum.at(label, label[a], low)
        np.minimum.at(label, label[b], low)
        label = label[label]
        label = label[label]
        if np.array_equal(before, label):
            break
    child = np.flatnonzero(label != np.arange(n))
    return child, label[child]


def classes(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``(node, root)`` for every end of the links ``(a, b)``; roots name components.

    Each round sends every node to the neighbour (or itself) that is least in a scrambled
    order, and relabels the links by it: connected nodes stay connected, the largest node of
    every neighbourhood goes, and loops and repeats drop out, so the links shrink by a factor
    a round.  A very common node costs no large group: the least neighbour is an aggregate
    with partial sums, and relabelling is a plain join that can be split.
    """
    order = lambda c: F.struct(F.xxhash64(F.col(c), F.lit(7)).alias("h"), F.col(c).alias("v"))
    links = links.select("a", "b").where("a <> b")
    names = cut(links.select(F.col("a").alias("node")).union(links.select("b")).distinct().select("node", F.col("node").alias("root")), "names")
    for _ in range(max_rounds):
        if links.isEmpty():
            return names
        both = links.union(links.select("b", "a"))
        to = cut(both.groupBy("a").agg(F.min(order("b")).alias("m")).select("a", F.least("m", order("a"))["v"].alias("to")), "least")
        step = links.join(to, "a").select("b", F.col("to").alias("x")).join(to.withColumnRenamed("a", "b"), "b").select("x", F.col("to").alias("y"))
        links = cut(step.where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct(), "links")
        names = cut(names.join(to.withColumnRenamed("a", "root"), "root", "left").select("node", F.coalesce("to", "root").alias("root")), "names")
    raise RuntimeError("components did not settle")
