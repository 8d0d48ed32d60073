"""Trees from walks: the edge by which each vertex is first entered."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import rng
from . import linalg
from .draws import bounds, pick


def _tree(sample, child, parent):
    return [sample, child.alias("child"), parent.alias("parent"), F.least(child, parent).alias("u"), F.greatest(child, parent).alias("v")]


def first_entries(walk: DataFrame) -> DataFrame:
    """``(sample_id, vertex, pos, prev)``: first place of every vertex and the vertex before it, by an
    equal join on the place: a walk without gaps is never gathered or sorted."""
    first = walk.groupBy("sample_id", "vertex").agg(F.min("pos").alias("pos"))
    before = walk.select("sample_id", (F.col("pos") + 1).alias("pos"), F.col("vertex").alias("prev"))
    return first.join(before, ["sample_id", "pos"], "left").select("sample_id", "vertex", "pos", "prev")


def first_visit(walk: DataFrame) -> DataFrame:
    """``(sample_id, child, parent, u, v)`` for every vertex but the start."""
    return first_entries(walk).where("prev IS NOT NULL").select(*_tree("sample_id", F.col("vertex"), F.col("prev")))


def first_visit_shortcut(walk: DataFrame, shortcut: DataFrame, arcs: DataFrame, active: DataFrame, seed: int, phase: int = 0, bits: int = linalg.BITS) -> DataFrame:
    """Real entry edges of a walk on the derived graph over ``active (vertex)``.

    Vertex ``v``, first seen after ``prev``, is entered from neighbour ``u`` with weight
    ``shortcut[prev, u] * w(u, v) / (weight from u into the active set)``.
    """
    into = arcs.join(active.withColumnRenamed("vertex", "j"), "j", "left_semi")
    mass = into.groupBy("i").agg(F.sum("w").alias("mass"))
    near = into.join(mass, "i").select(F.col("i").alias("u"), F.col("j").alias("vertex"), "w", "mass")
    q = shortcut.select(F.col("i").alias("prev"), F.col("j").alias("u"), F.col("x").alias("q"))
    new = first_entries(walk).where("prev IS NOT NULL").select("sample_id", "vertex", "prev")
    weight = F.expr("(q * w) div mass") if bits <= 31 else F.expr("(cast(q as decimal(19,0)) * cast(w as decimal(19,0))) div cast(mass as decimal(38,0))")
    pairs = new.select("vertex", "prev").distinct()
    cand = pairs.join(near, "vertex").join(q, ["prev", "u"]).withColumn("weight", weight).where("weight > 0")
    law = bounds(cand, ["vertex", "prev"], "u", "weight")
    drawn = pick(new, law, ["vertex", "prev"], "u", rng.below("total", seed, f"enter{phase}", "sample_id", "vertex"))
    return drawn.select(*_tree("sample_id", F.col("vertex"), F.col("u")))


def tree_key(tree: DataFrame) -> DataFrame:
    """One text per tree, the same for equal trees: ``(sample_id, tree)``."""
    edge = F.concat_ws("-", F.col("u").cast("string"), F.col("v").cast("string"))
    return tree.groupBy("sample_id").agg(F.array_join(F.array_sort(F.collect_list(edge)), ",").alias("tree"))
