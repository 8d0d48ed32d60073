"""Components, breadth-first trees, bipartiteness, triangles, degrees."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..ckpt import cut


def _both(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("u").alias("i"), F.col("v").alias("j")).union(edges.select("v", "u"))


def components(edges: DataFrame, vertices: DataFrame | None = None, max_rounds: int = 60) -> DataFrame:
    """``(vertex, component)``: the least vertex reachable.

    Each round every vertex goes to its least neighbour in a scrambled order, and the links are
    relabelled; they shrink by a factor a round.
    """
    order = lambda c: F.struct(F.xxhash64(F.col(c), F.lit(7)).alias("h"), F.col(c).alias("v"))
    links = edges.select(F.col("u").alias("a"), F.col("v").alias("b")).where("a <> b")
    every = edges.select(F.col("u").alias("vertex")).union(edges.select("v"))
    every = every if vertices is None else every.union(vertices.select("vertex"))
    names = cut(every.distinct().select("vertex", F.col("vertex").alias("root")), "names")
    for _ in range(max_rounds):
        if links.isEmpty():
            break
        both = links.union(links.select("b", "a"))
        to = cut(both.groupBy("a").agg(F.min(order("b")).alias("m")).select("a", F.least("m", order("a"))["v"].alias("to")), "least")
        step = links.join(to, "a").select("b", F.col("to").alias("x")).join(to.withColumnRenamed("a", "b"), "b").select("x", F.col("to").alias("y"))
        links = cut(step.where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct(), "links")
        names = cut(names.join(to.withColumnRenamed("a", "root"), "root", "left").select("vertex", F.coalesce("to", "root").alias("root")), "names")
    else:
        raise RuntimeError("components did not settle")
    least = names.groupBy("root").agg(F.min("vertex").alias("component"))
    return names.join(least, "root").select("vertex", "component")


def bfs_tree(edges: DataFrame, root: int, max_depth: int = 1000) -> DataFrame:
    """``(vertex, depth, parent)``: parent is the least one at the depth before; the root has none."""
    arcs = _both(edges)
    seen = edges.sparkSession.createDataFrame([(root, 0, None)], "vertex long, depth int, parent long")
    front = seen
    for depth in range(1, max_depth):
        new = front.join(arcs, front["vertex"] == arcs["i"]).groupBy("j").agg(F.min("i").alias("parent")).select(F.col("j").alias("vertex"), F.lit(depth).alias("depth"), "parent")
        front = cut(new.join(seen.select("vertex"), "vertex", "left_anti"), "front")
        if front.isEmpty():
            break
        seen = cut(seen.union(front), "seen")
    return seen


def is_bipartite(edges: DataFrame) -> bool:
    """No odd cycle: the doubled graph (each vertex once for each parity) splits."""
    big = 1 << 60
    e = edges.select(F.col("u"), (F.col("v") + big).alias("v")).union(edges.select("v", F.col("u") + big))
    c = components(e)
    a, b = c.where(F.col("vertex") < big), c.where(F.col("vertex") >= big).select((F.col("vertex") - big).alias("vertex"), F.col("component").alias("other"))
    return a.join(b, "vertex").where("component = other").isEmpty()


def triangles(edges: DataFrame) -> DataFrame:
    """``(a, b, c)`` with a < b < c; edges point to the end of higher degree, which bounds the wedges."""
    d = degrees(edges)
    e = edges.join(d.select(F.col("vertex").alias("u"), F.col("degree").alias("du")), "u").join(d.select(F.col("vertex").alias("v"), F.col("degree").alias("dv")), "v")
    up = F.struct("du", "u") < F.struct("dv", "v")
    o = e.select(F.when(up, F.col("u")).otherwise(F.col("v")).alias("x"), F.when(up, F.col("v")).otherwise(F.col("u")).alias("y"))
    wedge = o.alias("p").join(o.alias("q"), F.expr("p.x = q.x AND p.y < q.y")).select(F.col("p.x").alias("x"), F.col("p.y").alias("u"), F.col("q.y").alias("v"))
    t = wedge.join(edges.select("u", "v"), ["u", "v"])
    s = F.array_sort(F.array("x", "u", "v"))
    return t.select(s[0].alias("a"), s[1].alias("b"), s[2].alias("c"))


def degrees(edges: DataFrame) -> DataFrame:
    both = edges.select(F.col("u").alias("vertex"), "w").union(edges.select("v", "w"))
    return both.groupBy("vertex").agg(F.count(F.lit(1)).alias("degree"), F.sum("w").alias("strength"))


def degree_stats(edges: DataFrame) -> DataFrame:
    """One row: vertices, edges, least, greatest and mean degree."""
    return degrees(edges).agg(F.count(F.lit(1)).alias("n"), (F.sum("degree") / 2).cast("long").alias("m"), F.min("degree").alias("min_degree"), F.max("degree").alias("max_degree"), F.round(F.avg("degree"), 6).alias("mean_degree"))


def diameter_lower(edges: DataFrame, root: int) -> int:
    """Length of a longest shortest path from the far end of a breadth-first tree."""
    far = bfs_tree(edges, root).agg(F.max_by("vertex", F.struct("depth", "vertex"))).first()[0]
    return bfs_tree(edges, far).agg(F.max("depth")).first()[0]
