"""Reductions that keep the law of the tree."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..ckpt import cut
from .graph import components, degrees


def merge_parallel(edges: DataFrame) -> DataFrame:
    """Parallel edges become one with the sum of their weights."""
    return edges.groupBy("u", "v").agg(F.sum("w").alias("w"))


def pendant(edges: DataFrame, max_rounds: int = 1000) -> tuple[DataFrame, DataFrame]:
    """Edges at vertices of degree one are in every tree: ``(forced, rest)``."""
    forced, rest = edges.limit(0), edges
    for _ in range(max_rounds):
        leaf = degrees(rest).where("degree = 1").select("vertex")
        tip = rest.join(leaf.withColumnRenamed("vertex", "u"), "u", "left_semi").select("u", "v", "w").union(rest.join(leaf.withColumnRenamed("vertex", "v"), "v", "left_semi").select("u", "v", "w")).distinct()
        tip = cut(tip, "tip")
        if tip.isEmpty():
            break
        forced = cut(forced.union(tip), "forced")
        rest = cut(rest.join(tip, ["u", "v"], "left_anti").select("u", "v", "w"), "rest")
    return forced, rest


def blocks(edges: DataFrame, limit: int = 200_000) -> DataFrame:
    """Edges with their block (two-connected part): trees of blocks are independent, and a block of
    one edge is a bridge.  Worked out per component in a grouped task of bounded size."""
    comp = components(edges)
    e = edges.join(comp.withColumnRenamed("vertex", "u"), "u")
    big = e.groupBy("component").count().where(F.col("count") > limit)
    if not big.isEmpty():
        raise ValueError(f"a component has over {limit} edges; take off pendant trees first")

    def one(pdf):
        near: dict[int, list[tuple[int, int]]] = {}
        for k, (a, b) in enumerate(zip(pdf.u, pdf.v)):
            near.setdefault(a, []).append((b, k))
            near.setdefault(b, []).append((a, k))
        order, low, block, stack, n_blocks = {}, {}, {}, [], 0
        for root in near:
            if root in order:
                continue
            order[root] = low[root] = len(order)
            path = [(root, -1, iter(near[root]))]
            while path:
                v, via, it = path[-1]
                for x, k in it:
                    if k == via:
                        continue
                    if x not in order:
                        order[x] = low[x] = len(order)
                        stack.append(k)
                        path.append((x, k, iter(near[x])))
                        break
                    if order[x] < order[v]:
                        stack.append(k)
                        low[v] = min(low[v], order[x])
                else:
                    path.pop()
                    if path:
                        up = path[-1][0]
                        low[up] = min(low[up], low[v])
                        if low[v] >= order[up]:
                            while True:
                                k = stack.pop()
                                block[k] = n_blocks
                                if k == via:
                                    break
                            n_blocks += 1
        pdf = pdf.copy()
        pdf["block"] = [block[k] for k in range(len(pdf))]
        return pdf[["component", "block", "u", "v", "w"]]

    return e.groupBy("component").applyInPandas(one, "component long, block long, u long, v long, w long")
