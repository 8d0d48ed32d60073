"""User functions where built-in ones don't reach: vectorised, grouped and table functions."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.hashing import PolyHash
from . import kernels, matching


@F.udf(returnType=T.StringType(), useArrow=True)
def edge_label(name: str, key: int) -> str:
    return f"{name}#{key}"


def poly_hash_pd(family: PolyHash):
    @F.pandas_udf(T.LongType())
    def h(v: pd.Series, j: pd.Series) -> pd.Series:
        return family.pandas(v, j)

    return h


@F.pandas_udf(T.DoubleType())
def log_permanent(i: pd.Series, j: pd.Series, w: pd.Series) -> float:
    """Log of the permanent of a small square matrix given by its entries."""
    m = pd.DataFrame({"i": i, "j": j, "w": w}).pivot_table(index="i", columns="j", values="w", fill_value=0.0).to_numpy()
    p = matching.permanent(m)
    return math.log(p) if p > 0 else -math.inf


def _pairs(a: str, b: str) -> T.StructType:
    return T.StructType([T.StructField(a, T.LongType()), T.StructField(b, T.LongType())])


class _Walk:
    def eval(self, edges: str, start: int, length: int, seed: int):
        near: dict[int, list[int]] = {}
        for e in edges.split(","):
            a, b = map(int, e.split("-"))
            near.setdefault(a, []).append(b)
            near.setdefault(b, []).append(a)
        r, v = np.random.default_rng(seed), start
        yield 0, v
        for pos in range(1, length + 1):
            v = near[v][int(r.integers(len(near[v])))]
            yield pos, v


#: ``random_walk(edges, start, length, seed)``: edges as text ``a-b,c-d``.
random_walk_rows = F.udtf(_Walk, returnType=_pairs("pos", "vertex"))


class _Tree:
    """``sample_tree(TABLE(edges), seed, method)`` over rows with u, v and maybe w."""

    def __init__(self):
        self.rows, self.seed, self.method = [], 0, "loop_erased"

    def eval(self, row, seed: int, method: str):
        self.rows.append((row["u"], row["v"], row["w"]))
        self.seed, self.method = seed, method

    def terminate(self):
        order = sorted({a for a, _, _ in self.rows} | {b for _, b, _ in self.rows})
        at = {v: i for i, v in enumerate(order)}
        w = np.zeros((len(order), len(order)))
        for a, b, x in self.rows:
            w[at[a], at[b]] = w[at[b], at[a]] = x
        for c, p in kernels.METHODS[self.method](w, np.random.default_rng(self.seed)) if order else ():
            yield order[c], order[p]


sample_tree_rows = F.udtf(_Tree, returnType=_pairs("child", "parent"))
