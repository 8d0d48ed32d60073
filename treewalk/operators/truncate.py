"""Where to cut a partly filled walk: probes of a prefix and binary search over filled places."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def probe(walk: DataFrame, upto: int, rho: int) -> bool:
    """Whether the cut lies at ``upto`` or later.

    True if the prefix has under ``rho`` distinct vertices, or exactly ``rho`` with its last vertex
    seen once.  A middle counts only if its own place is in the prefix.
    """
    r = probe_facts(walk, upto).first()
    return r is None or r.n_distinct < rho or (r.n_distinct == rho and r.n_last == 1)


def probe_facts(walk: DataFrame, upto: int) -> DataFrame:
    """``(sample_id, n_distinct, n_last)`` of the prefix, as aggregates."""
    p = walk.where(F.col("pos") <= upto)
    last = p.groupBy("sample_id").agg(F.max_by("vertex", "pos").alias("last"), F.count_distinct("vertex").alias("n_distinct"))
    return p.join(last, "sample_id").groupBy("sample_id", "n_distinct").agg(F.sum((F.col("vertex") == F.col("last")).cast("long")).alias("n_last"))


def vertex_at(walk: DataFrame, pos: int) -> DataFrame:
    return walk.where(F.col("pos") == pos).select("sample_id", "vertex")


def search(walk: DataFrame, rho: int) -> tuple[int, int]:
    """Cut place of a single walk and the number of probes, by binary search over its filled
    places; one aggregate row comes to the driver for each probe."""
    bounds = walk.agg(F.min("pos"), F.max("pos")).first()
    lo, hi, probes = bounds[0], bounds[1], 0
    while lo < hi:  # greatest filled place whose probe is true
        middle = walk.where((F.col("pos") > lo) & (F.col("pos") <= hi)).agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY pos)")).first()[0]
        probes += 1
        if probe(walk, middle, rho):
            lo = middle
        else:
            hi = walk.where(F.col("pos") < middle).agg(F.max("pos")).first()[0]
    return lo, probes
