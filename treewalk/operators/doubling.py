"""Walks built from short ones by doubling, with and without balanced meeting places.

Stub ``(src, idx, endpoint, len)``, indices 1..k.  A prefix ``i`` of the lower half with end ``v``
meets the suffix ``k + 1 - i`` of ``v``.  Every level is kept, and a single walk is expanded from
them, so that no stub carries its path unless asked to.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..ckpt import cut
from ..functions import hashing, rng
from .draws import bounds, pick


def ranked(arcs: DataFrame) -> DataFrame:
    """Arcs with cumulative weight bounds at their start: ``(i, j, lo, hi, total)``."""
    return bounds(arcs, ["i"], "j", "w").select("i", "j", "lo", "hi", "total")


def init(arcs: DataFrame, k: int, seed: int) -> DataFrame:
    """``k`` random arcs of every vertex, by weight."""
    r = ranked(arcs)
    stubs = r.select("i").distinct().select("i", F.explode(F.sequence(F.lit(1), F.lit(k))).alias("idx"))
    hit = pick(stubs, r, ["i"], "j", rng.below("total", seed, "stub", "i", "idx"))
    return hit.select(F.col("i").alias("src"), F.col("idx").cast("long").alias("idx"), F.col("j").alias("endpoint"), F.lit(1).cast("long").alias("len"))


def meeting(stubs: DataFrame, k: int, family: hashing.PolyHash) -> DataFrame:
    """Where each stub goes in this iteration: ``(src, idx, role, place)``; ids are vertex numbers."""
    pre = stubs.where(F.col("idx") <= k // 2).select("src", "idx", F.lit("prefix").alias("role"), family.column(F.col("endpoint"), F.lit(k + 1) - F.col("idx")).alias("place"))
    suf = stubs.where(F.col("idx") > k // 2).select("src", "idx", F.lit("suffix").alias("role"), family.column(F.col("src"), F.col("idx")).alias("place"))
    return pre.union(suf)


def plain_meeting(stubs: DataFrame, k: int) -> DataFrame:
    """The unbalanced rule: prefixes go to their end vertex itself."""
    pre = stubs.where(F.col("idx") <= k // 2).select("src", "idx", F.lit("prefix").alias("role"), F.col("endpoint").alias("place"))
    return pre.union(stubs.where(F.col("idx") > k // 2).select("src", "idx", F.lit("suffix").alias("role"), F.col("src").alias("place")))


def loads(places: DataFrame) -> DataFrame:
    """``(place, n)``: stubs that each place receives."""
    return places.groupBy("place").agg(F.count(F.lit(1)).alias("n"))


def step(stubs: DataFrame, k: int, balance: str = "none", family: hashing.PolyHash | None = None, salts: int = 8, parts: int | None = None, seed: int = 0) -> DataFrame:
    """Halve the indices and double the lengths.

    ``none``: the join decides where stubs meet; ``hash``: both sides are dealt out by the hash of
    (vertex, suffix index); ``salted``: suffixes are replicated ``salts`` times and prefixes choose
    one copy, which also splits a single hot (vertex, index).  All give the same stubs.
    """
    pre = stubs.where(F.col("idx") <= k // 2).withColumn("need", F.lit(k + 1) - F.col("idx"))
    suf = stubs.where(F.col("idx") > k // 2).select(F.col("src").alias("mid"), F.col("idx").alias("need"), F.col("endpoint").alias("end2"), F.col("len").alias("len2"))
    on = (F.col("endpoint") == F.col("mid")) & (pre["need"] == suf["need"])
    if balance == "hash":
        n = parts or int(stubs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        pre = pre.withColumn("h", family.column(F.col("endpoint"), F.col("need"))).repartition(n, "h")
        suf = suf.withColumn("h", family.column(F.col("mid"), F.col("need"))).repartition(n, "h")
        on = (pre["h"] == suf["h"]) & (F.col("endpoint") == F.col("mid")) & (pre["need"] == suf["need"])
    elif balance == "salted":
        pre = pre.withColumn("salt", rng.bits(seed, "salt", "src", "idx") % salts)
        suf = suf.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
        on = on & (pre["salt"] == suf["salt"])
    # stubs are small as files and large in memory: by the size of files Spark would send them through the driver
    return pre.join(suf.hint("merge"), on).select("src", "idx", F.col("end2").alias("endpoint"), (F.col("len") + F.col("len2")).alias("len"))


def levels(arcs: DataFrame, tau: int, seed: int, balance: str = "none", c: float = 1.0) -> list[DataFrame]:
    """Stub tables of all levels; the last holds one walk of length >= ``tau`` for every vertex."""
    k = 1 << max(0, math.ceil(math.log2(max(tau, 1))))
    out = [cut(init(arcs, k, seed), "stubs")]
    n = arcs.select("i").distinct().count() if balance == "hash" else 0
    while k > 1:
        family = hashing.poly_family(hashing.independence(n, c), n, k, seed + k) if balance == "hash" else None
        out.append(cut(step(out[-1], k, balance, family, seed=seed), "stubs"))
        k //= 2
    return out


def expand(tables: list[DataFrame], source: int, sample_id: int = 0) -> DataFrame:
    """The walk of ``source`` of the last level, all positions: two joins a level, doubling rows."""
    spark, top = tables[0].sparkSession, len(tables) - 1
    rows = spark.createDataFrame([(0, source, 1)], "pos long, src long, idx long")
    for level in range(top, 0, -1):
        k = 1 << (top - level + 1)  # indices at the level below
        t = tables[level - 1].select("src", "idx", "endpoint")
        right = rows.join(t, ["src", "idx"]).select((F.col("pos") + (1 << (level - 1))).alias("pos"), F.col("endpoint").alias("src"), (F.lit(k + 1) - F.col("idx")).cast("long").alias("idx"))
        rows = cut(rows.union(right), "expand")
    ends = rows.join(tables[0], ["src", "idx"]).select((F.col("pos") + 1).alias("pos"), F.col("endpoint").alias("vertex"))
    start = spark.createDataFrame([(0, source)], "pos long, vertex long")
    return start.union(ends).select(F.lit(sample_id).cast("long").alias("sample_id"), "pos", "vertex")


def walk_from(arcs: DataFrame, source: int, tau: int, seed: int, balance: str = "none") -> DataFrame:
    return expand(levels(arcs, tau, seed, balance), source)


def walks(arcs: DataFrame, tau: int, seed: int, balance: str = "none") -> DataFrame:
    """Ends of one walk for every source: ``(src, idx, endpoint, len)``."""
    return levels(arcs, tau, seed, balance)[-1]


def stepwise(arcs: DataFrame, starts: DataFrame, steps: int, seed: int) -> DataFrame:
    """Plain walkers, one join a step, for ``starts (sample_id, vertex)``."""
    r = cut(ranked(arcs), "arcs")
    now = starts.select("sample_id", F.lit(0).cast("long").alias("pos"), "vertex")
    every = now
    for t in range(1, steps + 1):
        hit = pick(now.select("sample_id", F.col("vertex").alias("i")), r, ["i"], "j", rng.below("total", seed, "step", "sample_id", F.lit(t)))
        now = hit.select("sample_id", F.lit(t).cast("long").alias("pos"), F.col("j").alias("vertex"))
        if t % 8 == 0:
            now = cut(now, "walkers")
        every = every.union(now)
    return every


def stitch_overprovisioned(arcs: DataFrame, length: int, slack: int, seed: int) -> DataFrame:
    """Baseline without index pairing: many stubs; prefixes take unused suffixes of their end in
    turn.  Vertices with more visitors than stubs leave some prefixes short (they end early)."""
    k = max(2, length * slack)
    stubs = init(arcs, k, seed).select("src", "idx", "endpoint", "len")
    half = k
    while half > slack and half > 1:
        pre = stubs.where(F.col("idx") <= half // 2).withColumn("turn", F.row_number().over(Window.partitionBy("endpoint").orderBy("src", "idx")))
        suf = stubs.where(F.col("idx") > half // 2).withColumn("turn", F.row_number().over(Window.partitionBy("src").orderBy("idx"))).select(F.col("src").alias("mid"), "turn", F.col("endpoint").alias("end2"), F.col("len").alias("len2"))
        stubs = cut(pre.join(suf, (F.col("endpoint") == F.col("mid")) & (pre["turn"] == suf["turn"]), "left").select("src", "idx", F.coalesce("end2", "endpoint").alias("endpoint"), (F.col("len") + F.coalesce("len2", F.lit(0))).alias("len")), "stitch")
        half //= 2
    return stubs


def short_walks(arcs: DataFrame, length: int, seed: int, walks_per_vertex: int = 1) -> list[DataFrame]:
    """Stub tables of ``walks_per_vertex`` walks of ``length`` (a power of two) steps for every vertex."""
    k = length << max(0, math.ceil(math.log2(max(walks_per_vertex, 1))))
    out = [cut(init(arcs, k, seed), "stubs")]
    for _ in range(length.bit_length() - 1):
        out.append(cut(step(out[-1], k, seed=seed), "stubs"))
        k //= 2
    return out


def vertices_at(tables: list[DataFrame], asked: DataFrame) -> DataFrame:
    """The vertex of each walk after ``t`` steps, for ``asked (src, idx, t)`` with ids of the last table: one
    join a level, into the first half of a walk or past it."""
    top = len(tables) - 1
    k = tables[0].agg(F.max("idx")).first()[0] >> top if top else 0
    rows = asked.select("src", "idx", "t", F.col("src").alias("at"), F.col("idx").alias("stub"))
    for level in range(top, 0, -1):
        k *= 2  # indices at the level below
        t = tables[level - 1].select(F.col("src").alias("at"), F.col("idx").alias("stub"), "endpoint")
        past = F.col("t") >= (1 << (level - 1))
        rows = rows.join(t.hint("merge"), ["at", "stub"]).select("src", "idx", F.when(past, F.col("t") - (1 << (level - 1))).otherwise(F.col("t")).alias("t"), F.when(past, F.col("endpoint")).otherwise(F.col("at")).alias("at"), F.when(past, F.lit(k + 1) - F.col("stub")).otherwise(F.col("stub")).cast("long").alias("stub"))
        rows = cut(rows, "descend")
    ends = rows.join(tables[0].select(F.col("src").alias("at"), F.col("idx").alias("stub"), "endpoint").hint("merge"), ["at", "stub"])
    return ends.select("src", "idx", F.when(F.col("t") >= 1, F.col("endpoint")).otherwise(F.col("at")).alias("vertex"))


def pagerank(arcs: DataFrame, length: int, seed: int, walks_per_vertex: int = 1, stop: float = 0.15) -> DataFrame:
    """Share of walk ends by vertex; each walk stops after a geometric number of steps (at most
    ``length``, a power of two): the ends are distributed by the ranking with restart chance ``stop``.
    Walks are doubled, so the joins number twice the log of the length."""
    tables = short_walks(arcs, length, seed, walks_per_vertex)
    last = F.least(F.floor(F.log(F.lit(1.0) - rng.u(seed, "stop", "src", "idx")) / math.log(1 - stop)).cast("long"), F.lit(length).cast("long"))
    asked = tables[-1].where(F.col("idx") <= walks_per_vertex).select("src", "idx", last.alias("t"))
    return vertices_at(tables, asked).groupBy("vertex").agg(F.count(F.lit(1)).alias("n"))
