"""Graph views over the given tables: canonical edges ``(u, v, w)`` with ``u < v``, one row each.

Ids of a second side of a bipartite view start at ``SIDE``; string keys get ids by hash.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import rng
from .tables import table

SIDE = 1 << 40


@dataclass
class Graph:
    """Edges of a simple graph with positive integer weights."""

    edges: DataFrame

    @property
    def arcs(self) -> DataFrame:
        """Both directions: ``(i, j, w)``."""
        e = self.edges
        return e.select(F.col("u").alias("i"), F.col("v").alias("j"), "w").union(e.select("v", "u", "w"))

    @property
    def vertices(self) -> DataFrame:
        return self.edges.select(F.col("u").alias("vertex")).union(self.edges.select("v")).distinct()


def canonical(df: DataFrame, a: str, b: str, weight: Column | None = None) -> DataFrame:
    """Distinct undirected edges without loops; ``weight`` aggregates repeated rows (default: 1)."""
    pairs = df.where(F.col(a) != F.col(b)).select(F.least(a, b).cast("long").alias("u"), F.greatest(a, b).cast("long").alias("v"), *[c for c in df.columns if c not in (a, b)])
    if weight is None:
        return pairs.select("u", "v").distinct().withColumn("w", F.lit(1).cast("long"))
    return pairs.groupBy("u", "v").agg(weight.cast("long").alias("w"))


def _bipartite(df: DataFrame, a: str, b: Column) -> DataFrame:
    return canonical(df.select(F.col(a).cast("long").alias("a"), (b.cast("long") + SIDE).alias("b")), "a", "b")


def _trade(spark, sf) -> DataFrame:
    """Customer and supplier nation of every line item; two columns of the large table are read."""
    orders = table(spark, sf, "orders", "o_orderkey", "o_custkey")
    c = table(spark, sf, "customer", "c_custkey", "c_nationkey")
    s = table(spark, sf, "supplier", "s_suppkey", "s_nationkey")
    lines = table(spark, sf, "lineitem", "l_orderkey", "l_suppkey")
    placed = orders.join(c, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_nationkey")
    return lines.join(s, F.col("l_suppkey") == F.col("s_suppkey")).join(placed, F.col("l_orderkey") == F.col("o_orderkey")).select("c_nationkey", "s_nationkey")


def nation_trade(spark, sf) -> DataFrame:
    return canonical(_trade(spark, sf), "c_nationkey", "s_nationkey")


def nation_trade_w(spark, sf) -> DataFrame:
    return canonical(_trade(spark, sf), "c_nationkey", "s_nationkey", F.count(F.lit(1)))


def supp_part(spark, sf) -> DataFrame:
    return _bipartite(table(spark, sf, "lineitem", "l_suppkey", "l_partkey"), "l_suppkey", F.col("l_partkey"))


def order_part(spark, sf) -> DataFrame:
    return _bipartite(table(spark, sf, "lineitem", "l_orderkey", "l_partkey"), "l_orderkey", F.col("l_partkey"))


def _bought(spark, sf, col: str) -> DataFrame:
    lines, orders = table(spark, sf, "lineitem", "l_orderkey", col), table(spark, sf, "orders", "o_orderkey", "o_custkey")
    return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select("o_custkey", col)


def cust_supp(spark, sf) -> DataFrame:
    return _bipartite(_bought(spark, sf, "l_suppkey"), "o_custkey", F.col("l_suppkey"))


def cust_part(spark, sf) -> DataFrame:
    return _bipartite(_bought(spark, sf, "l_partkey"), "o_custkey", F.col("l_partkey"))


def _digits(col: str) -> Column:
    return F.regexp_extract(col, "([0-9]+)", 1).cast("long")


def brand_nation(spark, sf) -> DataFrame:
    lines = table(spark, sf, "lineitem", "l_partkey", "l_suppkey").distinct()
    p, s = table(spark, sf, "part", "p_partkey", "p_brand"), table(spark, sf, "supplier", "s_suppkey", "s_nationkey")
    j = lines.join(p, F.col("l_partkey") == F.col("p_partkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey"))
    return _bipartite(j.select(_digits("p_brand").alias("b"), "s_nationkey"), "b", F.col("s_nationkey"))


def _string_side(df: DataFrame, a: str, key: str) -> DataFrame:
    return canonical(df.select(F.col(a).cast("long").alias("a"), rng.key_id(key).alias("b")), "a", "b")


def brand_type(spark, sf) -> DataFrame:
    return _string_side(table(spark, sf, "part", "p_brand", "p_type").select(_digits("p_brand").alias("b"), "p_type").distinct(), "b", "p_type")


def user_type(spark, sf) -> DataFrame:
    return _string_side(table(spark, sf, "events", "user_id", "event_type").distinct(), "user_id", "event_type")


def user_bucket(spark, sf) -> DataFrame:
    e = table(spark, sf, "events", "user_id", "props")
    return _bipartite(e, "user_id", F.get_json_object("props", "$.k").cast("long") % 12)


def consecutive(df: DataFrame, slice_by: Column, order: list[str], value: str) -> DataFrame:
    """Pairs ``(prev, value)`` of rows next to each other in a global order, without one global
    sort: rows are ordered inside slices (which must follow the order), and the first row of a
    slice takes the last value of the nearest slice before it from a summary of the slices."""
    s = df.withColumn("slice", slice_by)
    key = F.struct(*order)
    inside = s.withColumn("prev", F.lag(value).over(Window.partitionBy("slice").orderBy(*order)))
    ends = s.groupBy("slice").agg(F.max_by(value, key).alias("last"))
    # one row a slice
    carried = ends.withColumn("before", F.lag("last").over(Window.orderBy("slice"))).select("slice", "before")
    return inside.join(carried, "slice").select(F.coalesce("prev", "before").alias("prev"), value).where("prev is not null")


def user_seq(spark, sf) -> DataFrame:
    e = table(spark, sf, "events", "event_id", "ts", "user_id")
    pairs = consecutive(e, F.date_trunc("day", "ts"), ["ts", "event_id"], "user_id")
    return canonical(pairs, "prev", "user_id")


def user_seq_w(spark, sf) -> DataFrame:
    e = table(spark, sf, "events", "event_id", "ts", "user_id")
    pairs = consecutive(e, F.date_trunc("day", "ts"), ["ts", "event_id"], "user_id")
    return canonical(pairs, "prev", "user_id", F.count(F.lit(1)))


def user_cooc_hour(spark, sf) -> DataFrame:
    """Users with an event in the same hour: found user by user, as nearly all pairs may share one."""
    from ..operators import pairs

    h = table(spark, sf, "events", "ts", "user_id").where("ts IS NOT NULL AND user_id IS NOT NULL").select(F.unix_seconds(F.date_trunc("hour", "ts").cast("timestamp")).alias("k"), F.col("user_id").cast("long").alias("i")).distinct()
    left, right = h.select("i", "k", pairs.one().alias("a")), h.select("k", F.col("i").alias("j"), pairs.one().alias("b"), pairs.one().alias("extra"))
    return pairs.sums(left, right, pairs.Any, ["u", "v"], above=True).withColumn("w", F.lit(1).cast("long"))


def region_tree(spark, sf) -> DataFrame:
    """Root 0, regions from 1, nations from 100, customers and suppliers from ``SIDE`` and twice it."""
    one = F.lit(1).cast("long").alias("w")
    r = table(spark, sf, "region", "r_regionkey").select(F.lit(0).cast("long").alias("u"), (F.col("r_regionkey") + 1).cast("long").alias("v"), one)
    n = table(spark, sf, "nation", "n_nationkey", "n_regionkey").select((F.col("n_regionkey") + 1).cast("long").alias("u"), (F.col("n_nationkey") + 100).cast("long").alias("v"), one)
    c = table(spark, sf, "customer", "c_custkey", "c_nationkey").select((F.col("c_nationkey") + 100).cast("long"), (F.col("c_custkey") + SIDE).cast("long"), one)
    s = table(spark, sf, "supplier", "s_suppkey", "s_nationkey").select((F.col("s_nationkey") + 100).cast("long"), (F.col("s_suppkey") + 2 * SIDE).cast("long"), one)
    return r.union(n).union(c).union(s)


def page_link(spark, sf) -> DataFrame:
    p = table(spark, sf, "pages", "page_id", "html")
    return _string_side(p.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("k")).distinct(), "page_id", "k")


def page_host(spark, sf) -> DataFrame:
    return _string_side(table(spark, sf, "pages", "page_id", "url").select("page_id", F.regexp_extract("url", "://([^/?#]*)", 1).alias("k")), "page_id", "k")


def conv_word(spark, sf) -> DataFrame:
    c = table(spark, sf, "conversations", "conv_id", "text")
    return _string_side(c.select("conv_id", F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("k")).where("k <> ''").distinct(), "conv_id", "k")


def doc_line(spark, sf) -> DataFrame:
    d = table(spark, sf, "documents", "doc_id", "text")
    return _string_side(d.select("doc_id", F.explode(F.split("text", "\n")).alias("x")).select("doc_id", F.trim("x").alias("k")).where("length(k) > 20").distinct(), "doc_id", "k")


def emb_knn10(spark, sf, k: int = 10, limit: int = 200_000) -> DataFrame:
    """Undirected union of ``k`` nearest by cosine: all rows, in blocks, against all rows.

    The vectors are broadcast, so their number is checked first.
    """
    import numpy as np
    import pandas as pd

    rows = table(spark, sf, "embeddings", "vec_id", "embedding").where("embedding is not null")
    if (n := rows.count()) > limit:
        raise ValueError(f"{n} vectors are above the broadcast bound of {limit}")
    base = rows.orderBy("vec_id").toPandas()
    ids, x = base["vec_id"].to_numpy(), np.array(base["embedding"].tolist(), np.float64)
    x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)
    shared = spark.sparkContext.broadcast((ids, x))

    def near(batches):
        ids, x = shared.value
        for b in batches:
            for lo in range(0, len(b), 512):
                part = b.iloc[lo : lo + 512]
                q = np.array(part["embedding"].tolist(), np.float64)
                q /= np.maximum(np.linalg.norm(q, axis=1, keepdims=True), 1e-300)
                s = np.round(q @ x.T, 12)
                s[ids[None, :] == part["vec_id"].to_numpy()[:, None]] = -9
                m = min(k, len(ids) - 1)
                top = np.argsort(-s, axis=1, kind="stable")[:, :m]
                yield pd.DataFrame({"a": np.repeat(part["vec_id"].to_numpy(), m), "b": ids[top].ravel()})

    return canonical(rows.mapInPandas(near, "a long, b long"), "a", "b")


VIEWS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (nation_trade, nation_trade_w, supp_part, order_part, cust_supp, cust_part, brand_nation, brand_type, user_type, user_bucket, user_seq, user_seq_w, user_cooc_hour, region_tree, page_link, page_host, conv_word, doc_line, emb_knn10)
}

#: Inline graphs with known answers: edges and weights.
FIXTURES = {
    "star": [(1, 4, 1), (2, 4, 1), (3, 4, 1)],
    "diamond": [(0, 1, 1), (1, 2, 1), (2, 3, 1), (0, 3, 1), (0, 2, 1)],
    "diamond_w": [(0, 1, 1), (1, 2, 2), (2, 3, 3), (0, 3, 4), (0, 2, 5)],
    "k4": [(a, b, 1) for a in range(4) for b in range(a + 1, 4)],
    "five": [(0, 1, 1), (1, 2, 1), (2, 3, 1), (3, 4, 1), (0, 4, 1), (0, 2, 1), (1, 3, 1)],
}


def path(n: int) -> list[tuple[int, int, int]]:
    return [(i, i + 1, 1) for i in range(n - 1)]


def cycle(n: int) -> list[tuple[int, int, int]]:
    return [*path(n), (0, n - 1, 1)]


def lollipop(clique: int, tail: int) -> list[tuple[int, int, int]]:
    """A clique with a path hanging from its last vertex: the slowest to cover."""
    return [(a, b, 1) for a in range(clique) for b in range(a + 1, clique)] + [(clique - 1 + i, clique + i, 1) for i in range(tail)]


def biclique(a: int, b: int) -> list[tuple[int, int, int]]:
    return [(i, a + j, 1) for i in range(a) for j in range(b)]


def graph(spark: SparkSession, sf_dir: str | None, name, weighted: bool = False) -> Graph:
    """A view by name, a fixture by name, or a list of ``(u, v, w)``."""
    if isinstance(name, list) or name in FIXTURES:
        rows = name if isinstance(name, list) else FIXTURES[name]
        return Graph(spark.createDataFrame([(min(a, b), max(a, b), w) for a, b, w in rows], "u bigint, v bigint, w bigint"))
    if weighted and f"{name}_w" in VIEWS:
        name = f"{name}_w"
    return Graph(VIEWS[name](spark, sf_dir))


def index_vertices(g: Graph) -> tuple[DataFrame, Graph]:
    """Dense numbers 0..n-1 for the vertices, and the graph on them.

    Numbers are a partition's offset plus the place in it, after a range partitioning by id; the
    offsets come from one count per partition.
    """
    from ..ckpt import cut

    v = g.vertices.repartitionByRange("vertex").sortWithinPartitions("vertex").withColumn("p", F.spark_partition_id()).withColumn("m", F.monotonically_increasing_id() % (1 << 33))
    v = cut(v, "vertices")
    counts = {r.p: r.n for r in v.groupBy("p").agg(F.count(F.lit(1)).alias("n")).collect()}
    offsets, total = [], 0
    for p in sorted(counts):
        offsets.append((p, total))
        total += counts[p]
    off = v.sparkSession.createDataFrame(offsets, "p int, o long") if offsets else v.sparkSession.createDataFrame([], "p int, o long")
    ids = v.join(F.broadcast(off), "p").select("vertex", (F.col("o") + F.col("m")).alias("vid"))  # a row per partition
    e = g.edges.join(ids.withColumnRenamed("vertex", "u").withColumnRenamed("vid", "a"), "u").join(ids.withColumnRenamed("vertex", "v").withColumnRenamed("vid", "b"), "v")
    return ids, Graph(e.select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"), "w"))


def shared_ids(keys: DataFrame, key: str) -> DataFrame:
    """String keys whose hashed ids fall together (expected: none)."""
    return keys.select(key).distinct().groupBy(rng.key_id(key).alias("vid")).agg(F.count(F.lit(1)).alias("n")).where("n > 1")
