"""The relational kit around the walk methods: joins, aggregates, windows, functions, each with SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import rng
from ..functions.hashing import poly_family
from ..operators.udf import edge_label, log_permanent, poly_hash_pd, random_walk_rows
from ..sources.graphs import VIEWS
from ..sources.tables import read_edges, table, write_edges
from .methods import VIEW_SQL, _arcs_sql

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def _sql(text: str, *names: str):
    """A query given as SQL that both engines take, over temporary views of the named tables."""

    def run(spark, sf) -> DataFrame:
        for n in names:
            table(spark, sf, n).createOrReplaceTempView(n)
        return spark.sql(text)

    return run


def both(name: str, text: str, *names: str) -> None:
    QUERIES[name], ORACLES[name] = _sql(text, *names), text


T = table

# ---- sources and sinks


@query(f"SELECT fmt, u, v, w FROM ({VIEW_SQL['nation_trade_w']}), (VALUES ('csv'), ('json'), ('orc'), ('parquet'), ('text')) t(fmt)")
def edge_list_formats(spark, sf):
    """Edges written and read back in every format."""
    from ..ckpt import shared_dir
    import uuid

    e, out = VIEWS["nation_trade_w"](spark, sf), None
    for fmt in ("csv", "json", "orc", "parquet", "text"):
        path = f"{shared_dir(spark)}/edges-{uuid.uuid4().hex}-{fmt}"
        write_edges(e, path, fmt)
        part = read_edges(spark, path, fmt).select(F.lit(fmt).alias("fmt"), "u", "v", "w")
        out = part if out is None else out.union(part)
    return out


# ---- projection, filters, joins

@query("SELECT DISTINCT least(c_nationkey, s_nationkey)::BIGINT AS u, greatest(c_nationkey, s_nationkey)::BIGINT AS v FROM customer, (SELECT DISTINCT s_nationkey FROM supplier) WHERE c_nationkey <> s_nationkey")
def edge_canon(spark, sf):
    c, s = T(spark, sf, "customer", "c_nationkey").distinct(), T(spark, sf, "supplier", "s_nationkey").distinct()
    return c.join(s, F.col("c_nationkey") != F.col("s_nationkey")).select(F.least("c_nationkey", "s_nationkey").cast("long").alias("u"), F.greatest("c_nationkey", "s_nationkey").cast("long").alias("v")).distinct()


@query("SELECT o_orderkey, o_orderstatus FROM orders WHERE o_totalprice BETWEEN 1000 AND 200000 AND o_orderstatus IN ('O', 'F') AND o_orderpriority LIKE '%-%' AND regexp_matches(o_orderpriority, '^[1-3]') AND o_custkey IS NOT NULL")
def filter_kit(spark, sf):
    o = T(spark, sf, "orders")
    return o.where(F.col("o_totalprice").between(1000, 200000) & F.col("o_orderstatus").isin("O", "F") & F.col("o_orderpriority").like("%-%") & F.col("o_orderpriority").rlike("^[1-3]") & F.col("o_custkey").isNotNull()).select("o_orderkey", "o_orderstatus")


@query("SELECT DISTINCT l_suppkey AS u, l_partkey AS v FROM lineitem")
def edge_distinct(spark, sf):
    return T(spark, sf, "lineitem", "l_suppkey", "l_partkey").select(F.col("l_suppkey").alias("u"), F.col("l_partkey").alias("v")).dropDuplicates()


@query("SELECT s_suppkey, n_name FROM supplier JOIN nation ON s_nationkey = n_nationkey")
def join_broadcast(spark, sf):
    n = T(spark, sf, "nation", "n_nationkey", "n_name")  # 25 rows by definition
    return T(spark, sf, "supplier", "s_suppkey", "s_nationkey").join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name")


def _hinted(hint: str):
    def run(spark, sf):
        o, c = T(spark, sf, "orders", "o_orderkey", "o_custkey"), T(spark, sf, "customer", "c_custkey", "c_nationkey")
        return o.join(c.hint(hint), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("n"))

    return run


for _n, _h in (("join_shuffle_hash", "shuffle_hash"), ("join_sort_merge", "merge")):
    QUERIES[_n], ORACLES[_n] = _hinted(_h), "SELECT c_nationkey, count(*)::BIGINT AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1"

both("join_left_default", "SELECT c_custkey, coalesce(n, 0) AS n FROM customer LEFT JOIN (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey) o ON c_custkey = o_custkey", "customer", "orders")
both("join_full_counts", "SELECT coalesce(a.k, b.k) AS k, coalesce(a.n, 0) AS n_cust, coalesce(b.n, 0) AS n_supp FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer WHERE c_nationkey < 15 GROUP BY 1) a FULL OUTER JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier WHERE s_nationkey > 5 GROUP BY 1) b ON a.k = b.k", "customer", "supplier")


@query("SELECT p_partkey FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 45)")
def join_semi(spark, sf):
    return T(spark, sf, "part", "p_partkey").join(T(spark, sf, "lineitem", "l_partkey", "l_quantity").where("l_quantity > 45"), F.col("p_partkey") == F.col("l_partkey"), "left_semi")


@query("SELECT p_partkey FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_suppkey = 1)")
def join_anti(spark, sf):
    return T(spark, sf, "part", "p_partkey").join(T(spark, sf, "lineitem", "l_partkey", "l_suppkey").where("l_suppkey = 1"), F.col("p_partkey") == F.col("l_partkey"), "left_anti")


both("join_cross", "SELECT a.n_nationkey AS i, b.n_nationkey AS j FROM nation a CROSS JOIN nation b", "nation")
both("join_theta", "SELECT a.n_nationkey AS i, b.n_nationkey AS j FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey", "nation")
both("join_nested_loop", "SELECT r_regionkey, count(*) AS n FROM region JOIN part ON p_size BETWEEN r_regionkey * 10 AND r_regionkey * 10 + 9 GROUP BY r_regionkey", "region", "part")


@query(f"WITH {_arcs_sql('nation_trade_w')}, c AS (SELECT i, j, sum(w) OVER (PARTITION BY i ORDER BY j) AS hi, w, sum(w) OVER (PARTITION BY i) AS total FROM arcs) SELECT i, d, j FROM (SELECT *, {rng.sql_below('total', 42, 'cdf', 'i', 'd')} AS r FROM c, (SELECT range AS d FROM range(20))) WHERE hi - w <= r AND r < hi")
def join_range_cdf(spark, sf):
    """Inverse-CDF draws: an equi-join on the row, filtered by cumulative bounds."""
    from ..operators.doubling import ranked
    from ..sources.graphs import Graph

    r = ranked(Graph(VIEWS["nation_trade_w"](spark, sf)).arcs)
    draws = r.select("i").distinct().select("i", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(19).cast("long"))).alias("d"))
    return draws.join(r, "i").withColumn("r", rng.below("total", 42, "cdf", "i", "d")).where("lo <= r AND r < hi").select("i", "d", "j")


@query("SELECT p.event_id, v.event_id AS view_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'view' GROUP BY 1, 2) v ON p.user_id = v.user_id AND p.ts >= v.ts".replace("ASOF LEFT JOIN", "ASOF JOIN"))
def asof_events(spark, sf):
    """Last view at or before each purchase."""
    e = T(spark, sf, "events", "event_id", "ts", "user_id", "event_type").where(F.col("event_type").isin("view", "purchase"))
    view = F.when(F.col("event_type") == "view", F.col("event_id"))
    w = Window.partitionBy("user_id").orderBy("ts", (F.col("event_type") == "purchase").cast("int"), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("view_id", F.last(view, ignorenulls=True).over(w)).where("event_type = 'purchase' AND view_id IS NOT NULL").select("event_id", "view_id")


@query("SELECT a.user_id AS u, b.user_id AS v, count(*)::BIGINT AS n FROM events a JOIN events b ON a.user_id < b.user_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 600000000 GROUP BY 1, 2")
def interval_cooc(spark, sf):
    """Pairs of events of two users within ten minutes, counted user by user against tiles of users."""
    from ..operators import pairs

    e = T(spark, sf, "events", "ts", "user_id").where("ts IS NOT NULL AND user_id IS NOT NULL").select(F.col("user_id").cast("long").alias("i"), F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    left = e.select("i", F.col("t").alias("k"), pairs.one().alias("a"))
    right = e.select(F.expr("t div 86400000000").alias("k"), F.col("i").alias("j"), F.col("t").alias("b"), pairs.one().alias("extra"))  # one list a day
    return pairs.sums(left, right, pairs.TenMinutes, ["u", "v", "n"], above=True)


@query(f"WITH {_arcs_sql('user_type')} SELECT a.i, b.j, count(*)::BIGINT AS n FROM arcs a JOIN arcs b ON a.j = b.i GROUP BY 1, 2")
def two_hop(spark, sf):
    from ..operators import pairs
    from ..sources.graphs import Graph

    a = Graph(VIEWS["user_type"](spark, sf)).arcs
    left = a.select("i", F.col("j").alias("k"), pairs.one().alias("a"))
    return pairs.sums(left, a.select(F.col("i").alias("k"), "j", pairs.one().alias("b"), pairs.one().alias("extra")), pairs.Count, ["i", "j", "n"])


# ---- aggregates

both("degrees_hash_agg", "SELECT l_suppkey, count(*) AS n, sum(l_quantity) AS q FROM lineitem GROUP BY l_suppkey", "lineitem")


@query("SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY n_regionkey")
def string_agg_sorted(spark, sf):
    return T(spark, sf, "nation", "n_regionkey", "n_name").groupBy("n_regionkey").agg(F.concat_ws(",", F.array_sort(F.collect_list("n_name"))).alias("names"))


@query("SELECT l_suppkey, count(*)::BIGINT AS n FROM lineitem GROUP BY 1")
def salted_count(spark, sf):
    """Two stages, for keys that hold much of the table."""
    salt = F.pmod(F.xxhash64("l_orderkey", "l_partkey"), F.lit(16))
    part = T(spark, sf, "lineitem", "l_suppkey", "l_orderkey", "l_partkey").groupBy("l_suppkey", salt.alias("salt")).agg(F.count(F.lit(1)).alias("n"))
    return part.groupBy("l_suppkey").agg(F.sum("n").alias("n"))


both("distinct_prefix", "SELECT user_id, count(DISTINCT event_type) AS n FROM events GROUP BY user_id", "events")


@query("SELECT event_type, true AS near FROM events GROUP BY event_type")
def approx_distinct(spark, sf):
    """Estimated beside counted: within a tenth."""
    n, m = F.approx_count_distinct("user_id", 0.02), F.count_distinct("user_id")
    return T(spark, sf, "events", "user_id", "event_type").groupBy("event_type").agg((F.abs(n - m) <= 0.1 * m).alias("near"))


@query("SELECT sum(quality)::BIGINT AS good, count(*) FILTER (WHERE toxic = 1)::BIGINT AS toxic, count(*) FILTER (WHERE quality = 1 AND toxic = 0)::BIGINT AS clean FROM labels")
def agg_filter(spark, sf):
    return T(spark, sf, "labels").agg(F.sum("quality").alias("good"), F.sum(F.when(F.col("toxic") == 1, 1).otherwise(0)).alias("toxic"), F.count_if((F.col("quality") == 1) & (F.col("toxic") == 0)).alias("clean"))


both("rollup_mass", "SELECT coalesce(n_regionkey, -1) AS region, coalesce(n_nationkey, -1) AS nation, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, n_nationkey)", "customer", "nation")
both("cube_mass", "SELECT coalesce(c_mktsegment, 'all') AS seg, coalesce(o_orderpriority, 'all') AS pri, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY CUBE (c_mktsegment, o_orderpriority)", "customer", "orders")
both("grouping_sets", "SELECT coalesce(p_brand, 'all') AS brand, coalesce(p_type, 'all') AS kind, count(*) AS n FROM part GROUP BY GROUPING SETS ((p_brand), (p_type), ())", "part")


@query("SELECT n_regionkey, count(*) FILTER (WHERE c_mktsegment = 'BUILDING')::BIGINT AS building, count(*) FILTER (WHERE c_mktsegment = 'MACHINERY')::BIGINT AS machinery FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def pivot_matrix(spark, sf):
    c, n = T(spark, sf, "customer", "c_nationkey", "c_mktsegment"), T(spark, sf, "nation", "n_nationkey", "n_regionkey")
    p = c.join(n, F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_regionkey").pivot("c_mktsegment", ["BUILDING", "MACHINERY"]).agg(F.count(F.lit(1)))
    return p.select("n_regionkey", F.coalesce("BUILDING", F.lit(0)).alias("building"), F.coalesce("MACHINERY", F.lit(0)).alias("machinery"))


@query("SELECT s_suppkey, 'nation' AS k, s_nationkey::BIGINT AS x FROM supplier UNION ALL SELECT s_suppkey, 'half', (s_suppkey // 2)::BIGINT FROM supplier")
def unpivot_matrix(spark, sf):
    s = T(spark, sf, "supplier", "s_suppkey", "s_nationkey").select("s_suppkey", F.col("s_nationkey").cast("long").alias("nation"), F.expr("s_suppkey div 2").alias("half"))
    return s.unpivot("s_suppkey", ["nation", "half"], "k", "x")


# ---- windows

both("rank_kit", "SELECT c_custkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)", "customer")
both("lead_lag", "SELECT event_id, coalesce(lead(event_type) OVER w, '-') AS nxt, coalesce(lag(event_type, 2) OVER w, '-') AS prv FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)", "events")
both("value_windows", "SELECT o_orderkey, first_value(o_orderkey) OVER w AS f, last_value(o_orderkey) OVER w AS l, coalesce(nth_value(o_orderkey, 3) OVER w, -1) AS third FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)", "orders")


@query("WITH f AS (SELECT event_id, ts, user_id, event_type, (row_number() OVER (PARTITION BY user_id, event_type ORDER BY ts, event_id) = 1)::BIGINT AS fresh FROM events) SELECT event_id, (sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW))::BIGINT AS seen FROM f")
def running_distinct(spark, sf):
    """Distinct types a user has seen so far."""
    e = T(spark, sf, "events", "event_id", "ts", "user_id", "event_type")
    fresh = (F.row_number().over(Window.partitionBy("user_id", "event_type").orderBy("ts", "event_id")) == 1).cast("long")
    return e.withColumn("fresh", fresh).select("event_id", F.sum("fresh").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)).alias("seen"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW)::BIGINT AS n FROM events")
def range_frame_hour(spark, sf):
    e = T(spark, sf, "events", "event_id", "ts", "user_id").withColumn("t", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("t").rangeBetween(-3_600_000_000, 0)).alias("n"))


@query("SELECT event_id, (sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) > 100) AS busy FROM events")
def rows_frame(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-3, 0)
    return T(spark, sf, "events", "event_id", "user_id", "ts", "value").select("event_id", (F.sum("value").over(w) > 100).alias("busy"))


@query(f"SELECT u, v, w FROM ({VIEW_SQL['nation_trade_w']}) ORDER BY w DESC, u, v LIMIT 40 OFFSET 10")
def page_edges(spark, sf):
    return VIEWS["nation_trade_w"](spark, sf).orderBy(F.desc("w"), "u", "v").offset(10).limit(40)


@query(f"SELECT u, v, w FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY w DESC, v) AS k FROM ({VIEW_SQL['nation_trade_w']})) WHERE k <= 3")
def topk_edges(spark, sf):
    return VIEWS["nation_trade_w"](spark, sf).withColumn("k", F.row_number().over(Window.partitionBy("u").orderBy(F.desc("w"), "v"))).where("k <= 3").drop("k")


@query("SELECT u, v FROM (SELECT l_suppkey AS u, l_partkey AS v FROM lineitem WHERE l_quantity > 25)")
def sorted_edges(spark, sf):
    return T(spark, sf, "lineitem", "l_suppkey", "l_partkey", "l_quantity").where("l_quantity > 25").select(F.col("l_suppkey").alias("u"), F.col("l_partkey").alias("v")).orderBy("u", "v")


# ---- sets

both("union_copies", "SELECT c_nationkey AS k, 'c' AS side FROM customer UNION ALL SELECT s_nationkey, 's' FROM supplier", "customer", "supplier")
both("set_intersect_all", "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier", "customer", "supplier")
both("set_intersect", "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier", "customer", "supplier")
both("set_except_all", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier", "customer", "supplier")
both("set_except", "SELECT p_size AS k FROM part EXCEPT SELECT r_regionkey FROM region", "part", "region")

# ---- functions


@query(r"SELECT page_id, lower(regexp_extract(url, '://([^/?#]*)', 1)) AS host, len(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1))::INT AS n_links, lpad(page_id::VARCHAR, 8, '0') AS padded, md5(url) AS m, sha256(url) AS s, length(html)::INT AS n, trim(string_split(url, '/')[3]) AS part, translate(left(url, 20), 'aeiou', 'AEIOU') AS t, levenshtein(left(url, 12), left(html, 12))::INT AS d FROM pages")
def string_kit(spark, sf):
    p = T(spark, sf, "pages")
    return p.select("page_id", F.lower(F.regexp_extract("url", "://([^/?#]*)", 1)).alias("host"), F.size(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("n_links"), F.lpad(F.col("page_id").cast("string"), 8, "0").alias("padded"), F.md5("url").alias("m"), F.sha2("url", 256).alias("s"), F.length("html").alias("n"), F.trim(F.split("url", "/")[2]).alias("part"), F.translate(F.substring("url", 1, 20), "aeiou", "AEIOU").alias("t"), F.levenshtein(F.substring("url", 1, 12), F.substring("html", 1, 12)).alias("d"))


@query("SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS mon, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS d, strftime(o_orderdate::DATE + 30, '%Y-%m-%d') AS later, epoch(o_orderdate)::BIGINT AS e FROM orders")
def date_kit(spark, sf):
    o = F.col("o_orderdate")
    return T(spark, sf, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", F.year(o).alias("y"), F.month(o).alias("m"), F.date_format(F.date_trunc("month", o), "yyyy-MM-dd").alias("mon"), F.datediff(o, F.lit("1992-01-01").cast("date")).alias("d"), F.date_format(F.date_add(o, 30), "yyyy-MM-dd").alias("later"), F.unix_timestamp(o).alias("e"))


@query("SELECT p_partkey, round(ln(p_size + 1.0), 6) AS lg, round(exp(p_size / 50.0), 6) AS ex, round(power(p_size, 1.5), 6) AS pw, round(sqrt(p_retailprice), 6) AS sq, floor(p_retailprice)::BIGINT AS fl, ceil(p_retailprice)::BIGINT AS ce, abs(25 - p_size)::INT AS ab, (p_partkey % 7)::BIGINT AS md, (p_partkey // 3)::BIGINT AS dv, (p_partkey >> 2)::BIGINT AS sh, greatest(p_size, 10)::INT AS gr FROM part")
def math_kit(spark, sf):
    s, k, r = F.col("p_size"), F.col("p_partkey"), F.col("p_retailprice")
    return T(spark, sf, "part", "p_partkey", "p_size", "p_retailprice").select("p_partkey", F.round(F.log(s + 1.0), 6).alias("lg"), F.round(F.exp(s / 50.0), 6).alias("ex"), F.round(F.pow(s, F.lit(1.5)), 6).alias("pw"), F.round(F.sqrt(r), 6).alias("sq"), F.floor(r).alias("fl"), F.ceil(r).alias("ce"), F.abs(25 - s).alias("ab"), F.pmod(k, F.lit(7)).alias("md"), F.expr("p_partkey div 3").alias("dv"), F.shiftright(k, 2).alias("sh"), F.greatest(s, F.lit(10)).alias("gr"))


@query("SELECT l_suppkey, CAST(sum(CAST(round(l_extendedprice * 100) AS DECIMAL(38, 0)) * 1000000007) AS VARCHAR) AS mass FROM lineitem GROUP BY 1")
def decimal_mass(spark, sf):
    x = F.round(F.col("l_extendedprice") * 100).cast("decimal(18,0)") * F.lit(1000000007).cast("decimal(10,0)")
    return T(spark, sf, "lineitem", "l_suppkey", "l_extendedprice").groupBy("l_suppkey").agg(F.sum(x.cast("decimal(38,0)")).cast("string").alias("mass"))


@query("SELECT o_custkey, len(a)::INT AS n, a[1] AS first, list_sum(list_transform(a, lambda x: x % 10))::BIGINT AS s, len(list_filter(a, lambda x: x % 2 = 0))::INT AS even, array_to_string(a[2:3], ',') AS cut, coalesce(list_position(a, a[len(a)]), 0)::BIGINT AS at FROM (SELECT o_custkey, list(o_orderkey ORDER BY o_orderkey) AS a FROM orders GROUP BY 1)")
def array_kit(spark, sf):
    a = F.col("a")
    g = T(spark, sf, "orders", "o_custkey", "o_orderkey").groupBy("o_custkey").agg(F.array_sort(F.collect_list("o_orderkey")).alias("a"))
    return g.select("o_custkey", F.size(a).alias("n"), F.element_at(a, 1).alias("first"), F.aggregate(F.transform(a, lambda x: x % 10), F.lit(0).cast("long"), lambda s, x: s + x).alias("s"), F.size(F.filter(a, lambda x: x % 2 == 0)).alias("even"), F.array_join(F.slice(a, 2, 2), ",").alias("cut"), F.array_position(a, F.element_at(a, -1)).alias("at"))


@query("SELECT a.vec_id AS u, b.vec_id AS v, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 4) AS c FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def array_cosine(spark, sf):
    """Cosine of vectors with ids next to each other."""
    e = T(spark, sf, "embeddings", "vec_id", "embedding").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    dot = lambda p, q: F.aggregate(F.zip_with(p, q, lambda s, t: s * t), F.lit(0.0), lambda s, t: s + t)
    j = e.select(F.col("vec_id").alias("u"), "x").join(e.select((F.col("vec_id") - 1).alias("u"), F.col("vec_id").alias("v"), F.col("x").alias("y")), "u")
    return j.select("u", "v", F.round(dot("x", "y") / F.sqrt(dot("x", "x") * dot("y", "y")), 4).alias("c"))


@query("SELECT user_id, string_agg(event_type || ':' || n, ',' ORDER BY event_type) AS counts, sum(2 * n)::BIGINT AS twice FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) GROUP BY 1")
def map_multiset(spark, sf):
    n = T(spark, sf, "events", "user_id", "event_type").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = n.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    doubled = F.map_zip_with("m", "m", lambda k, a, b: a + b)
    text = F.array_join(F.transform(F.array_sort(F.map_keys("m")), lambda k: F.concat(k, F.lit(":"), F.element_at("m", k).cast("string"))), ",")
    return m.select("user_id", text.alias("counts"), F.aggregate(F.map_values(doubled), F.lit(0).cast("long"), lambda s, x: s + x).alias("twice"))


@query("SELECT user_id, arg_min(event_type, event_id) AS first_type, arg_max(event_type, event_id) AS last_type FROM events GROUP BY 1")
def first_by(spark, sf):
    return T(spark, sf, "events", "user_id", "event_type", "event_id").groupBy("user_id").agg(F.min_by("event_type", "event_id").alias("first_type"), F.max_by("event_type", "event_id").alias("last_type"))


@query("SELECT event_id, json_extract_string(props, '$.k')::INT AS k, '{\"id\":' || event_id || '}' AS j FROM events")
def json_props(spark, sf):
    return T(spark, sf, "events", "event_id", "props").select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.to_json(F.struct(F.col("event_id").alias("id"))).alias("j"))


@query("SELECT l_returnflag, round(avg(l_quantity), 6) AS mean, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS c, round(quantile_cont(l_quantity, 0.9), 6) AS p90, round(median(l_quantity), 6) AS med FROM lineitem GROUP BY 1")
def stat_kit(spark, sf):
    q = T(spark, sf, "lineitem", "l_returnflag", "l_quantity", "l_extendedprice").groupBy("l_returnflag")
    return q.agg(F.round(F.avg("l_quantity"), 6).alias("mean"), F.round(F.stddev("l_quantity"), 6).alias("sd"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("c"), F.round(F.expr("percentile(l_quantity, 0.9)"), 6).alias("p90"), F.round(F.median("l_quantity"), 6).alias("med"))


@query("SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages")
def explode_hrefs(spark, sf):
    return T(spark, sf, "pages", "page_id", "html").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("href"))


both("subquery_kit", "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders) AND EXISTS (SELECT 1 FROM lineitem l WHERE l.l_orderkey = o.o_orderkey AND l_quantity > 40) AND o_custkey IN (SELECT c_custkey FROM customer WHERE c_nationkey < 10)", "orders", "lineitem", "customer")
both("recursive_reach", "WITH RECURSIVE r(k, depth) AS (SELECT 0, 0 UNION ALL SELECT n.n_nationkey, r.depth + 1 FROM r JOIN nation n ON n.n_nationkey = r.k + 5) SELECT k, depth FROM r", "nation")


@query(f"SELECT l_orderkey, l_partkey FROM lineitem WHERE {rng.sql_bits(42, 'sample', 'l_orderkey', 'l_partkey')} < {rng.SCALE // 10}")
def hash_sample(spark, sf):
    return T(spark, sf, "lineitem", "l_orderkey", "l_partkey").where(rng.bits(42, "sample", "l_orderkey", "l_partkey") < rng.SCALE // 10)


@query(f"SELECT doc_id, quality FROM (SELECT l.doc_id, quality, row_number() OVER (PARTITION BY quality ORDER BY {rng.sql_bits(42, 'strat', 'l.doc_id')}, l.doc_id) AS k FROM labels l JOIN documents d ON l.doc_id = d.doc_id) WHERE k <= 20")
def stratified(spark, sf):
    j = T(spark, sf, "labels", "doc_id", "quality").join(T(spark, sf, "documents", "doc_id"), "doc_id")
    return j.withColumn("k", F.row_number().over(Window.partitionBy("quality").orderBy(rng.bits(42, "strat", "doc_id"), "doc_id"))).where("k <= 20").select("doc_id", "quality")


# ---- time windows on batches (the same expressions as the streams)

@query("SELECT epoch(time_bucket(INTERVAL 1 HOUR, ts))::BIGINT AS start, event_type, count(*)::BIGINT AS n FROM events GROUP BY 1, 2")
def tumbling_batch(spark, sf):
    from ..streaming import windows

    return windows.tumbling(T(spark, sf, "events", "ts", "event_type"), "1 hour")


@query("SELECT s::BIGINT AS start, event_type, count(*)::BIGINT AS n FROM (SELECT event_type, unnest(list_transform(range(4), lambda k: epoch(time_bucket(INTERVAL 15 MINUTE, ts))::BIGINT - 900 * k)) AS s FROM events) GROUP BY 1, 2")
def sliding_batch(spark, sf):
    from ..streaming import windows

    return windows.sliding(T(spark, sf, "events", "ts", "event_type"), "1 hour", "15 minutes")


@query("WITH g AS (SELECT user_id, ts, event_id, CASE WHEN lag(ts) OVER w IS NULL OR epoch_us(ts) - epoch_us(lag(ts) OVER w) >= 1800000000 THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM g) SELECT user_id, count(*)::BIGINT AS n FROM s GROUP BY user_id, k")
def sessions_batch(spark, sf):
    from ..streaming import windows

    return windows.sessions(T(spark, sf, "events", "ts", "user_id"), "30 minutes").select("user_id", "n")


# ---- user functions

@query("SELECT n_nationkey, n_name || '#' || n_regionkey AS label FROM nation")
def udf_edge_label(spark, sf):
    return T(spark, sf, "nation").select("n_nationkey", edge_label("n_name", "n_regionkey").alias("label"))


_FAM = poly_family(8, 101, 16, 42)
_WIDE = poly_family(6, 1 << 31, 64, 42)  # a domain above the small prime


@query(f"SELECT v, j, {_FAM.sql('v', 'j')} AS h, {_FAM.sql('v', 'j')} AS h_pd, {_WIDE.sql('v', 'j')} AS wide FROM (SELECT range % 500 AS v, range % 16 + 1 AS j FROM range(2000))")
def udf_poly_hash(spark, sf):
    """The hash family as expression and as vectorised function, and with the larger prime."""
    fam = _FAM
    d = spark.range(2000).select((F.col("id") % 500).alias("v"), (F.col("id") % 16 + 1).alias("j"))
    return d.select("v", "j", fam.column(F.col("v"), F.col("j")).alias("h"), poly_hash_pd(fam)("v", "j").alias("h_pd"), _WIDE.column(F.col("v"), F.col("j")).alias("wide"))


@query("WITH m AS (SELECT g, i, j, ((g + i * j) % 5 + 1)::DOUBLE AS w FROM range(4) a(g), range(5) b(i), range(5) c(j)) SELECT a.g, round(ln(sum(a.w * b.w * c.w * d.w * e.w)), 9) AS log_permanent FROM m a JOIN m b ON b.g = a.g AND b.i = 1 JOIN m c ON c.g = a.g AND c.i = 2 JOIN m d ON d.g = a.g AND d.i = 3 JOIN m e ON e.g = a.g AND e.i = 4 WHERE a.i = 0 AND len(list_distinct([a.j, b.j, c.j, d.j, e.j])) = 5 GROUP BY a.g")
def udaf_log_permanent(spark, sf):
    d = spark.createDataFrame([(g, i, j, float((g + i * j) % 5 + 1)) for g in range(4) for i in range(5) for j in range(5)], "g long, i long, j long, w double")
    return d.groupBy("g").agg(F.round(log_permanent("i", "j", "w"), 9).alias("log_permanent"))


@query(f"WITH e AS ({VIEW_SQL['nation_trade']}) SELECT 201::BIGINT AS n_rows, 200::BIGINT AS steps_on_edges, count(*)::BIGINT AS edges FROM e")
def udtf_random_walk(spark, sf):
    """A walk by table function on the trade graph: positions 0..length, on edges only."""
    spark.udtf.register("random_walk", random_walk_rows)
    e = VIEWS["nation_trade"](spark, sf)
    text = e.agg(F.concat_ws(",", F.sort_array(F.collect_list(F.concat_ws("-", "u", "v")))).alias("t"), F.count(F.lit(1)).alias("n")).first()  # 25 nations
    r = spark.sql(f"SELECT * FROM random_walk('{text.t}', 0, 200, 42)").select("pos", "vertex")
    hop = r.join(r.select((F.col("pos") + 1).alias("pos"), F.col("vertex").alias("before")), "pos").select(F.least("vertex", "before").alias("u"), F.greatest("vertex", "before").alias("v"))
    good = hop.join(F.broadcast(e), ["u", "v"]).agg(F.count(F.lit(1)).alias("steps_on_edges"))  # at most 300 edges
    return r.agg(F.count(F.lit(1)).alias("n_rows")).crossJoin(good).select("n_rows", "steps_on_edges", F.lit(text.n).cast("long").alias("edges"))


@query(f"WITH e AS ({VIEW_SQL['nation_trade']}) SELECT (count(DISTINCT x) - 1)::BIGINT AS n_edges FROM (SELECT u AS x FROM e UNION ALL SELECT v FROM e)")
def udtf_sample_tree(spark, sf):
    """A spanning tree of a table argument, edges of the graph only."""
    from .. import sqlapi
    from ..sources.graphs import graph

    sqlapi.register(spark)
    graph(spark, sf, "nation_trade").edges.createOrReplaceTempView("trade_edges")
    return spark.sql("SELECT count(DISTINCT e.u, e.v) AS n_edges FROM sample_tree(TABLE(trade_edges) WITH SINGLE PARTITION, 42, 'loop_erased') t JOIN trade_edges e ON e.u = least(t.child, t.parent) AND e.v = greatest(t.child, t.parent)")
