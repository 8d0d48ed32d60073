"""Queries of the walk and tree methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..ckpt import cut
from ..functions import hashing, rng
from ..operators import accuracy, apps, derived, doubling, graph, ledger, linalg, matching, params, reduce, sample, topdown, trees, truncate, walks
from ..sources import graphs
from ..sources.graphs import SIDE, VIEWS, Graph

SEED, BITS, ONE = 42, 30, 1 << 30
QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        key = name or f.__name__
        QUERIES[key] = f
        if sql:
            ORACLES[key] = sql
        return f

    return add


# ---- graph views -------------------------------------------------------------------------------

_TRADE = """FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
 JOIN supplier ON l_suppkey = s_suppkey WHERE c_nationkey <> s_nationkey"""
_PAIR = "least({a}, {b})::BIGINT AS u, greatest({a}, {b})::BIGINT AS v"


def _bip(a: str, b: str, source: str) -> str:
    return f"SELECT DISTINCT ({a})::BIGINT AS u, ({b})::BIGINT + {SIDE} AS v, 1::BIGINT AS w FROM {source}"


def _strings(a: str, key: str, source: str) -> str:
    return f"SELECT DISTINCT ({a})::BIGINT AS u, {rng.sql_key_id(key)} AS v, 1::BIGINT AS w FROM {source}"


_BOUGHT = "lineitem JOIN orders ON l_orderkey = o_orderkey"
_SEQ = "(SELECT lag(user_id) OVER (ORDER BY ts, event_id) AS a, user_id AS b FROM events)"
VIEW_SQL = {
    "nation_trade": f"SELECT DISTINCT {_PAIR.format(a='c_nationkey', b='s_nationkey')}, 1::BIGINT AS w {_TRADE}",
    "nation_trade_w": f"SELECT {_PAIR.format(a='c_nationkey', b='s_nationkey')}, count(*)::BIGINT AS w {_TRADE} GROUP BY 1, 2",
    "supp_part": _bip("l_suppkey", "l_partkey", "lineitem"),
    "order_part": _bip("l_orderkey", "l_partkey", "lineitem"),
    "cust_supp": _bip("o_custkey", "l_suppkey", _BOUGHT),
    "cust_part": _bip("o_custkey", "l_partkey", _BOUGHT),
    "brand_nation": _bip("regexp_extract(p_brand, '([0-9]+)', 1)::BIGINT", "s_nationkey", "lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey"),
    "brand_type": _strings("regexp_extract(p_brand, '([0-9]+)', 1)", "p_type", "part"),
    "user_type": _strings("user_id", "event_type", "events"),
    "user_bucket": _bip("user_id", "json_extract_string(props, '$.k')::BIGINT % 12", "events"),
    "user_seq": f"SELECT DISTINCT {_PAIR.format(a='a', b='b')}, 1::BIGINT AS w FROM {_SEQ} WHERE a <> b",
    "user_seq_w": f"SELECT {_PAIR.format(a='a', b='b')}, count(*)::BIGINT AS w FROM {_SEQ} WHERE a <> b GROUP BY 1, 2",
    "user_cooc_hour": "SELECT DISTINCT a.user_id::BIGINT AS u, b.user_id::BIGINT AS v, 1::BIGINT AS w FROM (SELECT DISTINCT date_trunc('hour', ts) AS h, user_id FROM events) a JOIN (SELECT DISTINCT date_trunc('hour', ts) AS h, user_id FROM events) b ON a.h = b.h AND a.user_id < b.user_id",
    "region_tree": f"SELECT 0::BIGINT AS u, (r_regionkey + 1)::BIGINT AS v, 1::BIGINT AS w FROM region UNION ALL SELECT (n_regionkey + 1)::BIGINT, (n_nationkey + 100)::BIGINT, 1 FROM nation UNION ALL SELECT (c_nationkey + 100)::BIGINT, c_custkey + {SIDE}, 1 FROM customer UNION ALL SELECT (s_nationkey + 100)::BIGINT, s_suppkey + {2 * SIDE}, 1 FROM supplier",
    "page_link": _strings("page_id", "k", "(SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS k FROM pages)"),
    "page_host": _strings("page_id", "k", "(SELECT page_id, regexp_extract(url, '://([^/?#]*)', 1) AS k FROM pages)"),
    "conv_word": _strings("conv_id", "k", "(SELECT conv_id, unnest(regexp_split_to_array(lower(text), '[^a-z]+')) AS k FROM conversations) WHERE k <> ''"),
    "doc_line": _strings("doc_id", "k", "(SELECT doc_id, trim(unnest(string_split(text, chr(10)))) AS k FROM documents) WHERE length(k) > 20"),
}
VIEW_SQL["emb_knn10"] = "WITH x AS (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings WHERE embedding IS NOT NULL), s AS (SELECT a.vec_id AS a, b.vec_id AS b, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(a.e, b.e), 12) DESC, b.vec_id) AS k FROM x a JOIN x b ON a.vec_id <> b.vec_id) SELECT DISTINCT least(a, b)::BIGINT AS u, greatest(a, b)::BIGINT AS v, 1::BIGINT AS w FROM s WHERE k <= 10"
for _name, _view in VIEWS.items():
    query(VIEW_SQL.get(_name), f"edges_{_name}")(_view)


def _g(spark, sf, name) -> Graph:
    return graphs.graph(spark, sf, name)


def _arcs_sql(view: str) -> str:
    return f"e AS ({VIEW_SQL[view]}), arcs AS (SELECT u AS i, v AS j, w FROM e UNION ALL SELECT v, u, w FROM e)"


def _transition_sql(view: str, bits: int = BITS, name: str = "m0") -> str:
    return f"{_arcs_sql(view)}, {name} AS (SELECT i, j, ((w * {1 << bits}) // (sum(w) OVER (PARTITION BY i))::BIGINT)::BIGINT AS x FROM arcs)"


def _square_sql(src: str, dst: str, bits: int = BITS) -> str:
    return f"{dst} AS (SELECT a.i, b.j, (sum(a.x::HUGEINT * b.x) // {1 << bits})::BIGINT AS x FROM {src} a JOIN {src} b ON a.j = b.i GROUP BY a.i, b.j HAVING sum(a.x::HUGEINT * b.x) // {1 << bits} > 0)"


# ---- matrices ----------------------------------------------------------------------------------

@query(f"WITH {_transition_sql('nation_trade_w')} SELECT * FROM m0")
def transition_fixed(spark, sf):
    return linalg.transition(_g(spark, sf, "nation_trade_w").arcs, BITS)


@query(f"WITH {_transition_sql('nation_trade_w')}, {_square_sql('m0', 'm1')} SELECT * FROM m1")
def matrix_square_fixed(spark, sf):
    a = cut(linalg.transition(_g(spark, sf, "nation_trade_w").arcs, BITS), "a")
    return linalg.matmul_floor(a, a, BITS)


@query(f"WITH {_transition_sql('nation_trade_w')}, {_square_sql('m0', 'm1')}, {_square_sql('m1', 'm2')}, {_square_sql('m2', 'm3')} SELECT 0 AS t, * FROM m0 UNION ALL SELECT 1, * FROM m1 UNION ALL SELECT 2, * FROM m2 UNION ALL SELECT 3, * FROM m3")
def power_ladder_8(spark, sf):
    return linalg.stacked(linalg.power_ladder(linalg.transition(_g(spark, sf, "nation_trade_w").arcs, BITS), 3, BITS))


@query(f"WITH {_transition_sql('nation_trade', 24)}, {_square_sql('m0', 'm1', 24)} SELECT * FROM m1")
def matrix_square_tiles(spark, sf):
    g = _g(spark, sf, "nation_trade")
    return linalg.matmul_tiles(linalg.transition(g.arcs, 24), linalg.transition(g.arcs, 24), 25, 24, 10)


@query(f"WITH {_transition_sql('nation_trade_w', 30, 'f')}, {_square_sql('f', 'f1', 30)}, c AS (SELECT i, j, ((w * 4096) // (sum(w) OVER (PARTITION BY i))::BIGINT)::BIGINT AS x FROM arcs), {_square_sql('c', 'c1', 12)} SELECT max(f1.x - coalesce(c1.x, 0) * {1 << 18})::BIGINT AS max_entry, min(f1.x - coalesce(c1.x, 0) * {1 << 18})::BIGINT AS min_entry, count(*)::BIGINT AS n FROM f1 LEFT JOIN c1 USING (i, j)")
def subtractive_error(spark, sf):
    arcs = cut(_g(spark, sf, "nation_trade_w").arcs, "arcs")
    fine, coarse = cut(linalg.transition(arcs, 30), "f"), cut(linalg.transition(arcs, 12), "c")
    c = linalg.matmul_floor(coarse, coarse, 12).withColumnRenamed("x", "y")
    d = F.col("x") - F.coalesce("y", F.lit(0)) * (1 << 18)
    return linalg.matmul_floor(fine, fine, 30).join(c, ["i", "j"], "left").agg(F.max(d).alias("max_entry"), F.min(d).alias("min_entry"), F.count(F.lit(1)).alias("n"))


@query(f"WITH {_transition_sql('nation_trade_w')} SELECT * FROM m0 WHERE i % 3 = 0 AND j % 3 = 0")
def submatrix_used(spark, sf):
    g = _g(spark, sf, "nation_trade_w")
    return linalg.submatrix(linalg.transition(g.arcs, BITS), g.vertices.where("vertex % 3 = 0"))


@query(f"WITH {_arcs_sql('nation_trade_w')} SELECT i, j, -w AS x FROM arcs UNION ALL SELECT i, i, sum(w)::BIGINT FROM arcs GROUP BY i")
def laplacian_entries(spark, sf):
    return linalg.laplacian(_g(spark, sf, "nation_trade_w").edges)


# ---- walks from the ends inwards ---------------------------------------------------------------

def _end_sql(m: str, length: int, samples: int, start: int = 0) -> str:
    below = rng.sql_below("total", SEED, "end", "s")
    return f"""starts AS (SELECT range AS s FROM range({samples})),
 law AS (SELECT i, j, x, sum(x) OVER (PARTITION BY i ORDER BY j) AS hi, sum(x) OVER (PARTITION BY i) AS total FROM {m}),
 ends AS (SELECT s, {length}::BIGINT AS pos, j AS vertex FROM (SELECT *, {below} AS r FROM starts, law WHERE i = {start}) WHERE hi - x <= r AND r < hi),
 w{length} AS (SELECT s, 0::BIGINT AS pos, {start}::BIGINT AS vertex FROM starts UNION ALL SELECT * FROM ends)"""


def _fill_sql(level: int, half: str) -> str:
    """From walk w(2*step) to w(step)."""
    step = 1 << (level - 1)
    w, out = f"w{2 * step}", f"w{step}"
    below = rng.sql_below("total", SEED, f"mid{level}", "s", "p", "q", "occ")
    return f"""g{level} AS (SELECT *, row_number() OVER (PARTITION BY s, p, q ORDER BY pos) AS occ FROM (SELECT s, pos, vertex AS p, lead(vertex) OVER (PARTITION BY s ORDER BY pos) AS q FROM {w}) WHERE q IS NOT NULL),
 l{level} AS (SELECT p, q, vertex, weight, sum(weight) OVER (PARTITION BY p, q ORDER BY vertex) AS hi, sum(weight) OVER (PARTITION BY p, q) AS total FROM (SELECT d.p, d.q, a.j AS vertex, a.x * b.x AS weight FROM (SELECT DISTINCT p, q FROM g{level}) d JOIN {half} a ON a.i = d.p JOIN {half} b ON b.i = a.j AND b.j = d.q)),
 d{level} AS (SELECT s, pos, p, q, occ, vertex FROM (SELECT *, {below} AS r FROM g{level} JOIN l{level} USING (p, q)) WHERE hi - weight <= r AND r < hi),
 {out} AS (SELECT s, pos, vertex FROM {w} UNION ALL SELECT s, pos + {step}, vertex FROM d{level})"""


def _walk_sql(view: str, samples: int, levels: int = 3) -> str:
    squares = ", ".join(_square_sql(f"m{k}", f"m{k + 1}") for k in range(levels))
    fills = ", ".join(_fill_sql(level, f"m{level - 1}") for level in range(levels, 0, -1))
    return f"{_transition_sql(view)}, {squares}, {_end_sql(f'm{levels}', 1 << levels, samples)}, {fills}"


def _walks(spark, sf, view: str, samples: int, levels: int = 3, until: int = 0):
    """Ladder and the walk filled down to level ``until``."""
    g = Graph(cut(VIEWS[view](spark, sf), "edges"))
    ladder = linalg.power_ladder(linalg.transition(g.arcs, BITS), levels, BITS)
    starts = spark.range(samples).select(F.col("id").alias("sample_id"), F.lit(0).cast("long").alias("vertex"))
    walk = cut(topdown.sample_end(ladder[levels], starts, 1 << levels, SEED), "walk")
    for level in range(levels, until, -1):
        walk = cut(topdown.fill_level(walk, ladder[level - 1], 1 << (level - 1), SEED, level), "walk")
    return ladder, walk


_V = "nation_trade_w"


@query(f"WITH {_walk_sql(_V, 200)} SELECT s AS sample_id, pos, vertex FROM w8")
def sample_end(spark, sf):
    return _walks(spark, sf, _V, 200, 3, 3)[1]


@query(f"WITH {_walk_sql(_V, 200)} SELECT s AS sample_id, p, q, count(*)::BIGINT AS c FROM g1 GROUP BY ALL")
def pair_counts(spark, sf):
    return topdown.requests(_walks(spark, sf, _V, 200, 3, 1)[1], 2)


@query(f"WITH {_walk_sql(_V, 20)} SELECT p, q, vertex, weight::BIGINT AS weight, (hi - weight)::BIGINT AS lo, hi::BIGINT AS hi, total::BIGINT AS total FROM l2")
def midpoint_law(spark, sf):
    ladder, walk = _walks(spark, sf, _V, 20, 3, 2)
    return topdown.midpoint_law(topdown.requests(walk, 4), ladder[1])


@query(f"WITH {_walk_sql(_V, 200)} SELECT s AS sample_id, pos, vertex FROM w4")
def fill_level_order(spark, sf):
    return _walks(spark, sf, _V, 200, 3, 2)[1]


@query(f"WITH {_walk_sql(_V, 200)} SELECT s AS sample_id, pos, vertex FROM w1")
def walk_8_steps(spark, sf):
    return _walks(spark, sf, _V, 200)[1]


@query(f"WITH {_walk_sql(_V, 100, 6)} SELECT s AS sample_id, pos, vertex FROM w1")
def walk_64_steps(spark, sf):
    return _walks(spark, sf, _V, 100, 6)[1]


_CUT = "f AS (SELECT s, vertex, min(pos) AS pos FROM w1 GROUP BY ALL), k AS (SELECT s, pos AS cut FROM (SELECT *, row_number() OVER (PARTITION BY s ORDER BY pos) AS n FROM f) WHERE n = 5)"


@query(f"WITH {_walk_sql(_V, 200)}, {_CUT} SELECT s AS sample_id, pos, vertex FROM w1 LEFT JOIN k USING (s) WHERE cut IS NULL OR pos <= cut")
def truncate_window(spark, sf):
    return topdown.truncate_window(_walks(spark, sf, _V, 200)[1], 5)


@query(f"WITH {_walk_sql(_V, 200)}, p AS (SELECT * FROM w2 WHERE pos <= 5), l AS (SELECT s, arg_max(vertex, pos) AS last, count(DISTINCT vertex) AS n_distinct FROM p GROUP BY s) SELECT s AS sample_id, n_distinct, sum((vertex = last)::BIGINT)::BIGINT AS n_last FROM p JOIN l USING (s) GROUP BY s, n_distinct")
def truncate_probe(spark, sf):
    return truncate.probe_facts(_walks(spark, sf, _V, 200, 3, 1)[1], 5)


@query(f"WITH {_walk_sql(_V, 1, 6)}, {_CUT} SELECT cut::BIGINT AS by_window, cut::BIGINT AS by_search FROM k")
def truncate_search(spark, sf):
    walk = _walks(spark, sf, _V, 1, 6)[1]
    found, _ = truncate.search(walk, 5)
    return topdown.cut_position(walk, 5).select(F.col("cut").alias("by_window"), F.lit(found).cast("long").alias("by_search"))


@query(f"WITH {_walk_sql(_V, 200)} SELECT s AS sample_id, vertex, count(*)::BIGINT AS c FROM d1 GROUP BY ALL")
def multiset_counts(spark, sf):
    ladder, walk = _walks(spark, sf, _V, 200, 3, 1)
    return matching.multiset(topdown.generate_midpoints(topdown.requests(walk, 2), ladder[0], SEED, 1))


@query(f"WITH {_walk_sql(_V, 200)} SELECT s AS sample_id, p, q, vertex, count(*)::BIGINT AS c FROM d1 GROUP BY ALL")
def midpoint_counts(spark, sf):
    ladder, walk = _walks(spark, sf, _V, 200, 3, 1)
    return topdown.midpoint_counts(topdown.requests(walk, 2), ladder[0], SEED, 1)


def _placed_mids(spark, sf, samples):
    ladder, walk = _walks(spark, sf, _V, samples, 3, 1)
    mids = topdown.generate_midpoints(topdown.requests(walk, 2), ladder[0], SEED, 1)
    return ladder, walk, mids


@query(f"WITH {_walk_sql(_V, 200)}, f AS (SELECT s, max(pos) AS pos FROM d1 GROUP BY s) SELECT d1.s AS sample_id, vertex, count(*)::BIGINT AS c FROM d1 JOIN f ON d1.s = f.s AND d1.pos < f.pos GROUP BY ALL")
def split_final(spark, sf):
    _, walk, mids = _placed_mids(spark, sf, 200)
    placed = topdown.gaps(walk, 2).join(mids, ["sample_id", "p", "q", "occ"]).select("sample_id", "pos", "vertex")
    return matching.split_final(placed)[1]


@query(f"WITH {_walk_sql(_V, 200)} SELECT s AS sample_id, p, q, row_number() OVER (PARTITION BY s, p, q ORDER BY {rng.sql_bits(SEED, 'shuffle1', 's', 'p', 'q', 'occ')}, occ) AS occ, vertex FROM d1")
def place_per_pair(spark, sf):
    return matching.per_pair(_placed_mids(spark, sf, 200)[2], SEED, 1)


def _bip_frame(spark, sf, samples: int) -> DataFrame:
    ladder, walk, mids = _placed_mids(spark, sf, samples)
    slots = topdown.gaps(walk, 2).join(mids, ["sample_id", "p", "q", "occ"])
    places = slots.select("sample_id", F.col("pos").alias("pos_id"), "p", "q", (F.col("p") * 1000 + F.col("q")).alias("place_class"))
    items = slots.select("sample_id", F.col("pos").alias("mid_id"), "vertex")
    a = ladder[0].select(F.col("i").alias("p"), F.col("j").alias("vertex"), F.col("x").alias("a"))
    b = ladder[0].select(F.col("i").alias("vertex"), F.col("j").alias("q"), F.col("x").alias("b"))
    full = places.join(items, "sample_id").join(a, ["p", "vertex"], "left").join(b, ["vertex", "q"], "left")
    weight = (F.coalesce("a", F.lit(0)) / ONE) * (F.coalesce("b", F.lit(0)) / ONE)
    return full.select("sample_id", "pos_id", "mid_id", "place_class", "vertex", weight.alias("weight"))


_ALL_PLACED = f"WITH {_walk_sql(_V, 40)} SELECT s AS sample_id, vertex, count(*)::BIGINT AS c FROM d1 GROUP BY ALL"


def _placement(method: str):
    def run(spark, sf):
        bip = cut(_bip_frame(spark, sf, 40), "bip")
        match = matching.place(bip, method, SEED)
        vertex = bip.select("sample_id", "mid_id", "vertex").distinct()
        return match.join(vertex, ["sample_id", "mid_id"]).groupBy("sample_id", "vertex").agg(F.count_distinct("pos_id").alias("c"))

    return run


for _m in ("exact", "approx_count", "swap", "classes"):  # every placement keeps the multiset
    query(_ALL_PLACED, f"place_{_m}")(_placement(_m))


# ---- derived graphs ----------------------------------------------------------------------------

_B20 = 1 << 20


def _schur_sql(view: str) -> str:
    return f"WITH e AS ({VIEW_SQL[view]}), d AS (SELECT v, sum(w)::BIGINT AS d FROM e GROUP BY v) SELECT a.u, b.u AS v, sum((a.w * b.w * {_B20}) // d.d)::BIGINT AS x FROM e a JOIN e b ON a.v = b.v AND a.u < b.u JOIN d ON d.v = a.v GROUP BY 1, 2"


@query(_schur_sql("user_type"))
def schur_bipartite(spark, sf):
    return derived.schur_bipartite(_g(spark, sf, "user_type").edges)


@query(_schur_sql("brand_nation"))
def schur_bipartite_brand(spark, sf):
    return derived.eliminate_independent(_g(spark, sf, "brand_nation").edges)


@query(f"WITH e AS ({VIEW_SQL['nation_trade_w']}), n AS (SELECT CASE WHEN u = 7 THEN v ELSE u END AS a, w FROM e WHERE 7 IN (u, v)), d AS (SELECT sum(w)::BIGINT AS d FROM n) SELECT u, v, sum(x)::BIGINT AS x FROM (SELECT u, v, w * {_B20} AS x FROM e WHERE u <> 7 AND v <> 7 UNION ALL SELECT p.a, q.a, (p.w * q.w * {_B20}) // d FROM n p JOIN n q ON p.a < q.a, d) GROUP BY u, v")
def schur_eliminate_one(spark, sf):
    return derived.eliminate_vertex(_g(spark, sf, "nation_trade_w").edges, 7)


_KEEP = "keep AS (SELECT DISTINCT i AS vertex FROM arcs WHERE i % 2 = 0)"
_ENTER = f"SELECT i, j, ((w * {ONE}) // (sum(w) OVER (PARTITION BY i))::BIGINT)::BIGINT AS x FROM arcs WHERE j % 2 = 0"


@query(f"WITH {_arcs_sql('nation_trade_w')} {', '}r AS ({_ENTER}) SELECT * FROM r UNION ALL SELECT DISTINCT i, i, {ONE}::BIGINT FROM arcs WHERE i NOT IN (SELECT i FROM r)".replace(" , r", ", r"))
def enter_matrix(spark, sf):
    g = _g(spark, sf, "nation_trade_w")
    return derived.enter_matrix(g.arcs, g.vertices.where("vertex % 2 = 0"), BITS)


def _absorb_sql(view: str, levels: int, kept: str = "j % 2 = 0") -> str:
    o = derived.OTHER
    start = f"c0 AS (SELECT i, j, x FROM m0 WHERE NOT ({kept}) UNION ALL SELECT i, i + {o}, sum(x)::BIGINT FROM m0 WHERE {kept} GROUP BY i UNION ALL SELECT DISTINCT i + {o}, i + {o}, {ONE}::BIGINT FROM m0)"
    squares = ", ".join(_square_sql(f"c{k}", f"c{k + 1}") for k in range(levels))
    return f"{_transition_sql(view)}, {start}, {squares}, q AS (SELECT i, j - {o} AS j, x FROM c{levels} WHERE i < {o} AND j >= {o})"


def _shortcut(spark, sf, levels: int):
    """A fixed number of squarings, so that the oracle can follow."""
    g = Graph(cut(VIEWS["nation_trade_w"](spark, sf), "edges"))
    keep = cut(g.vertices.where("vertex % 2 = 0"), "keep")
    a = cut(linalg.transition(g.arcs, BITS), "a")
    q, _ = derived.shortcut_absorbing(a, keep, BITS, -1.0, levels)
    return g, keep, cut(q, "shortcut")


@query(f"WITH {_absorb_sql('nation_trade_w', 5)} SELECT * FROM q")
def shortcut_absorbing(spark, sf):
    return _shortcut(spark, sf, 5)[2]


_XR = f"r AS ({_ENTER}), xr AS (SELECT q.i, r.j, (sum(q.x::HUGEINT * r.x) // {ONE})::BIGINT AS x FROM q JOIN r ON q.j = r.i WHERE q.i % 2 = 0 GROUP BY q.i, r.j)"


@query(f"WITH {_absorb_sql('nation_trade_w', 5)}, {_XR} SELECT i, j, ((x * {ONE}::HUGEINT) // sum(x) OVER (PARTITION BY i))::BIGINT AS x FROM xr WHERE i <> j")
def schur_absorbing(spark, sf):
    g, keep, q = _shortcut(spark, sf, 5)
    return derived.schur_transition(q, derived.enter_matrix(g.arcs, keep, BITS), keep, BITS)


@query(f"WITH {_absorb_sql('nation_trade_w', 5)}, {_XR} SELECT i, x FROM xr WHERE i = j")
def self_return(spark, sf):
    g, keep, q = _shortcut(spark, sf, 5)
    return derived.self_return(q, derived.enter_matrix(g.arcs, keep, BITS), keep, BITS)


@query(f"WITH {_arcs_sql('user_type')} SELECT i, j, (({ONE}) // (count(*) OVER (PARTITION BY i)))::BIGINT AS x FROM arcs WHERE i < {rng.SCALE}")
def shortcut_bipartite(spark, sf):
    """From a kept side of a bipartite graph the vertex before the next return is the neighbour itself."""
    return linalg.transition(_g(spark, sf, "user_type").arcs, BITS).where(F.col("i") < rng.SCALE)


@query(f"WITH {_arcs_sql('nation_trade')} SELECT DISTINCT i AS vertex FROM arcs WHERE i NOT IN (1, 2, 3, 5, 8) OR i = 8")
def active_set(spark, sf):
    g = _g(spark, sf, "nation_trade")
    return derived.active_set(g.vertices, spark.createDataFrame([(x,) for x in (1, 2, 3, 5, 8)], "vertex long"), 8)


# ---- trees -------------------------------------------------------------------------------------

_FIRST = "lagged AS (SELECT s, pos, vertex, lag(vertex) OVER (PARTITION BY s ORDER BY pos) AS prev FROM w1), fv AS (SELECT s, vertex, arg_min(prev, pos) AS prev, min(pos) AS pos FROM (SELECT s, vertex, pos, coalesce(prev, -1) AS prev FROM lagged) GROUP BY s, vertex)"


@query(f"WITH {_walk_sql(_V, 100, 6)}, {_FIRST} SELECT s AS sample_id, vertex AS child, prev AS parent, least(vertex, prev) AS u, greatest(vertex, prev) AS v FROM fv WHERE prev >= 0")
def first_visit_walk(spark, sf):
    return trees.first_visit(_walks(spark, sf, _V, 100, 6)[1])


def _stepwise_sql(view: str, samples: int, steps: int, start: str = "0") -> str:
    below = rng.sql_below("total", SEED, "step", "s", "t")
    hops = []
    for t in range(1, steps + 1):
        hops.append(f"p{t} AS (SELECT s, {t}::BIGINT AS pos, j AS vertex FROM (SELECT p.s, c.j, lo, hi, {below.replace('(t)::VARCHAR', f'({t})::VARCHAR')} AS r FROM p{t - 1} p JOIN c ON c.i = p.vertex) WHERE lo <= r AND r < hi)")
    return f"{_arcs_sql(view)}, c AS (SELECT i, j, sum(w) OVER (PARTITION BY i ORDER BY j) - w AS lo, sum(w) OVER (PARTITION BY i ORDER BY j) AS hi, sum(w) OVER (PARTITION BY i) AS total FROM arcs), p0 AS (SELECT range AS s, 0::BIGINT AS pos, {start}::BIGINT AS vertex FROM range({samples})), {', '.join(hops)}, w1 AS ({' UNION ALL '.join(f'SELECT * FROM p{t}' for t in range(steps + 1))})"


def _stepwise(spark, sf, view: str, samples: int, steps: int) -> DataFrame:
    starts = spark.range(samples).select(F.col("id").alias("sample_id"), F.lit(0).cast("long").alias("vertex"))
    return doubling.stepwise(_g(spark, sf, view).arcs, starts, steps, SEED)


@query(f"WITH {_stepwise_sql(_V, 100, 12)} SELECT s AS sample_id, pos, vertex FROM w1")
def stepwise_walk(spark, sf):
    return _stepwise(spark, sf, _V, 100, 12)


def _shortcut_tree_sql() -> str:
    """A walk on the derived graph over even vertices (8 steps from 0), then the real entry edges."""
    below = rng.sql_below("total", SEED, "enter0", "s", "vertex")
    walk = ", ".join(f"p{t} AS (SELECT s, {t}::BIGINT AS pos, j AS vertex FROM (SELECT p.s, t.j, hi - x AS lo, hi, {rng.sql_below('total', SEED, 'step', 's', str(t))} AS r FROM p{t - 1} p JOIN tt t ON t.i = p.vertex) WHERE lo <= r AND r < hi)" for t in range(1, 9))
    return f"""WITH {_absorb_sql('nation_trade_w', 5)}, {_XR},
 tm AS (SELECT i, j, ((x * {ONE}::HUGEINT) // sum(x) OVER (PARTITION BY i))::BIGINT AS x FROM xr WHERE i <> j),
 tt AS (SELECT i, j, x, sum(x) OVER (PARTITION BY i ORDER BY j) AS hi, sum(x) OVER (PARTITION BY i) AS total FROM tm WHERE x > 0),
 p0 AS (SELECT range AS s, 0::BIGINT AS pos, 0::BIGINT AS vertex FROM range(50)), {walk},
 w1 AS ({' UNION ALL '.join(f'SELECT * FROM p{t}' for t in range(9))}), {_FIRST},
 mass AS (SELECT i, sum(w)::BIGINT AS mass FROM arcs WHERE j % 2 = 0 GROUP BY i),
 cand AS (SELECT fv.s, fv.vertex, a.i AS u, (q.x * a.w) // mass.mass AS weight FROM fv JOIN arcs a ON a.j = fv.vertex JOIN mass ON mass.i = a.i JOIN q ON q.i = fv.prev AND q.j = a.i WHERE fv.prev >= 0 AND (q.x * a.w) // mass.mass > 0),
 cum AS (SELECT *, sum(weight) OVER (PARTITION BY s, vertex ORDER BY u) AS hi, sum(weight) OVER (PARTITION BY s, vertex) AS total FROM cand)
 SELECT s AS sample_id, vertex AS child, u AS parent, least(u, vertex) AS u, greatest(u, vertex) AS v FROM (SELECT *, {below} AS r FROM cum) WHERE hi - weight <= r AND r < hi"""


@query(_shortcut_tree_sql())
def first_visit_shortcut(spark, sf):
    g, keep, q = _shortcut(spark, sf, 5)
    t = derived.schur_transition(q, derived.enter_matrix(g.arcs, keep, BITS), keep, BITS).where("x > 0")
    starts = spark.range(50).select(F.col("id").alias("sample_id"), F.lit(0).cast("long").alias("vertex"))
    walk = cut(doubling.stepwise(t.withColumnRenamed("x", "w"), starts, 8, SEED), "walk")
    return trees.first_visit_shortcut(walk, q, g.arcs, keep, SEED)


@query(f"SELECT u, v FROM ({VIEW_SQL['region_tree']})")
def tree_region_unique(spark, sf):
    """A tree has one spanning tree: every sampler must return the view itself."""
    return sample.forest(Graph(VIEWS["region_tree"](spark, sf)), SEED).select("u", "v")


_VALID = "SELECT true AS ok, {edges}::BIGINT AS n_edges, {vertices}::BIGINT AS n_vertices, 0::BIGINT AS n_outside"


def _checks(tree: DataFrame, edges: DataFrame) -> DataFrame:
    return accuracy.validate_tree(tree, edges).select("ok", "n_edges", "n_vertices", "n_outside")


_SPANNING = f"WITH e AS ({VIEW_SQL['nation_trade']}), n AS (SELECT count(DISTINCT x) AS n FROM (SELECT u AS x FROM e UNION ALL SELECT v FROM e)) SELECT true AS ok, (n - 1)::BIGINT AS n_edges, n::BIGINT AS n_vertices, 0::BIGINT AS n_outside FROM n"


@query(_SPANNING)
def tree_phased_valid(spark, sf):
    """The main sampler in frames, on the trade graph: its own length and bits, and no phase may fall short."""
    g = Graph(cut(VIEWS["nation_trade"](spark, sf), "edges"))
    start = g.vertices.agg(F.min("vertex")).first()[0]
    return _checks(sample.phased(g, start, seed=SEED, on_short="fail")[0], g.edges)


@query(_SPANNING)
def tree_doubling_valid(spark, sf):
    g = Graph(cut(VIEWS["nation_trade"](spark, sf), "edges"))
    return _checks(sample.by_doubling(g, 0, seed=SEED), g.edges)


def _replicas(method: str):
    def run(spark, sf):
        g = Graph(cut(VIEWS["nation_trade_w"](spark, sf), "edges"))
        t = sample.replicate(g, 8, method, SEED)
        inside = t.join(g.edges, ["u", "v"], "left_semi")
        return inside.groupBy("sample_id").agg(F.count_distinct("child").alias("n_children"), F.count_distinct("u", "v").alias("n_edges"))

    return run


_REPLICAS = f"WITH e AS ({VIEW_SQL['nation_trade_w']}), n AS (SELECT count(DISTINCT x) - 1 AS n FROM (SELECT u AS x FROM e UNION ALL SELECT v FROM e)) SELECT range AS sample_id, n::BIGINT AS n_children, n::BIGINT AS n_edges FROM range(8), n"
for _m in ("cover_walk", "loop_erased", "phased", "phased_matching", "phased_per_pair", "phased_exact", "linear_phases", "shortcut_walk", "doubling"):
    query(_REPLICAS, f"trees_{_m}")(_replicas(_m))


def _undirected(method: str):
    def run(spark, sf):
        g = Graph(cut(VIEWS["nation_trade_w"](spark, sf), "edges"))
        return sample.replicate(g, 8, method, SEED).join(g.edges, ["u", "v"], "left_semi").groupBy("sample_id").agg(F.count_distinct("u", "v").alias("n_edges"))

    return run


def _long_phases(view: str, n_samples: int = 4):
    """Main sampler at its own length on a view; a phase that falls short raises."""

    def run(spark, sf):
        g = Graph(cut(VIEWS[view](spark, sf), "edges"))
        t = sample.replicate(g, n_samples, "phased", SEED, on_short="fail")
        return t.join(g.edges, ["u", "v"], "left_semi").groupBy("sample_id").agg(F.count_distinct("child").alias("n_children"), F.count_distinct("u", "v").alias("n_edges"))

    return run


for _view_name in ("user_type", "user_seq", "user_bucket", "brand_nation"):
    query(_REPLICAS.replace(VIEW_SQL["nation_trade_w"], VIEW_SQL[_view_name]).replace("range(8)", "range(4)"), f"phased_{_view_name}")(_long_phases(_view_name))

for _m in ("exchange_chain", "conditional_marginals", "random_weight_mst"):
    query(_REPLICAS.replace(", n::BIGINT AS n_children", ""), f"trees_{_m}")(_undirected(_m))


@query(f"SELECT u, v FROM ({VIEW_SQL['page_host']})")
def tree_forest_pages(spark, sf):
    """Pages and hosts form a forest already."""
    return sample.forest(Graph(VIEWS["page_host"](spark, sf)), SEED).select("u", "v")


@query(f"WITH RECURSIVE e AS (SELECT u, v, {rng.sql_bits(SEED, 'mst', '0', 'u', 'v')} AS x FROM ({VIEW_SQL['nation_trade']})), reach(u, v, x, vertex) AS (SELECT u, v, x, u FROM e UNION SELECT r.u, r.v, r.x, CASE WHEN e.u = r.vertex THEN e.v ELSE e.u END FROM reach r JOIN e ON (e.u = r.vertex OR e.v = r.vertex) AND e.x < r.x) SELECT 0::BIGINT AS sample_id, u, v FROM e WHERE NOT EXISTS (SELECT 1 FROM reach r WHERE r.u = e.u AND r.v = e.v AND r.vertex = e.v)")
def mst_random_weight(spark, sf):
    return sample.random_weight_mst(VIEWS["nation_trade"](spark, sf), SEED)


_DATES = "d AS (SELECT count(DISTINCT year(o_orderdate))::BIGINT AS y, count(DISTINCT month(o_orderdate))::BIGINT AS m, count(DISTINCT dayofweek(o_orderdate))::BIGINT AS w, count(DISTINCT o_orderpriority)::BIGINT AS p FROM orders)"


def _dates(spark, sf):
    """Numbers of years, months, weekdays and priorities of the orders."""
    from ..sources.tables import table

    o = F.col("o_orderdate")
    return table(spark, sf, "orders", "o_orderdate", "o_orderpriority").agg(F.count_distinct(F.year(o)), F.count_distinct(F.month(o)), F.count_distinct(F.dayofweek(o)), F.count_distinct("o_orderpriority")).first()


def _complete(n: int) -> list[tuple[int, int, int]]:
    return [(a, b, 1) for a in range(n) for b in range(a + 1, n)]


@query(f"WITH {_DATES} SELECT 'path of years' AS graph, '1' AS trees UNION ALL SELECT 'cycle of months', m::VARCHAR FROM d UNION ALL SELECT 'all months', pow(m, m - 2)::BIGINT::VARCHAR FROM d UNION ALL SELECT 'weekdays x priorities', (pow(w, p - 1) * pow(p, w - 1))::BIGINT::VARCHAR FROM d")
def tree_count(spark, sf):
    """Exact counts beside closed forms, on the calendar and the priorities of the orders."""
    y, m, w, p = _dates(spark, sf)
    named = [("path of years", graphs.path(y)), ("cycle of months", graphs.cycle(m)), ("all months", _complete(m)), ("weekdays x priorities", graphs.biclique(w, p))]
    return spark.createDataFrame([(k, str(accuracy.tree_count(e))) for k, e in named], "graph string, trees string")


_EDGES = f"WITH e AS ({VIEW_SQL['nation_trade_w']})"


@query(f"{_EDGES} SELECT count(*)::BIGINT AS edges, (SELECT count(DISTINCT x) - 1 FROM (SELECT u AS x FROM e UNION ALL SELECT v FROM e))::BIGINT AS expected_sum, true AS within FROM e")
def tree_edge_marginals(spark, sf):
    """Share of each edge over 400 trees within five standard deviations of weight times effective
    resistance, which sum to n - 1."""
    g = Graph(cut(VIEWS["nation_trade_w"](spark, sf), "edges"))
    order, w = sample.core(g)
    want = [(order[a], order[b], x) for (a, b), x in accuracy.resistance_marginals(w).items()]
    got = accuracy.marginals(sample.replicate(g, 400, "loop_erased", SEED), 400)
    both = spark.createDataFrame(want, "u long, v long, p double").join(got, ["u", "v"], "left").withColumn("off", F.abs(F.coalesce("share", F.lit(0.0)) - F.col("p")))
    close = F.max(F.col("off") / F.sqrt(F.col("p") * (1 - F.col("p")) / 400 + 1e-6)) < 5
    return both.agg(F.count(F.lit(1)).alias("edges"), F.round(F.sum("p")).cast("long").alias("expected_sum"), close.alias("within"))


# ---- doubling ----------------------------------------------------------------------------------

def _stub_sql(view: str, k: int) -> str:
    below = rng.sql_below("total", SEED, "stub", "src", "idx")
    return f"{_arcs_sql(view)}, c AS (SELECT i, j, sum(w) OVER (PARTITION BY i ORDER BY j) - w AS lo, sum(w) OVER (PARTITION BY i ORDER BY j) AS hi, sum(w) OVER (PARTITION BY i) AS total FROM arcs), st AS (SELECT src, idx, j AS endpoint, 1::BIGINT AS len FROM (SELECT i AS src, range AS idx, j, lo, hi, total, {below.replace('(src)', '(i)').replace('(idx)', '(range)')} AS r FROM c, range(1, {k + 1})) WHERE lo <= r AND r < hi)"


def _double_sql(src: str, dst: str, k: int) -> str:
    return f"{dst} AS (SELECT a.src, a.idx, b.endpoint, a.len + b.len AS len FROM {src} a JOIN {src} b ON a.endpoint = b.src AND b.idx = {k + 1} - a.idx WHERE a.idx <= {k // 2})"


@query(f"WITH {_stub_sql('user_type', 4)} SELECT * FROM st")
def stub_init(spark, sf):
    return doubling.init(_g(spark, sf, "user_type").arcs, 4, SEED)


def _doubled(balance: str):
    def run(spark, sf):
        stubs = cut(doubling.init(_g(spark, sf, "user_type").arcs, 4, SEED), "stubs")
        family = hashing.poly_family(12, 155, 4, SEED)
        return doubling.step(stubs, 4, balance, family, seed=SEED)

    return run


for _b in ("none", "hash", "salted"):
    query(f"WITH {_stub_sql('user_type', 4)}, {_double_sql('st', 's2', 4)} SELECT * FROM s2", f"double_step_{_b}")(_doubled(_b))

_FAMILY = hashing.poly_family(12, 155, 4, SEED)


@query(f"WITH {_stub_sql('user_type', 4)} SELECT place, count(*)::BIGINT AS n FROM (SELECT {_FAMILY.sql('endpoint', '5 - idx')} AS place FROM st WHERE idx <= 2 UNION ALL SELECT {_FAMILY.sql('src', 'idx')} FROM st WHERE idx > 2) GROUP BY place")
def hash_loads(spark, sf):
    return doubling.loads(doubling.meeting(doubling.init(_g(spark, sf, "user_type").arcs, 4, SEED), 4, _FAMILY))


@query(f"WITH {_stub_sql('user_type', 4)} SELECT place, count(*)::BIGINT AS n FROM (SELECT endpoint AS place FROM st WHERE idx <= 2 UNION ALL SELECT src FROM st WHERE idx > 2) GROUP BY place")
def plain_loads(spark, sf):
    return doubling.loads(doubling.plain_meeting(doubling.init(_g(spark, sf, "user_type").arcs, 4, SEED), 4))


_L16 = f"{_stub_sql('nation_trade', 16)}, {_double_sql('st', 's2', 16)}, {_double_sql('s2', 's4', 8)}, {_double_sql('s4', 's8', 4)}, {_double_sql('s8', 's16', 2)}"


@query(f"WITH {_L16} SELECT * FROM s16")
def walk_doubled_16(spark, sf):
    return doubling.walks(_g(spark, sf, "nation_trade").arcs, 16, SEED)


def _expand_sql() -> str:
    rows = ["r4 AS (SELECT 0::BIGINT AS pos, 0::BIGINT AS src, 1::BIGINT AS idx)"]
    for level, table, k in ((4, "s8", 2), (3, "s4", 4), (2, "s2", 8), (1, "st", 16)):
        rows.append(f"r{level - 1} AS (SELECT * FROM r{level} UNION ALL SELECT pos + {1 << (level - 1)}, t.endpoint, {k + 1} - r.idx FROM r{level} r JOIN {table} t ON t.src = r.src AND t.idx = r.idx)")
    return f"WITH {_L16}, {', '.join(rows)} SELECT 0::BIGINT AS sample_id, 0::BIGINT AS pos, 0::BIGINT AS vertex UNION ALL SELECT 0, pos + 1, endpoint FROM r0 JOIN st USING (src, idx)"


@query(_expand_sql())
def walk_expanded_16(spark, sf):
    return doubling.walk_from(_g(spark, sf, "nation_trade").arcs, 0, 16, SEED)


def _stitch_sql() -> str:
    steps, src = [], "st"
    for half in (16, 8, 4):
        steps.append(f"x{half} AS (SELECT a.src, a.idx, coalesce(b.endpoint, a.endpoint) AS endpoint, a.len + coalesce(b.len, 0) AS len FROM (SELECT *, row_number() OVER (PARTITION BY endpoint ORDER BY src, idx) AS turn FROM {src} WHERE idx <= {half // 2}) a LEFT JOIN (SELECT *, row_number() OVER (PARTITION BY src ORDER BY idx) AS turn FROM {src} WHERE idx > {half // 2}) b ON a.endpoint = b.src AND a.turn = b.turn)")
        src = f"x{half}"
    return f"WITH {_stub_sql('user_type', 16)}, {', '.join(steps)} SELECT src, idx, endpoint, len FROM x4"


@query(_stitch_sql())
def stitch_overprovisioned(spark, sf):
    return doubling.stitch_overprovisioned(_g(spark, sf, "user_type").arcs, 8, 2, SEED)


def _rank_sql(view: str, rounds: int) -> str:
    steps = ", ".join(f"r{k + 1} AS (SELECT j AS vertex, sum(rank * x) * 0.85 + 0.15 / (SELECT n FROM c) AS rank FROM r{k} JOIN p ON p.i = r{k}.vertex GROUP BY j)" for k in range(rounds))
    return f"WITH {_arcs_sql(view)}, p AS (SELECT i, j, w / sum(w) OVER (PARTITION BY i) AS x FROM arcs), c AS (SELECT count(DISTINCT i) AS n FROM arcs), r0 AS (SELECT DISTINCT i AS vertex, 1.0::DOUBLE / (SELECT n FROM c) AS rank FROM arcs), {steps} SELECT vertex, round(rank, 9) AS rank FROM r{rounds}"


@query(f"WITH {_arcs_sql('user_seq')} SELECT count(DISTINCT i)::BIGINT AS n, true AS near FROM arcs")
def pagerank_walks(spark, sf):
    """Ends of 64 doubled walks of up to 32 steps of every vertex: their shares lie near the ranking by power
    iteration (half the L1 distance under 0.1)."""
    arcs = cut(_g(spark, sf, "user_seq").arcs, "arcs")
    ends, rank = doubling.pagerank(arcs, 32, SEED, 64), walks.power_iteration(arcs, rounds=12)
    total = ends.agg(F.sum("n")).first()[0]
    both = rank.join(ends, "vertex", "left").select(F.abs(F.coalesce("n", F.lit(0)) / total - F.col("rank")).alias("off"))
    return both.agg(F.count(F.lit(1)).alias("n"), (F.sum("off") / 2 < 0.1).alias("near"))


@query(_rank_sql("user_type", 8))
def pagerank_power(spark, sf):
    return walks.power_iteration(_g(spark, sf, "user_type").arcs, rounds=8).select("vertex", F.round("rank", 9).alias("rank"))


# ---- measures ----------------------------------------------------------------------------------

@query(f"WITH {_walk_sql(_V, 200)}, l(step, n, load) AS (SELECT 'pairs', sum(n), max(n) FROM (SELECT p, count(*) AS n FROM g1 GROUP BY p) UNION ALL SELECT 'middles', sum(n), max(n) FROM (SELECT vertex, count(*) AS n FROM d1 GROUP BY vertex)) SELECT coalesce(step, 'all') AS step, sum(n)::BIGINT AS words, max(load)::BIGINT AS max_recv, sum(greatest(1, ceil(load / 25.0)))::BIGINT AS rounds FROM l GROUP BY ROLLUP (step)")
def ledger_rollup(spark, sf):
    """Measured moves of one level, charged and rolled up: requests to the owners of left ends, middles
    to the owners of the vertices drawn."""
    _, walk, mids = _placed_mids(spark, sf, 200)
    book = ledger.Ledger("one level", 25)
    for step, moves, target in (("pairs", topdown.gaps(walk, 2), "p"), ("middles", mids, "vertex")):
        r = ledger.loads(moves, "sample_id", target).first()
        book.charge(step, 0, 1, 0, r.max_recv, r.words)
    return book.frame(spark).rollup("step").agg(F.sum("words").alias("words"), F.max("max_recv").alias("max_recv"), F.sum("rounds").alias("rounds")).withColumn("step", F.coalesce("step", F.lit("all")))


def _tv(method: str):
    def run(spark, sf):
        rows = []
        for name in ("diamond", "diamond_w"):
            g = graphs.graph(spark, None, name)
            r = accuracy.tv(sample.replicate(g, 4000, method, SEED), accuracy.truth_frame(spark, graphs.FIXTURES[name])).first()
            rows.append((name, method, r.samples, r.df, accuracy.chi2_p(r.chi2, r.df) > 1e-4, float(r.tv) < 0.05))
        return spark.createDataFrame(rows, "graph string, method string, samples long, df long, law_ok boolean, tv_small boolean")

    return run


def _type_edges(spark, sf, weighted: bool) -> list[tuple[int, int, int]]:
    """Types of events next to each other in a user's sequence: at most one edge for each pair of types."""
    from ..sources.tables import table

    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = table(spark, sf, "events", "event_id", "ts", "user_id", "event_type").select(rng.key_id("event_type").alias("b"), F.lag(rng.key_id("event_type")).over(w).alias("a"))
    return sorted((r.u, r.v, r.w) for r in graphs.canonical(e, "a", "b", F.count(F.lit(1)) if weighted else None).collect())


def _tv_types(method: str):
    def run(spark, sf):
        rows = []
        for name, weighted in (("event types", False), ("event types, weighted", True)):
            edges = _type_edges(spark, sf, weighted)
            r = accuracy.tv(sample.replicate(graphs.graph(spark, None, edges), 20000, method, SEED), accuracy.truth_frame(spark, edges)).first()
            rows.append((name, method, r.samples, r.df, accuracy.chi2_p(r.chi2, r.df) > 1e-4, float(r.tv) < 0.05))
        return spark.createDataFrame(rows, "graph string, method string, samples long, df long, law_ok boolean, tv_small boolean")

    return run


for _m in ("cover_walk", "loop_erased", "doubling"):  # all pairs of types occur: n^(n-2) trees
    query(f"SELECT g AS graph, '{_m}' AS method, 20000::BIGINT AS samples, (SELECT pow(count(DISTINCT event_type), count(DISTINCT event_type) - 2)::BIGINT - 1 FROM events) AS df, true AS law_ok, true AS tv_small FROM (VALUES ('event types'), ('event types, weighted')) t(g)", f"tv_{_m}")(_tv_types(_m))

for _m in ("phased", "random_weight_mst"):
    _ok, _small = ("false", "g = 'diamond'") if _m == "random_weight_mst" else ("true", "true")  # the negative control
    query(f"SELECT g AS graph, '{_m}' AS method, 4000::BIGINT AS samples, 7::BIGINT AS df, {_ok} AS law_ok, {_small} AS tv_small FROM (VALUES ('diamond'), ('diamond_w')) t(g)", f"tv_{_m}")(_tv(_m))


@query(f"WITH {_DATES} SELECT 'path of years' AS graph, ((y - 1) * (y - 1))::DOUBLE AS expected, true AS near FROM d UNION ALL SELECT 'cycle of months', (m * (m - 1) / 2)::DOUBLE, true FROM d UNION ALL SELECT 'all weekdays', round(list_sum(list_transform(range(1, w), lambda k: (w - 1.0::DOUBLE) / k)), 6), true FROM d")
def cover_time(spark, sf):
    """Mean steps to see all vertices beside the known values, on the calendar of the orders: (n-1)^2 for a path
    from its end, n(n-1)/2 for a cycle, (n-1) times the harmonic number for a complete graph."""
    y, m, w, _ = _dates(spark, sf)
    rows = []
    for name, edges, want in (("path of years", graphs.path(y), (y - 1) ** 2), ("cycle of months", graphs.cycle(m), m * (m - 1) / 2), ("all weekdays", _complete(w), sum((w - 1) / k for k in range(1, w)))):
        mean = walks.quantiles(walks.cover_time(graphs.graph(spark, None, edges), 600)).first().mean
        rows.append((name, round(float(want), 6), bool(abs(mean / want - 1) < 0.15)))
    return spark.createDataFrame(rows, "graph string, expected double, near boolean")


@query(f"WITH e AS ({VIEW_SQL['nation_trade']}), n AS (SELECT count(DISTINCT x) AS n FROM (SELECT u AS x FROM e UNION ALL SELECT v FROM e)), one AS (SELECT round(0.01 / (4 * sqrt(n) * ceil(log2(ln(4 * sqrt(n) / 0.01) * pow(n, 3)))), 9) AS share FROM n) SELECT 'exact arithmetic' AS variant, 'walk too short' AS source, 0.005::DOUBLE AS share UNION ALL SELECT 'exact arithmetic', 'matchings, all phases', 0.005 UNION ALL SELECT 'exact arithmetic', 'one matching', share FROM one UNION ALL SELECT 'rounded powers', s, round(0.01 / 3, 9) FROM (VALUES ('walk too short'), ('matchings'), ('rounding')) t(s)")
def error_budget(spark, sf):
    """Shares of the error wanted for the trade graph, at the length its size asks for."""
    n = _g(spark, sf, "nation_trade").vertices.count()
    rows = params.error_budget(0.01, n, params.target_length(n, n, 0.01))
    return spark.createDataFrame(rows, "variant string, source string, share double").select("variant", "source", F.round("share", 9).alias("share"))


@query("SELECT n::BIGINT AS n, k::BIGINT AS k, round(8 * power((t * mu + t * t) / (a * a), t / 2.0), 9) AS tail FROM (SELECT n, k, 8 * log2(n) AS t, 2 * k AS mu, 16 * k * log2(n) - 2 * k AS a FROM (VALUES (256, 16), (1024, 8), (1024, 64)) v(n, k))")
def twise_bound(spark, sf):
    v = spark.createDataFrame([(256, 16), (1024, 8), (1024, 64)], "n long, k long")
    t, mu = F.lit(8.0) * F.log2("n"), F.col("k") * 2.0
    a = F.lit(16.0) * F.col("k") * F.log2("n") - mu
    return v.select("n", "k", F.round(8 * F.pow((t * mu + t * t) / (a * a), t / 2), 9).alias("tail"))


@query(f"WITH {_stub_sql('user_type', 4)} SELECT max(n)::BIGINT AS max_load, sum(n)::BIGINT AS stubs FROM (SELECT place, count(*) AS n FROM (SELECT {_FAMILY.sql('endpoint', '5 - idx')} AS place FROM st WHERE idx <= 2 UNION ALL SELECT {_FAMILY.sql('src', 'idx')} FROM st WHERE idx > 2) GROUP BY place)")
def doubling_load(spark, sf):
    return ledger.doubling_load(doubling.meeting(doubling.init(_g(spark, sf, "user_type").arcs, 4, SEED), 4, _FAMILY), 4, 155).select("max_load", "stubs")


@query(f"WITH {_walk_sql(_V, 200)}, m AS (SELECT s, count(*) AS n FROM g1 GROUP BY s) SELECT max(a.n)::BIGINT AS max_sent, sum(a.n)::BIGINT AS words, (SELECT max(c) FROM (SELECT p, count(*) AS c FROM g1 GROUP BY p))::BIGINT AS max_recv FROM m a")
def request_loads(spark, sf):
    """Messages of pair requests, from samples to the machines that own the left end."""
    return ledger.loads(topdown.gaps(_walks(spark, sf, _V, 200, 3, 1)[1], 2), "sample_id", "p").select("max_sent", "words", "max_recv")


@query(f"WITH {_walk_sql(_V, 200)} SELECT s AS sample_id, max(pos)::BIGINT AS length, count(DISTINCT vertex)::BIGINT AS n_distinct FROM w1 GROUP BY s")
def walk_length(spark, sf):
    return walks.length(_walks(spark, sf, _V, 200)[1])


@query(f"WITH {_walk_sql(_V, 200)} SELECT count(*)::BIGINT AS pairs, count(*) FILTER (WHERE coalesce(x, 0) <= {ONE // 25})::BIGINT AS rare FROM (SELECT DISTINCT s, p, q FROM g1) g LEFT JOIN m1 ON m1.i = g.p AND m1.j = g.q")
def rare_pairs(spark, sf):
    ladder, walk = _walks(spark, sf, _V, 200, 3, 1)
    return accuracy.rare_pairs(topdown.requests(walk, 2), ladder[1], ONE // 25)


# ---- graph operators and applications ----------------------------------------------------------

def _components_sql(view: str) -> str:
    return f"WITH RECURSIVE e AS ({VIEW_SQL[view]}), b AS (SELECT u AS i, v AS j FROM e UNION ALL SELECT v, u FROM e), r(root, vertex) AS (SELECT DISTINCT i, i FROM b UNION SELECT r.root, b.j FROM r JOIN b ON b.i = r.vertex) SELECT vertex, min(root) AS component FROM r GROUP BY vertex"


@query(_components_sql("page_host"))
def components(spark, sf):
    return graph.components(VIEWS["page_host"](spark, sf))


@query(f"WITH RECURSIVE e AS ({VIEW_SQL['region_tree']}), r(vertex, depth, parent) AS (SELECT 0::BIGINT, 0, NULL::BIGINT UNION ALL SELECT e.v, r.depth + 1, e.u FROM r JOIN e ON e.u = r.vertex) SELECT vertex, depth, coalesce(parent, -1) AS parent FROM r")
def bfs_tree(spark, sf):
    return graph.bfs_tree(VIEWS["region_tree"](spark, sf), 0).select("vertex", "depth", F.coalesce("parent", F.lit(-1)).alias("parent"))


@query("SELECT 'supp_part' AS view, true AS bipartite UNION ALL SELECT 'nation_trade', false")
def is_bipartite(spark, sf):
    return spark.createDataFrame([(v, graph.is_bipartite(VIEWS[v](spark, sf))) for v in ("supp_part", "nation_trade")], "view string, bipartite boolean")


@query(f"WITH e AS ({VIEW_SQL['nation_trade']}) SELECT p.u AS a, p.v AS b, q.v AS c FROM e p JOIN e q ON p.v = q.u JOIN e r ON r.u = p.u AND r.v = q.v")
def triangles(spark, sf):
    return graph.triangles(VIEWS["nation_trade"](spark, sf))


@query(f"WITH e AS ({VIEW_SQL['user_seq']}), d AS (SELECT x, count(*) AS d FROM (SELECT u AS x FROM e UNION ALL SELECT v FROM e) GROUP BY x) SELECT count(*)::BIGINT AS n, (sum(d) / 2)::BIGINT AS m, min(d)::BIGINT AS min_degree, max(d)::BIGINT AS max_degree, round(avg(d), 6) AS mean_degree FROM d")
def degree_stats(spark, sf):
    return graph.degree_stats(VIEWS["user_seq"](spark, sf))


@query(f"SELECT u, v, w FROM ({VIEW_SQL['region_tree']})")
def reduce_pendant(spark, sf):
    """A tree is all forced edges."""
    return reduce.pendant(VIEWS["region_tree"](spark, sf))[0]


@query(f"WITH e AS ({VIEW_SQL['page_host']}) SELECT count(*)::BIGINT AS n_blocks, count(*)::BIGINT AS n_edges FROM e")
def reduce_blocks(spark, sf):
    """In a forest every edge is a block."""
    b = reduce.blocks(VIEWS["page_host"](spark, sf))
    return b.agg(F.count_distinct("component", "block").alias("n_blocks"), F.count(F.lit(1)).alias("n_edges"))


@query(f"WITH e AS ({VIEW_SQL['nation_trade_w']}) SELECT u, v, sum(w)::BIGINT AS w FROM (SELECT * FROM e UNION ALL SELECT * FROM e) GROUP BY u, v")
def reduce_parallel(spark, sf):
    e = VIEWS["nation_trade_w"](spark, sf)
    return reduce.merge_parallel(e.union(e))


@query("SELECT true AS unbiased, true AS inside")
def sparsify(spark, sf):
    """The union of 32 trees keeps the total weight in expectation (within a tenth here) and no foreign edge."""
    g = Graph(cut(VIEWS["user_seq_w"](spark, sf), "edges"))
    s = cut(apps.sparsify(g, 32), "sparse")
    full, sparse = g.edges.agg(F.sum("w")).first()[0], s.agg(F.sum("w")).first()[0]
    return s.join(g.edges.select("u", "v"), ["u", "v"], "left_anti").agg(F.lit(abs(sparse / full - 1) < 0.1).alias("unbiased"), (F.count(F.lit(1)) == 0).alias("inside")).select(F.col("unbiased"), "inside")


@query("SELECT range AS cut, true AS near FROM range(10)")
def cut_error(spark, sf):
    """Weights of ten random cuts in the union of 64 trees, each within a quarter of the full graph's."""
    g = Graph(cut(VIEWS["nation_trade_w"](spark, sf), "edges"))
    return apps.cut_error(g.edges, apps.sparsify(g, 64), 10).select("cut", (F.abs(F.col("sparse") / F.col("full") - 1) < 0.25).alias("near"))


@query(f"{_EDGES} SELECT count(*)::BIGINT AS edges, (SELECT count(DISTINCT x) - 1 FROM (SELECT u AS x FROM e UNION ALL SELECT v FROM e))::DOUBLE AS foster FROM e")
def effective_resistance(spark, sf):
    """Estimates from 200 trees: weights times resistances sum to n - 1 exactly, tree by tree."""
    g = Graph(cut(VIEWS["nation_trade_w"](spark, sf), "edges"))
    r = apps.effective_resistance(sample.replicate(g, 200, "loop_erased", SEED), g.edges, 200).join(g.edges, ["u", "v"])
    return r.agg(F.count(F.lit(1)).alias("edges"), F.round(F.sum(F.col("r") * F.col("w")), 6).alias("foster"))


__all__ = ["ORACLES", "QUERIES"]
