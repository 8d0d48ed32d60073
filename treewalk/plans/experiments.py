"""The claims as experiments: small queries whose outcome an SQL engine can state or recompute."""

from __future__ import annotations

import math
from decimal import Decimal

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..ckpt import cut
from ..functions import hashing, rng
from ..operators import accuracy, derived, doubling, kernels, ledger, linalg, matching, params, sample, split, topdown, trees, truncate, walks
from ..sources import graphs
from ..sources.graphs import VIEWS, Graph
from .methods import _CUT, _V, _XR, BITS, ONE, SEED, VIEW_SQL, _absorb_sql, _arcs_sql, _double_sql, _g, _placed_mids, _shortcut, _square_sql, _stepwise, _stepwise_sql, _stub_sql, _transition_sql, _walk_sql, _walks

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return add


# ---- pieces of the walk that have no other query

_SEQ = f"s AS (SELECT user_id, row_number() OVER w - 1 AS pos, {rng.sql_key_id('event_type')} AS vertex, lag({rng.sql_key_id('event_type')}) OVER w AS p, lead({rng.sql_key_id('event_type')}) OVER w AS q FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), m AS (SELECT * FROM s WHERE pos % 2 = 1 AND q IS NOT NULL)"


@query(f"WITH {_SEQ}, c AS (SELECT user_id, p, q, count(*) AS c FROM m GROUP BY ALL), v AS (SELECT user_id, vertex, count(*) AS c FROM m GROUP BY ALL), f AS (SELECT * FROM s WHERE pos % 2 = 0 OR q IS NOT NULL) SELECT 'pairs' AS what, count(*)::BIGINT AS n, sum(c * (p % 1009 + q % 1013))::BIGINT AS mass FROM c UNION ALL SELECT 'multiset', count(*)::BIGINT, sum(c * (vertex % 1009))::BIGINT FROM v UNION ALL SELECT 'filled', count(*)::BIGINT, sum((pos + 1) * (vertex % 1009))::BIGINT FROM f")
def pair_figure(spark, sf):
    """Every user's sequence of event types as a walk whose odd places are open: counts sent to the owners of pairs,
    the multisets that come back, and the filled walks, which are the sequences again."""
    from ..sources.tables import table

    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = table(spark, sf, "events", "event_id", "ts", "user_id", "event_type").withColumn("vertex", rng.key_id("event_type"))
    seq = cut(e.select(F.col("user_id").alias("sample_id"), (F.row_number().over(w) - 1).cast("long").alias("pos"), "vertex", F.lag("vertex").over(w).alias("p"), F.lead("vertex").over(w).alias("q")), "sequence")
    walk = seq.where("pos % 2 = 0").select("sample_id", "pos", "vertex")
    mids = seq.where("pos % 2 = 1 AND q IS NOT NULL").select("sample_id", "p", "q", F.row_number().over(Window.partitionBy("sample_id", "p", "q").orderBy("pos")).cast("long").alias("occ"), "vertex")
    mass = lambda df, what, x: df.agg(F.count(F.lit(1)).alias("n"), F.sum(F.expr(x)).alias("mass")).select(F.lit(what).alias("what"), "n", "mass")
    pairs = mass(topdown.requests(walk, 2), "pairs", "c * (p % 1009 + q % 1013)")
    multiset = mass(matching.multiset(mids), "multiset", "c * (vertex % 1009)")
    return pairs.union(multiset).union(mass(topdown.place_in_order(walk, mids, 1), "filled", "(pos + 1) * (vertex % 1009)"))


@query(f"WITH {_transition_sql('nation_trade_w')}, r AS (SELECT i AS vertex, sum(x)::BIGINT AS row_mass FROM m0 GROUP BY i), c AS (SELECT j AS vertex, sum(x)::BIGINT AS column_mass FROM m0 GROUP BY j) SELECT * FROM r JOIN c USING (vertex)")
def colocate(spark, sf):
    """Row and column of each vertex, side by side on one machine."""
    rows, cols = linalg.colocate(linalg.transition(_g(spark, sf, "nation_trade_w").arcs, BITS), 4)
    return rows.groupBy(F.col("i").alias("vertex")).agg(F.sum("x").alias("row_mass")).join(cols.groupBy(F.col("j").alias("vertex")).agg(F.sum("x").alias("column_mass")), "vertex")


def _cut_query(f):
    query(f"WITH {_walk_sql(_V, 200)}, {_CUT} SELECT s AS sample_id, pos, vertex FROM w1 LEFT JOIN k USING (s) WHERE cut IS NULL OR pos <= cut")(f)
    return f


def _ladder_and_starts(spark, sf, samples: int = 200):
    ladder = linalg.power_ladder(linalg.transition(_g(spark, sf, _V).arcs, BITS), 3, BITS)
    return ladder, spark.range(samples).select(F.col("id").alias("sample_id"), F.lit(0).cast("long").alias("vertex"))


@_cut_query
def truncate_each_level(spark, sf):
    """Cut after every level: the same walks as when the cut waits for the end."""
    return topdown.full_walk(*_ladder_and_starts(spark, sf), SEED, 5)


@_cut_query
def truncate_deferred(spark, sf):
    return topdown.full_walk(*_ladder_and_starts(spark, sf), SEED, 5, "end")


@_cut_query
def truncated_walk(spark, sf):
    """The whole of phase one."""
    return topdown.truncated_walk(_g(spark, sf, _V).arcs, 0, 5, 8, SEED, BITS, samples=200)


@_cut_query
def walks_in_task(spark, sf):
    ladder, starts = _ladder_and_starts(spark, sf)
    return topdown.walks_in_task(ladder, starts, SEED, 5)


@query(f"WITH {_walk_sql(_V, 200)} SELECT s AS sample_id, vertex FROM w2 WHERE pos = 6")
def vertex_at(spark, sf):
    return truncate.vertex_at(_walks(spark, sf, _V, 200, 3, 1)[1], 6)


def _hugeint_square(src: str, dst: str) -> str:
    return _square_sql(src, dst, 60)


@query(f"WITH {_arcs_sql('nation_trade_w')}, m0 AS (SELECT i, j, ((w::HUGEINT * {1 << 60}) // (sum(w) OVER (PARTITION BY i)))::BIGINT AS x FROM arcs), {_hugeint_square('m0', 'm1')}, {_hugeint_square('m1', 'm2')} SELECT i, j, x FROM m2")
def power_60_bits(spark, sf):
    """The fourth power at 60 bits, by joins and decimals."""
    return linalg.power_ladder(linalg.transition(_g(spark, sf, "nation_trade_w").arcs, 60), 2, 60)[2]


@query(f"WITH {_arcs_sql('nation_trade_w')}, m0 AS (SELECT i, j, ((w::HUGEINT * {1 << 60}) // (sum(w) OVER (PARTITION BY i)))::BIGINT AS x FROM arcs), {_hugeint_square('m0', 'm1')}, {_hugeint_square('m1', 'm2')} SELECT i, j, x FROM m2")
def power_60_bits_in_task(spark, sf):
    """The same in one task, by limbs."""
    return linalg.power_ladder(linalg.transition(_g(spark, sf, "nation_trade_w").arcs, 60), 2, 60, 25)[2]


@query(f"WITH {_absorb_sql('nation_trade_w', 5)}, {_XR} SELECT round(max({float(ONE)!r} / ({ONE} - x)), 6) AS factor FROM xr WHERE i = j")
def max_self_return(spark, sf):
    g, keep, q = _shortcut(spark, sf, 5)
    r = derived.self_return(q, derived.enter_matrix(g.arcs, keep, BITS), keep, BITS)
    return accuracy.max_self_return(r, BITS).select(F.round("factor", 6).alias("factor"))


# ---- parameter rules

_RULED = ("nation_trade", "user_type", "supp_part")
_RULED_SQL = " UNION ALL ".join(f"SELECT count(DISTINCT x) AS n FROM (SELECT u AS x FROM ({VIEW_SQL[v]}) UNION ALL SELECT v FROM ({VIEW_SQL[v]}))" for v in _RULED)


@query(f"SELECT n::BIGINT AS n, eps, length::BIGINT AS length, floor(sqrt(n))::BIGINT AS rho, floor(pow(n, 1 / 3.0) + 1e-9)::BIGINT AS rho_exact, CASE WHEN log2(3 * ceil(2 * sqrt(n)) * n * (2 * length - 1) / eps) <= 30 THEN 30 WHEN log2(3 * ceil(2 * sqrt(n)) * n * (2 * length - 1) / eps) <= 60 THEN 60 ELSE 0 END::BIGINT AS bits, round(eps / (4 * sqrt(n) * log2(length)), 12) AS matching_tv FROM (SELECT n, eps, pow(2, ceil(log2(ln(4 * sqrt(n) / eps) * pow(n, 3)))) AS length FROM ({_RULED_SQL}) a(n), (VALUES (0.1::DOUBLE), (0.01::DOUBLE)) b(eps))")
def parameter_sweep(spark, sf):
    """Length, goal, bits and the error of one matching over n of three views and the error wanted (bits 0:
    beyond 60)."""
    return _sweep(spark, [_g(spark, sf, v).vertices.count() for v in _RULED])


def _sweep(spark, sizes: list[int]) -> DataFrame:
    """Lengths are whole and exact: from 2^63 on, where a long (and the SQL's cast) overflows, the column is a decimal."""
    rows = []
    for n, eps in ((n, e) for n in sizes for e in (0.1, 0.01)):
        length = params.target_length(n, n, eps)
        try:
            bits = params.precision(n, length, eps)
        except ValueError:
            bits = 0
        rows.append((n, eps, length, params.rho(n), params.rho(n, "cbrt"), bits, round(params.matching_tv(eps, n, length), 12)))
    kind = "long"
    if max(r[2] for r in rows) >= 1 << 63:
        kind, rows = "decimal(38,0)", [(*r[:2], Decimal(r[2]), *r[3:]) for r in rows]
    return spark.createDataFrame(rows, f"n long, eps double, length {kind}, rho long, rho_exact long, bits long, matching_tv double")


# ---- experiments

_CORES = ("nation_trade", "brand_nation", "user_type")


def _phase_facts(spark, sf, view: str, **options) -> dict:
    """Facts of one run of the phased kernel on a core, of its classes where a side is small."""
    g = Graph(cut(VIEWS[view](spark, sf), "edges"))
    if found := sample.split_core(g):
        facts: dict = {"n": found[1].n}
        split.phased(found[1], np.random.default_rng(SEED), facts=facts, on_short="fail", **options)
        return facts
    _, w = sample.core(g)
    facts = {"n": len(w)}
    kernels.phased(w, np.random.default_rng(SEED), facts=facts, **options)
    return facts


_SIZES = " UNION ALL ".join(f"SELECT '{v}' AS graph, count(DISTINCT x)::BIGINT AS n FROM (SELECT u AS x FROM ({VIEW_SQL[v]}) UNION ALL SELECT v FROM ({VIEW_SQL[v]}))" for v in _CORES)


def _frames_law(walker):
    """First-visit trees of many walks made in frames, against the exact law (chi-square)."""

    def run(spark, sf):
        rows = []
        for name in ("diamond", "diamond_w"):
            g = graphs.graph(spark, None, name)
            starts = spark.range(1200).select(F.col("id").alias("sample_id"), F.lit(0).cast("long").alias("vertex"))
            tree = cut(trees.first_visit(walker(g, starts)), "tree")
            r = accuracy.tv(tree, accuracy.truth_frame(spark, graphs.FIXTURES[name])).first()
            rows.append((name, r.samples, r.df, accuracy.chi2_p(r.chi2, r.df) > 1e-4))
        return spark.createDataFrame(rows, "graph string, samples long, df long, law_ok boolean")

    return run


_LAW = "SELECT g AS graph, 1200::BIGINT AS samples, 7::BIGINT AS df, true AS law_ok FROM (VALUES ('diamond'), ('diamond_w')) t(g)"
query(_LAW, "tv_frames_truncated")(_frames_law(lambda g, s: topdown.full_walk(linalg.power_ladder(linalg.transition(g.arcs), 7, BITS, 4), s, SEED, 4)))


@query(f"SELECT graph, n, true AS phases_ok, true AS distinct_ok FROM ({_SIZES})")
def x3_phases(spark, sf):
    """No more than 2 sqrt(n) phases, and no phase sees over sqrt(n) vertices."""
    rows = []
    for v in _CORES:
        f = _phase_facts(spark, sf, v)
        rows.append((v, f["n"], f["phases"] <= params.phases_bound(f["n"]), max(f["distinct"]) <= params.rho(f["n"])))
    return spark.createDataFrame(rows, "graph string, n long, phases_ok boolean, distinct_ok boolean")


@query(f"SELECT graph, true AS more_phases FROM ({_SIZES}) WHERE graph <> 'brand_nation'")
def x4_exact_needs_more_phases(spark, sf):
    """The exact variant's cube-root goal takes more phases than the square-root one."""
    rows = [(v, _phase_facts(spark, sf, v, exact=True)["phases"] > _phase_facts(spark, sf, v)["phases"]) for v in ("nation_trade", "user_type")]
    return spark.createDataFrame(rows, "graph string, more_phases boolean")


def _load_sql(view: str, tau: int, place_end: str, place_src: str) -> str:
    return f"(WITH {_stub_sql(view, tau)} SELECT max(n) FROM (SELECT place, count(*) AS n FROM (SELECT {place_end} AS place FROM st WHERE idx <= {tau // 2} UNION ALL SELECT {place_src} FROM st WHERE idx > {tau // 2}) GROUP BY place))::BIGINT"


_F155 = {tau: hashing.poly_family(12, 155, tau, SEED) for tau in (16, 64)}


@query(" UNION ALL ".join(f"SELECT {tau}::BIGINT AS tau, {_load_sql('user_type', tau, 'endpoint', 'src')} AS plain, {_load_sql('user_type', tau, f.sql('endpoint', f'{tau + 1} - idx'), f.sql('src', 'idx'))} AS balanced" for tau, f in _F155.items()))
def x5_loads(spark, sf):
    """Most stubs that one place receives in the first iteration, on a graph of five hot vertices."""
    arcs, out = cut(_g(spark, sf, "user_type").arcs, "arcs"), None
    for tau, family in _F155.items():
        stubs = cut(doubling.init(arcs, tau, SEED), "stubs")
        plain = doubling.loads(doubling.plain_meeting(stubs, tau)).agg(F.max("n").alias("plain"))
        row = plain.crossJoin(doubling.loads(doubling.meeting(stubs, tau, family)).agg(F.max("n").alias("balanced"))).select(F.lit(tau).cast("long").alias("tau"), "plain", "balanced")
        out = row if out is None else out.union(row)
    return out


_F150 = {tau: hashing.poly_family(12, 150, tau, SEED) for tau in (4, 64)}


@query("SELECT tau, load, greatest(1, ceil(load / 150.0))::BIGINT AS rounds, load <= bound AS within FROM (" + " UNION ALL ".join(f"SELECT {tau}::BIGINT AS tau, {_load_sql('user_seq', tau, f.sql('endpoint', f'{tau + 1} - idx'), f.sql('src', 'idx'))} AS load, 16 * {tau} * log2(150) AS bound" for tau, f in _F150.items()) + ")")
def x6_regimes(spark, sf):
    """One round an iteration while tau is below n / log n, and then in proportion to tau."""
    arcs, out = cut(_g(spark, sf, "user_seq").arcs, "arcs"), None
    for tau, family in _F150.items():
        places = doubling.meeting(doubling.init(arcs, tau, SEED), tau, family)
        row = ledger.doubling_load(places, tau, 150).select(F.lit(tau).cast("long").alias("tau"), F.col("max_load").alias("load"), F.greatest(F.lit(1), F.ceil(F.col("max_load") / 150.0)).cast("long").alias("rounds"), "within")
        out = row if out is None else out.union(row)
    return out


@query("SELECT range::BIGINT AS bits, true AS nonnegative, true AS in_bound FROM range(12, 31, 6)")
def x10_rounding(spark, sf):
    """Error of the eighth power never negative, and within the recursive and the row-mass bound."""
    g, rows = _g(spark, sf, "nation_trade"), []
    order, w = sample.core(g)
    exact = np.linalg.matrix_power(w / w.sum(1, keepdims=True), 8)
    arcs = cut(g.arcs, "arcs")
    for bits in (12, 18, 24, 30):
        m = linalg.power_ladder(linalg.transition(arcs, bits), 3, bits, len(order))[3]
        e = accuracy.subtractive_error(exact, m, order, bits)
        rows.append((bits, e["min_entry"] >= -1e-12, e["max_entry"] <= accuracy.error_bound(len(order), 8, 2.0**-bits) and e["max_row_mass"] <= accuracy.row_mass_bound(len(order), 8, 2.0**-bits) + 1e-12))
    return spark.createDataFrame(rows, "bits long, nonnegative boolean, in_bound boolean")


@query("SELECT range::BIGINT AS bits, true AS in_bound FROM range(20, 31, 5)")
def x11_midpoint_law(spark, sf):
    """Total variation of a middle's law under rounding, within 2 beta n^(c+1) where pairs are not rare."""
    _, w = sample.core(_g(spark, sf, "nation_trade_w"))
    n, p = len(w), w / w.sum(1, keepdims=True)
    half, rows = p @ p, []
    for bits in (20, 25, 30):
        off = accuracy.midpoint_tv(half, np.floor(half * 2.0**bits) / 2.0**bits)
        weight = half @ half
        c = -math.log(weight[weight > 0].min()) / math.log(n) + 1e-9
        rows.append((bits, bool(np.nanmax(off) <= accuracy.midpoint_bound(n, 2.0**-bits, c))))
    return spark.createDataFrame(rows, "bits long, in_bound boolean")


@query("SELECT 'schur' AS what, true AS close UNION ALL SELECT 'shortcut', true")
def x12_schur_and_shortcut(spark, sf):
    """Absorbing chain in frames beside the linear solves, on every second vertex."""
    g, keep, q = _shortcut(spark, sf, 8)
    order, w = sample.core(g)
    kept = [k for k, v in enumerate(order) if v % 2 == 0]
    got = linalg.dense(derived.schur_transition(q, derived.enter_matrix(g.arcs, keep, BITS), keep, BITS), [order[k] for k in kept], float(ONE))
    s = derived.schur_dense(w, kept)
    at = linalg.dense(q, order, float(ONE))
    return spark.createDataFrame([("schur", bool(np.abs(got - s / s.sum(1, keepdims=True)).max() < 1e-4)), ("shortcut", bool(np.abs(at - derived.shortcut_dense(w, kept)).max() < 1e-2))], "what string, close boolean")


@query("SELECT true AS same")
def x13_filtered_walk(spark, sf):
    """Plain walks with all vertices outside a set left out move like the derived graph (chi-square)."""
    walk = _stepwise(spark, sf, _V, 400, 24)
    w = Window.partitionBy("sample_id").orderBy("pos")  # 25 rows a sample
    inside = walk.where("vertex % 2 = 0").withColumn("next", F.lead("vertex").over(w))
    # returns to the same vertex are no moves of the derived graph; the last 12 steps only end moves begun before
    moves = inside.where("next IS NOT NULL AND next <> vertex AND pos <= 12").groupBy(F.col("vertex").alias("i"), F.col("next").alias("j")).agg(F.count(F.lit(1)).alias("n"))
    g, keep, q = _shortcut(spark, sf, 8)
    t = derived.schur_transition(q, derived.enter_matrix(g.arcs, keep, BITS), keep, BITS)
    return accuracy.same_counts(moves, t.select("i", "j", (F.col("x") / float(ONE)).alias("share"))).select("same")


@query("SELECT true AS same_cut, true AS few_probes")
def x14_probes(spark, sf):
    """The binary search finds the window's cut with about the log of the filled places in probes."""
    walk = _walks(spark, sf, _V, 1, 6)[1]
    found, probes = truncate.search(walk, 5)
    want = topdown.cut_position(walk, 5).first()
    return spark.createDataFrame([(want is None or want.cut == found, probes <= math.log2(walk.count()) + 2)], "same_cut boolean, few_probes boolean")


@query(f"WITH {_walk_sql(_V, 200)} SELECT s AS sample_id, count(*)::BIGINT AS sequence_words, 2 * count(DISTINCT vertex)::BIGINT AS multiset_words FROM d1 GROUP BY s")
def x15_words(spark, sf):
    """Words to send all middles in order, and as vertex and count."""
    mids = _placed_mids(spark, sf, 200)[2]
    sequence = mids.groupBy("sample_id").agg(F.count(F.lit(1)).alias("sequence_words"))
    return sequence.join(matching.multiset(mids).groupBy("sample_id").agg((2 * F.count(F.lit(1))).alias("multiset_words")), "sample_id")


@query(f"WITH {_stepwise_sql('nation_trade', 60, 25)} SELECT s AS sample_id, count(DISTINCT vertex)::BIGINT AS visited, count(DISTINCT vertex) >= floor(pow(25, 1 / 3.0)) AS above FROM w1 GROUP BY s")
def x16_linear_walk(spark, sf):
    """Vertices that a walk of n steps visits: at least the cube root of n."""
    seen = _stepwise(spark, sf, "nation_trade", 60, 25).groupBy("sample_id").agg(F.count_distinct("vertex").alias("visited"))
    return seen.withColumn("above", F.col("visited") >= int(25 ** (1 / 3)))


@query(" UNION ALL ".join(f"SELECT '{v}' AS graph, true AS below_classical, true AS near_linear FROM (SELECT 1)" for v in ("nation_trade", "user_bucket", "user_seq")))
def x9_cover_classes(spark, sf):
    """Cover time below 2 m (n - 1), and of order n log n on the dense views (within eight times)."""
    rows = []
    for v in ("nation_trade", "user_bucket", "user_seq"):
        g = Graph(cut(VIEWS[v](spark, sf), "edges"))
        n, m = g.vertices.count(), g.edges.count()
        mean = walks.quantiles(walks.cover_time(g, 40)).first().mean
        rows.append((v, mean <= 2 * m * (n - 1), mean <= 8 * n * math.log(n)))
    return spark.createDataFrame(rows, "graph string, below_classical boolean, near_linear boolean")


@query(f"WITH e AS ({VIEW_SQL['doc_line']}), r AS ({VIEW_SQL['page_host']}) SELECT 'page_host' AS graph, (SELECT count(*) FROM r)::BIGINT AS edges, true AS ok")
def x19_forest(spark, sf):
    """A forest of the page graph, valid in every component."""
    e = cut(VIEWS["page_host"](spark, sf), "edges")
    check = accuracy.validate_tree(sample.forest(Graph(e), SEED), e)
    return check.select(F.lit("page_host").alias("graph"), F.col("n_edges").alias("edges"), "ok")


__all__ = ["ORACLES", "QUERIES"]
