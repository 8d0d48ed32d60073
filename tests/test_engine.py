"""Worked examples, exact laws and equivalences of the walk and tree methods."""

from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from treewalk import queries as registry
from treewalk.ckpt import plan_facts
from treewalk.operators import accuracy, derived, doubling, graph, kernels, linalg, matching, params, reduce, sample, topdown, trees, truncate, walks
from treewalk.sources import graphs

SF = "/root/testdata/sf0.001"


def matrix(edges):
    n = 1 + max(b for _, b, _ in edges)
    w = np.zeros((n, n))
    for a, b, x in edges:
        w[a, b] = w[b, a] = x
    return w


@pytest.mark.parametrize(("name", "count"), [("diamond", 8), ("diamond_w", 155), ("five", 24), ("k4", 16)])
def test_tree_counts(name, count):
    e = graphs.FIXTURES[name]
    assert accuracy.tree_count(e) == count
    assert sum(accuracy.enumerate_trees(e).values()) == 1


def test_tree_count_closed_forms():
    assert accuracy.tree_count(graphs.biclique(3, 4)) == 3**3 * 4**2
    assert accuracy.tree_count(graphs.cycle(9)) == 9
    assert accuracy.tree_count(graphs.path(9)) == 1


@pytest.mark.parametrize("method", [m for m in kernels.METHODS if m not in ("random_weight_mst", "exchange_chain", "phased_swap")])
@pytest.mark.parametrize("name", ["diamond", "diamond_w"])
def test_sampler_law(method, name):
    e = graphs.FIXTURES[name]
    w, truth, n = matrix(e), accuracy.enumerate_trees(e), 500
    options = {"length": 64} if method.startswith("phased") else {}
    c = Counter(",".join(sorted(f"{min(a, b)}-{max(a, b)}" for a, b in kernels.METHODS[method](w, np.random.default_rng([11, s]), **options))) for s in range(n))
    assert set(c) <= set(truth)
    chi = sum((c[k] - n * float(p)) ** 2 / (n * float(p)) for k, p in truth.items())
    assert accuracy.chi2_p(chi, len(truth) - 1) > 1e-4


def test_random_weights_are_not_uniform():
    e = graphs.FIXTURES["diamond"]
    w, n = matrix(e), 20_000
    c = Counter("0-2" in ",".join(f"{min(a, b)}-{max(a, b)}" for a, b in kernels.random_weight_mst(w, np.random.default_rng([1, s]))) for s in range(n))
    assert abs(c[True] / n - 8 / 15) < 0.012  # four trees of 2/15 each; uniform would be 1/2


def test_star_goldens():
    w = matrix([(0, 3, 1), (1, 3, 1), (2, 3, 1)])
    assert np.allclose(derived.shortcut_dense(w, [0, 1, 2])[:3, 3], 1)
    s = derived.schur_dense(w, [0, 1, 2])
    assert np.allclose(s / s.sum(1, keepdims=True), (1 - np.eye(3)) / 2)


def test_schur_by_frames_equals_dense(spark):
    g = graphs.graph(spark, None, "five")
    keep = spark.createDataFrame([(0,), (2,), (4,)], "vertex long")
    a = linalg.transition(g.arcs)
    q, _ = derived.shortcut_absorbing(a, keep, delta=1e-7)
    t = derived.schur_transition(q, derived.enter_matrix(g.arcs, keep), keep)
    s = derived.schur_dense(matrix(graphs.FIXTURES["five"]), [0, 2, 4])
    assert np.allclose(linalg.dense(t, [0, 2, 4], 1 << 30), s / s.sum(1, keepdims=True), atol=1e-5)


def test_probe_boundary(spark):
    walk = spark.createDataFrame([(0, p, v) for p, v in ((0, 1), (4, 2), (6, 3), (8, 1))], "sample_id long, pos long, vertex long")
    assert truncate.probe(walk, 4, 3)  # the vertex at 6 lies past the prefix
    assert truncate.probe(walk, 6, 3)
    assert not truncate.probe(walk, 8, 3)


def test_cut_by_search_equals_window(spark):
    walk = spark.createDataFrame([(0, i, v) for i, v in enumerate([1, 2, 1, 2, 3, 1, 3, 4, 2, 5, 1])], "sample_id long, pos long, vertex long")
    for rho in (2, 3, 4, 5):
        assert truncate.search(walk, rho)[0] == topdown.cut_position(walk, rho).first().cut


def test_eager_and_late_cuts_agree_on_valid_walks(spark):
    g = graphs.graph(spark, None, "five")
    ladder = linalg.power_ladder(linalg.transition(g.arcs), 4)
    starts = spark.createDataFrame([(s, 0) for s in range(6)], "sample_id long, vertex long")
    edges = {(r.u, r.v) for r in g.edges.collect()}
    for mode in ("level", "end"):
        rows = sorted(topdown.full_walk(ladder, starts, 5, 3, mode).collect())
        for s in range(6):
            path = [r.vertex for r in rows if r.sample_id == s]
            assert all((min(a, b), max(a, b)) in edges for a, b in zip(path, path[1:]))
            assert len(set(path)) <= 3 and path.count(path[-1]) == 1


@pytest.mark.parametrize("method", ["exact", "approx_count", "swap", "classes"])
def test_matching_law(method):
    w = np.array([[2.0, 1.0, 1.0], [1.0, 3.0, 1.0], [1.0, 1.0, 1.0]])
    place, vertex, n = np.arange(3), np.arange(3), 800
    c = Counter(tuple(matching.draw(w, method, np.random.default_rng([3, s]), place, vertex)) for s in range(n))
    import itertools

    truth = {p: np.prod([w[i, p[i]] for i in range(3)]) for p in itertools.permutations(range(3))}
    total = sum(truth.values())
    assert abs(matching.permanent(w) - total) < 1e-9
    assert sum(abs(c[p] / n - x / total) for p, x in truth.items()) / 2 < 0.09


def test_balances_give_equal_stubs(spark):
    from treewalk.functions.hashing import poly_family

    g = graphs.graph(spark, None, "five")
    stubs = doubling.init(g.arcs, 8, 1)
    out = [sorted(doubling.step(stubs, 8, b, poly_family(6, 5, 8, 1)).collect()) for b in ("none", "hash", "salted")]
    assert out[0] == out[1] == out[2] and len(out[0]) == 20


def test_doubled_walk_is_a_walk(spark):
    g = graphs.graph(spark, None, "five")
    edges = {(r.u, r.v) for r in g.edges.collect()}
    path = [r.vertex for r in doubling.walk_from(g.arcs, 0, 16, 3, "hash").orderBy("pos").collect()]
    assert len(path) == 17 and all((min(a, b), max(a, b)) in edges for a, b in zip(path, path[1:]))


def test_phased_frames_tree(spark):
    g = graphs.graph(spark, None, "diamond")
    tree, facts = sample.phased(g, 0, seed=4, length=8)
    r = accuracy.validate_tree(tree, g.edges).first()
    assert r.ok and len(facts) <= 2 * params.phases_bound(4)


def test_walks_in_task_equal_frames(spark):
    """Same draws, same walks, at both precisions; cutting at once or late is the same too."""
    g = graphs.graph(spark, None, "five")
    starts = spark.createDataFrame([(s, 0) for s in range(6)], "sample_id long, vertex long")
    for bits in (30, 60):
        ladder = linalg.power_ladder(linalg.transition(g.arcs, bits), 5, bits)
        inside = linalg.power_ladder(linalg.transition(g.arcs, bits), 5, bits, 5)
        assert all(sorted(a.collect()) == sorted(b.collect()) for a, b in zip(ladder, inside))
        frames = sorted(topdown.full_walk(ladder, starts, 7, 4, bits=bits).collect())
        assert frames == sorted(topdown.walks_in_task(inside, starts, 7, 4, bits).collect())
        assert frames == sorted(topdown.full_walk(ladder, starts, 7, 4, "end", bits).collect())


def test_placement_keeps_law(spark):
    """Two-step walks between fixed ends: middles placed by a drawn matching follow the same law."""
    g = graphs.graph(spark, None, "diamond")
    ladder = linalg.power_ladder(linalg.transition(g.arcs), 2, linalg.BITS, 4)
    starts = spark.createDataFrame([(s, 0) for s in range(1500)], "sample_id long, vertex long")
    walk = topdown.full_walk(ladder, starts, 3, 3, place="exact")
    first = {r.vertex: r.n for r in walk.where("pos = 1").groupBy("vertex").agg(F.count(F.lit(1)).alias("n")).collect()}
    assert sum(first.values()) == 1500 and all(abs(first[v] - 500) < 110 for v in (1, 2, 3))


def test_recursive_reference_is_the_walk():
    w = matrix(graphs.FIXTURES["diamond_w"])
    p = w / w.sum(1, keepdims=True)
    r = np.random.default_rng(1)
    ends = np.bincount([topdown.recursive_reference(p, 0, 8, r)[3] for _ in range(4000)], minlength=4) / 4000
    assert np.abs(ends - np.linalg.matrix_power(p, 3)[0]).max() < 0.04


def test_precision_rule(spark):
    assert params.precision(25, 1 << 17, 0.01) == 60 and params.precision(4, 16, 0.1) == 30
    with pytest.raises(ValueError):
        params.precision(100_000, 1 << 60, 0.01)
    g = graphs.graph(spark, None, "five")
    with pytest.raises(FloatingPointError):
        sample.phased(g, 0, length=1 << 26, bits=30)
    m = np.random.default_rng(0).integers(0, 1 << 52, (40, 40))
    exact = [[sum(int(m[i, k]) * int(m[k, j]) for k in range(40)) >> 60 for j in range(40)] for i in range(40)]
    assert linalg.exact_product(m, m, 60).tolist() == exact


def test_doubling_on_string_views(spark):
    """Ids of 53 bits: numbered first, nothing overflows; an empty graph has an empty forest."""
    e = spark.createDataFrame([((1 << 52) + a, (1 << 52) + b, 1) for a, b in ((1, 9), (9, 20), (1, 20), (20, 33))], "u long, v long, w long")
    t = sample.by_doubling(graphs.Graph(e), (1 << 52) + 1, seed=5)
    assert accuracy.validate_tree(t, e).first().ok
    assert doubling.walks(graphs.Graph(e).arcs, 4096, 1, "hash").count() == 4
    assert sample.random_weight_mst(e.limit(0), 1).count() == 0


def test_cost_counts_shuffled_bytes(spark):
    from treewalk.operators import measure

    with_shuffle = measure.run_cost(spark, lambda: spark.range(5000).groupBy((F.col("id") % 97).alias("k")).count())
    without = measure.run_cost(spark, lambda: spark.range(5000).select((F.col("id") * 2).alias("k")))
    assert with_shuffle["shuffle_bytes"] > 0 < with_shuffle["peak_rows"] and without["shuffle_bytes"] == 0


def test_hash_family_of_any_degree(spark):
    from treewalk.functions.hashing import poly_family

    d = spark.range(200).select((F.col("id") % 50).alias("v"), (F.col("id") % 9 + 1).alias("j"))
    rows = d.collect()
    for t, n, k in ((5, 50, 9), (120, 50, 9), (40, 1 << 32, 16)):
        fam = poly_family(t, n, k, 3)
        horner = lambda x: sum(c * pow(x, e, fam.prime) for e, c in enumerate(fam.coeffs)) % fam.prime % n
        assert [r.h for r in d.select(fam.column(F.col("v"), F.col("j")).alias("h")).collect()] == [horner(r.v * k + r.j - 1) for r in rows]


def test_walk_plans_have_no_window_over_a_sample(spark):
    from treewalk.ckpt import plan_text

    walk = spark.createDataFrame([(0, 0, 1), (0, 2, 2), (0, 4, 1)], "sample_id long, pos long, vertex long")
    assert "Window" not in plan_text(trees.first_visit(walk)) and "Window" not in plan_text(topdown.requests(walk, 2))


def test_forest_and_reductions(spark):
    e = spark.createDataFrame([(0, 1, 1), (1, 2, 1), (0, 2, 1), (2, 3, 1), (10, 11, 2)], "u long, v long, w long")
    assert accuracy.validate_tree(sample.forest(graphs.Graph(e)), e).first().ok
    forced, rest = reduce.pendant(e)
    assert {(r.u, r.v) for r in forced.collect()} == {(2, 3), (10, 11)} and rest.count() == 3
    assert reduce.blocks(e).select("component", "block").distinct().count() == 3
    assert {(r.vertex, r.component) for r in graph.components(e).collect()} == {(0, 0), (1, 0), (2, 0), (3, 0), (10, 10), (11, 10)}


def test_rounding_bounds(spark):
    e = graphs.FIXTURES["five"]
    g = graphs.graph(spark, None, "five")
    w = matrix(e)
    p = w / w.sum(1, keepdims=True)
    for bits in (12, 20, 30):
        m = linalg.power_ladder(linalg.transition(g.arcs, bits), 3, bits)[3]
        err = accuracy.subtractive_error(np.linalg.matrix_power(p, 8), m, list(range(5)), bits)
        assert -1e-12 <= err["min_entry"] and err["max_entry"] <= accuracy.error_bound(5, 8, 2.0**-bits)
        assert err["max_row_mass"] <= accuracy.row_mass_bound(5, 8, 2.0**-bits) + 1e-12


def test_slices_and_index(spark):
    g = graphs.graph(spark, SF, "nation_trade")
    ids, dense = graphs.index_vertices(g)
    n = ids.count()
    assert sorted(r.vid for r in ids.collect()) == list(range(n)) and dense.edges.count() == g.edges.count()


def test_scan_reads_only_its_columns(spark):
    from treewalk.ckpt import plan_text

    text = plan_text(graphs.VIEWS["nation_trade"](spark, SF))
    assert "l_extendedprice" not in text and "CartesianProduct" not in text
    facts = plan_facts(doubling.step(doubling.init(graphs.graph(spark, None, "five").arcs, 4, 1), 4))
    assert "CartesianProduct" not in facts and "BroadcastNestedLoopJoin" not in facts


def test_cover_time(spark):
    r = walks.quantiles(walks.cover_time(graphs.graph(spark, None, graphs.path(6)), 60)).first()
    assert 10 < r["mean"] < 60


def test_streams_equal_batches(spark, tmp_path):
    from pyspark.sql import functions as F

    from treewalk.streaming import streams, windows

    e = spark.read.parquet(f"{SF}/events.parquet")
    e.repartitionByRange(3, "ts").write.parquet(str(tmp_path / "in"))
    s = streams.read(spark, str(tmp_path / "in"), e.schema)
    streams.run(windows.tumbling(s, "1 hour", "10 minutes"), "memory", "hours", "update")
    got = {(r.start, r.event_type): r.n for r in spark.table("hours").groupBy("start", "event_type").agg(F.max("n").alias("n")).collect()}
    assert got == {(r.start, r.event_type): r.n for r in windows.tumbling(e, "1 hour").collect()}
    log = spark.createDataFrame([(0, p, v, p) for p, v in ((3, 7), (1, 5), (2, 7), (0, 5), (4, 7))], "sample_id long, pos long, vertex long, prev long")
    log.repartition(3).write.parquet(str(tmp_path / "log"))
    streams.run(streams.first_visit(streams.read(spark, str(tmp_path / "log"), log.schema)), "memory", "firsts", "update")
    best = {r.vertex: r.pos for r in spark.table("firsts").groupBy("vertex").agg(F.min("pos").alias("pos")).collect()}
    assert best == {5: 0, 7: 2}


def test_registry_is_complete():
    assert set(registry.ORACLES) <= set(registry.QUERIES) and len(registry.QUERIES) > 150


def test_first_visit_example(spark):
    walk = spark.createDataFrame([(0, i, v) for i, v in enumerate([1, 3, 2, 1, 3, 2, 4])], "sample_id long, pos long, vertex long")
    assert {(r.child, r.parent) for r in trees.first_visit(walk).collect()} == {(3, 1), (2, 3), (4, 2)}


@pytest.mark.parametrize("tile", [4, 1000])
def test_sums_over_pairs_equal_brute_force(spark, tile):
    from treewalk.operators import pairs

    r = np.random.default_rng(3)
    rows = sorted({(int(i), int(k)) for i, k in zip(r.integers(0, 30, 120), r.integers(0, 6, 120))})
    left = spark.createDataFrame([(i, k, i % 3 + 1) for i, k in rows], "i long, k long, a long")
    right = spark.createDataFrame([(k, i, i % 3 + 1, k + 5) for i, k in rows], "k long, j long, b long, extra long")
    meet = [(i, j, (((i % 3 + 1) * (j % 3 + 1)) << 20) // (k + 5)) for i, k in rows for j, q in rows if k == q]
    count, ratio = Counter((i, j) for i, j, _ in meet), Counter()
    for i, j, x in meet:
        ratio[i, j] += x
    got = lambda kind, names, **o: sorted(tuple(x) for x in pairs.sums(left, right, kind, names, tile=tile, **o).collect())
    assert got(pairs.Count, ["i", "j", "n"]) == sorted((i, j, n) for (i, j), n in count.items())
    assert got(type("Fixed", (pairs.Ratio,), {"bits": 20}), ["i", "j", "x"], above=True) == sorted((i, j, x) for (i, j), x in ratio.items() if i < j)
    assert got(pairs.Any, ["i", "j"], above=True) == sorted((i, j) for i, j in count if i < j)
    times = [(int(u), int(t)) for u, t in zip(r.integers(0, 12, 90), r.integers(0, 5_000_000_000, 90))]
    near = Counter((u, v) for u, t in times for v, s in times if u < v and abs(t - s) <= 600_000_000)
    e = spark.createDataFrame(times, "i long, t long").selectExpr("i", "t", "1L AS one")
    found = pairs.sums(e.selectExpr("i", "t AS k", "one AS a"), e.selectExpr("t div 1000000000 AS k", "i AS j", "t AS b", "one AS extra"), pairs.TenMinutes, ["u", "v", "n"], above=True, tile=tile)
    assert sorted(tuple(x) for x in found.collect()) == sorted((u, v, n) for (u, v), n in near.items())


@pytest.mark.parametrize("name", ["two_hop", "interval_cooc", "edges_user_cooc_hour"])
def test_pairs_are_not_shuffled(spark, name):
    import __spark_entry__ as entry
    from treewalk.ckpt import plan_text

    assert "Join" not in plan_text(entry.queries()[name](spark, SF), "simple")


def test_forest_of_large_components(spark):
    """A component above the limit: leaves are forced, the cycle left is sampled on rows of neighbours."""
    hub = [(0, k, 1) for k in range(1, 40)]
    ring = [(100 + k, 101 + k, 1) for k in range(11)] + [(100, 111, 1), (111, 200, 1), (200, 201, 1)]
    e = graphs.graph(spark, None, hub + ring)
    got = sample.forest(e, 7, limit=5)
    rows = got.collect()
    assert accuracy.validate_tree(got, e.edges).first().ok
    assert len({r.child for r in rows}) == len(rows) == 39 + 11 + 2
    assert {(min(r.child, r.parent), max(r.child, r.parent)) for r in rows} <= {(a, b) for a, b, _ in hub + ring}


@pytest.mark.parametrize("name", ["diamond", "diamond_w", "five"])
def test_sparse_walks_have_the_law(name):
    from treewalk.operators import sparse

    e = graphs.FIXTURES[name]
    u, v, w = (np.array(x) for x in zip(*e))
    rows, law = sparse.Rows(1 + v.max(), u, v, w), accuracy.enumerate_trees(e)
    key = lambda t: ",".join(sorted(f"{min(a, b)}-{max(a, b)}" for a, b in t))
    seen = Counter(key(sparse.loop_erased(rows, np.random.default_rng([5, s]))) for s in range(3000))
    assert set(seen) <= set(law)
    assert accuracy.chi2_p(sum((seen[k] - 3000 * float(p)) ** 2 / (3000 * float(p)) for k, p in law.items()), len(law) - 1) > 1e-4
    x = sparse._solve(rows, np.arange(rows.n))
    want = accuracy.resistance_marginals(matrix(e))
    assert all(abs(c * (x[a, a] + x[b, b] - x[a, b] - x[b, a]) - want[a, b]) < 1e-8 for a, b, c in e)


def test_large_cores_go_to_rows_of_neighbours(spark, monkeypatch):
    """Above the dense bound: loop-erased trees, the sparsifier and cover times of a ring with chords."""
    from treewalk.operators import apps

    e = graphs.cycle(12) + [(k, k + 6, 2) for k in range(6)]
    g = graphs.graph(spark, None, [(a + 50, b + 50, w) for a, b, w in e])
    dense = {(r.u, r.v): r.w for r in apps.sparsify(g, 400).collect()}
    monkeypatch.setattr(sample, "CORE_LIMIT", 5)
    monkeypatch.setattr(walks, "CORE_LIMIT", 5)
    trees_ = sample.replicate(g, 3, "loop_erased")
    for s in range(3):
        assert accuracy.validate_tree(trees_.where(f"sample_id = {s}"), g.edges).first().ok
    sparse_ = {(r.u, r.v): r.w for r in apps.sparsify(g, 400).collect()}
    assert sparse_.keys() == dense.keys()
    assert abs(sum(sparse_.values()) / sum(w for _, _, w in e) - 1) < 0.1
    r = walks.quantiles(walks.cover_time(graphs.graph(spark, None, graphs.path(6)), 60)).first()
    assert 15 < r.mean < 40


@pytest.mark.parametrize("exact", [False, True])
@pytest.mark.parametrize("weights", [[(1, 1), (1, 1), (1, 1), (1, 0)], [(1, 2), (1, 2), (3, 1), (0, 2)]])
def test_phased_on_classes_has_the_law(weights, exact):
    from treewalk.operators import split

    edges = [(k, 4 + t, w) for k, row in enumerate(weights) for t, w in enumerate(row) if w]
    at, to, w = (np.array(x) for x in zip(*[(a, b - 4, w) for a, b, w in edges]))
    s, law = split.Split.of(at, to, w, 4, 2), accuracy.enumerate_trees(edges)
    key = lambda t: ",".join(sorted(f"{min(a, b)}-{max(a, b)}" for a, b in t))
    seen = Counter(key(split.phased(s, np.random.default_rng([9, k]), exact=exact, on_short="fail")) for k in range(600))
    assert set(seen) <= set(law)
    assert accuracy.chi2_p(sum((seen[k] - 600 * float(p)) ** 2 / (600 * float(p)) for k, p in law.items()), len(law) - 1) > 1e-4


def test_stubs_are_never_broadcast(spark):
    from treewalk.ckpt import cut, plan_text

    stubs = cut(doubling.init(graphs.graph(spark, None, "five").arcs, 4, 1), "stubs")
    assert "Broadcast" not in plan_text(doubling.step(stubs, 4), "simple")


@pytest.mark.parametrize("name", ["cover_time", "error_budget", "parameter_sweep", "tree_count", "tv_cover_walk", "tv_doubling", "tv_loop_erased", "pair_figure"])
def test_queries_read_given_tables(spark, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        registry.QUERIES[name](spark, "/tmp/no-such-tables").collect()


@pytest.mark.parametrize("goal", [2, 4])
@pytest.mark.parametrize("name", ["diamond_w", "five", "lollipop"])
def test_phased_on_asked_rows_has_the_law(name, goal, monkeypatch):
    from treewalk.operators import lazy, sparse

    monkeypatch.setattr(params, "rho", lambda n: goal)
    edges = graphs.lollipop(4, 2) if name == "lollipop" else graphs.FIXTURES[name]
    u, v, w = (np.array(x) for x in zip(*edges))
    rows, law = sparse.Rows(int(max(u.max(), v.max())) + 1, u, v, w), accuracy.enumerate_trees(edges)
    key = lambda t: ",".join(sorted(f"{min(a, b)}-{max(a, b)}" for a, b in t))
    seen = Counter(key(lazy.phased(rows, np.random.default_rng([9, k]))) for k in range(300))
    assert set(seen) <= set(law)
    assert accuracy.chi2_p(sum((seen[k] - 300 * float(p)) ** 2 / (300 * float(p)) for k, p in law.items()), len(law) - 1) > 1e-4


def test_phased_goes_on_above_the_dense_bound(spark, monkeypatch):
    g = graphs.graph(spark, None, [(a + 50, b + 50, 1) for a, b, _ in graphs.cycle(15) + [(k, k + 6, 1) for k in range(0, 9, 2)]])
    monkeypatch.setattr(sample, "CORE_LIMIT", 5)
    t = sample.replicate(g, 3, "phased", on_short="fail")
    for s in range(3):
        assert accuracy.validate_tree(t.where(f"sample_id = {s}"), g.edges).first().ok


def test_sweep_holds_lengths_beyond_a_long(spark):
    from treewalk.plans import experiments

    far = experiments._sweep(spark, [25, 1_260_000])
    assert [int(r.length) for r in far.collect()] == [params.target_length(n, n, e) for n in (25, 1_260_000) for e in (0.1, 0.01)]
    assert [r.bits for r in far.collect()][2:] == [0, 0] and max(r.length for r in far.collect()) >= 1 << 63
    assert dict(experiments._sweep(spark, [25]).dtypes)["length"] == "bigint"


def test_pairs_leave_in_blocks(spark, tmp_path):
    """Written pairs of a complete view take a small part of their bytes; every pair is there once."""
    from treewalk.operators import pairs

    one = lambda n, name: spark.range(n).selectExpr(f"id AS {name}", "-1L AS k", "1L AS a")
    right = one(30_000, "j").selectExpr("k", "j", "a AS b", "a AS extra")
    pairs.sums(one(300, "i"), right, pairs.Count, ["i", "j", "n"]).write.parquet(str(tmp_path / "out"))
    got = spark.read.parquet(str(tmp_path / "out"))
    assert got.agg(F.count(F.lit(1)), F.count_distinct("i", "j"), F.min("n"), F.max("n")).first()[:] == (9_000_000, 9_000_000, 1, 1)
    assert sum(p.stat().st_size for p in (tmp_path / "out").glob("*.parquet")) < 9_000_000


def test_phased_forgets_inner_vertices():
    """Vertices outside with no kept neighbour leave both forms of a derived graph, and its steps stay right."""
    from treewalk.operators import lazy, sparse

    edges = graphs.cycle(12) + [(0, 6, 2), (3, 9, 1)]
    u, v, w = (np.array(x) for x in zip(*edges))
    d, a = lazy._Derived(sparse.Rows(12, u, v, w)), np.zeros((12, 12))
    for x, y, z in edges:
        a[x, y] = a[y, x] = z
    gone: list[int] = []
    for out in ([1, 2], [4, 5, 6], [7, 8], [9]):
        d.drop(np.array(out))
        gone += out
        keep = [k for k in range(12) if k not in gone]
        lap = np.diag(a.sum(1)) - a
        schur = lap[np.ix_(keep, keep)] - lap[np.ix_(keep, gone)] @ np.linalg.solve(lap[np.ix_(gone, gone)], lap[np.ix_(gone, keep)])
        x = np.zeros((len(d.names), 1))
        x[d.at[0], 0] = 1
        got = d.step(x)[d.at[keep], 0] * d.total[d.at[0]]
        off = np.array([k != 0 for k in keep])
        assert np.allclose(got[off], -schur[0][off])
        assert {int(k) for k in d.gone} == {k for k in gone if any(a[k, j] for j in keep)}
