"""Measured figures of the experiments: one JSON line each.

    python measurements.py SF_DIR [names]

Seconds, bytes shuffled and rows of the fullest stage come from Spark's own stage records; rounds from the
ledger, charged from loads that were counted.
"""

from __future__ import annotations

import json
import math
import os
import sys

os.environ.setdefault("OMP_NUM_THREADS", "1")
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from treewalk.ckpt import cut
from treewalk.functions import hashing
from treewalk.operators import accuracy, doubling, kernels, ledger, linalg, measure, params, sample, walks
from treewalk.sources.graphs import VIEWS, Graph, index_vertices

ALPHAS = (0.157, 1 / 3)


def _graph(spark, sf, view) -> Graph:
    return index_vertices(Graph(cut(VIEWS[view](spark, sf), "edges")))[1]


def x3(spark, sf):
    """Main sampler in frames: facts and rounds charged, by alpha."""
    for view in ("nation_trade", "brand_nation"):
        g = _graph(spark, sf, view)
        n, found = g.vertices.count(), {}
        cost = measure.run_cost(spark, lambda: found.setdefault("tree", sample.phased(g, 0, on_short="fail")) and found["tree"][0])
        tree, facts = found["tree"]
        for alpha in ALPHAS:
            book = ledger.Ledger(view, n)
            book.charge_phases(facts, 60, alpha)
            rounds = book.frame(spark).agg(F.sum("rounds")).first()[0]
            yield {"graph": view, "n": n, "alpha": round(alpha, 3), "phases": len(facts), "bound": params.phases_bound(n), "levels": max(f["levels"] for f in facts), "lost": max(f["lost"] for f in facts), "largest_pairs": max(f["pairs"] for f in facts), "rounds": rounds, "valid": accuracy.validate_tree(tree, g.edges).first().ok, **cost}


def x4(spark, sf):
    """Phases and seconds of the approximate and the exact kernel."""
    import time

    import numpy as np

    for view in ("nation_trade", "user_type", "user_seq"):
        _, w = sample.core(_graph(spark, sf, view))
        for exact in (False, True):
            facts, began = {}, time.time()
            kernels.phased(w, np.random.default_rng(1), facts=facts, exact=exact)
            yield {"graph": view, "n": len(w), "exact": exact, "phases": facts["phases"], "seconds": round(time.time() - began, 2)}


def x5(spark, sf):
    """Largest load of one place in the first iteration, plain and balanced, beside the bound."""
    for view in ("user_type", "user_bucket", "nation_trade", "user_seq", "page_host"):
        g = _graph(spark, sf, view)
        arcs, n = cut(g.arcs, "arcs"), g.vertices.count()
        for tau in (16, 64, 256, 1024):
            stubs = cut(doubling.init(arcs, tau, 1), "stubs")
            row = {"graph": view, "n": n, "tau": tau, "plain": doubling.loads(doubling.plain_meeting(stubs, tau)).agg(F.max("n")).first()[0]}
            for c in (1, 2):
                family = hashing.poly_family(hashing.independence(n, c), n, tau, 7)
                row[f"balanced_c{c}"] = doubling.loads(doubling.meeting(stubs, tau, family)).agg(F.max("n")).first()[0]
            yield row | {"bound_c1": round(16 * tau * math.log2(n)), "rounds_plain": ledger.rounds_for(row["plain"], n), "rounds_balanced": ledger.rounds_for(row["balanced_c1"], n)}


def x6(spark, sf):
    """Rounds of a whole balanced walk below and above n / log n, charged from each iteration's load."""
    g = _graph(spark, sf, "user_seq")
    arcs, n = cut(g.arcs, "arcs"), g.vertices.count()
    for tau in (4, 16, 64, 256):
        k, rounds, stubs = tau, 0, cut(doubling.init(arcs, tau, 1), "stubs")
        while k > 1:
            family = hashing.poly_family(hashing.independence(n), n, k, k)
            rounds += ledger.rounds_for(doubling.loads(doubling.meeting(stubs, k, family)).agg(F.max("n")).first()[0], n)
            stubs, k = cut(doubling.step(stubs, k), "stubs"), k // 2
        yield {"graph": "user_seq", "n": n, "n_over_log": round(n / math.log2(n), 1), "tau": tau, "rounds": rounds, "iterations": int(math.log2(tau))}


def x7(spark, sf):
    """Trees by doubled walks: cost, and the cover time that the length follows."""
    for view in ("nation_trade", "user_bucket", "user_seq"):
        g = _graph(spark, sf, view)
        n = g.vertices.count()
        mean = walks.quantiles(walks.cover_time(g, 40)).first().mean
        yield {"graph": view, "n": n, "cover_time": mean, "n_ln_n": round(n * math.log(n), 1), **measure.run_cost(spark, lambda: sample.by_doubling(g, 0, seed=3))}


def x20(spark, sf):
    """Cost of the table-wide steps on the large sparse views."""
    from treewalk.operators import derived, reduce

    for view in ("order_part", "supp_part"):
        g = Graph(cut(VIEWS[view](spark, sf), "edges"))
        yield {"graph": view, "step": "view", **measure.run_cost(spark, lambda: VIEWS[view](spark, sf))}
        yield {"graph": view, "step": "transition", **measure.run_cost(spark, lambda: linalg.transition(g.arcs))}
        yield {"graph": view, "step": "eliminate one side", **measure.run_cost(spark, lambda: derived.schur_bipartite(g.edges, keep_left=False))}
        yield {"graph": view, "step": "forced edges", **measure.run_cost(spark, lambda: reduce.pendant(g.edges)[0])}
        for balance in ("none", "salted"):
            yield {"graph": view, "step": f"walks of 8, {balance}", **measure.run_cost(spark, lambda: doubling.walks(g.arcs, 8, 1, balance))}


def main() -> None:
    sf, names = sys.argv[1], sys.argv[2:] or ["x3", "x4", "x5", "x6", "x7", "x20"]
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("OFF")
    for name in names:
        for row in globals()[name](spark, sf):
            print(json.dumps({"run": name, "sf": sf.rstrip("/").rsplit("sf", 1)[-1], **row}), flush=True)


if __name__ == "__main__":
    main()
