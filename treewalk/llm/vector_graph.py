"""Embedding near-duplicates by a robust-pruned flat graph.

1. Equal vectors are one class; only classes go on.
2. Centres are fitted on a bounded sample.  A class lives in the shard of its nearest centre and
   is copied to the next nearest one, so shards overlap.  Above ``MAX_SHARDS`` shards each has up to
   ``LEAVES`` centres of its own, fitted in tasks, and its leaves take the place of shards.  What is still
   above ``SLICE`` classes is cut into slices by hash.
3. In each slice a graph is built: nearest candidates, then robust pruning (a candidate goes if an
   already chosen neighbour is ``ALPHA`` times nearer to it), then reverse links.  The adjacency
   lists of a class from all its slices are united.
4. Search: every class is a query to each shard in which a neighbour can have its home.  The home
   of a neighbour is nearer to its centre than to any other, so a query that lies further than the
   angle of ``near`` behind the plane between two centres has no neighbour there; planes to the
   ``RIVALS`` centres nearest to the query are tried.  This bound loses nothing, but holds for the worst
   direction; in many dimensions nearly no neighbour lies there.  So ``calibrate`` takes the share of the
   bound that covers ``QUANTILE`` of partners at exactly ``near``, in directions of the data, and, with room
   to spare, every link within the sample.  ``link`` then audits a sample of queries by brute force
   against all rows, and searches again with the full bound where the recall is below ``WANTED``.
   Queries stream past the slice, which alone is held in memory.  In a slice each node lies within
   ``COVER`` of an entry that links to it.  The search starts from all entries that may, by the angles,
   own a neighbour, and expands over the nodes in range (and a little around it) until none is new,
   so it finds every neighbour in the slice, however large its group.  Cosines are in double
   precision, so every link reported is verified.
5. Only counts and a forest of links leave a slice; components follow from the forests.

The result carries the audited recall.  ``audit`` measures it anew on the rows whose id is divisible
by 20.

Defined cases: vectors that are null, zero, of a length other than the most common one, or
hold null or non-finite parts link with nothing and are their own component; repeated rows
link with each other; an empty table gives no rows; other columns are ignored; a null id
counts as a vector and keeps its null.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, parts
from .components import classes

NEAR, SLICE, MAX_SHARDS, LEAVES, SAMPLE = 0.9, 3000, 1024, 64, 20_000
AUDIT, WANTED, QUANTILE, ROOM = 256, 0.99, 0.95, 1.25
CANDIDATES, DEGREE, ALPHA, COVER, AROUND, RIVALS = 48, 24, 1.2, 0.8, 0.08, 8


def _unit(col: pa.Array) -> np.ndarray:
    x = pa.compute.list_flatten(col).to_numpy().astype(np.float64).reshape(len(col), -1)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def centres(x: np.ndarray, k: int, rounds: int = 8) -> np.ndarray:
    c = x[np.random.default_rng(0).permutation(len(x))[:k]]
    for _ in range(rounds):
        own = np.concatenate([(x[i : i + 4096] @ c.T).argmax(1) for i in range(0, len(x), 4096)])
        s = np.zeros_like(c)
        np.add.at(s, own, x)
        n = np.linalg.norm(s, axis=1, keepdims=True)
        c = np.where(n > 1e-12, s / np.maximum(n, 1e-12), c)
    return c


class Routes:
    """Which centres a query has to visit."""

    def __init__(self, c: np.ndarray, near: float, share: float = 1.0):
        self.c, self.reach = c, float(np.sqrt(1 - near**2)) if near > 0 else 1.0
        self.gap, self.share = np.sqrt(np.maximum(2 - 2 * c @ c.T, 1e-18)), share

    def need(self, s: np.ndarray, home: np.ndarray) -> np.ndarray:
        """Share of the bound at which queries with cosines ``s`` visit the centre ``home``."""
        at, worst = np.arange(len(s)), np.zeros(len(s))
        for rival in np.argsort(-s, axis=1, kind="stable")[:, :RIVALS].T:
            behind = (s[at, rival] - s[at, home]) / (self.reach * self.gap[rival, home])
            worst = np.maximum(worst, np.where(rival == home, 0, behind))
        return worst

    def visits(self, s: np.ndarray) -> np.ndarray:
        at, visit = np.arange(len(s)), np.ones(s.shape, bool)
        for rival in np.argsort(-s, axis=1, kind="stable")[:, :RIVALS].T:
            visit &= s[at, rival][:, None] - s <= self.share * self.reach * self.gap[rival] + 1e-7
        visit[at, s.argmax(1)] = True
        return visit


def calibrate(x: np.ndarray, c: np.ndarray, near: float) -> float:
    """Share of the lossless bound that keeps ``QUANTILE`` of the partners at ``near`` and, times ``ROOM``,
    all links within the sample ``x``.

    Partners are made from sampled vectors, turned towards and away from the sampled vectors next to
    them, so they lie where the data do.
    """
    if len(c) < 2 or len(x) < 3:
        return 1.0
    routes = Routes(c, near)
    pick = np.random.default_rng(1).permutation(len(x))
    q, others = x[pick[:1000]], x[pick[:4000]]
    s, need = q @ c.T, []
    t = q @ others.T
    t[t > 1 - 1e-9] = -2
    for j in np.argsort(-t, axis=1)[:, :4].T:
        side = others[j] - (others[j] * q).sum(1, keepdims=True) * q
        side /= np.maximum(np.linalg.norm(side, axis=1, keepdims=True), 1e-12)
        need += [routes.need(s, ((near * q + sign * routes.reach * side) @ c.T).argmax(1)) for sign in (1, -1)]
    share = float(np.quantile(np.concatenate(need), QUANTILE))
    home = np.concatenate([(x[i : i + 4096] @ c.T).argmax(1) for i in range(0, len(x), 4096)])
    for i in range(0, len(q), 100):
        a, b = np.nonzero(q[i : i + 100] @ x.T >= near)
        if len(a):
            share = max(share, ROOM * float(routes.need(s[i : i + 100][a], home[b]).max()))
    return min(1.0, share)


def build(x: np.ndarray) -> list[np.ndarray]:
    """Adjacency lists of a robust-pruned graph over unit vectors ``x``."""
    n = len(x)
    if n == 1:
        return [np.zeros(0, np.int64)]
    k = min(CANDIDATES, n - 1)
    links: list[list[int]] = [[] for _ in range(n)]
    for lo in range(0, n, 256):
        s = x[lo : lo + 256] @ x.T
        rows = np.arange(len(s))
        s[rows, lo + rows] = -2
        cand = np.argpartition(-s, k - 1, axis=1)[:, :k]
        order = np.argsort(-np.take_along_axis(s, cand, 1), axis=1, kind="stable")
        cand = np.take_along_axis(cand, order, 1)
        dist = 2 - 2 * np.take_along_axis(s, cand, 1)  # squared
        v = x[cand]
        between = 2 - 2 * np.einsum("nid,njd->nij", v, v)
        alive, chosen = np.ones_like(dist, bool), np.zeros_like(dist, bool)
        for _ in range(DEGREE):
            pick = alive.argmax(1)
            ok = alive[rows, pick]
            if not ok.any():
                break
            chosen[rows[ok], pick[ok]] = True
            covered = ALPHA**2 * between[rows, pick] <= dist
            alive &= ~(covered & ok[:, None])
            alive[rows, pick] = False
        for i in rows:
            links[lo + i] += cand[i, chosen[i]].tolist()
    for i in range(n):
        for j in links[i][:DEGREE]:
            if i not in links[j]:
                links[j].append(i)
    return [np.array(a, np.int64) for a in links]


def cells(x: np.ndarray) -> np.ndarray:
    """For each node an entry node within ``COVER`` in cosine; an entry has itself."""
    own, heads = np.full(len(x), -1), np.zeros(0, np.int64)
    for lo in range(0, len(x), 256):
        part = np.arange(lo, min(lo + 256, len(x)))
        if len(heads):
            s = x[part] @ x[heads].T
            best = s.argmax(1)
            ok = s[np.arange(len(part)), best] >= COVER
            own[part[ok]] = heads[best[ok]]
        rest = part[own[part] < 0]
        s = x[rest] @ x[rest].T >= COVER
        for i, node in enumerate(rest):
            if own[node] < 0:
                own[rest[s[i] & (own[rest] < 0)]] = node
                own[node] = node
        heads = np.concatenate([heads, rest[own[rest] == rest]])
    return own


class Searcher:
    """Range search over one slice: from the entries that can own a neighbour, then along the graph.

    An entry has links to all nodes of its cell.  A neighbour of a query lies within ``COVER`` of its
    entry, so by the angles its entry lies above a floor of the query: nothing is missed.
    """

    def __init__(self, x: np.ndarray, adjacency: list[np.ndarray], near: float):
        self.x, self.near = x, near
        own = cells(x)
        order = np.argsort(own, kind="stable")
        self.heads, first = np.unique(own[order], return_index=True)
        self.adj = list(adjacency)
        for head, cell in zip(self.heads.tolist(), np.split(order, first[1:])):
            self.adj[head] = np.concatenate([self.adj[head], cell])
        self.entries = x[self.heads]
        wide = np.arccos(near) + np.arccos(COVER)
        self.floor = float(np.cos(wide)) - 1e-9 if wide < np.pi else -2.0
        self.stamp, self.now, self.slot = np.zeros(len(x), np.int64), 0, np.zeros(len(x), np.int64)

    def _fresh(self, nodes: np.ndarray) -> np.ndarray:
        a = np.concatenate([self.adj[i] for i in nodes.tolist()])
        a = a[self.stamp[a] != self.now]
        at = np.arange(len(a))
        self.slot[a] = at
        a = a[self.slot[a] == at]  # each once
        self.stamp[a] = self.now
        return a

    def queries(self, q: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
        """``(row of q, nodes in range)`` for the rows that any entry is open to."""
        for lo in range(0, len(q), 512):
            s = q[lo : lo + 512] @ self.entries.T
            row, seed = np.nonzero(s >= self.floor)
            at, first = np.unique(row, return_index=True)
            for i, seeds in zip(at.tolist(), np.split(seed, first[1:])):
                yield lo + i, self._range(q[lo + i], self.heads[seeds], s[i, seeds])

    def _range(self, q: np.ndarray, ids: np.ndarray, cos: np.ndarray) -> np.ndarray:
        self.now += 1
        self.stamp[ids] = self.now
        done = np.zeros(len(ids), bool)
        go = np.arange(len(ids))
        while len(go):
            done[go] = True
            new = self._fresh(ids[go])
            ids, cos, done = np.concatenate([ids, new]), np.concatenate([cos, self.x[new] @ q]), np.concatenate([done, np.zeros(len(new), bool)])
            go = np.flatnonzero((cos >= self.near - AROUND) & ~done)
        return ids[cos >= self.near]


def _groups(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[pa.Table]:
    """Complete groups of rows that agree in the first ``keys`` columns (rows come sorted)."""
    held: list[pa.RecordBatch] = []
    last = None
    for b in batches:
        k = list(zip(*(b.column(i).to_pylist() for i in range(keys))))
        edges = [i for i in range(1, len(k)) if k[i] != k[i - 1]]
        for lo, hi in zip([0, *edges], [*edges, len(k)]):
            if hi == lo:
                continue
            if held and k[lo] != last:
                yield pa.Table.from_batches(held)
                held = []
            held.append(b.slice(lo, hi - lo))
            last = k[lo]
    if held:
        yield pa.Table.from_batches(held)


def _valid(e):
    return e.isNotNull() & (F.size(e) > 0) & ~F.exists(e, lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == F.lit(float("inf")))) & F.exists(e, lambda v: v != 0)


def _leaf_centres(reps: DataFrame, c: np.ndarray, leaves: int, u, share: float) -> dict[int, np.ndarray]:
    """Centres inside each shard, fitted in its own task on a sample of some ten rows a leaf."""
    shared = reps.sparkSession.sparkContext.broadcast(c)

    def home(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array((_unit(b.column(0)) @ shared.value.T).argmax(1).astype(np.int32)), b.column(0)], names=["shard", "v"])

    def fit(pdf):
        import pandas as pd

        x = np.array(pdf.v.tolist())
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        return pd.DataFrame({"shard": pdf.shard.iloc[0], "centre": list(centres(x, min(leaves, len(x))))})

    few = reps.where(u < share).select("v").mapInArrow(home, "shard int, v array<double>")
    found: dict[int, list] = {}
    for r in few.groupBy("shard").applyInPandas(fit, "shard int, centre array<double>").collect():  # at most MAX_SHARDS * LEAVES vectors
        found.setdefault(r.shard, []).append(r.centre)
    return {k: np.array(found[k]) if k in found else c[k : k + 1] for k in range(len(c))}


def link(vectors: DataFrame, near: float = NEAR, slice_size: int = SLICE, share: float | None = None, max_shards: int = MAX_SHARDS) -> tuple[DataFrame, DataFrame]:
    """Per row ``(vec_id, n_links, component_id, kept, audit_recall)`` and, for audits, the class map.

    ``share``: part of the lossless bound to route by; calibrated and audited if not given.
    """
    spark = vectors.sparkSession
    e = F.col("embedding").cast("array<double>")
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), e.alias("v"))
    usual = [r[0] for r in rows.where(_valid(F.col("v"))).groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), "n").limit(1).collect()]
    usual = usual[0] if usual else -1
    good = rows.where(_valid(F.col("v")) & (F.size("v") == usual)).withColumn("v", F.transform("v", lambda x: x + 0.0))
    reps = cut(good.groupBy("v").agg(F.min("vec_id").alias("cls"), F.count(F.lit(1)).alias("copies")).withColumn("id", F.monotonically_increasing_id()), "vector-classes")
    n = reps.count()
    if not n:
        none = rows.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"), F.lit(1.0).alias("audit_recall"))
        return none, reps
    u = F.pmod(F.xxhash64("id", F.lit(3)), F.lit(1 << 30)) / F.lit(float(1 << 30))
    sample = np.array([r.v for r in reps.where(u < min(1.0, SAMPLE / n)).select("v").collect()] or [reps.first().v])
    sample /= np.linalg.norm(sample, axis=1, keepdims=True)
    wanted = -(-n // max(slice_size // 2, 1))
    c = centres(sample, max(1, min(max_shards, wanted, len(sample))))
    leaves = min(LEAVES, -(-wanted // len(c)))
    inner = _leaf_centres(reps, c, leaves, u, min(1.0, 10 * leaves * len(c) / n)) if leaves > 1 else {}
    asked = _asked(reps, n)
    tries = [share] if share is not None else list(dict.fromkeys([calibrate(sample, c, near), 1.0]))
    for part in tries:
        found = _search(reps, c, inner, near, slice_size, part)
        counts = found.groupBy(F.col("a").alias("id")).agg(F.sum("n").alias("n"))
        recall = _recall(asked, reps, counts, near)
        if recall >= WANTED:
            break
    comps = classes(found.where("b is not null").select("a", "b"))
    named = reps.join(counts, "id", "left").join(comps.withColumnRenamed("node", "id"), "id", "left").select("v", "cls", "copies", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("root", "id").alias("root"))
    least = named.groupBy("root").agg(F.min("cls").alias("component_id"))
    full = named.join(least, "root").select("v", (F.col("n") + F.col("copies") - 1).alias("n_links"), "component_id")
    plain = rows.where(~F.coalesce(_valid(F.col("v")) & (F.size("v") == usual), F.lit(False))).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    every = good.join(full, "v").select("vec_id", "n_links", "component_id").union(plain)
    return every.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id"))).withColumn("audit_recall", F.lit(float(recall))), reps


def _asked(reps: DataFrame, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids and vectors of about ``AUDIT`` classes, chosen by hash."""
    u = F.pmod(F.xxhash64("id", F.lit(23)), F.lit(1 << 30)) / F.lit(float(1 << 30))
    some = reps.where(u < min(1.0, AUDIT / n)).select("id", "v").collect()
    x = np.array([r.v for r in some]).reshape(len(some), -1)
    return np.array([r.id for r in some], np.int64), x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)


def _recall(asked: tuple[np.ndarray, np.ndarray], reps: DataFrame, counts: DataFrame, near: float) -> float:
    """Share of the links of the asked classes that were found; brute force against all classes."""
    if not len(asked[0]):
        return 1.0
    shared = reps.sparkSession.sparkContext.broadcast(asked)  # about AUDIT vectors

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, x = shared.value
        for b in batches:
            hit = (x @ _unit(b.column(1)).T >= near) & (ids[:, None] != b.column(0).to_numpy())
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(hit @ b.column(2).to_numpy())], names=["id", "truth"])

    truth = reps.select("id", "v", "copies").mapInArrow(count, "id long, truth long").groupBy("id").agg(F.sum("truth").alias("truth")).where("truth > 0")
    got = truth.join(counts, "id", "left").agg(F.sum("truth"), F.sum(F.least(F.coalesce("n", F.lit(0)), "truth"))).first()
    return 1.0 if not got[0] else got[1] / got[0]


def _search(reps: DataFrame, c: np.ndarray, inner: dict[int, np.ndarray], near: float, slice_size: int, share: float) -> DataFrame:
    """Counts and forests of links, slice by slice: ``(a, b, n)``."""
    spark = reps.sparkSession
    n_parts = parts(spark)
    shared = spark.sparkContext.broadcast((c, inner))  # at most MAX_SHARDS * (LEAVES + 1) vectors

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c, inner = shared.value
        outer = Routes(c, near, share)
        below = {k: Routes(v, near, share) for k, v in inner.items()}
        for b in batches:
            for lo in range(0, b.num_rows, 2048):
                part = b.slice(lo, 2048)
                x = _unit(part.column(1))
                s = x @ c.T
                home, visit = s.argmax(1), outer.visits(s)
                member = np.zeros_like(visit)
                member[np.arange(len(s))[:, None], np.argsort(-s, axis=1, kind="stable")[:, :2]] = True
                r, shard = np.nonzero(visit | member)
                if not inner:
                    cols = r, shard, member[r, shard], home[r] == shard, visit[r, shard]
                else:  # leaves of the shards: the nearest as member, all that can own a neighbour to visit
                    made = []
                    for k in np.unique(shard).tolist():
                        i = r[shard == k]
                        t = x[i] @ inner[k].T
                        own, go = t.argmax(1), below[k].visits(t) & visit[i, k][:, None]
                        mine = np.zeros_like(go)
                        mine[np.arange(len(i)), own] = member[i, k]
                        p, leaf = np.nonzero(go | mine)
                        made.append((i[p], k * LEAVES + leaf, mine[p, leaf], (home[i] == k)[p] & (own[p] == leaf), go[p, leaf]))
                    cols = tuple(map(np.concatenate, zip(*made)))
                yield pa.RecordBatch.from_arrays([pa.array(cols[1].astype(np.int32)), part.column(0).take(pa.array(cols[0])), *[pa.array(x) for x in cols[2:]]], names=["shard", "id", "member", "home", "visit"])

    placed = cut(reps.select("id", "v").mapInArrow(place, "shard int, id long, member boolean, home boolean, visit boolean"), "vector-places")
    sizes = placed.where("member").groupBy("shard").count().select("shard", F.ceil(F.col("count") / slice_size).cast("int").alias("slices"))
    cutting = F.broadcast(sizes)  # at most MAX_SHARDS * LEAVES rows
    own = F.pmod(F.xxhash64("id", F.lit(5)), F.col("slices")).cast("int")
    members = placed.where("member").join(cutting, "shard").select("shard", own.alias("slice"), "id", "home")
    queries = placed.where("visit").join(cutting, "shard").select("shard", F.explode(F.sequence(F.lit(0), F.col("slices") - 1)).alias("slice"), "id")
    bodies = reps.select("id", "v", "copies")

    def construct(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _groups(batches, 2):
            ids = t.column("id").to_numpy()
            adj = build(_unit(t.column("v")))
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array([ids[a].tolist() for a in adj], pa.list_(pa.int64()))], names=["id", "near"])

    in_order = lambda df, *then: df.repartition(n_parts, "shard", "slice").sortWithinPartitions("shard", "slice", *then, "id")
    built = in_order(members.join(bodies, "id").select("shard", "slice", "id", "v")).mapInArrow(construct, "id long, near array<long>")
    united = cut(built.groupBy("id").agg(F.array_distinct(F.flatten(F.collect_list("near"))).alias("near")), "vector-graph")

    def indexed(m: pa.Table):
        """Answers to batches of queries over the members of one slice."""
        ids, copies, home = m.column("id").to_numpy(), m.column("copies").to_numpy(), m.column("home").to_numpy()
        order = np.argsort(ids)
        local = []
        for a in m.column("near").to_pylist():
            a = np.array(a or [], np.int64)
            p = order[np.minimum(np.searchsorted(ids[order], a), len(ids) - 1)] if len(a) else a
            local.append(p[ids[p] == a] if len(a) else a)
        index = Searcher(_unit(m.column("v")), local, near)
        joined: np.ndarray = np.arange(len(ids))  # known root of each local node
        parent: dict = {}

        def root(i):
            while parent.setdefault(i, i) != i:
                parent[i] = parent[parent[i]]
                i = parent[i]
            return i

        def answer(q: pa.RecordBatch) -> pa.RecordBatch:
            who = q.column("id").to_numpy()
            a, b, n_links = [], [], []
            for at, found in index.queries(_unit(q.column("v"))):
                i = int(who[at])
                found = found[ids[found] != i]
                if not len(found):
                    continue
                a.append(i)
                b.append(None)
                n_links.append(int(copies[found][home[found]].sum()))
                for r in np.unique(joined[found]).tolist():
                    top, other = root(("q", i)), root(r)
                    if top != other:
                        parent[top if isinstance(top, tuple) else other] = other if isinstance(top, tuple) else top
                        a.append(i)
                        b.append(int(ids[r]))
                        n_links.append(0)
                joined[found] = [root(r) for r in joined[found].tolist()] if len(found) < 64 else np.array([root(r) for r in np.unique(joined[found]).tolist()])[np.unique(joined[found], return_inverse=True)[1]]
            return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(n_links, pa.int64())], names=["a", "b", "n"])

        return answer

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, held, answer = None, [], None
        for b in batches:
            key = np.stack([b.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("shard", "slice", "ask")], 1)
            edges = [0, *(np.flatnonzero((key[1:] != key[:-1]).any(1)) + 1).tolist(), b.num_rows]
            for lo, hi in zip(edges[:-1], edges[1:]):
                if hi == lo:
                    continue
                shard, own, ask = key[lo].tolist()
                if (shard, own) != at:
                    at, held, answer = (shard, own), [], None
                if not ask:
                    held.append(b.slice(lo, hi - lo))
                elif held or answer:
                    if answer is None:
                        answer, held = indexed(pa.Table.from_batches(held)), []
                    yield answer(b.slice(lo, hi - lo))

    loaded = members.join(bodies, "id").join(united, "id").select("shard", "slice", "id", "v", "copies", "home", "near", F.lit(False).alias("ask"))
    asked = queries.join(bodies, "id").select("shard", "slice", "id", "v", "copies", F.lit(False).alias("home"), F.lit(None).cast("array<long>").alias("near"), F.lit(True).alias("ask"))
    return cut(in_order(loaded.union(asked), "ask").mapInArrow(search, "a long, b long, n long"), "vector-links")


def run(vectors: DataFrame, near: float = NEAR) -> DataFrame:
    return link(vectors, near)[0]


def audit(vectors: DataFrame, result: DataFrame, near: float = NEAR, every: int = 20) -> float:
    """Share of the links of the query rows (id divisible by ``every``) that were found, by
    brute force of the queries, in blocks, against all rows."""
    asked = vectors.where(F.col("vec_id") % every == 0).select("vec_id", F.col("embedding").cast("array<double>").alias("v")).where(_valid(F.col("v")))
    rows = vectors.select(F.col("vec_id").alias("other"), F.col("embedding").cast("array<double>").alias("w")).where(_valid(F.col("w")))
    q = asked.toPandas()
    if not len(q):
        return 1.0
    ids, x = q["vec_id"].to_numpy(), np.array(q["v"].tolist())
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    shared = vectors.sparkSession.sparkContext.broadcast((ids, x))

    def count(batches):
        ids, x = shared.value
        for b in batches:
            s = x @ _unit(b.column(1)).T >= near
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(s.sum(1))], names=["vec_id", "n"])

    truth = rows.mapInArrow(count, "vec_id long, n long").groupBy("vec_id").agg((F.sum("n") - 1).alias("truth"))
    got = truth.join(result.select("vec_id", "n_links"), "vec_id").agg(F.sum("truth"), F.sum("n_links")).first()
    return 1.0 if not got[0] else got[1] / got[0]


#: DuckDB SQL with the same rule, by comparing all pairs: for small tables.
ORACLE = f"""WITH RECURSIVE x AS (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings),
 l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM x a JOIN x b ON a.vec_id <> b.vec_id AND isfinite(list_cosine_similarity(a.e, b.e)) AND list_cosine_similarity(a.e, b.e) >= {NEAR}),
 r(root, v) AS (SELECT vec_id, vec_id FROM x UNION SELECT r.root, l.b FROM r JOIN l ON l.a = r.v),
 c AS (SELECT v AS vec_id, min(root) AS component_id FROM r GROUP BY v)
 SELECT vec_id, (SELECT count(*) FROM l WHERE a = c.vec_id)::BIGINT AS n_links, component_id, vec_id = component_id AS kept, 1.0::DOUBLE AS audit_recall FROM c"""
