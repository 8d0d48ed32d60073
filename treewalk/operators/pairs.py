"""Sums over pairs ``(i, j)`` that meet in many keys, row by row: no pair of a meeting is ever shuffled.

A join of ``(i, k)`` with ``(k, j)`` makes a row for every meeting, and an aggregate then moves them all.  Here the
``j`` side is dealt into tiles of about ``TILE`` values, a task holds one tile, and each ``i`` comes with the list of
its keys; its sums over the tile are made in an array and leave the task finished.  Equal lists of keys stand next to
each other and are worked out once.  What is shuffled are lists: those of ``i`` once a tile, those of ``k`` once a part.

Rows leave in blocks of up to ``DEEP`` values of ``i`` by ``WIDE`` of the tile, ``i`` by ``i``: a result that is written
repeats few values of ``j`` at a time, which dictionaries and compression of a columnar file make small.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TILE, ROWS, WIDE, DEEP = 1 << 15, 1 << 18, 256, 256


class _Meet:
    """Lists ``(j, b)`` of every key of a tile."""

    def __init__(self, keys, extra, counts, j, b):
        self.ids, at = np.unique(j, return_inverse=True)
        self.at, self.b = at.reshape(-1).astype(np.int64), b
        ends = np.cumsum(counts)
        self.where: dict[int, list[tuple[int, int, int]]] = {}
        for k, d, lo, hi in zip(keys.tolist(), extra.tolist(), (ends - counts).tolist(), ends.tolist()):
            self.where.setdefault(k, []).append((lo, hi, d))

    def slices(self, k: np.ndarray) -> list[tuple[int, tuple[int, int, int]]]:
        return [(n, s) for n, key in enumerate(k.tolist()) for s in self.where.get(key, ())]


class Count(_Meet):
    """How often each ``j`` is met."""

    def row(self, k, a):
        found = [self.at[lo:hi] for _, (lo, hi, _) in self.slices(k)]
        n = np.bincount(np.concatenate(found), minlength=len(self.ids)) if found else np.zeros(0, np.int64)
        j = np.flatnonzero(n)
        return j, n[j]


class Ratio(_Meet):
    """Sum over the keys of ``(a * b << bits) div d``, ``d`` belonging to the key."""

    bits = 0

    def row(self, k, a):
        x, met = np.zeros(len(self.ids), np.int64), np.zeros(len(self.ids), bool)
        for n, (lo, hi, d) in self.slices(k):
            b = self.b[lo:hi]
            if float(a[n]) * float(b.max()) * 2.0**self.bits >= 2.0**63:
                raise OverflowError("weights are too large for fixed point")
            np.add.at(x, self.at[lo:hi], ((int(a[n]) * b) << self.bits) // d)
            met[self.at[lo:hi]] = True
        j = np.flatnonzero(met)
        return j, x[j]



class Any(_Meet):
    """Whether ``j`` is met at all: keys with long lists as packed bits."""

    def __init__(self, *parts):
        super().__init__(*parts)
        n = len(self.ids)
        self.dense, rows = {}, []
        for k, found in self.where.items():
            if sum(hi - lo for lo, hi, _ in found) * 64 >= n:  # so bits take no more room than the lists
                hit = np.zeros(n, bool)
                for lo, hi, _ in found:
                    hit[self.at[lo:hi]] = True
                self.dense[k] = len(rows)
                rows.append(np.packbits(hit))
        self.bits = np.array(rows, np.uint8)

    def row(self, k, a):
        n, dense, rest = len(self.ids), [], []
        for key in k.tolist():
            if key in self.dense:
                dense.append(self.dense[key])
            else:
                rest += [self.at[lo:hi] for lo, hi, _ in self.where.get(key, ())]
        if not dense:
            j = np.unique(np.concatenate(rest)) if rest else np.zeros(0, np.int64)
        else:
            hit = np.unpackbits(np.bitwise_or.reduce(self.bits[dense], axis=0), count=n)
            for at in rest:
                hit[at] = 1
            j = np.flatnonzero(hit)
        return j, None


class Near:
    """How often ``j`` has a time ``b`` within ``reach`` of a time of ``i`` (its keys are times)."""

    reach = 0

    def __init__(self, keys, extra, counts, j, b):
        self.ids, at = np.unique(j, return_inverse=True)
        order = np.argsort(b, kind="stable")
        self.b, self.at = b[order], at.reshape(-1)[order]

    def row(self, k, a):
        lo, hi = np.searchsorted(self.b, k - self.reach, "left"), np.searchsorted(self.b, k + self.reach, "right")
        found = [self.at[x:y] for x, y in zip(lo.tolist(), hi.tolist()) if y > x]
        n = np.bincount(np.concatenate(found), minlength=len(self.ids)) if found else np.zeros(0, np.int64)
        j = np.flatnonzero(n)
        return j, n[j]


class TenMinutes(Near):
    reach = 600_000_000


def _lists(table: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Lengths of the lists, and both columns of their entries."""
    items = table.column("items").combine_chunks()
    items = items.combine_chunks() if isinstance(items, pa.ChunkedArray) else items
    flat = items.flatten()
    return np.diff(items.offsets.to_numpy()), flat.field("a").to_numpy(), flat.field("b").to_numpy()


def _blocks(rows: list[tuple], ids: np.ndarray, above: bool) -> Iterator[tuple[np.ndarray, ...]]:
    """Columns of the rows ``(i, j, sums)``, those of ``WIDE`` neighbouring ``ids`` together and there ``i`` by ``i``."""
    i, (_, j, x) = np.array([r[0] for r in rows], np.int64), rows[0]
    if not above and all(r[1] is j for r in rows):
        for lo in range(0, len(j), WIDE):
            some = j[lo : lo + WIDE]
            yield np.repeat(i, len(some)), np.tile(some, len(i)), *(() if x is None else (np.tile(x[lo : lo + WIDE], len(i)),))
        return
    first = [int(np.searchsorted(r[1], r[0], "right")) if above else 0 for r in rows]
    j = np.concatenate([r[1][f:] for r, f in zip(rows, first)])
    order = np.argsort((np.searchsorted(ids, j) // WIDE).astype(np.uint16 if len(ids) <= WIDE << 16 else np.int64), kind="stable")
    cols = [np.repeat(i, [len(r[1]) - f for r, f in zip(rows, first)]), j]
    if x is not None:
        cols.append(np.concatenate([r[2][f:] for r, f in zip(rows, first)]))
    for s in range(0, len(j), ROWS):
        yield tuple(c[order[s : s + ROWS]] for c in cols)


def _kernel(kind: type, above: bool, names: list[str]) -> Callable:
    def out(rows: list) -> pa.RecordBatch:
        cols = [np.concatenate([r[c] for r in rows]) for c in range(len(names))]
        return pa.RecordBatch.from_arrays([pa.array(c.astype(np.int64, copy=False)) for c in cols], names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tile, held, last, j, x = None, [], None, None, None
        ready, n, rows, size = [], 0, [], 0

        def full(parts: Iterator) -> Iterator[pa.RecordBatch]:
            nonlocal ready, n
            for part in parts:
                ready.append(part)
                n += len(part[0])
                if n >= ROWS:
                    yield out(ready)
                    ready, n = [], 0

        for batch in batches:
            right = batch.filter(pa.compute.equal(batch.column("kind"), 0))
            if right.num_rows:
                held.append(right)
            left = batch.filter(pa.compute.equal(batch.column("kind"), 1))
            if not left.num_rows or not held:
                continue
            if tile is None:  # the lists of the tile come first
                t = pa.Table.from_batches(held)
                tile = kind(t.column("key").to_numpy(), t.column("extra").to_numpy(), *_lists(t))
                held, t = [None], None
            count, k, a = _lists(pa.Table.from_batches([left]))
            ends = np.cumsum(count)
            for i, lo, hi in zip(left.column("key").to_pylist(), (ends - count).tolist(), ends.tolist()):
                mine = (k[lo:hi].tobytes(), a[lo:hi].tobytes())
                if mine != last:
                    at, x = tile.row(k[lo:hi], a[lo:hi])
                    j, last = tile.ids[at], mine
                rows.append((i, j, x))
                size += len(j)
                if len(rows) == DEEP or size >= 4 * ROWS and (above or rows[0][1] is not j):
                    yield from full(_blocks(rows, tile.ids, above))
                    rows, size = [], 0
        if rows:
            yield from full(_blocks(rows, tile.ids, above))
        if ready:
            yield out(ready)

    return run


def sums(left: DataFrame, right: DataFrame, kind: type, names: list[str], above: bool = False, tile: int = TILE) -> DataFrame:
    """Rows ``names`` = (i, j[, sum]) of all pairs that meet; ``above``: only those with ``i < j``.

    ``left (i, k, a)``; ``right (k, j, b, extra)``, ``extra`` a value of the key."""
    spark = left.sparkSession
    tiles = max(1, -(-right.select("j").distinct().count() // tile))
    parts = max(1, -(-2 * spark.sparkContext.defaultParallelism // tiles))
    dealt = lambda c, n: F.pmod(F.xxhash64(c), F.lit(n)).cast("int")
    entry = lambda a, b: F.array_sort(F.collect_list(F.struct(F.col(a).alias("a"), F.col(b).alias("b")))).alias("items")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    ls = left.groupBy("i").agg(entry("k", "a")).withColumn("tile", every(tiles))
    ls = ls.select((dealt("i", parts) * tiles + F.col("tile")).alias("cell"), F.lit(1).alias("kind"), F.col("i").alias("key"), F.lit(0).cast("long").alias("extra"), "items")
    rs = right.withColumn("tile", dealt("j", tiles)).groupBy("tile", "k").agg(F.max("extra").alias("extra"), entry("j", "b")).withColumn("part", every(parts))
    rs = rs.select((F.col("part") * tiles + F.col("tile")).alias("cell"), F.lit(0).alias("kind"), F.col("k").alias("key"), "extra", "items")
    cells = rs.union(ls).repartitionById(parts * tiles, F.col("cell")).sortWithinPartitions("kind", "items")
    return cells.select("kind", "key", "extra", "items").mapInArrow(_kernel(kind, above, names), ", ".join(f"{c} long" for c in names))


def one(value: int = 1) -> Column:
    return F.lit(value).cast("long")
