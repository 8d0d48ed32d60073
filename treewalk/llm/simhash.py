"""SimHash near-duplicate grouping with anchor points of covering codes.

Two fingerprints at ``d`` or fewer differing bits are found without comparing all pairs.  The
bits are cut into blocks with a threshold each.  For a block the words of a covering code are
the anchors: each block value lies within the covering radius of one anchor at least, and every
fingerprint is replicated to all anchors within radius plus threshold.  A pair that is within the
block's threshold then meets at the anchor next to either of them.  The code of
``group`` is the perfect one-error-correcting one of 31 bits (radius 1, threshold 1).

``group``: 64 bits, links at two or fewer differing bits.  Thresholds that sum to ``d - blocks + 1``
make a block of every such pair fit: 31 bits with threshold 1, and 33 bits with all values as
anchors and threshold 0.  No link is lost.

``representatives``: five-word shingles at a similarity of 0.8 or more, read from 128 bits.  Such pairs differ in up
to 23 bits, so in two at most of one of eight blocks of 16 bits: all values of a block are anchors, every fingerprint is
replicated to those within one bit of it, and two fingerprints meet halfway.  No such pair is lost.

Only distinct fingerprints are replicated.  Links come out of an anchor's bucket as a forest, never
as all pairs.

Defined cases: null and empty texts have fingerprint zero and are linked like any other; very
long texts are hashed whole; ties between bits (set in exactly half) give 0; repeated rows share
their class; an empty table gives no rows; other columns of the input are ignored; rows with
a null ``doc_id`` take part, and a class of such rows only has a null ``component_id``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bites, cut, fresh_name, give_back, numbered, parts
from .components import classes, forest

_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
_LOCAL, _PIVOTS = 64, 8


def _shingles(text: str, words: int, seed: int) -> np.ndarray:
    """Hashes of all shingles, repeats included."""
    w = (text or "").encode().translate(_LOWER).split()
    if not w:
        return np.zeros(0, np.uint64)
    if len(w) < words:
        return np.array([xxhash.xxh64_intdigest(b" ".join(w), seed)], np.uint64)
    flat = b" ".join(w)
    ends = np.cumsum(np.fromiter(map(len, w), np.int64, len(w))) + np.arange(len(w))
    starts = [0, *(ends[:-1] + 1).tolist()]
    digest = xxhash.xxh64_intdigest
    return np.array([digest(flat[a:b], seed) for a, b in zip(starts, ends[words - 1 :].tolist())], np.uint64)


def _majority(h: np.ndarray) -> int:
    ones = np.zeros(64, np.int64)
    for i in range(0, len(h), 1 << 14):
        ones += np.unpackbits(h[i : i + (1 << 14)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(h), bitorder="little").view(np.uint64)[0])


def fingerprint(text: str, words: int = 3, seed: int = 42) -> int:
    return _majority(_shingles(text, words, seed))


def fingerprint_wide(text: str, words: int = 5, seed: int = 42) -> tuple[int, int]:
    """128 bits: the second half from the same shingle hashes, scrambled."""
    h = _shingles(text, words, seed)
    other = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return _majority(h), _majority(other ^ (other >> np.uint64(32)))


def fingerprints(docs: DataFrame, words: int = 3, seed: int = 42) -> DataFrame:
    """``(doc_id, fp)`` with the 64 bits as a signed long."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece, texts in bites(batches, "text"):
            fp = np.array([fingerprint(t, words, seed) for t in texts], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([piece.column(0), pa.array(fp)], names=["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(kernel, "doc_id long, fp long")


def _near_words(value: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Words within distance 2 of each value in the perfect code of ``bits`` (2**k - 1) bits whose check
    column of bit i is i + 1: the words, and the row each comes from."""
    s = np.zeros(len(value), np.uint64)
    for i in range(bits):
        s ^= ((value >> np.uint64(i)) & np.uint64(1)) * np.uint64(i + 1)
    bit = lambda k: np.where(k > 0, np.uint64(1) << (np.maximum(k, np.uint64(1)) - np.uint64(1)), np.uint64(0))
    rows, words = [np.arange(len(value))], [value ^ bit(s)]
    # Distance 2: flip i and j with (i+1) ^ (j+1) == syndrome; none when the value is a word itself.
    for i in range(1, bits + 1):
        j = s ^ np.uint64(i)
        ok = (s > 0) & (j > i)
        rows.append(np.flatnonzero(ok))
        words.append((value ^ np.uint64(1 << (i - 1)) ^ bit(j))[ok])
    return np.concatenate(words), np.concatenate(rows)


def anchors(fp: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Anchor of each replica, and the row it comes from.  Anchors of the two blocks are told
    apart by their top bit."""
    words, rows = _near_words(fp & np.uint64((1 << 31) - 1), 31)
    return np.concatenate([words, (fp >> np.uint64(31)) | np.uint64(1 << 63)]), np.concatenate([rows, np.arange(len(fp))])


def _popcount(x: np.ndarray) -> np.ndarray:
    return np.bitwise_count(x)


def link_bucket(fp: np.ndarray, limit: int = 2) -> tuple[np.ndarray, np.ndarray]:
    """Forest of links (child, parent) with at most ``limit`` (2) differing bits in a bucket."""
    n = len(fp)
    if n <= _LOCAL:
        a, b = np.nonzero(np.triu(_popcount(fp[:, None] ^ fp[None, :]) <= limit, 1))
        return forest(n, a, b)
    # Two values differ in at most two bits exactly if they share a value one bit (or none) away.
    near = np.concatenate([fp, *[fp ^ np.uint64(1 << i) for i in range(64)]])
    who = np.tile(np.arange(n), 65)
    order = np.argsort(near, kind="stable")
    near, who = near[order], who[order]
    same = np.flatnonzero(near[1:] == near[:-1])
    return forest(n, who[same], who[same + 1])


def links(distinct: DataFrame, limit: int = 2) -> DataFrame:
    """Links ``(a, b)`` that connect the same fingerprints as all pairs within ``limit`` bits."""
    if limit != 2:
        raise ValueError("the codes chosen here are for a threshold of two bits")
    spark = distinct.sparkSession

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = b.column(0).to_numpy(zero_copy_only=False)
            key, row = anchors(fp.view(np.uint64))
            yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(fp[row])], names=["anchor", "fp"])

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for fp, *_ in _buckets(batches):
            child, parent = link_bucket(fp.view(np.uint64))
            if len(child):
                yield pa.RecordBatch.from_arrays([pa.array(fp[child]), pa.array(fp[parent])], names=["a", "b"])

    replicas = distinct.select("fp").mapInArrow(spread, "anchor long, fp long")
    return replicas.repartition(parts(spark), "anchor").sortWithinPartitions("anchor").mapInArrow(compare, "a long, b long").distinct()


def _buckets(batches: Iterator[pa.RecordBatch]) -> Iterator[list[np.ndarray]]:
    """Columns after the first, for each run of two rows and more with one value of the first."""
    held: list[list[np.ndarray]] = []
    for b in batches:
        cols = [c.to_numpy(zero_copy_only=False) for c in b.columns]
        if not b.num_rows:
            continue
        edges = [0, *(np.flatnonzero(np.diff(cols[0])) + 1).tolist(), b.num_rows]
        for lo, hi in zip(edges[:-1], edges[1:]):
            if held and held[-1][0][0] != cols[0][lo]:
                if sum(len(h[0]) for h in held) > 1:
                    yield [np.concatenate(c) for c in list(zip(*held))[1:]]
                held = []
            held.append([c[lo:hi] for c in cols])
    if sum(len(h[0]) for h in held) > 1:
        yield [np.concatenate(c) for c in list(zip(*held))[1:]]


def _whole_runs(batches: Iterator[pa.RecordBatch]) -> Iterator[list[np.ndarray]]:
    """All columns, in pieces that end where the first one changes."""
    held: list[list[np.ndarray]] = []
    for b in batches:
        if not b.num_rows:
            continue
        cols = [c.to_numpy(zero_copy_only=False) for c in b.columns]
        last = int(np.searchsorted(cols[0], cols[0][-1], "left"))  # the run still open
        if last or (held and held[-1][0][0] != cols[0][0]):
            held.append([c[:last] for c in cols])
            yield [np.concatenate(c) for c in zip(*held)]
            held = []
        held.append([c[last:] for c in cols])
    if held:
        yield [np.concatenate(c) for c in zip(*held)]


def link_wide(f: np.ndarray, home: np.ndarray, limit: int) -> tuple[np.ndarray, np.ndarray]:
    """Forest of the links between rows of ``f`` (two words each) and those in ``home``.

    Rows near a pivot are one class at once and are compared only with rows outside it, so a crowd of
    copies costs no square.
    """
    n, held = len(f), np.flatnonzero(home)
    if not len(held):
        return held, held
    far = lambda i, j: _popcount(f[i, 0][:, None] ^ f[j, 0]) + _popcount(f[i, 1][:, None] ^ f[j, 1])
    of, a, b = np.full(n, -1), [], []
    for _ in range(_PIVOTS):
        free = held[of[held] < 0]
        if len(free) <= _LOCAL:
            break
        near = np.flatnonzero(far(free[:1], np.arange(n))[0] <= limit)
        of[near[of[near] < 0]] = free[0]
        a.append(np.full(len(near), free[0]))
        b.append(near)
    for g in np.unique(of[held]).tolist():
        mine, others = held[of[held] == g], np.flatnonzero(of != g) if g >= 0 else np.arange(n)
        step = max(1, 2_000_000 // max(len(others), 1))
        for lo in range(0, len(mine) if len(others) else 0, step):
            i, j = np.nonzero(far(mine[lo : lo + step], others) <= limit)
            child, parent = forest(n, mine[lo + i], others[j])
            a.append(child)
            b.append(parent)
    return forest(n, np.concatenate(a), np.concatenate(b)) if a else (held[:0], held[:0])


def wide_anchors(f: np.ndarray, block: int) -> tuple[np.ndarray, np.ndarray]:
    """Anchor of each replica of rows of ``f`` (two words each) in one of eight blocks, and the row it comes from."""
    value = (f[:, block // 4] >> np.uint64(16 * (block % 4))) & np.uint64(0xFFFF)
    flips = np.concatenate([np.zeros(1, np.uint64), np.uint64(1) << np.arange(16, dtype=np.uint64)])
    return (value[:, None] ^ flips).reshape(-1) | np.uint64(block << 16), np.repeat(np.arange(len(f)), 17)


def link_runs(key: np.ndarray, f: np.ndarray, limit: int) -> tuple[np.ndarray, np.ndarray]:
    """Forest of the links between rows with equal ``key`` (sorted): runs of up to ``_LOCAL`` rows all at once, by their
    offsets, larger ones one by one."""
    n = len(key)
    edges = np.concatenate([[0], np.flatnonzero(key[1:] != key[:-1]) + 1, [n]])
    size = np.diff(edges)
    end = np.repeat(edges[1:], size)
    at = np.flatnonzero(np.repeat(size, size) <= _LOCAL)
    a, b = [at[:0]], [at[:0]]
    for off in range(1, _LOCAL):
        at = at[at + off < end[at]]
        if not len(at):
            break
        hit = at[_popcount(f[at, 0] ^ f[at + off, 0]) + _popcount(f[at, 1] ^ f[at + off, 1]) <= limit]
        a.append(hit)
        b.append(hit + off)
    for g in np.flatnonzero(size > _LOCAL).tolist():
        child, parent = link_wide(f[edges[g] : edges[g + 1]], np.ones(size[g], bool), limit)
        a.append(edges[g] + child)
        b.append(edges[g] + parent)
    return forest(n, np.concatenate(a), np.concatenate(b))


def link_limit(similarity: float, bits: int = 128) -> int:
    """Differing bits that five of six pairs at a Jaccard similarity stay within: the expected
    share of their angle, and one standard deviation."""
    share = np.arccos(2 * similarity / (1 + similarity)) / np.pi
    return int(bits * share + np.sqrt(bits * share * (1 - share)))


def similar(docs: DataFrame, words: int = 5, similarity: float = 0.8) -> DataFrame:
    """``(row, least)`` for ``docs (row, text)``: the least row of each one's class."""
    spark, limit = docs.sparkSession, link_limit(similarity)
    if limit > 23:
        raise ValueError("the blocks chosen here are for a threshold of 23 bits")

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece, texts in bites(batches, "text"):
            f = np.array([fingerprint_wide(t, words) for t in texts], np.uint64).reshape(-1, 2).view(np.int64)
            yield pa.RecordBatch.from_arrays([piece.column(0), pa.array(f[:, 0]), pa.array(f[:, 1])], names=["row", "f0", "f1"])

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, b.num_rows, 4096):
                node, f0, f1 = (c.to_numpy(zero_copy_only=False) for c in b.slice(lo, 4096).columns)
                for block in range(8):
                    word, at = wide_anchors(np.stack([f0, f1], 1).view(np.uint64), block)
                    yield pa.RecordBatch.from_arrays([pa.array(word.view(np.int64)), pa.array(node[at]), pa.array(f0[at]), pa.array(f1[at])], names=["anchor", "node", "f0", "f1"])

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for key, node, f0, f1 in _whole_runs(batches):
            a, b = link_runs(key, np.stack([f0, f1], 1).view(np.uint64), limit)
            if len(a):
                links = np.unique(np.stack([node[a], node[b]], 1), axis=0)
                yield pa.RecordBatch.from_arrays([pa.array(links[:, 0].copy()), pa.array(links[:, 1].copy())], names=["a", "b"])
        give_back()

    fps = cut(docs.select("row", "text").mapInArrow(hashed, "row long, f0 long, f1 long"), "simhash-wide")
    distinct = fps.groupBy("f0", "f1").agg(F.min("row").alias("node"))
    replicas = distinct.select("node", "f0", "f1").mapInArrow(spread, "anchor long, node long, f0 long, f1 long")
    met = replicas.repartition(parts(spark), "anchor").sortWithinPartitions("anchor").mapInArrow(compare, "a long, b long")
    found = classes(cut(met.distinct(), "simhash-wide-links"))
    least = found.groupBy("root").agg(F.min("node").alias("least"))
    named = distinct.join(found.join(least, "root").select("node", "least"), "node", "left").select("f0", "f1", F.coalesce("least", "node").alias("least"))
    return fps.join(named, ["f0", "f1"]).select("row", "least")


def group(docs: DataFrame, words: int = 3, limit: int = 2, seed: int = 42) -> DataFrame:
    """``(doc_id, fingerprint, component_id)`` for every row of ``docs``."""
    fps = cut(fingerprints(docs, words, seed), "simhash")
    distinct = fps.groupBy("fp").agg(F.min("doc_id").alias("least"))
    found = classes(cut(links(distinct, limit), "simhash-links"))  # node, root
    labelled = distinct.join(found.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    named = labelled.join(labelled.groupBy("root").agg(F.min("least").alias("component_id")), "root").select("fp", "component_id")
    return fps.join(named, "fp").select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def representatives(docs: DataFrame, words: int = 5, similarity: float = 0.8) -> DataFrame:
    """Rows of ``docs``, with all their columns: the first document of each group by ``doc_id``.

    Where ids are null or repeated, rows are told apart and the first is the first in number; names of
    its own avoid those of the table.
    """
    fixed, key = docs, "doc_id"
    if numbered(docs)[1] is not None:
        key = fresh_name(docs, "row")
        fixed = cut(docs.withColumn(key, F.monotonically_increasing_id()), "simhash-rows")
    rows = fixed.select(F.col(key).cast("long").alias("row"), F.col("text").cast("string").alias("text"))
    name = fresh_name(fixed, "kept")
    kept = similar(rows, words, similarity).where("row = least").select(F.col("row").alias(name))
    return fixed.join(kept, F.col(key).cast("long") == F.col(name), "left_semi").select(*docs.columns)
