"""Exact substring deduplication with range-partitioned suffixes.

A byte goes if it lies in a string of ``LENGTH`` bytes that starts anywhere else too, in the same
document or another.  Not every suffix needs sorting:

1. Anchors.  Each ``LENGTH``-byte string belongs to one anchor: its leftmost ``GRAM``-byte string of
   least hash.  Equal strings have equal anchors at equal places.  The strings of one anchor start
   side by side, so an anchor stands for a run of text, its context, of 264 bytes on average.
2. Verdicts.  Anchors meet by the bytes they share, their key, as 64-bit hashes.  A key seen once
   has no repeat.  A context seen twice (64 bits more) is a repeat as a whole.  Equal contexts of
   an input slice travel as one, and their places stay with their documents as merged spans.
   What is left is open: contexts that share a key and differ somewhere, that is the edges of
   repeated passages.
3. Splitting.  A key that a bounded sample shows to be common is cut into longer ones: the places
   that the anchor can have in a string are halved again and again, which lengthens the bytes that the
   strings of one part share, until no part is common or each string is its own part.  Every
   anchor of that key is cut alike, so the split moves work and changes no result.
4. Suffixes.  Open contexts are range-partitioned by sampled splitters on their key's bytes, so that
   the common prefix over a bucket's border is too short for a repeat.  Each bucket sorts its
   suffixes, and the reversed bytes before the keys, by multikey quicksort; common prefixes of
   neighbours give, for every place of a string over its key, the classes of equal strings.

Defined cases: null counts as the empty text; texts under ``LENGTH`` bytes keep everything; very
long texts are treated whole, block by block; repeated rows remove each other's bytes; an empty
table gives no rows; other columns are ignored; rows with null or repeated ids are told apart inside.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bites, cut, fresh_name, give_back, numbered, parts, renamed
from .word_memo import _B1, _B2, _Powers

LENGTH, GRAM = 200, 64
LEFT = LENGTH - GRAM
#: Rows per sort; bytes and anchors held while hashing; anchors sampled at least and for each
#: partition, and how many of them with one key and different contexts make it common.
BUCKET_ROWS, BLOCK, HELD, SAMPLE, SAMPLE_EACH, CROWD = 20_000, 1 << 19, 200_000, 20_000, 400, 20
_SINGLE, _MANY, _KNOWN = 0, 1, 2
_P1, _P2 = _Powers(_B1), _Powers(_B2)
_MIX, _MIX2 = np.uint64(0xD6E8FEB86659FD93), np.uint64(0xA0761D6478BD642F)


class _Hash:
    """Hashes of any stretches of ``b``, from running sums."""

    def __init__(self, b: np.ndarray, powers: _Powers):
        up, self.down = powers.get(len(b) + 1)
        self.total = np.zeros(len(b) + 1, np.uint64)
        np.cumsum((b.astype(np.uint64) + np.uint64(1)) * up[:-1], out=self.total[1:])

    def of(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        return _mixed((self.total[hi] - self.total[lo]) * self.down[lo])

    def rolling(self, k: int) -> np.ndarray:
        return _mixed((self.total[k:] - self.total[:-k]) * self.down[: len(self.total) - k])


def _mixed(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(32))
    h *= _MIX
    h ^= h >> np.uint64(29)
    return h


def _slide(h: np.ndarray, k: int) -> np.ndarray:
    """Minimum over each ``k`` neighbours."""
    size, m = 1, h
    while size * 2 <= k:
        m = np.minimum(m[:-size], m[size:])
        size *= 2
    return m if size == k else np.minimum(m[: len(h) - k + 1], m[k - size : k - size + len(h) - k + 1])


def _flat(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    raw = [t.encode() for t in texts]
    offs = np.zeros(len(raw) + 1, np.int64)
    np.cumsum([len(r) for r in raw], out=offs[1:])
    return np.frombuffer(b"".join(raw), np.uint8), offs


def _blocks(b: np.ndarray, offs: np.ndarray, splits: dict[int, list]) -> Iterator[tuple[np.ndarray, ...]]:
    """Keyed contexts block by block: key, context hash, first and last string start, start and
    spread of the key (its length is ``LENGTH`` less the spread), in places of ``b``."""
    hot = np.array(sorted(splits), np.uint64)
    for base in range(0, len(b) - LENGTH + 1, BLOCK):
        part = b[base : base + BLOCK + LENGTH - 1]
        one, two = _Hash(part, _P1), _Hash(part, _P2)
        gram = one.rolling(GRAM)
        place = np.arange(len(gram), dtype=np.uint64)
        at = (_slide(gram & ~np.uint64(0xFFFFFF) | place, LEFT + 1) & np.uint64(0xFFFFFF)).astype(np.int64)
        inner = np.diff(np.clip(offs, base, base + len(at)))
        start = np.arange(len(at))
        fits = start + base <= np.repeat(offs[1:] - LENGTH, inner)
        same = fits[1:] & fits[:-1] & (at[1:] == at[:-1])
        lo = np.flatnonzero(fits & ~np.concatenate([[False], same]))
        hi = np.flatnonzero(fits & ~np.concatenate([same, [False]]))
        p = at[lo]
        key = gram[p]
        plain = ~np.isin(key, hot) if len(hot) else np.ones(len(key), bool)
        made = [(key[plain], lo[plain], hi[plain], p[plain], np.full(int(plain.sum()), LEFT))]
        for g in np.unique(key[~plain]).tolist():
            mine = np.flatnonzero(key == np.uint64(g))
            for near, far in splits[g]:
                i = mine[(p[mine] - hi[mine] <= far) & (p[mine] - lo[mine] >= near)]
                q = p[i] - near
                longer = two.of(q, q + LENGTH - (far - near)) * _MIX2 + np.uint64(near * 256 + far)
                made.append((key[i] ^ longer, np.maximum(lo[i], p[i] - far), np.minimum(hi[i], q), q, np.full(len(i), far - near)))
        key, lo, hi, q, spread = map(np.concatenate, zip(*made))
        context = two.of(lo, hi + LENGTH) + (q - lo).astype(np.uint64) * _MIX2
        yield key, context, lo + base, hi + base, q + base, spread


def _merged(row: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Spans that overlap or touch, as one."""
    if not len(row):
        return row, lo, hi
    o = np.lexsort((lo, row))
    row, lo, hi = row[o], lo[o], hi[o]
    _, group = np.unique(row, return_inverse=True)
    reach = np.maximum.accumulate(hi + group * (1 << 32)) - group * (1 << 32)
    new = np.ones(len(row), bool)
    new[1:] = (row[1:] != row[:-1]) | (lo[1:] > reach[:-1])
    first = np.flatnonzero(new)
    return row[first], lo[first], reach[np.append(first[1:], len(row)) - 1]


def _anchor_rows(rows: DataFrame, shared) -> DataFrame:
    """``(key, context, row, lo, meta)``: one row for each distinct context of an input slice; known
    repeats as merged spans whose end stands in ``context``."""

    def settle(held: list[tuple]) -> pa.RecordBatch:
        key, context, row, lo, meta = map(np.concatenate, zip(*held))
        o = np.lexsort((context, key))
        key, context, row, lo, meta = key[o], context[o], row[o], lo[o], meta[o]
        new = np.ones(len(key), bool)
        new[1:] = (key[1:] != key[:-1]) | (context[1:] != context[:-1])
        first = np.flatnonzero(new)
        many = np.diff(np.append(first, len(key))) > 1
        again = many[np.cumsum(new) - 1]
        k_row, k_lo, k_hi = _merged(row[again], lo[again], lo[again] + (meta[again] >> 8 & 255) + LENGTH)
        k_key = _mixed(k_row.view(np.uint64) * _MIX2)
        meta = meta[first] | np.where(many, _MANY << 24, 0)
        cols = [(np.concatenate([key[first], k_key])).view(np.int64), np.concatenate([context[first].view(np.int64), k_hi]), np.concatenate([row[first], k_row]), np.concatenate([lo[first], k_lo]).astype(np.int32), np.concatenate([meta, np.full(len(k_row), _KNOWN << 24)]).astype(np.int32)]
        return pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["key", "context", "row", "lo", "meta"])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        splits, held, size = shared.value, [], 0
        for piece, texts in bites(batches, "text", BLOCK):
            b, offs = _flat(texts)
            row = piece.column(0).to_numpy(zero_copy_only=False)
            for key, context, lo, hi, q, spread in _blocks(b, offs, splits):
                doc = np.searchsorted(offs, lo, side="right") - 1
                held.append((key, context, row[doc], lo - offs[doc], spread | (hi - lo) << 8 | (q - lo) << 16))
                size += len(key)
                if size >= HELD:
                    yield settle(held)
                    held, size = [], 0
        if size:
            yield settle(held)

    return rows.mapInArrow(kernel, "key long, context long, row long, lo int, meta int")


def _verdicts(found: DataFrame) -> DataFrame:
    """``(row, lo, hi, meta)``: repeated spans (``meta`` -1), and the contexts to be compared; of
    equal ones a single place, marked in bit 24 if it is open."""

    def judge(cols: list[np.ndarray]) -> list[np.ndarray]:
        key, context, row, lo, meta = cols
        new_key = np.ones(len(key), bool)
        new_key[1:] = key[1:] != key[:-1]
        new = new_key.copy()
        new[1:] |= context[1:] != context[:-1]
        first, of, size = np.flatnonzero(new), np.cumsum(new) - 1, meta & 0xFFFFFF
        many = np.add.reduceat(np.where(meta >> 24 == _MANY, 2, 1), first) > 1
        span = many[of] & (meta >> 24 == _SINGLE)
        group = np.cumsum(new_key[first]) - 1
        compare = (np.bincount(group) > 1) & (np.bincount(group, ~many) > 0)
        ask = first[compare[group]]
        out_meta = size[ask] | np.where(many[compare[group]], 0, 1 << 24)
        end = lo + (size >> 8 & 255) + LENGTH
        return [np.concatenate([row[span], row[ask]]), np.concatenate([lo[span], lo[ask]]), np.concatenate([end[span], end[ask]]), np.concatenate([np.full(int(span.sum()), -1), out_meta])]

    def batch(row, lo, hi, meta) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(row), pa.array(lo.astype(np.int32)), pa.array(hi.astype(np.int32)), pa.array(meta.astype(np.int32))], names=["row", "lo", "hi", "meta"])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = []
        for b in batches:
            cols = [c.to_numpy(zero_copy_only=False) for c in b.columns]
            known = cols[4] >> 24 == _KNOWN
            if known.any():
                yield batch(cols[2][known], cols[3][known], cols[1][known], np.full(int(known.sum()), -1))
                cols = [c[~known] for c in cols]
            if not len(cols[0]):
                continue
            other = np.flatnonzero(cols[0] != cols[0][-1])
            ready = int(other[-1]) + 1 if len(other) else 0
            if held and cols[0][0] != held[-1][0][-1] and not ready:
                yield batch(*judge([np.concatenate(c) for c in zip(*held)]))
                held = []
            if ready:
                yield batch(*judge([np.concatenate(c) for c in zip(*held, [c[:ready] for c in cols])]))
                held = []
            held.append([c[ready:] for c in cols])
        if held:
            yield batch(*judge([np.concatenate(c) for c in zip(*held)]))

    return found.repartition(parts(found.sparkSession), "key").sortWithinPartitions("key", "context").mapInArrow(kernel, "row long, lo int, hi int, meta int")


def _gather(b: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> pa.Array:
    """Stretches of ``b`` as binary values."""
    ends = np.zeros(len(lo) + 1, np.int64)
    np.cumsum(hi - lo, out=ends[1:])
    flat = b[np.repeat(lo - ends[:-1], hi - lo) + np.arange(ends[-1])]
    return pa.Array.from_buffers(pa.binary(), len(lo), [None, pa.py_buffer(ends.astype(np.int32).tobytes()), pa.py_buffer(flat.tobytes())])


def _contexts(asked: DataFrame) -> DataFrame:
    """``(bytes, row, lo, meta)`` of the contexts to be compared; ``asked``: (row, text, asks)."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece, texts in bites(batches, "text"):
            b, offs = _flat(texts)
            asks = [np.array([(a["lo"], a["hi"], a["meta"]) for a in x], np.int64).reshape(-1, 3) for x in piece.column(2).to_pylist()]
            doc = np.repeat(np.arange(len(texts)), [len(x) for x in asks])
            lo, hi, meta = np.concatenate(asks).T
            row = piece.column(0).to_numpy(zero_copy_only=False)[doc]
            for i in range(0, len(lo), 20_000):
                s = slice(i, i + 20_000)
                yield pa.RecordBatch.from_arrays([_gather(b, offs[doc[s]] + lo[s], offs[doc[s]] + hi[s]), pa.array(row[s]), pa.array(lo[s].astype(np.int32)), pa.array(meta[s].astype(np.int32))], names=["bytes", "row", "lo", "meta"])

    return asked.mapInArrow(kernel, "bytes binary, row long, lo int, meta int")


def multikey_quicksort(keys: np.ndarray) -> np.ndarray:
    """Order of the rows of ``keys`` (rows x columns), by three-way partition column by column."""
    order = np.arange(len(keys))
    todo = [(0, len(keys), 0)]
    while todo:
        lo, hi, col = todo.pop()
        while hi - lo > 1 and col < keys.shape[1]:
            part = order[lo:hi]
            if hi - lo <= 512:
                order[lo:hi] = part[np.lexsort(keys[part, col:].T[::-1])]
                break
            k = keys[part, col]
            pivot = np.partition(k[:: max(1, len(k) // 99)], len(k[:: max(1, len(k) // 99)]) // 2)[len(k[:: max(1, len(k) // 99)]) // 2]
            less, more = k < pivot, k > pivot
            a, z = int(less.sum()), int(more.sum())
            order[lo:hi] = np.concatenate([part[less], part[~less & ~more], part[more]])
            todo += [(lo, lo + a, col), (hi - z, hi, col)]
            lo, hi, col = lo + a, hi - z, col + 1
    return order


def _sorted(b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order of byte rows, and the common prefix of each with the one before it in the order."""
    n, width = b.shape
    words = np.zeros((n, -(-width // 8) * 8), np.uint8)
    words[:, :width] = b
    order = multikey_quicksort(words.view(">u8").astype(np.uint64))
    s = b[order]
    differs = s[1:] != s[:-1]
    prefix = np.where(differs.any(1), differs.argmax(1), width)
    return order, np.concatenate([[0], prefix])


def extents(ctx: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """How far repeats reach to the left and right of the key's start in each context (0, 0:
    none).  A row holds ``LEFT`` bytes before that start and ``LENGTH`` after it; 255 stands
    outside the context."""
    n = len(ctx)
    room_l = LEFT - (ctx[:, :LEFT] == 255).sum(1)
    room_r = LENGTH - (ctx[:, LEFT:] == 255).sum(1)
    least, most = np.full(n, LEFT + 1), np.full(n, -1)
    r_order, r_prefix = _sorted(ctx[:, LEFT:])
    l_order, l_prefix = _sorted(ctx[:, :LEFT][:, ::-1])
    shared = np.zeros(n, bool)  # some other context has the same leading GRAM bytes
    together = r_prefix >= GRAM
    shared[r_order[together]] = True
    shared[r_order[np.flatnonzero(together) - 1]] = True
    live = np.flatnonzero(shared)
    rc, lc = np.empty(n, np.int64), np.empty(n, np.int64)
    for l in range(LEFT + 1) if len(live) else ():
        rc[r_order] = np.cumsum(r_prefix < LENGTH - l)
        lc[l_order] = np.cumsum(l_prefix < l)
        inside = live[(l <= room_l[live]) & (LENGTH - l <= room_r[live])]
        key = rc[inside] * (n + 1) + lc[inside]
        o = np.argsort(key, kind="stable")
        k = key[o]
        same = k[1:] == k[:-1]
        dup = np.zeros(len(inside), bool)
        dup[o[1:][same]] = True
        dup[o[:-1][same]] = True
        hit = inside[dup]
        most[hit] = l
        least[hit] = np.minimum(least[hit], l)
    found = most >= 0
    return np.where(found, most, 0), np.where(found, LENGTH - least, 0)


def _bucket_spans(contexts: DataFrame) -> DataFrame:
    """Repeated spans ``(row, lo, hi)`` of the open contexts, bucket by bucket."""

    def spans_of(t: pa.Table) -> pa.RecordBatch:
        row, lo, meta = (t.column(i).to_numpy() for i in (1, 2, 3))
        raw = t.column(0).combine_chunks()
        raw = raw.chunk(0) if isinstance(raw, pa.ChunkedArray) else raw
        ends = np.frombuffer(raw.buffers()[1], np.int32)[raw.offset : raw.offset + len(raw) + 1].astype(np.int64)
        flat = np.frombuffer(raw.buffers()[2], np.uint8)[ends[0] : ends[-1]]
        size, before = np.diff(ends), (meta >> 16 & 255).astype(np.int64)
        ctx = np.full(len(row) * (LEFT + LENGTH), 255, np.uint8)
        ctx[np.repeat(np.arange(len(row)) * (LEFT + LENGTH) + LEFT - before - (ends[:-1] - ends[0]), size) + np.arange(len(flat))] = flat
        left, right = extents(ctx.reshape(-1, LEFT + LENGTH))
        keep = (right > 0) & (meta >> 24 == 1)
        at = (lo + before)[keep]
        return pa.RecordBatch.from_arrays([pa.array(row[keep]), pa.array((at - left[keep]).astype(np.int32)), pa.array((at + right[keep]).astype(np.int32))], names=["row", "lo", "hi"])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        size, last = 0, None
        for b in batches:
            keys = [v[m >> 16 & 255 : (m >> 16 & 255) + LENGTH - (m & 255)] for v, m in zip(b.column(0).to_pylist(), b.column(3).to_pylist())]
            edges = [i for i in range(len(keys)) if keys[i] != (keys[i - 1] if i else last)]
            at = 0
            for i in edges:  # a key ends before each of these
                if size + i - at >= BUCKET_ROWS:
                    held.append(b.slice(at, i - at))
                    yield spans_of(pa.Table.from_batches(held))
                    held, size, at = [], 0, i
            held.append(b.slice(at))
            size += b.num_rows - at
            last = keys[-1] if keys else last
        if size:
            yield spans_of(pa.Table.from_batches(held))

    lead = F.expr(f"substring(bytes, (shiftright(meta, 16) & 255) + 1, {LENGTH} - (meta & 255))")
    spread = contexts.repartitionByRange(parts(contexts.sparkSession), lead).sortWithinPartitions(lead)
    return spread.mapInArrow(kernel, "row long, lo int, hi int")


def _halved(ctx: list[bytes], near: int, far: int, crowd: int) -> list[tuple[int, int]]:
    """Parts of the places ``near``..``far`` of a key in a string, none of them common in the sample.

    ``ctx``: sampled surroundings, ``LEFT`` bytes before the key and ``LENGTH`` after its start, 255
    outside the context.
    """
    parts_of: dict[bytes, set[bytes]] = {}
    for c in ctx:
        inside = c[LEFT - far : LEFT - near + LENGTH]
        if b"\xff" not in inside[far - near : LENGTH]:
            parts_of.setdefault(inside[far - near : LENGTH], set()).add(inside)
    if near == far or max(map(len, parts_of.values()), default=0) <= crowd:
        return [(near, far)]
    half = (near + far) // 2
    return _halved(ctx, near, half, crowd) + _halved(ctx, half + 1, far, crowd)


def _splits(rows: DataFrame, crowd: int) -> dict[int, list]:
    """How to cut the keys that are common in a bounded sample of the anchors."""
    spark = rows.sparkSession
    want = max(SAMPLE, SAMPLE_EACH * parts(spark))
    n, size = rows.agg(F.count(F.lit(1)), F.sum(F.octet_length("text"))).first()
    rate = min(1.0, want * (LEFT + 1) / 2 / (size or 1))
    of_rows = min(1.0, max(16 * rate, 2000 / (n or 1)))
    u = F.pmod(F.xxhash64("row", F.lit(17)), F.lit(1 << 30)) / F.lit(float(1 << 30))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece, texts in bites(batches, "text", BLOCK):
            b, offs = _flat(texts)
            row = piece.column(0).to_numpy(zero_copy_only=False)
            for key, _, lo, hi, q, _ in _blocks(b, offs, {}):
                doc = np.searchsorted(offs, lo, side="right") - 1
                draw = _mixed(row[doc].view(np.uint64) * _MIX2 + (lo - offs[doc]).astype(np.uint64) * _MIX)
                i = np.flatnonzero((draw >> np.uint64(32)) < np.uint64(int(rate / of_rows * 2**32)))
                yield pa.RecordBatch.from_arrays([pa.array(key[i].view(np.int64)), pa.array((q - lo)[i].astype(np.int32)), _gather(b, lo[i], hi[i] + LENGTH)], names=["key", "before", "bytes"])

    drawn = rows.where(u < of_rows).mapInArrow(kernel, "key long, before int, bytes binary").toArrow()  # about ``want`` rows
    cuts = _cuts(drawn, crowd)
    del drawn
    give_back()
    return cuts


def _cuts(drawn: pa.Table, crowd: int) -> dict[int, list]:
    """Parts of each key of ``drawn (key, before, bytes)`` that more than ``crowd`` surroundings share.  Only rows
    of such keys become Python objects, a key at a time."""
    key = drawn.column(0).to_numpy()
    order = np.argsort(key, kind="stable")
    first = np.flatnonzero(np.diff(key[order], prepend=key[order[:1]] - 1)) if len(key) else order
    cuts: dict[int, list] = {}
    for lo, hi in zip(first.tolist(), [*first[1:].tolist(), len(key)]):
        if hi - lo > crowd:
            mine = drawn.take(order[lo:hi])
            ctx = {(b"\xff" * (LEFT - before) + raw).ljust(LEFT + LENGTH, b"\xff") for before, raw in zip(mine.column(1).to_pylist(), mine.column(2).to_pylist())}
            if len(ctx) > crowd and len(c := _halved(sorted(ctx), 0, LEFT, crowd)) > 1:
                cuts[int(key[order[lo]]) & (1 << 64) - 1] = c
    return cuts


def spans(rows: DataFrame, crowd: int = CROWD) -> DataFrame:
    """Removed spans ``(row, lo, hi)`` in bytes of ``rows (row, text)``; they may overlap."""
    long = rows.where(F.octet_length("text") >= LENGTH)
    shared = rows.sparkSession.sparkContext.broadcast(_splits(long, crowd))  # at most a part of the sample
    judged = cut(_verdicts(_anchor_rows(long, shared)), "verdicts")
    asks = judged.where("meta >= 0").groupBy("row").agg(F.collect_list(F.struct("lo", "hi", "meta")).alias("asks"))  # within one document
    asked = rows.join(asks.hint("shuffle_hash"), "row").select("row", "text", "asks")
    return judged.where("meta < 0").select("row", "lo", "hi").union(_bucket_spans(_contexts(asked)))


def _merge(lo: list[int], hi: list[int]) -> list[tuple[int, int]]:
    runs: list[list[int]] = []
    for a, z in sorted(zip(lo, hi)):
        if runs and a <= runs[-1][1]:
            runs[-1][1] = max(runs[-1][1], z)
        else:
            runs.append([a, z])
    return [tuple(r) for r in runs]


def _removed(rows: DataFrame, finish, schema: str, crowd: int) -> DataFrame:
    gathered = spans(rows, crowd).groupBy("row").agg(F.collect_list(F.struct("lo", "hi")).alias("runs"))
    names = [x.split()[0] for x in schema.split(", ")]
    kinds = {"long": pa.int64(), "string": pa.string()}
    kinds = [kinds[x.split()[1]] for x in schema.split(", ")]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece, texts in bites(batches, "text"):
            out = []
            for row, text, runs in zip(piece.column(0).to_pylist(), texts, piece.column(2).to_pylist()):
                raw, cutter, kept, at = text.encode(), [], [], 0
                if runs:
                    cutter = _merge([r["lo"] for r in runs], [r["hi"] for r in runs])
                for a, z in cutter:
                    kept.append(raw[at:a])
                    at = z
                out.append((row, *finish(raw, cutter, b"".join([*kept, raw[at:]]))))
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), kinds)], names=names)

    return rows.join(gathered.hint("shuffle_hash"), "row", "left").select("row", "text", "runs").mapInArrow(kernel, schema)


def _keyed(docs: DataFrame) -> tuple[DataFrame, DataFrame | None]:
    """Rows by a key that is never null; saying so lets both joins with the texts share one exchange."""
    rows, names = numbered(docs)
    return rows.where("row IS NOT NULL"), names


def digests(docs: DataFrame, crowd: int = CROWD) -> DataFrame:
    """``(doc_id, n_bytes, n_removed, n_spans, kept_sha256)``."""
    rows, names = _keyed(docs)
    one = lambda raw, runs, kept: (len(raw), len(raw) - len(kept), len(runs), hashlib.sha256(kept).hexdigest())
    return renamed(_removed(rows, one, "row long, n_bytes long, n_removed long, n_spans long, kept_sha256 string", crowd), names)


def texts(docs: DataFrame, crowd: int = CROWD) -> DataFrame:
    """``(doc_id, text, n_removed)``: what is left; bytes of characters cut in two go as well."""
    rows, names = _keyed(docs)
    one = lambda raw, runs, kept: (kept.decode(errors="ignore"), len(raw) - len(kept))
    return renamed(_removed(rows, one, "row long, text string, n_removed long", crowd), names)


def clean(docs: DataFrame, crowd: int = CROWD) -> DataFrame:
    """Rows of ``docs`` with their columns, the text without its repeated bytes and, where there is
    such a column, ``n_chars`` counted again.  Names of its own avoid those of the table."""
    fixed, key = docs, "doc_id"
    if numbered(docs)[1] is not None:
        key = fresh_name(docs, "row")
        fixed = cut(docs.withColumn(key, F.monotonically_increasing_id()), "suffix-rows")
    other, text = fresh_name(fixed, "key"), fresh_name(fixed, "text")
    left = texts(fixed.select(F.col(key).alias("doc_id"), "text"), crowd).select(F.col("doc_id").alias(other), F.col("text").alias(text))
    joined = fixed.drop("text").join(left, F.col(key) == F.col(other))
    new = {"text": F.col(text), "n_chars": F.length(text).cast("long")}
    return joined.select(*[new[c].alias(c) if c in new else F.col(c) for c in docs.columns])


#: DuckDB SQL with the same rule, by counting all strings; bytes are taken as pairs of hexadecimal digits.
ORACLE = f"""WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
 p AS (SELECT doc_id, i, md5(substr(h, 2 * i + 1, {2 * LENGTH})) AS k FROM (SELECT doc_id, h, unnest(range(greatest(length(h) // 2 - {LENGTH - 1}, 0))) AS i FROM d)),
 s AS (SELECT doc_id, i FROM p JOIN (SELECT k FROM p GROUP BY k HAVING count(*) > 1) USING (k)),
 g AS (SELECT doc_id, i, sum(fresh) OVER (PARTITION BY doc_id ORDER BY i) AS run FROM (SELECT doc_id, i, CASE WHEN i <= lag(i) OVER (PARTITION BY doc_id ORDER BY i) + {LENGTH} THEN 0 ELSE 1 END AS fresh FROM s)),
 r AS (SELECT doc_id, min(i) AS lo, max(i) + {LENGTH} AS hi FROM g GROUP BY doc_id, run),
 c AS (SELECT doc_id, lo, hi, lag(hi, 1, 0) OVER (PARTITION BY doc_id ORDER BY lo) AS past FROM r),
 k AS (SELECT doc_id, sum(hi - lo)::BIGINT AS n_removed, count(*)::BIGINT AS n_spans, max(hi) AS last, string_agg(substr(h, 2 * past + 1, 2 * (lo - past)), '' ORDER BY lo) AS kept FROM c JOIN d USING (doc_id) GROUP BY doc_id)
 SELECT doc_id, (length(h) // 2)::BIGINT AS n_bytes, coalesce(n_removed, 0) AS n_removed, coalesce(n_spans, 0) AS n_spans, sha256(unhex(coalesce(kept || substr(h, 2 * last + 1), h))) AS kept_sha256 FROM d LEFT JOIN k USING (doc_id)"""
