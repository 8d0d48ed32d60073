"""BPE encoding with content-defined chunk reuse, and decoding.

1. A rolling hash over 32 characters cuts each text where the hash has given low bits, so equal
   passages in different documents yield equal chunks.
   Chunks have some four thousand characters, so a passage of that length that documents share is
   mostly encoded once; ``reuse`` reports how many are.
2. Chunks meet by content hash and each distinct chunk is encoded once.  Within an input slice
   equal chunks are one row already; a chunk that a slice holds many times is dealt out over
   ``SPREAD`` places, so that a passage found in a third of all documents is no single task's.
   A document of one chunk is finished here, once for all its copies.
3. The chunks of any other document come together in order and every join is repaired: the text from
   the last white space before the join to the first one after it is encoded again, over as
   many chunks as needed, until the tokens on both sides stand at white space, where the
   encoding of a chunk and of the whole text agree exactly.

Defined cases: a null text counts as the empty text (no ids); very long texts are many chunks;
a text without white space is encoded whole at its joins; repeated rows reuse chunks and each
gets its own result; an empty table gives no rows; other columns of the input are ignored; rows
with a null ``doc_id`` are numbered apart and keep their null id.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bites, numbered, parts, renamed
from .word_memo import encoder

MEAN, LEAST, MOST, SPREAD, MANY = 4096, 512, 65536, 64, 4
ALONE = -1  # place of the only chunk of a document
_GAP = re.compile(r"[ \t\n\r]")


def cuts(text: str) -> list[int]:
    """Ends of the chunks of ``text``."""
    n = len(text)
    if n <= LEAST:
        return [n]
    h = np.frombuffer(text.encode("utf-32-le"), np.uint32).astype(np.uint64)
    h = (h + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
    h ^= h >> np.uint64(31)
    for step in (1, 2, 4, 8, 16):
        h[step:] = h[step:] + (h[:-step] << np.uint64(step))  # right side is read in full first
    ends, last = [], 0
    for e in (np.flatnonzero((h >> np.uint64(40)) % np.uint64(MEAN) == 0) + 1).tolist():
        if e - last >= LEAST and n - e >= LEAST:
            ends += range(last + MOST, e, MOST)
            ends.append(e)
            last = e
    ends += range(last + MOST, n, MOST)
    return [*ends, n]


def _chunks(docs: DataFrame) -> DataFrame:
    """One row for each distinct chunk of an input slice: its key, text and places."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        squeeze = zstandard.ZstdCompressor(level=3)
        for piece, texts in bites(batches, "text", 8_000_000):
            found: dict[bytes, list] = {}
            for row, text in zip(piece.column(0).to_pylist(), texts):
                lo, ends = 0, cuts(text)
                for seq, hi in enumerate(ends):
                    part = text[lo:hi].encode()
                    key = hashlib.blake2b(part, digest_size=16).digest()
                    if key not in found:
                        found[key] = [part, [], []]
                    found[key][1].append(row)
                    found[key][2].append(seq if len(ends) > 1 else ALONE)
                    lo = hi
            keys = list(found)
            places = [found[k] for k in keys]
            salt = [1 + p[1][0] % SPREAD if len(p[1]) >= MANY else 0 for p in places]
            cols = [pa.array(keys, pa.binary()), pa.array(salt, pa.int32()), pa.array([squeeze.compress(p[0]) for p in places], pa.binary()), pa.array([p[1] for p in places], pa.list_(pa.int64())), pa.array([p[2] for p in places], pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays(cols, names=["key", "salt", "text", "rows", "seqs"])

    return docs.mapInArrow(kernel, "key binary, salt int, text binary, rows array<long>, seqs array<long>")


def _encoded(chunks: DataFrame, tokenizer: str, kind: str, finish, schema: str) -> DataFrame:
    """Ids of each distinct chunk at each of its places, or the finished result of a document
    that has no other chunk."""
    done_names, done_kinds = _fields(schema)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, squeeze, loose = encoder(tokenizer, kind), zstandard.ZstdCompressor(level=3), zstandard.ZstdDecompressor()
        finisher, wide = finish(enc), enc.tok.get_vocab_size() > 65536
        previous = None
        for b in _slices(batches, 512):
            keys, zs, rows, seqs = (b.column(i).to_pylist() for i in (0, 2, 3, 4))
            fresh, of = [], []
            for key, z in zip(keys, zs):
                if previous is None or key != previous[0] or fresh and key != fresh[-1][0]:
                    if not fresh or fresh[-1][0] != key:
                        fresh.append((key, loose.decompress(z).decode()))
                    of.append(len(fresh) - 1)
                else:
                    of.append(len(fresh) - 1 if fresh else -1)
            texts = [t for _, t in fresh]
            heads = [(_GAP.search(t) or re.search("$", t)).start() if t else 0 for t in texts]
            gaps = [max(t.rfind(c) for c in " \t\n\r") for t in texts]
            ids, lens = enc.encode(texts + [t[:h] for t, h in zip(texts, heads)] + [t[g + 1 :] for t, g in zip(texts, gaps)])
            n = len(texts)
            whole = np.split(ids, np.cumsum(lens)[:-1])[:n]
            made = []
            for (k, t), w, h, g, a, z in zip(fresh, whole, heads, gaps, lens[n : 2 * n], lens[2 * n :]):
                made.append([k, w, None, (squeeze.compress(w.astype("<u4" if wide else "<u2").tobytes()), t[:h], int(a), t[g + 1 :] if g >= 0 else None, int(z))])
            out = []
            for i, r, s in zip(of, rows, seqs):
                it = made[i] if i >= 0 else previous
                for x, y in zip(r, s):
                    if y == ALONE:
                        it[2] = it[2] or finisher(it[1], 0, 0)
                        out.append((x, y, None, None, None, None, None, *it[2]))
                    else:
                        out.append((x, y, *it[3], *[None] * len(done_names)))
            previous = made[-1] if made else previous
            kinds = [pa.int64(), pa.int64(), pa.binary(), pa.string(), pa.int64(), pa.string(), pa.int64(), *done_kinds]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), kinds)], names=["row", "seq", "_ids", "_head", "_n_head", "_tail", "_n_tail", *done_names])

    n = parts(chunks.sparkSession)
    return chunks.repartition(n, "key", "salt").sortWithinPartitions("key", "salt").mapInArrow(kernel, "row long, seq long, _ids binary, _head string, _n_head long, _tail string, _n_tail long, " + schema)


def _slices(batches, size):
    for b in batches:
        for lo in range(0, b.num_rows, size):
            yield b.slice(lo, size)


def _join(enc, pieces: list[list[tuple]]) -> list[tuple[np.ndarray, int, int]]:
    """Ids, joins and joins whose tokens changed, of each document (its pieces in order).

    A piece: ids, head (text before the first white space), its tokens, tail (text after the
    last white space, None without any), its tokens.
    """
    plans, again = [], []
    for doc in pieces:
        if len(doc) == 1:
            plans.append([doc[0][0]])
            continue
        plan, open_text, old = [], "", []
        for ids, head, n_head, tail, n_tail in doc:
            if tail is None:  # no white space: the join goes on
                open_text += head
                old.append(ids)
                continue
            plan.append((len(again), np.concatenate([*old, ids[:n_head]])))
            again.append(open_text + head)
            plan.append(ids[n_head : len(ids) - n_tail])
            open_text, old = tail, [ids[len(ids) - n_tail :]]
        plan.append((len(again), np.concatenate(old) if old else np.zeros(0, np.uint32)))
        again.append(open_text)
        plans.append(plan)
    ids, lens = enc.encode(again) if again else (np.zeros(0, np.uint32), np.zeros(0, np.int64))
    repaired = np.split(ids, np.cumsum(lens)[:-1]) if again else []
    out = []
    for doc, plan in zip(pieces, plans):
        got = [repaired[x[0]] if isinstance(x, tuple) else x for x in plan]
        changed = sum(isinstance(x, tuple) and not np.array_equal(repaired[x[0]], x[1]) for x in plan)
        out.append((np.concatenate(got), len(doc) - 1, changed))
    return out


def _assembled(pieces: DataFrame, tokenizer: str, kind: str, finish, schema: str) -> DataFrame:
    names, kinds = _fields("row long, " + schema)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, loose = encoder(tokenizer, kind), zstandard.ZstdDecompressor()
        finisher, size = finish(enc), "<u4" if enc.tok.get_vocab_size() > 65536 else "<u2"
        docs, rows, held = [], [], 0

        def flush(keep_last: bool):
            nonlocal docs, rows, held
            n = len(docs) - keep_last
            joined = _join(enc, docs[:n])
            out = [(row, *finisher(*x)) for row, x in zip(rows[:n], joined)]
            docs, rows = docs[n:], rows[n:]
            held = sum(len(p[0]) for d in docs for p in d)
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), kinds)], names=names) if out else None

        for b in _slices(batches, 256):
            alone = pc.equal(b.column(1), ALONE)
            done = b.filter(alone)
            if done.num_rows:
                yield pa.RecordBatch.from_arrays([done.column(0), *done.columns[7:]], names=names)
            for row, _, ids, head, n_head, tail, n_tail in zip(*(c.to_pylist() for c in b.filter(pc.invert(alone)).columns[:7])):
                if not rows or rows[-1] != row:
                    rows.append(row)
                    docs.append([])
                got = np.frombuffer(loose.decompress(ids), size)
                docs[-1].append((got, head, n_head, tail, n_tail))
                held += len(got)
            if held > 1_000_000 and len(docs) > 1 and (made := flush(True)) is not None:
                yield made
        if docs and (made := flush(False)) is not None:
            yield made

    n = parts(pieces.sparkSession)
    return pieces.repartition(n, "row").sortWithinPartitions("row", "seq").mapInArrow(kernel, "row long, " + schema)


def _fields(schema: str) -> tuple[list[str], list[pa.DataType]]:
    kinds = {"long": pa.int64(), "string": pa.string(), "array<int>": pa.list_(pa.int32())}
    pairs = [x.split() for x in schema.split(", ")]
    return [p[0] for p in pairs], [kinds[p[1]] for p in pairs]


def _run(docs: DataFrame, tokenizer: str, kind: str, finish, schema: str) -> DataFrame:
    rows, names = numbered(docs)
    return renamed(_assembled(_encoded(_chunks(rows), tokenizer, kind, finish, schema), tokenizer, kind, finish, schema), names)


def reuse(docs: DataFrame) -> DataFrame:
    """One row ``(chunks, distinct_chunks, shared_chunks)``: chunks of all distinct texts, how many
    are left when each is encoded once, and how many of these stand in more than one text."""
    texts = docs.select(F.col("text").cast("string").alias("text")).where("text IS NOT NULL").distinct()
    rows = texts.select(F.monotonically_increasing_id().alias("row"), "text")
    by_key = _chunks(rows).groupBy("key").agg(F.sum(F.size("rows")).alias("n"))
    return by_key.agg(F.sum("n").alias("chunks"), F.count(F.lit(1)).alias("distinct_chunks"), F.count_if(F.col("n") > 1).alias("shared_chunks"))


def encode(docs: DataFrame, tokenizer: str, kind: str = "word") -> DataFrame:
    """``(doc_id, ids, n_joins, n_repaired)``."""
    return _run(docs, tokenizer, kind, lambda enc: lambda ids, joins, changed: (ids.astype(np.int32), joins, changed), "ids array<int>, n_joins long, n_repaired long")


def decode(encoded: DataFrame, tokenizer: str) -> DataFrame:
    """``(doc_id, text)`` by the library's decoder."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok = encoder(tokenizer, "word").tok
        for b in _slices(batches, 256):
            texts = tok.decode_batch([x or [] for x in b.column(1).to_pylist()], skip_special_tokens=False)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(kernel, "doc_id long, text string")


def digests(docs: DataFrame, tokenizer: str) -> DataFrame:
    """``(doc_id, n_tokens, ids_sha256, decoded_sha256, n_joins, n_repaired)``.

    The vocabulary used has no decoder, so a decoded text is its tokens with spaces between.
    """

    def finish(enc):
        if enc.tok.decoder is not None:
            raise ValueError("this digest is for vocabularies without a decoder")
        size = enc.tok.get_vocab_size(with_added_tokens=True)
        digits, shown = [str(i) for i in range(size)], [enc.tok.id_to_token(i) or "" for i in range(size)]
        sha = lambda words: hashlib.sha256(" ".join(words).encode()).hexdigest()

        def one(ids: np.ndarray, joins: int, changed: int):
            x = ids.tolist()
            return len(x), sha(map(digits.__getitem__, x)), sha(map(shown.__getitem__, x)), joins, changed

        return one

    return _run(docs, tokenizer, "word", finish, "n_tokens long, ids_sha256 string, decoded_sha256 string, n_joins long, n_repaired long")
