"""Token ids as word-aligned binary files (Simple-8b).

A 64-bit word holds a 4-bit selector in its top bits and, below it, ``COUNT[s]`` values of
``BITS[s]`` bits each, the first value lowest.  Selector 0 stands for 240 zeros, selector 1 is
the escape: the next word is one raw 64-bit value.  Values are packed greedily, block by block
of ``BLOCK`` values, so that every block starts on a word; the block table holds the words of
each block, which lets a reader decode any block, or all of them at once, with array
operations.  A file is a row of segments, each with its own document and block tables; both
writer and reader hold one segment at a time.

Defined cases: a null text counts as the empty text (one end id only); null ``doc_id`` sorts
first and is kept as a row; repeated rows are all written; an empty table gives no file and
no row; other columns of the input are ignored.  Files carry the partition's number and are
renamed into place when complete, so a task that runs again replaces its file by an equal one.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bites, parts, scratch
from .word_memo import encoder

#: Fixed values of the format: values per word and bits per value, by selector.
COUNT = np.array([240, 1, 60, 30, 20, 15, 12, 10, 8, 7, 6, 5, 4, 3, 2, 1])
BITS = np.array([0, 64, 1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 15, 20, 30, 60])
BLOCK = 1024
_HEAD = struct.Struct("<8sQQQ")
_MAGIC = b"TWALKS8B"


def _widths(v: np.ndarray) -> np.ndarray:
    """Bits that each value needs."""
    w = np.zeros(len(v), np.uint8)
    for b in sorted(set(BITS.tolist()) - {64}, reverse=True):
        w[v < (np.uint64(1) << np.uint64(b))] = b
    w[v >= np.uint64(1 << 60)] = 64
    return w


def pack(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Words of all blocks, and the number of words of each block."""
    n = len(values)
    if not n:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    v = values.astype(np.uint64)
    blocks = -(-n // BLOCK)
    w = np.full(blocks * BLOCK + 240, 255, np.uint8)
    w[:n] = _widths(v)
    best = np.full(blocks * BLOCK, 1, np.uint8)
    best[: n][w[:n] <= 60] = 15
    # widest run of values that fits, tried from the fewest values up
    for s in range(14, 1, -1):
        fits = w <= BITS[s]
        k = int(COUNT[s])
        if int(fits.sum()) >= k:
            upto = np.cumsum(np.concatenate([[0], fits]), dtype=np.int32)
            best[(upto[k:] - upto[:-k] == k)[: len(best)].nonzero()[0]] = s
    zero = w == 0
    if int(zero.sum()) >= 240:
        upto = np.cumsum(np.concatenate([[0], zero]), dtype=np.int32)
        best[(upto[240:] - upto[:-240] == 240)[: len(best)].nonzero()[0]] = 0
    # A run may not cross its block: near a block's end take a selector with fewer values.
    last = np.minimum(np.arange(1, blocks + 1) * BLOCK, n)
    at, live = np.arange(blocks) * BLOCK, np.arange(blocks)
    chain, owner = [], []
    padded = np.zeros(blocks * BLOCK + 240, np.uint64)
    padded[:n] = v
    while len(live):
        pos, room = at[live], last[live] - at[live]
        s = best[pos].astype(np.int64)
        tight = COUNT[s] > room
        if tight.any():
            for i in np.flatnonzero(tight):
                need = w[pos[i] : pos[i] + room[i]]
                ok = [x for x in range(2, 16) if COUNT[x] <= room[i] and need[: COUNT[x]].max() <= BITS[x]]
                s[i] = ok[0] if ok else 1
        chain.append(pos)
        owner.append(s)
        at[live] = pos + COUNT[s]
        live = live[at[live] < last[live]]
    pos, sel = np.concatenate(chain), np.concatenate(owner)
    order = np.argsort(pos, kind="stable")
    pos, sel = pos[order], sel[order]
    size = np.where(sel == 1, 2, 1)
    where = np.cumsum(size) - size
    words = np.zeros(int(size.sum()), np.uint64)
    for s in np.unique(sel):
        m = sel == s
        p, word = pos[m], np.full(int(m.sum()), np.uint64(s) << np.uint64(60), np.uint64)
        if s == 1:
            words[where[m] + 1] = padded[p]
        elif s:
            for j in range(COUNT[s]):
                word |= padded[p + j] << np.uint64(j * int(BITS[s]))
        words[where[m]] = word
    per = np.bincount(pos // BLOCK, weights=size, minlength=blocks).astype(np.int64)
    return words, per


def unpack(words: np.ndarray, per: np.ndarray, n: int) -> np.ndarray:
    """All values; ``per`` is the block table, ``n`` the number of values."""
    out = np.zeros(n, np.uint64)
    if not n:
        return out
    sel = (words >> np.uint64(60)).astype(np.int64)
    raw = np.zeros(len(words), bool)
    if (sel == 1).any():  # the word after an escape is raw, whatever its top bits say
        i = 0
        marks = np.flatnonzero(sel == 1)
        after = -1
        for i in marks.tolist():
            if i != after:
                raw[i + 1] = True
                after = i + 1
    count = np.where(raw, 0, COUNT[sel])
    start = np.cumsum(count) - count
    for s in np.unique(sel[~raw]):
        m = np.flatnonzero((sel == s) & ~raw)
        if s == 1:
            out[start[m]] = words[m + 1]
        elif s:
            mask = np.uint64((1 << int(BITS[s])) - 1)
            for j in range(COUNT[s]):
                out[start[m] + j] = (words[m] >> np.uint64(j * int(BITS[s]))) & mask
    return out


def segment(doc_ids: list, lens: np.ndarray, ids: np.ndarray) -> bytes:
    words, per = pack(ids)
    none = np.array([d is None for d in doc_ids], np.uint8)
    docs = np.array([0 if d is None else d for d in doc_ids], np.int64)
    return b"".join([_HEAD.pack(_MAGIC, len(docs), len(ids), len(per)), none.tobytes(), docs.tobytes(), lens.astype("<u4").tobytes(), per.astype("<u4").tobytes(), words.astype("<u8").tobytes()])


def read_segments(stream) -> Iterator[tuple[list, np.ndarray, np.ndarray]]:
    while head := stream.read(_HEAD.size):
        magic, docs, n, blocks = _HEAD.unpack(head)
        if magic != _MAGIC:
            raise ValueError("not a token file")
        none = np.frombuffer(stream.read(docs), np.uint8)
        ids = np.frombuffer(stream.read(8 * docs), np.int64)
        lens = np.frombuffer(stream.read(4 * docs), "<u4")
        per = np.frombuffer(stream.read(4 * blocks), "<u4")
        words = np.frombuffer(stream.read(8 * int(per.sum())), "<u8")
        yield [None if x else d for x, d in zip(none, ids.tolist())], lens, unpack(words, per, n)


def write(docs: DataFrame, tokenizer: str, out: str, end_id: int = 0, kind: str = "byte", limit: int = 1_000_000) -> DataFrame:
    """Encode ``docs (doc_id, text)`` and write one file per range of ascending ``doc_id``.

    Returns the manifest ``(part, path, n_docs, n_tokens, start)``: one row per file, as many
    as there are partitions; ``start`` counts the ids in the files before it.
    """
    spark = docs.sparkSession

    def save(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, part, n_docs, n_tokens = encoder(tokenizer, kind), TaskContext.get().partitionId(), 0, 0
        fs, root = pyarrow.fs.FileSystem.from_uri(out)
        path, draft = f"{root}/part-{part:06d}.s8b", f"{root}/.part-{part:06d}.{uuid.uuid4().hex}"
        sink = None
        for piece, texts in bites(batches, "text", limit):
            ids, lens = enc.encode(texts)
            at = np.cumsum(lens)
            ids = np.insert(ids.astype(np.uint32), at, end_id)
            lens = lens + 1
            if sink is None:
                fs.create_dir(root, recursive=True)
                sink = fs.open_output_stream(draft)
            sink.write(segment(piece.column(0).to_pylist(), lens, ids))
            n_docs += len(lens)
            n_tokens += len(ids)
        if sink is not None:
            sink.close()
            fs.move(draft, path)
            yield pa.RecordBatch.from_pylist([{"part": part, "path": f"{out}/part-{part:06d}.s8b", "n_docs": n_docs, "n_tokens": n_tokens}])

    ordered = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).repartitionByRange(parts(spark), "doc_id").sortWithinPartitions("doc_id", "text")
    files = ordered.mapInArrow(save, "part long, path string, n_docs long, n_tokens long").collect()  # a row per file
    rows, start = [], 0
    for r in sorted(files, key=lambda r: r.part):
        rows.append((r.part, r.path, r.n_docs, r.n_tokens, start))
        start += r.n_tokens
    return spark.createDataFrame(rows, "part long, path string, n_docs long, n_tokens long, start long")


def read(manifest: DataFrame) -> DataFrame:
    """``(doc_id, start, n_tokens, ids)`` of every document in the manifest's files."""
    return _scan(manifest, "doc_id long, start long, n_tokens long, ids array<long>", lambda ids: ids.astype(np.int64))


def digests(manifest: DataFrame) -> DataFrame:
    """``(doc_id, start, n_tokens, ids_crc32)`` of every document, from the files."""
    return _scan(manifest, "doc_id long, start long, n_tokens long, ids_crc32 long", lambda ids: zlib.crc32(ids.astype("<u4").tobytes()))


def _scan(manifest: DataFrame, schema: str, last) -> DataFrame:
    names = [x.split()[0] for x in schema.split(", ")]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()) if "array" in schema else pa.int64()]

    def load(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for path, start in zip(b.column(1).to_pylist(), b.column(4).to_pylist()):
                fs, name = pyarrow.fs.FileSystem.from_uri(path)
                with fs.open_input_stream(name) as stream:
                    for docs, lens, values in read_segments(stream):
                        at = np.cumsum(lens.astype(np.int64))
                        cols = [docs, (start + at - lens).tolist(), lens.tolist(), [last(x) for x in np.split(values, at[:-1])]]
                        start += int(at[-1])
                        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names=names)

    n = max(1, len(manifest.collect()))
    spread = manifest.repartition(n, "part") if n > 1 else manifest
    return spread.mapInArrow(load, schema)


def run(spark: SparkSession, docs: DataFrame, tokenizer: str, out: str | None = None) -> DataFrame:
    return digests(write(docs, tokenizer, out or scratch(spark, "token-files")))


__all__ = ["BLOCK", "digests", "pack", "read", "run", "unpack", "write"]
