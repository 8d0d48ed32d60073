"""Quality scores by attention-based multiple-instance learning.

A document is a bag of passages of ``PASSAGE`` bytes, and only the bag has a label.  Each passage
is encoded (shares of byte classes, variety of its three-byte strings, repeated words, hashed
three-byte strings by fixed projection, then a learned layer); a gated attention gives it a
weight within its document; the weighted sum of the passages is scored.  Encoder, attention and
score are learned together from document labels, with plain numpy and Adam, on a bounded sample.

Defined cases: null and empty texts have no passage and get the score of the empty bag; very
long texts are encoded whole, passage by passage; repeated rows give equal scores; without
labels every score is 0.5; an empty table gives no rows; other columns are ignored; rows with a
null ``doc_id`` are scored, are not held out and are not learned from.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bites
from .sampling import labelled, remainder

PASSAGE, VARIETY, PROJECTED, HIDDEN = 256, 1024, 16, 16
#: Byte classes: lower case, upper case, digit, blank, line end, bar, stop, mark, shout, high, rest.
_CLASS = np.array([3 if c == 32 else 4 if c in b"\n\r" else 5 if c == 124 else 6 if c in b".,;:" else 8 if c == 33 else 9 if c >= 128 else 0 if chr(c).islower() else 1 if chr(c).isupper() else 2 if chr(c).isdigit() else 7 if 33 < c < 127 else 10 for c in range(256)], np.int64)
_SIGN = np.random.default_rng(5).standard_normal((VARIETY, PROJECTED)).astype(np.float32)
FEATURES = 11 + 5 + PROJECTED


def passages(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Features of all passages, and the number of passages of each text."""
    raw = [t.encode() for t in texts]
    sizes = np.array([len(r) for r in raw], np.int64)
    count = -(-sizes // PASSAGE)
    n = int(count.sum())
    if not n:
        return np.zeros((0, FEATURES), np.float32), count
    b = np.frombuffer(b"".join(raw), np.uint8)
    begin = np.cumsum(sizes) - sizes
    doc = np.repeat(np.arange(len(texts)), sizes)
    first = np.cumsum(count) - count
    own = first[doc] + (np.arange(len(b)) - begin[doc]) // PASSAGE
    size = np.bincount(own, minlength=n)
    share = np.bincount(own * 11 + _CLASS[b], minlength=n * 11).reshape(n, 11) / size[:, None]
    # three-byte strings that lie within one passage
    key = (b[:-2].astype(np.uint32) | b[1:-1].astype(np.uint32) << np.uint32(8) | b[2:].astype(np.uint32) << np.uint32(16)) if len(b) > 2 else np.zeros(0, np.uint32)
    inside = own[:-2] == own[2:] if len(b) > 2 else np.zeros(0, bool)
    at = own[:-2][inside] * VARIETY + ((key[inside] * np.uint32(2654435761)) >> np.uint32(22)) if len(b) > 2 else np.zeros(0, np.int64)
    seen = np.zeros(n * VARIETY, np.float32)
    seen[at] = 1
    seen = seen.reshape(n, VARIETY)
    variety = seen.sum(1) / np.maximum(size - 2, 1)
    # a word equal to the one before it
    space = (_CLASS[b] == 3) | (_CLASS[b] == 4)
    step = np.ones(len(b), bool)
    step[1:] = own[1:] != own[:-1]
    start = np.flatnonzero(~space & (np.concatenate([[True], space[:-1]]) | step))
    stop = np.flatnonzero(~space & (np.concatenate([space[1:], [True]]) | np.concatenate([step[1:], [True]]))) + 1
    again = np.zeros(n)
    words = np.bincount(own[start], minlength=n) if len(start) else np.zeros(n)
    if len(start) > 1:
        mixed = np.cumsum(np.concatenate([[0], (b.astype(np.uint64) + np.uint64(3)) ** np.uint64(5)]).astype(np.uint64))
        tag = (mixed[stop] - mixed[start]) * np.uint64(31) + (stop - start).astype(np.uint64)
        same = (tag[1:] == tag[:-1]) & (own[start[1:]] == own[start[:-1]])
        again = np.bincount(own[start[1:]][same], minlength=n)
    words = np.maximum(words, 1)
    more = np.stack([variety, again / words, np.minimum(size / words, 40) / 10, size / PASSAGE, np.log1p(count[np.repeat(np.arange(len(texts)), count)]) / 5], 1)
    hashed = seen @ _SIGN / np.sqrt(np.maximum(seen.sum(1, keepdims=True), 1))
    return np.concatenate([share * 4, more, hashed], 1).astype(np.float32), count


_sig = lambda x: 1 / (1 + np.exp(-np.clip(x, -30, 30)))


class Net:
    def __init__(self, seed: int = 3):
        r = np.random.default_rng(seed)
        g = lambda *s: (r.standard_normal(s) / np.sqrt(s[0])).astype(np.float32)
        self.p = {"W": g(FEATURES, HIDDEN), "b": np.zeros(HIDDEN, np.float32), "V": g(HIDDEN, 8), "U": g(HIDDEN, 8), "w": g(8), "c": g(HIDDEN), "d": np.zeros(1, np.float32)}
        self.mean, self.std = np.zeros(FEATURES, np.float32), np.ones(FEATURES, np.float32)

    def _forward(self, x: np.ndarray, count: np.ndarray):
        p = self.p
        bag = np.repeat(np.arange(len(count)), count)
        h = np.tanh(((x - self.mean) / self.std) @ p["W"] + p["b"])
        t, s = np.tanh(h @ p["V"]), _sig(h @ p["U"])
        e = np.clip((t * s) @ p["w"], -30, 30)
        e = np.exp(e)
        a = e / np.maximum(np.bincount(bag, weights=e, minlength=len(count)), 1e-30)[bag]
        z = np.stack([np.bincount(bag, weights=a * h[:, k], minlength=len(count)) for k in range(HIDDEN)], 1)
        return _sig(z @ p["c"] + p["d"][0]), (bag, h, t, s, a, z)

    def score(self, x: np.ndarray, count: np.ndarray) -> np.ndarray:
        return self._forward(x, count)[0]

    def gradients(self, x: np.ndarray, count: np.ndarray, y: np.ndarray) -> dict[str, np.ndarray]:
        """Of the mean log loss of the bags."""
        out, (bag, h, t, s, a, z) = self._forward(x, count)
        p, g = self.p, {}
        do = (out - y) / len(y)
        g["c"], g["d"] = z.T @ do, np.array([do.sum()])
        dz = do[:, None] * p["c"]
        dot = (dz[bag] * h).sum(1)
        de = a * (dot - np.bincount(bag, weights=a * dot, minlength=len(count))[bag])
        g["w"] = (t * s).T @ de
        dts = de[:, None] * p["w"]
        dt, ds = dts * s * (1 - t * t), dts * t * s * (1 - s)
        g["V"], g["U"] = h.T @ dt, h.T @ ds
        dh = (a[:, None] * dz[bag] + dt @ p["V"].T + ds @ p["U"].T) * (1 - h * h)
        g["W"], g["b"] = ((x - self.mean) / self.std).T @ dh, dh.sum(0)
        return g

    def train(self, x: np.ndarray, count: np.ndarray, y: np.ndarray, epochs: int = 30, rate: float = 0.01, batch: int = 128) -> None:
        self.mean, self.std = x.mean(0), x.std(0) + 1e-3
        first, r = np.cumsum(count) - count, np.random.default_rng(1)
        m = {k: [np.zeros_like(v), np.zeros_like(v)] for k, v in self.p.items()}
        step = 0
        for _ in range(epochs):
            order = r.permutation(len(y))
            for lo in range(0, len(y), batch):
                ids = order[lo : lo + batch]
                rows = np.concatenate([np.arange(first[i], first[i] + count[i]) for i in ids])
                xs, cs = x[rows], count[ids]
                p, step = self.p, step + 1
                for k, v in self.gradients(xs, cs, y[ids]).items():
                    m[k][0] = 0.9 * m[k][0] + 0.1 * v
                    m[k][1] = 0.999 * m[k][1] + 0.001 * v * v
                    self.p[k] = (p[k] - rate * (m[k][0] / (1 - 0.9**step)) / (np.sqrt(m[k][1] / (1 - 0.999**step)) + 1e-8) - 1e-5 * p[k]).astype(np.float32)


def fit(docs: DataFrame, labels: DataFrame, per_class: int = 2500) -> Net | None:
    """Learn from at most about ``per_class`` labelled documents of each class."""
    rows = labelled(docs, labels, "quality", 5, per_class)
    if len({y for _, y in rows}) < 2:
        return None
    made = [passages([t for t, _ in rows[i : i + 50]]) for i in range(0, len(rows), 50)]  # in small blocks: bounded memory
    net = Net()
    net.train(np.concatenate([x for x, _ in made]), np.concatenate([c for _, c in made]), np.array([y for _, y in rows], np.float32))
    return net


def score(docs: DataFrame, net: Net | None, threshold: float = 0.3) -> DataFrame:
    """``(doc_id, held_out, score, predicted)``."""
    shared = docs.sparkSession.sparkContext.broadcast(net)  # a few thousand numbers

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece, texts in bites(batches, "text", 1_000_000):
            out = np.full(len(texts), 0.5) if shared.value is None else shared.value.score(*passages(texts))
            yield pa.RecordBatch.from_arrays([piece.column(0), pa.array(out.astype(np.float64))], names=["doc_id", "score"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    out = rows.mapInArrow(kernel, "doc_id long, score double")
    return out.select("doc_id", F.coalesce(remainder(5) == 0, F.lit(False)).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
