"""Toxicity scores by a bidirectional gated recurrent network with attention pooling.

Each word enters with word inputs (a hashed word's association with the label, its rarity) and
character inputs (strongest and mean association of its hashed four-byte strings, its length).
A gated recurrent layer reads a window of ``WINDOW`` words in both directions, attention pools
its states, and a logistic output scores the window.  All windows, each overlapping the next by
half, of every document are scored; a document's score is its worst window's.  Only documents
have labels, so training picks, in turns, the worst window of each document under the current
network (multiple instances).  Associations used while training come from the other half of the
sample, so that words seen in one document only don't look telling.  Plain numpy throughout.

Defined cases: null texts and texts without a word score 0; very long texts are scored whole,
window by window; repeated rows score alike; with labels of one kind only, or none, every score
is 0; an empty table gives no rows; other columns are ignored; rows with a null ``doc_id`` are
scored, are not held out and are not learned from.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bites, give_back
from .sampling import labelled, remainder

WINDOW, STRIDE, HIDDEN, INPUTS, BUCKETS, LEAST = 16, 8, 6, 5, 1 << 17, 2.0
_FOLD = np.array([c + 32 if 65 <= c <= 90 else c if 97 <= c <= 122 or c >= 128 or 48 <= c <= 57 else 32 for c in range(256)], np.uint64)


def words(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Word buckets, buckets of four-byte strings, first string of each word, word lengths, and
    words per text."""
    raw = [t.encode() for t in texts]
    flat = np.frombuffer(b" " + b" ".join(raw) + b"   ", np.uint8)
    b = _FOLD[flat]
    inner = b != 32
    start = np.flatnonzero(inner & ~np.concatenate([[False], inner[:-1]]))
    stop = np.flatnonzero(inner & ~np.concatenate([inner[1:], [False]])) + 1
    ends = 1 + np.cumsum([len(r) + 1 for r in raw])
    per = np.diff(np.concatenate([[0], np.searchsorted(start, ends)]))
    mix = np.cumsum(np.concatenate([[0], (b + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15) ** np.uint64(1)]).astype(np.uint64))
    # four-byte strings from the blank before a word to the blank after it
    g = b[:-3] | b[1:-2] << np.uint64(8) | b[2:-1] << np.uint64(16) | b[3:] << np.uint64(24)
    g = ((g * np.uint64(0xC2B2AE3D27D4EB4F)) >> np.uint64(47)).astype(np.int64)
    scrambled = np.cumsum(np.concatenate([[0], (g.astype(np.uint64) + np.uint64(1)) * np.uint64(0xD6E8FEB86659FD93)]).astype(np.uint64))
    n = np.maximum(stop - start - 1, 1)  # strings per word
    word = (scrambled[start - 1 + n] - scrambled[start - 1]) + (mix[stop] - mix[start])
    word ^= word >> np.uint64(31)
    word = ((word * np.uint64(0xC2B2AE3D27D4EB4F)) >> np.uint64(47)).astype(np.int64)
    first = np.cumsum(n) - n
    at = np.repeat(start - 1 - first, n) + np.arange(int(n.sum()))
    return word, g[at], first, stop - start, per


def _odds(buckets: list[np.ndarray], y: np.ndarray) -> np.ndarray:
    """Smoothed log odds of the label given that a document holds the bucket."""
    seen, hits = np.zeros(BUCKETS), np.zeros(BUCKETS)
    for b, label in zip(buckets, y):
        u = np.unique(b)
        seen[u] += 1
        hits[u] += label
    base = y.mean()
    k = LEAST
    p = (hits + k * base) / (seen + k)
    return (np.log(p / (1 - p)) - np.log(base / (1 - base))).astype(np.float32)


_sig = lambda x: 1 / (1 + np.exp(-np.clip(x, -30, 30)))


class Net:
    def __init__(self, seed: int = 2):
        r = np.random.default_rng(seed)
        g = lambda *s: (r.standard_normal(s) * 0.4).astype(np.float32)
        self.p = {f"{k}{d}": v for d in "fb" for k, v in (("W", g(INPUTS, 3 * HIDDEN)), ("U", g(HIDDEN, 3 * HIDDEN)), ("b", np.zeros(3 * HIDDEN, np.float32)))}
        self.p |= {"A": g(2 * HIDDEN, 6), "a": g(6), "o": g(2 * HIDDEN), "c": np.full(1, -1.0, np.float32)}
        self.word = self.char = np.zeros(BUCKETS, np.float32)

    def inputs(self, word, gram, first, length) -> np.ndarray:
        if not len(word):
            return np.zeros((0, INPUTS), np.float32)
        c = self.char[gram]
        n = np.diff(np.append(first, len(gram)))
        x = np.stack([self.word[word], np.maximum.reduceat(c, first), np.add.reduceat(c, first) / n, np.minimum(length, 20) / 10, (self.word[word] > 1)], 1)
        return x.astype(np.float32)

    def _direction(self, d: str, x: np.ndarray, mask: np.ndarray, tape: list | None):
        """States of one direction; ``x``: windows x steps x inputs."""
        W, U, b = (self.p[k + d] for k in "WUb")
        n, steps = mask.shape
        h, out = np.zeros((n, HIDDEN), np.float32), np.empty((steps, n, HIDDEN), np.float32)
        px = x @ W + b
        for t in range(steps) if d == "f" else range(steps - 1, -1, -1):
            u = h @ U
            zr = _sig(px[:, t, : 2 * HIDDEN] + u[:, : 2 * HIDDEN])
            z, r = zr[:, :HIDDEN], zr[:, HIDDEN:]
            c = np.tanh(px[:, t, 2 * HIDDEN :] + r * u[:, 2 * HIDDEN :])
            new = np.where(mask[:, t, None], z * h + (1 - z) * c, h)
            if tape is not None:
                tape.append((t, h, u, z, r, c))
            h = out[t] = new
        return out

    def forward(self, x: np.ndarray, mask: np.ndarray, keep: bool = False):
        tf, tb = ([], []) if keep else (None, None)
        h = np.concatenate([self._direction("f", x, mask, tf), self._direction("b", x, mask, tb)], 2)
        q = np.tanh(h @ self.p["A"])
        e = np.where(mask.T, np.exp(np.clip(q @ self.p["a"], -30, 30)), 0)
        a = e / np.maximum(e.sum(0), 1e-30)
        pooled = (a[:, :, None] * h).sum(0)
        return _sig(pooled @ self.p["o"] + self.p["c"][0]), (h, q, a, pooled, tf, tb)

    def gradients(self, x: np.ndarray, mask: np.ndarray, y: np.ndarray, weight: np.ndarray) -> dict:
        p = self.p
        out, (h, q, a, pooled, tf, tb) = self.forward(x, mask, True)
        do = (out - y) * weight / weight.sum()
        g = {"o": pooled.T @ do, "c": np.array([do.sum()])}
        dp = do[:, None] * p["o"]
        dot = (h * dp).sum(2)
        de = a * (dot - (a * dot).sum(0))
        dq = de[:, :, None] * p["a"] * (1 - q * q)
        g["a"], g["A"] = np.einsum("tnk,tn->k", q, de), np.einsum("tnk,tnj->kj", h, dq)
        dh = a[:, :, None] * dp + dq @ p["A"].T
        for d, tape, part in (("f", tf, dh[:, :, :HIDDEN]), ("b", tb, dh[:, :, HIDDEN:])):
            U, back = p["U" + d], np.zeros((len(y), HIDDEN), np.float32)
            dW, dU, db = np.zeros_like(p["W" + d]), np.zeros_like(U), np.zeros_like(p["b" + d])
            for t, before, u, z, r, c in reversed(tape):
                total = back + part[t]
                m = mask[:, t, None]
                now = np.where(m, total, 0)
                dc = now * (1 - z) * (1 - c * c)
                dz = now * (before - c) * z * (1 - z)
                dr = dc * u[:, 2 * HIDDEN :] * r * (1 - r)
                pre = np.concatenate([dz, dr, dc], 1)
                du = np.concatenate([dz, dr, dc * r], 1)
                dW += x[:, t].T @ pre
                db += pre.sum(0)
                dU += before.T @ du
                back = np.where(m, now * z, total) + du @ U.T
            g["W" + d], g["U" + d], g["b" + d] = dW, dU, db
        return g

    def windows(self, x: np.ndarray, per: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """First word and owner of every window."""
        count = np.where(per > 0, np.maximum(-(-(per - WINDOW) // STRIDE), 0) + 1, 0)
        owner = np.repeat(np.arange(len(per)), count)
        first = np.cumsum(per) - per
        nth = np.arange(int(count.sum())) - np.repeat(np.cumsum(count) - count, count)
        return first[owner] + nth * STRIDE, owner

    def cut(self, x: np.ndarray, start: np.ndarray, owner: np.ndarray, per: np.ndarray):
        at = start[:, None] + np.arange(WINDOW)
        mask = at < np.cumsum(per)[owner][:, None]
        return x[np.where(mask, at, start[:, None])], mask

    def score(self, texts: list[str]) -> np.ndarray:
        *parts_, per = words(texts)
        x = self.inputs(*parts_)
        start, owner = self.windows(x, per)
        best = np.zeros(len(texts))
        for lo in range(0, len(start), 8192):
            s, o = start[lo : lo + 8192], owner[lo : lo + 8192]
            np.maximum.at(best, o, self.forward(*self.cut(x, s, o, per))[0])
        return best


def train(rows: list[tuple[str, int]], turns: int = 6, epochs: int = 4, rate: float = 0.02, batch: int = 256) -> Net | None:
    y = np.array([r[1] for r in rows], np.float32)
    if len(set(y.tolist())) < 2:
        return None
    split = [[a.astype(np.int32) for a in words([t])] for t, _ in rows]
    net, r = Net(), np.random.default_rng(4)
    half = np.arange(len(rows)) % 2
    tables = [(_odds([s[0] for s, h in zip(split, half) if h != k], y[half != k]), _odds([s[1] for s, h in zip(split, half) if h != k], y[half != k])) for k in (0, 1)]
    xs, pers = [], np.array([int(s[4].sum()) for s in split])
    for s, h in zip(split, half):
        net.word, net.char = tables[h]
        xs.append(net.inputs(*s[:4]))
    x = np.concatenate(xs)
    xs.clear()
    start, owner = net.windows(x, pers)
    strength = np.array([x[s : s + WINDOW, 0].max() + x[s : s + WINDOW, 1].max() for s in start])
    moments = {k: [np.zeros_like(v), np.zeros_like(v)] for k, v in net.p.items()}
    step = 0
    for turn in range(turns):
        score = strength if turn == 0 else np.concatenate([net.forward(*net.cut(x, start[i : i + 8192], owner[i : i + 8192], pers))[0] for i in range(0, len(start), 8192)])
        order = np.lexsort((-score, owner))
        worst = order[np.concatenate([[True], owner[order][1:] != owner[order][:-1]])]
        clean = np.flatnonzero(y[owner] == 0)
        pick = np.unique(np.concatenate([worst, r.choice(clean, min(len(clean), len(worst)), replace=False)]))
        wx, wm = net.cut(x, start[pick], owner[pick], pers)
        wy = y[owner[pick]]
        weight = np.where(wy > 0, 0.5 / max(wy.mean(), 1e-6), 0.5 / max(1 - wy.mean(), 1e-6)).astype(np.float32)
        for _ in range(epochs):
            shuffle = r.permutation(len(pick))
            for lo in range(0, len(pick), batch):
                i = shuffle[lo : lo + batch]
                step += 1
                for k, v in net.gradients(wx[i], wm[i], wy[i], weight[i]).items():
                    m = moments[k]
                    m[0], m[1] = 0.9 * m[0] + 0.1 * v, 0.999 * m[1] + 0.001 * v * v
                    net.p[k] = (net.p[k] - rate * (m[0] / (1 - 0.9**step)) / (np.sqrt(m[1] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
    net.word, net.char = _odds([s[0] for s in split], y), _odds([s[1] for s in split], y)
    return net


def fit(docs: DataFrame, labels: DataFrame, per_class: int = 3000) -> Net | None:
    """Learn from at most about ``per_class`` labelled documents of each class."""
    net = train(labelled(docs, labels, "toxic", 5, per_class))
    give_back()
    return net


def score(docs: DataFrame, net: Net | None, threshold: float = 0.5) -> DataFrame:
    """``(doc_id, held_out, score, predicted)``."""
    shared = docs.sparkSession.sparkContext.broadcast(net)  # two tables of fixed size

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece, texts in bites(batches, "text", 1_000_000):
            out = np.zeros(len(texts)) if shared.value is None else shared.value.score(texts)
            yield pa.RecordBatch.from_arrays([piece.column(0), pa.array(out.astype(np.float64))], names=["doc_id", "score"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    out = rows.mapInArrow(kernel, "doc_id long, score double")
    return out.select("doc_id", F.coalesce(remainder(5) == 0, F.lit(False)).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def keep(docs: DataFrame, net: Net | None, threshold: float = 0.5) -> DataFrame:
    """Rows of ``docs``, with all their columns, that score below ``threshold``."""
    shared = docs.sparkSession.sparkContext.broadcast(net)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece, texts in bites(batches, "text", 1_000_000):
            ok = np.ones(len(texts), bool) if shared.value is None else shared.value.score(texts) < threshold
            yield piece.filter(pa.array(ok))

    return docs.mapInArrow(kernel, docs.schema)
