"""Language identification by mixtures: each document is a blend of known languages.

Every language has a distribution over hashed three-byte strings of its letters, learned from a
bounded, stratified sample.  A document's proportions come from expectation-maximisation over
the likelihoods of all its three-byte strings; nested sets of languages (most likely first) are
fitted and the one with the best penalised likelihood is kept.  For speed the likelihood
profile of a string over the languages is rounded to ``LEVELS`` steps of ``STEP`` in the log, so
that a document is a short count vector over profiles and EM is a few matrix products.

Defined cases: null texts and texts without a letter are ``und`` with score 0; very long texts
count whole; ties go to the language first in name order; repeated rows give equal results; an
empty table, or one without any language to learn, gives ``und`` or no rows; other columns are
ignored; rows with a null ``doc_id`` are predicted and not held out.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bites
from .sampling import LONGEST, bounded, remainder

BUCKETS, LEVELS, STEP, ROUNDS, OVERLAP = 1 << 15, 7, 0.7, 10, 3
_FOLD = np.array([c + 32 if 65 <= c <= 90 else c if 97 <= c <= 122 or c >= 128 else 32 for c in range(256)], np.uint32)


def grams(text: str) -> np.ndarray:
    """Buckets of the three-byte strings that hold a letter."""
    b = _FOLD[np.frombuffer(f" {text} ".encode(), np.uint8)]
    if len(b) < 3:
        return np.zeros(0, np.int64)
    g = b[:-2] | b[1:-1] << np.uint32(8) | b[2:] << np.uint32(16)
    g = g[(b[1:-1] != 32)]
    return ((g * np.uint32(2654435761)) >> np.uint32(17)).astype(np.int64)


class Model:
    def __init__(self, langs: list[str], counts: np.ndarray):
        """``counts``: languages x buckets."""
        self.langs = langs
        if not langs:
            return
        p = (counts + 0.1) / (counts + 0.1).sum(1, keepdims=True)
        log = np.log(p).T
        drop = np.minimum(np.round((log.max(1, keepdims=True) - log) / STEP), LEVELS).astype(np.int64)
        kinds, self.kind = np.unique(drop, axis=0, return_inverse=True)
        self.kind = self.kind.reshape(-1)
        self.like = np.exp(-STEP * kinds).astype(np.float32)  # kinds x languages, up to a factor for each kind

    def profile(self, text: str) -> np.ndarray:
        return np.bincount(self.kind[grams(text)], minlength=len(self.like))

    def _em(self, c: np.ndarray, theta: np.ndarray, rounds: int = ROUNDS) -> tuple[np.ndarray, np.ndarray]:
        """Proportions after ``rounds`` steps from ``theta``, and their log-likelihood."""
        total = np.maximum(c.sum(1, keepdims=True), 1)
        for _ in range(rounds):
            theta = theta * ((c / np.maximum(theta @ self.like.T, 1e-30)) @ self.like) / total
            theta /= np.maximum(theta.sum(1, keepdims=True), 1e-30)
        return theta, (c * np.log(np.maximum(theta @ self.like.T, 1e-30))).sum(1)

    def mixture(self, c: np.ndarray) -> np.ndarray:
        """Proportions of each language for each row of profile counts ``c``.

        Sets of every size are fitted, each of the languages with most weight in the full mixture;
        those of one language need no iteration.
        """
        c, n = c.astype(np.float32), len(self.langs)
        full, _ = self._em(c, np.full((len(c), n), 1 / n, np.float32))
        order = np.argsort(-full, axis=1, kind="stable")
        rank = np.argsort(order, axis=1, kind="stable")
        kept = (rank == 0).astype(np.float32)
        best = self._em(c, kept, 0)[1] / OVERLAP
        size = np.log(np.maximum(c.sum(1) / OVERLAP, 2))  # neighbouring strings overlap
        for k in range(2, n + 1):
            start = full * (rank < k) + 1e-6 * (rank < k)
            theta, fit = self._em(c, start / start.sum(1, keepdims=True))
            value = fit / OVERLAP - 0.5 * (k - 1) * size
            better = value > best
            best[better], kept[better] = value[better], theta[better]
        return kept


def fit(docs: DataFrame, per_language: int = 1000) -> Model:
    """Learn from text and language of rows that aren't held out (at most about
    ``per_language`` documents of each language, of up to ``LONGEST`` bytes)."""
    usable = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.col("lang").cast("string").alias("lang")).where(F.col("lang").isNotNull() & (F.octet_length("text") <= LONGEST) & (remainder(4) != 2))
    counts: dict[str, np.ndarray] = {}
    for r in bounded(usable, "lang", per_language).select("lang", "text").collect():
        counts.setdefault(r.lang, np.zeros(BUCKETS))
        counts[r.lang] += np.bincount(grams(r.text), minlength=BUCKETS)
    langs = sorted(counts)
    return Model(langs, np.array([counts[k] for k in langs]))


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """``(doc_id, held_out, lang_pred, score, mixture)``; ``mixture`` maps the kept languages to
    their proportions."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # languages x buckets: fixed size

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for piece, texts in bites(batches, "text"):
            known = [bool(m.langs) and any(map(str.isalpha, t)) for t in texts]
            theta = m.mixture(np.array([m.profile(t) for t in texts])) if m.langs else np.zeros((len(texts), 1))
            top = theta.argmax(1)
            lang = [m.langs[i] if k else "und" for i, k in zip(top, known)]
            score = [min(1.0, float(theta[r, i])) if k else 0.0 for r, (i, k) in enumerate(zip(top, known))]
            mix = [[(m.langs[i], float(x[i])) for i in np.flatnonzero(x > 1e-3)] if k else [] for x, k in zip(theta, known)]
            yield pa.RecordBatch.from_arrays([piece.column(0), pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array(mix, pa.map_(pa.string(), pa.float64()))], names=["doc_id", "lang_pred", "score", "mixture"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    out = rows.mapInArrow(kernel, "doc_id long, lang_pred string, score double, mixture map<string,double>")
    return out.select("doc_id", F.coalesce(remainder(4) == 2, F.lit(False)).alias("held_out"), "lang_pred", "score", "mixture")
