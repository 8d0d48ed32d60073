"""Rounds and words of the all-to-all machine model, charged from data frames.

A machine moves n words a round; moving at most M words by any machine takes max(1, ceil(M / n))
rounds; a dense product takes n^alpha rounds per word of an entry.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ALPHA = 0.157
SCHEMA = "run_id string, phase int, level int, step string, max_sent long, max_recv long, words long, rounds long"


def rounds_for(words: int, n: int) -> int:
    return max(1, math.ceil(words / max(n, 1)))


def matmul_rounds(n: int, bits: int, alpha: float = ALPHA) -> int:
    return math.ceil(n**alpha) * max(1, math.ceil(bits / max(1, math.ceil(math.log2(max(n, 2))))))


def loads(moves: DataFrame, source: str, target: str) -> DataFrame:
    """One row ``(max_sent, max_recv, words)`` of messages from ``source`` to ``target`` machines."""
    sent = moves.groupBy(source).count().agg(F.max("count").alias("max_sent"), F.sum("count").alias("words"))
    return sent.crossJoin(moves.groupBy(target).count().agg(F.max("count").alias("max_recv")))


@dataclass
class Ledger:
    run_id: str
    n: int
    rows: list[tuple] = field(default_factory=list)

    def charge(self, step: str, phase: int = 0, level: int = 0, sent: int = 0, recv: int = 0, words: int = 0, rounds: int | None = None) -> None:
        self.rows.append((self.run_id, phase, level, step, sent, recv, words, rounds if rounds is not None else rounds_for(max(sent, recv), self.n)))

    def charge_moves(self, step: str, moves: DataFrame, source: str, target: str, phase: int = 0, level: int = 0) -> None:
        r = loads(moves, source, target).first()
        self.charge(step, phase, level, r.max_sent or 0, r.max_recv or 0, r.words or 0)

    def charge_product(self, bits: int, phase: int = 0, level: int = 0, alpha: float = ALPHA) -> None:
        self.charge("product", phase, level, self.n, self.n, self.n * self.n, matmul_rounds(self.n, bits, alpha))

    def charge_phases(self, facts: list[dict], bits: int = 30, alpha: float = ALPHA) -> None:
        """Charges of a phased run from its facts: products, then for each level the pair requests (words and
        largest load as counted on the last, fullest level), the multiset of middles for the matching, and
        the probes of a binary search over the places that were filled."""
        for f in facts:
            for level in range(f["levels"] + f["squarings"]):
                self.charge_product(bits, f["phase"], level, alpha)
            for level in range(f["levels"]):
                self.charge("pairs", f["phase"], level, f["pairs"], f["pair_load"], f["pairs"])
                probes = max(1, math.ceil(math.log2(max(2, f["rows"]))))
                self.charge("probes", f["phase"], level, 3 * probes, 3 * f["pairs"], 3 * probes * f["pairs"], 3 * probes)
                self.charge("matching", f["phase"], level, f["distinct"], f["pairs"], f["distinct"] * max(1, f["pairs"]))
            self.charge("first visits", f["phase"], 0, f["distinct"], f["distinct"], f["distinct"])

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, SCHEMA)


def summary(ledger: DataFrame) -> DataFrame:
    """Totals by phase and step, with subtotals."""
    return ledger.rollup("phase", "step").agg(F.sum("rounds").alias("rounds"), F.sum("words").alias("words"), F.max("max_recv").alias("max_recv"), F.count(F.lit(1)).alias("charges"))


def doubling_load(places: DataFrame, k: int, n: int, c: float = 1.0) -> DataFrame:
    """Measured largest load beside the bound 16 c k log2 n (reported, not asserted: one hot vertex
    and index can exceed it for small k)."""
    bound = 16 * c * k * math.log2(max(n, 2))
    top = places.groupBy("place").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n").alias("max_load"), F.sum("n").alias("stubs"))
    return top.select("max_load", "stubs", F.lit(bound).alias("bound"), (F.col("max_load") <= bound).alias("within"))
