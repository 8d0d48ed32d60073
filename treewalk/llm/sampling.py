"""Bounded samples of labelled rows for fitting small models on the driver."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


#: Longest text, in bytes, that a model is fitted on: with the number of rows this bounds what the
#: driver collects.  Longer texts are scored like any other.
LONGEST = 100_000


def remainder(mod: int, key: str = "doc_id") -> Column:
    """crc32 of the id as text, modulo ``mod``: decides what is held out."""
    return F.crc32(F.col(key).cast("string").cast("binary")) % mod


def bounded(rows: DataFrame, label: str, per_class: int, key: str = "doc_id") -> DataFrame:
    """About ``per_class`` rows of each class, chosen by a hash of the key.

    Counts first (one row per class comes back), then keeps each class's share, so the number
    of rows kept has a bound that doesn't depend on the size of the table.
    """
    sizes = {r[0]: r[1] for r in rows.groupBy(label).count().collect() if r[0] is not None}
    if not sizes:
        return rows.limit(0)
    share = F.create_map(*[F.lit(x) for k, n in sorted(sizes.items()) for x in (k, min(1.0, per_class / n))])
    u = F.pmod(F.xxhash64(F.col(key), F.lit(11)), F.lit(1 << 30)) / F.lit(float(1 << 30))
    return rows.where(u < share[F.col(label)])


def labelled(docs: DataFrame, labels: DataFrame, label: str, mod: int, per_class: int) -> list[tuple[str, int]]:
    """Texts and labels of a bounded sample of the rows that may be learned from; texts above
    ``LONGEST`` bytes are left out of it."""
    usable = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y")).where(F.col("doc_id").isNotNull() & F.col("y").isin(0, 1) & (remainder(mod) != 0))
    once = usable.groupBy("doc_id").agg(F.max("y").alias("y"))
    few = bounded(once, "y", per_class)  # at most a few thousand pairs of numbers
    found = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where(F.coalesce(F.octet_length("text"), F.lit(0)) <= LONGEST).join(F.broadcast(few), "doc_id").select("doc_id", F.coalesce("text", F.lit("")).alias("text"), "y").toArrow()
    rows = sorted(zip(*(c.to_pylist() for c in found.columns)), key=lambda r: r[:2])
    return [r[1:] for r in rows]
