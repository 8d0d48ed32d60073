"""Helpers shared by the operators of this subpackage."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """Scan one table, reading only ``cols``."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Where the session names none (tests) a temporary folder is made, but only if driver and
    executors are one machine.
    """
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        found = spark.conf.get("treewalk.scratch.dir", None)
        if not found:
            master = spark.sparkContext.master
            if master != "local" and not master.startswith("local["):
                raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
            found = "file://" + tempfile.mkdtemp(prefix="treewalk-")
            spark.conf.set("treewalk.scratch.dir", found)
    return found


def scratch(spark: SparkSession, what: str) -> str:
    """A fresh path under the shared folder."""
    return f"{shared_dir(spark).rstrip('/')}/{what}-{uuid.uuid4().hex}"


def cut(df: DataFrame, what: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: the lineage ends there.

    Survives the loss of any executor, since the files lie in shared storage.
    """
    spark = df.sparkSession
    path = scratch(spark, what)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def fresh_name(df: DataFrame, base: str) -> str:
    """A column name like ``base`` that ``df`` does not have, whatever the case."""
    taken = {c.lower() for c in df.columns}
    return next(n for n in (f"_{base}{k or ''}" for k in range(len(taken) + 1)) if n not in taken)


def parts(spark: SparkSession) -> int:
    """Number of partitions for an explicit exchange; follows the session's setting."""
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def bites(batches: Iterator[pa.RecordBatch], text_col: str, limit: int = 2_000_000) -> Iterator[tuple[pa.RecordBatch, list[str]]]:
    """Slices of Arrow batches holding about ``limit`` bytes of text each, with null texts as ''.

    Bounds the memory of vectorised kernels; a text above the limit makes a slice of its own.
    """
    for b in batches:
        col = b.column(b.schema.get_field_index(text_col))
        n, lo, size = b.num_rows, 0, 0
        lens = pa.compute.fill_null(pa.compute.binary_length(col), 0).to_pylist()
        for i in range(n):
            size += lens[i]
            if size >= limit or i == n - 1:
                piece = b.slice(lo, i + 1 - lo)
                yield piece, [t or "" for t in piece.column(b.schema.get_field_index(text_col)).to_pylist()]
                lo, size = i + 1, 0


def give_back() -> None:
    """Return memory that this process has freed to the system, where the C library can; it would keep most of
    what many small arrays and texts took."""
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def numbered(docs: DataFrame) -> tuple[DataFrame, DataFrame | None]:
    """``(row, text)`` with a key of its own for each row, and the map ``(row, doc_id)``.

    Where ``doc_id`` is a key already it is used itself and the map is None; null or repeated
    ids get numbers, fixed by writing them.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    n, distinct = rows.select("doc_id").agg(F.count(F.lit(1)), F.count_distinct("doc_id")).first()
    if n == distinct:
        return rows.withColumnRenamed("doc_id", "row"), None
    fixed = cut(rows.withColumn("row", F.monotonically_increasing_id()), "numbered")
    return fixed.select("row", "text"), fixed.select("row", "doc_id")


def renamed(done: DataFrame, names: DataFrame | None) -> DataFrame:
    """Undo ``numbered``: the result with ``doc_id`` in place of ``row``."""
    return done.withColumnRenamed("row", "doc_id") if names is None else names.join(done, "row").drop("row")
