"""Readers and writers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

EDGE = "u bigint, v bigint, w bigint"


def table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """Parquet scan of one table, with only ``cols``."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = EDGE) -> DataFrame:
    """Edge list from Parquet, ORC, CSV, JSON or tab-separated text; malformed rows fail."""
    reader = spark.read.schema(schema)
    if fmt in ("csv", "json"):
        reader = reader.option("mode", "FAILFAST")
    if fmt == "text":
        return reader.option("sep", "\t").option("mode", "FAILFAST").csv(path)
    return reader.format(fmt).load(path)


def write_edges(df: DataFrame, path: str, fmt: str = "parquet") -> None:
    w = df.write.mode("overwrite")
    if fmt == "text":
        w.option("sep", "\t").csv(path)
    else:
        w.format(fmt).save(path)


def write_trees(df: DataFrame, path: str, fmt: str = "parquet", partition_by: str | None = "sample_id") -> None:
    w = df.write.mode("overwrite").format(fmt)
    (w.partitionBy(partition_by) if partition_by else w).save(path)


def write_dot(tree: DataFrame, path: str) -> None:
    """DOT text, one line an edge."""
    tree.selectExpr("concat(u, ' -- ', v, ';') AS line").write.mode("overwrite").text(path)


def save_ladder(entry: DataFrame, name: str, buckets: int = 32, by: str = "i") -> None:
    """Matrix entries as a table bucketed by row (or column), so that joins on it need no shuffle;
    levels are partitions and are pruned."""
    entry.write.mode("overwrite").partitionBy("t").bucketBy(buckets, by).sortBy(by).saveAsTable(name)
