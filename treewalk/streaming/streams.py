"""Streams over ``events`` and walk logs."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from .windows import marked


def read(spark: SparkSession, folder: str, schema, files_per_trigger: int = 1) -> DataFrame:
    """Parquet files of a folder, as they come."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def dedup(stream: DataFrame, keys: list[str], watermark: str = "10 minutes") -> DataFrame:
    return marked(stream, watermark).dropDuplicatesWithinWatermark(keys)


def enrich(stream: DataFrame, static: DataFrame, key: str) -> DataFrame:
    """Stream-static join."""
    return stream.join(static, key)


def cooc(a: DataFrame, b: DataFrame, within: str = "10 minutes", watermark: str = "10 minutes") -> DataFrame:
    """Stream-stream join: events of two users in one bucket of time and within the bound."""
    left = marked(a, watermark).select(F.col("ts").alias("ts1"), F.col("user_id").alias("u"), F.col("event_type"))
    right = marked(b, watermark).select(F.col("ts").alias("ts2"), F.col("user_id").alias("v"), F.col("event_type").alias("type2"))
    return left.join(right, F.expr(f"event_type = type2 AND u < v AND ts2 BETWEEN ts1 - INTERVAL {within} AND ts1 + INTERVAL {within}"))


def first_visit(steps: DataFrame) -> DataFrame:
    """First place of every vertex of a walk log ``(sample_id, pos, vertex, prev)``, corrected when an
    earlier step comes late: ``(sample_id, vertex, pos, prev)`` in update mode."""

    def track(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        best = state.get if state.exists else None
        for f in frames:
            f = f.sort_values("pos")
            pos, prev = int(f.pos.iloc[0]), int(f.prev.iloc[0])
            if best is None or pos < best[0]:
                best = (pos, prev)
        state.update(best)
        yield pd.DataFrame({"sample_id": [key[0]], "vertex": [key[1]], "pos": [best[0]], "prev": [best[1]]})

    return steps.groupBy("sample_id", "vertex").applyInPandasWithState(track, "sample_id long, vertex long, pos long, prev long", "pos long, prev long", "update", GroupStateTimeout.NoTimeout)


def late_split(all_rows: DataFrame, counted: DataFrame, key: str) -> DataFrame:
    """Rows that a windowed stream left out as too late: an anti-join on its sink."""
    return all_rows.join(counted, key, "left_anti")


def resample(stream: DataFrame, draw: Callable[[DataFrame, int], DataFrame], out: str, checkpoint: str):
    """A fresh tree for every micro-batch; the batch's number is in the path, so that a batch that
    runs again replaces its own output only."""

    def each(batch: DataFrame, number: int) -> None:
        draw(batch, number).write.mode("overwrite").parquet(f"{out}/batch={number}")

    return stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def run(df: DataFrame, sink: str, name: str, mode: str = "append", checkpoint: str | None = None, path: str | None = None):
    """Run to the end of what is there: memory table or files."""
    w = df.writeStream.outputMode(mode).trigger(availableNow=True)
    if checkpoint:
        w = w.option("checkpointLocation", checkpoint)
    q = w.format(sink).queryName(name).start(path) if path else w.format(sink).queryName(name).start()
    q.awaitTermination()
    return q
