"""What a job cost: seconds, shuffled and spilled bytes, rows of the fullest task."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


def _stages(spark: SparkSession) -> dict:
    """Stage id and attempt to (bytes written to shuffles, bytes spilled, records written to shuffles)."""
    gateway = spark.sparkContext._gateway
    none = gateway.new_array(gateway.jvm.double, 0)  # no quantiles wanted
    found = spark.sparkContext._jsc.sc().statusStore().stageList(None, False, False, none, gateway.jvm.java.util.ArrayList())
    out = {}
    for k in range(found.size()):
        s = found.apply(k)
        out[s.stageId(), s.attemptId()] = (s.shuffleWriteBytes(), s.diskBytesSpilled(), s.shuffleWriteRecords())
    return out


def run_cost(spark: SparkSession, job: Callable[[], DataFrame]) -> dict:
    """Run ``job`` to its end, without keeping the rows: seconds, shuffle_bytes, spill_bytes and peak_rows
    (most records that one stage shuffled)."""
    before, began = set(_stages(spark)), time.time()
    job().write.format("noop").mode("overwrite").save()
    took = time.time() - began
    new = [v for k, v in _stages(spark).items() if k not in before]
    return {"seconds": round(took, 2), "shuffle_bytes": sum(v[0] for v in new), "spill_bytes": sum(v[1] for v in new), "peak_rows": max((v[2] for v in new), default=0)}
