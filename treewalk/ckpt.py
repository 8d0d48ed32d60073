"""Lineage cuts in shared storage, and plan facts."""

from __future__ import annotations

import contextlib
import io
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session.  Where it is unset, as in tests, a temporary folder, but only
    if driver and executors are one machine."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("treewalk.scratch.dir", None)
    if not found:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        found = "file://" + tempfile.mkdtemp(prefix="treewalk-")
        spark.conf.set("treewalk.scratch.dir", found)
    return found


def cut(df: DataFrame, name: str = "cut") -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it again.

    Plans stay of constant size over iterations, and a lost executor costs no recomputation of
    earlier rounds.
    """
    path = f"{shared_dir(df.sparkSession).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def plan_text(df: DataFrame, mode: str = "formatted") -> str:
    out = io.StringIO()
    with contextlib.redirect_stdout(out):
        df.explain(mode)
    return out.getvalue()


def plan_facts(df: DataFrame) -> dict[str, int]:
    """How often each physical operator occurs in the plan."""
    names = re.findall(r"^\(\d+\) ([A-Za-z]+)", plan_text(df), re.M)
    return {n: names.count(n) for n in sorted(set(names))}
