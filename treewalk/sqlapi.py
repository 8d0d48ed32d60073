"""SQL access: graph views as temporary views, walks and trees as table functions."""

from __future__ import annotations

from pyspark.sql import SparkSession

from .operators.udf import random_walk_rows, sample_tree_rows
from .sources.graphs import VIEWS


def register(spark: SparkSession, sf_dir: str | None = None) -> list[str]:
    """Names that were registered."""
    spark.udtf.register("random_walk", random_walk_rows)
    spark.udtf.register("sample_tree", sample_tree_rows)
    names = ["random_walk", "sample_tree"]
    for name, view in VIEWS.items() if sf_dir else ():
        view(spark, sf_dir).createOrReplaceTempView(name)
        names.append(name)
    return names
