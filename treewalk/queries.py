"""Registry of the engine's queries and their SQL oracles."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .plans import experiments, methods, relops

QUERIES: dict = methods.QUERIES | experiments.QUERIES | relops.QUERIES
ORACLES: dict[str, str] = methods.ORACLES | experiments.ORACLES | relops.ORACLES


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A random spanning tree of the trade graph, by walks doubled with balanced meeting places."""
    from .operators import sample
    from .sources.graphs import graph

    return sample.by_doubling(graph(spark, sf_dir, "nation_trade"), 0, seed=42)
