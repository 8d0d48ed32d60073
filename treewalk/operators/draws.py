"""Weighted draws without a product of draws and choices."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def bounds(law: DataFrame, keys: list[str], value: str, weight: str) -> DataFrame:
    """``law`` with cumulative bounds ``lo``, ``hi`` and the ``total`` of each key."""
    w = Window.partitionBy(*keys)
    hi = law.withColumn("hi", F.sum(weight).over(w.orderBy(value))).withColumn("total", F.sum(weight).over(w))
    return hi.withColumn("lo", F.col("hi") - F.col(weight))


def pick(draws: DataFrame, law: DataFrame, keys: list[str], value: str, uniform: Column) -> DataFrame:
    """``draws`` with the ``value`` whose bounds hold its uniform number in [0, total).

    ``law`` comes from ``bounds``; ``uniform`` may use the column ``total``.  Draws and upper bounds of a
    key are sorted together and each draw takes the least bound above it: the rows are the sum of both
    sides, where a join by key would make their product.
    """
    totals = law.groupBy(*keys).agg(F.max("hi").alias("total"))
    rest = [c for c in draws.columns if c not in keys]
    # both sides are dealt by the keys for the window anyway; draws made by explode look small to Spark and are not
    asked = draws.join(totals.hint("merge"), keys).select(*keys, uniform.alias("_at"), F.lit(0).alias("_kind"), F.lit(None).cast(law.schema[value].dataType).alias("_value"), F.struct(F.lit(0).alias("_"), *rest).alias("_rest"))
    shape = asked.schema["_rest"].dataType
    limits = law.select(*keys, F.col("hi").alias("_at"), F.lit(1).alias("_kind"), F.col(value).alias("_value"), F.lit(None).cast(shape).alias("_rest"))
    downwards = Window.partitionBy(*keys).orderBy(F.desc("_at"), "_kind").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    found = asked.union(limits).withColumn("_value", F.last("_value", ignorenulls=True).over(downwards)).where("_kind = 0")
    return found.select(*keys, *[F.col(f"_rest.{c}").alias(c) for c in rest], F.col("_value").alias(value))
