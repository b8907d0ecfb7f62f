"""Joins the engine needs that Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def bounded(df: DataFrame, most: int = 200_000) -> DataFrame:
    """A broadcast hint if there are few rows, counted up to the bound; the frame as it is if not."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def range_join(outer: DataFrame, inner: DataFrame, width: int) -> DataFrame:
    """(above, below) of intervals (node, b, e) with outer.b <= inner.b and inner.e < outer.e.

    Outer intervals are laid out over buckets of the begin, inner ones lie in the bucket they begin in: an equi-join, then a filter.
    """
    a = outer.select(F.col("node").alias("above"), F.col("b").alias("ab"), F.col("e").alias("ae"), F.explode(F.sequence(F.floor(F.col("b") / width), F.floor(F.col("e") / width))).alias("bucket"))
    b = inner.select(F.col("node").alias("below"), F.col("b").alias("bb"), F.col("e").alias("be"), F.floor(F.col("b") / width).alias("bucket"))
    return a.join(b, "bucket").where("ab <= bb and be < ae")


def asof_last(rows: DataFrame, key: str, order: list[str], is_value: Column, is_asked: Column, value: str) -> DataFrame:
    """Asked rows with `last`: the value of the newest value row strictly before, of the same key. One sort, no join."""
    w = Window.partitionBy(key).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    return rows.withColumn("last", F.last(F.when(is_value, F.col(value)), ignorenulls=True).over(w)).where(is_asked)
