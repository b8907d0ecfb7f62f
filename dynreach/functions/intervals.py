"""Interval labels as column expressions: no Python runs where labels are compared."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, LongType, StructField, StructType

IV = "array<struct<b:long,e:long>>"


def label_covers(outer: Column, inner: Column) -> Column:
    """Whether each interval of inner lies in outer's, strictly at the end; true for k = 0."""
    return F.forall(F.zip_with(outer, inner, lambda o, i: (o["b"] <= i["b"]) & (i["e"] < o["e"])), lambda x: x)


def label_hull(ivs: Column, k: int) -> Column:
    """Aggregate: the least label around a group's labels of k dimensions (ends as they are); combined before the shuffle."""
    one = lambda d: F.struct(F.min(ivs[d]["b"]).alias("b"), F.max(ivs[d]["e"]).alias("e"))
    return F.array(*map(one, range(k))) if k else F.array().cast(IV)


def register(spark: SparkSession) -> None:
    """SQL function label_covers(outer, inner)."""
    spark.sql(
        f"create or replace temporary function label_covers(outer_iv {IV}, inner_iv {IV}) returns boolean "
        "return forall(zip_with(outer_iv, inner_iv, (o, i) -> o.b <= i.b and i.e < o.e), x -> x)"
    )


def hull_in_groups(key: str):
    """For groupBy(key).applyInPandas: the hull of each group's (b, e)."""

    def run(group: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({key: [group[key].iloc[0]], "b": [int(group["b"].min())], "e": [int(group["e"].max())]})

    return run


def step_path():
    """A table function over arrays handed to it: (start, step, node) along a chain of successors."""
    from pyspark.sql.functions import udtf

    schema = StructType([StructField("start", LongType()), StructField("step", IntegerType()), StructField("node", LongType())])

    class Path:
        def eval(self, start: int, heads: list[int], tails: list[int]):
            after, x, step = dict(zip(heads, tails)), start, 0
            while x in after and step < len(heads):
                x, step = after[x], step + 1
                yield start, step, x

    return udtf(Path, returnType=schema)
