"""Measures over graphs, indexes and logs of operations, as tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dynreach.functions.intervals import label_covers
from dynreach.model import Index
from dynreach.operators import condense
from dynreach.operators.query import resolve


def profile(nodes: DataFrame, edges: DataFrame, membership: DataFrame) -> DataFrame:
    """(nodes, edges, comps, largest, several): the graph's size, its condensation's and its largest component's."""
    sizes = membership.groupBy("comp").agg(F.count("*").alias("size"))
    parts = sizes.agg(F.count("*").alias("comps"), F.max("size").alias("largest"), F.count_if(F.col("size") > 1).alias("several"))
    return nodes.agg(F.count("*").alias("nodes")).join(edges.agg(F.count("*").alias("edges"))).join(parts).select("nodes", "edges", "comps", "largest", "several")  # single rows


def avg_ms(op_log: DataFrame) -> DataFrame:
    """(kind, n, avg_ms) of a log of operations."""
    return op_log.groupBy("kind").agg(F.count("*").alias("n"), F.avg("ms").alias("avg_ms"))


def cases(op_log: DataFrame) -> DataFrame:
    """(kind, case, n, touched, changed)."""
    return op_log.groupBy("kind", "case").agg(F.count("*").alias("n"), F.sum("comps_touched").alias("touched"), F.sum("labels_changed").alias("changed"))


def index_rows(index: Index) -> DataFrame:
    return condense.index_rows(index.edges, index.membership, index.dag_edges, index.k)


def label_fp(index: Index, answers: DataFrame) -> DataFrame:
    """(unreachable, covered, share): of the pairs without a path, those whose labels are nested."""
    rows = resolve(index, answers).where("s is not null and t is not null").join(answers.select("qid", "reachable"), "qid").where("not reachable")
    counted = rows.agg(F.count("*").alias("unreachable"), F.count_if(label_covers(F.col("ls"), F.col("lt"))).alias("covered"))
    return counted.withColumn("share", F.col("covered") / F.greatest("unreachable", F.lit(1)))


def expansion(answers: DataFrame) -> DataFrame:
    """(decided_by, n, expanded): how questions were decided and what searching cost."""
    return answers.groupBy("decided_by").agg(F.count("*").alias("n"), F.sum("expanded").alias("expanded"))
