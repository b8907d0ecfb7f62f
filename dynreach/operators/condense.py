"""The condensation: components and the edges between them, each with its multiplicity."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def ends(edges: DataFrame, membership: DataFrame) -> DataFrame:
    """The rows of edges with s and t, their ends' components; nodes without a row stand for themselves."""
    a, b = membership.select(F.col("node").alias("src"), F.col("comp").alias("s")), membership.select(F.col("node").alias("dst"), F.col("comp").alias("t"))
    return edges.join(a, "src", "left").join(b, "dst", "left").select(*edges.columns, F.coalesce("s", "src").alias("s"), F.coalesce("t", "dst").alias("t"))


def build(edges: DataFrame, membership: DataFrame) -> DataFrame:
    """dag_edges(s, t, mult)."""
    return ends(edges, membership).where("s <> t").groupBy("s", "t").agg(F.count("*").alias("mult"))


def compact(membership: DataFrame) -> DataFrame:
    """Only rows of nodes in components of several nodes: a single node is its own component and needs none."""
    several = membership.groupBy("comp").agg(F.count("*").alias("n")).where("n > 1").select("comp")
    return membership.join(several, "comp").select("node", "comp")


def view(edges: DataFrame, sparse: DataFrame | None, acyclic: bool) -> DataFrame:
    """dag_edges without a copy: an acyclic graph is its own condensation and needs no components."""
    if acyclic:
        return edges.select(F.col("src").alias("s"), F.col("dst").alias("t"), F.lit(1).cast("long").alias("mult"))
    return build(edges, sparse)


def index_rows(edges: DataFrame, membership: DataFrame, dag_edges: DataFrame, k: int) -> DataFrame:
    """(part, n): rows of each table of the index, with and without the space saver."""
    nodes, sparse = membership.count(), compact(membership).count()
    comps = membership.select("comp").distinct().count()
    rows = [("live_edges", edges.count()), ("membership_full", nodes), ("membership_kept", sparse), ("components", comps), ("dag_edges", dag_edges.count()), ("intervals", comps * k)]
    return edges.sparkSession.createDataFrame(rows, "part string, n long")
