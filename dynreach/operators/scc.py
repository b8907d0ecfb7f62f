"""Strongly connected components, each named by its smallest node.

Small graphs (rows counted first) go through one task's depth-first kernel, and so do the weakly connected parts of
larger ones, each in its own task. Parts that no task takes are decomposed by sets: nodes without in- or out-edges are trimmed; a pivot with a large product of
degrees takes the giant component by a forward and a backward sweep; what is left is coloured with
the smallest id that reaches a node, and every colour's root takes what reaches it inside the colour.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dynreach.conf import DEFAULT, EngineConf
from dynreach.operators.kernel import index_of, strongly_connected as local_components
from dynreach.plans.loops import cut, empty
from dynreach.sources.graphs import nodes_of

METHODS = ("auto", "local", "parts", "trim_color", "fwbw")


def strongly_connected(nodes: DataFrame | None, edges: DataFrame, method: str = "auto", conf: EngineConf = DEFAULT, bins: DataFrame | None = None) -> DataFrame:
    """membership(node, comp) of all nodes. bins: parts.dealt of the edges, if known."""
    if method not in METHODS:
        raise ValueError(f"method is one of {METHODS}")
    nodes = nodes_of(edges) if nodes is None else nodes.select("node").union(nodes_of(edges)).distinct()
    if method == "auto":
        method = "local" if edges.limit(conf.local_rows + 1).count() <= conf.local_rows else "parts" if conf.local_rows else "fwbw"
    if method == "local":
        found = local(edges)
    elif method == "parts":
        found = by_parts(nodes, edges, conf, bins)
    else:
        found = by_sets(nodes, edges, pivot=method == "fwbw", conf=conf)
    return nodes.join(found, "node", "left").select("node", F.coalesce("comp", "node").alias("comp"))


def local(edges: DataFrame, by: Column | None = None) -> DataFrame:
    """(node, comp) of the components with several nodes, by one task for each value of `by`."""

    def run(group: pd.DataFrame) -> pd.DataFrame:
        out = index_of(zip(group["src"].tolist(), group["dst"].tolist()))
        parts = [p for p in local_components(list(out), lambda x: out.get(x, ())) if len(p) > 1]
        return pd.DataFrame({"node": [n for p in parts for n in p], "comp": [c for p in parts for c in [min(p)] * len(p)]}, dtype="int64")

    return edges.where("src <> dst").groupBy(F.lit("all") if by is None else by).applyInPandas(run, "node long, comp long")


def by_parts(nodes: DataFrame, edges: DataFrame, conf: EngineConf = DEFAULT, bins: DataFrame | None = None) -> DataFrame:
    from dynreach.operators import parts

    e = edges.where("src <> dst")
    bins = parts.dealt(e, conf) if bins is None else bins
    at = cut(e.join(bins.select(F.col("node").alias("src"), "bin"), "src").select("src", "dst", "bin"))
    found, rest = local(at.where("bin is not null"), F.col("bin")), at.where("bin is null").select("src", "dst")
    return found if empty(rest) else found.union(by_sets(nodes, rest, conf=conf).select("node", "comp"))


def by_sets(nodes: DataFrame, edges: DataFrame, pivot: bool = True, conf: EngineConf = DEFAULT) -> DataFrame:
    e = cut(edges.where("src <> dst").distinct())
    found, giant = [], pivot
    for _ in range(conf.max_rounds):
        e = trim(e, conf)
        if empty(e):
            break
        if giant:
            giant = False
            top = e.groupBy("src").count().join(e.groupBy("dst").count().withColumnRenamed("count", "back"), F.col("src") == F.col("dst"))
            start = top.orderBy(F.desc(F.col("count") * F.col("back")), "src").select(F.col("src").alias("node")).limit(1)
            part = sweep(start, e, conf).join(sweep(start, turned(e), conf), "node")
            comp = cut(part.withColumn("comp", F.lit(part.agg(F.min("node")).first()[0]).cast("long")))
        else:
            comp = coloured(e, conf)
        found.append(comp.select("node", "comp"))
        inside = comp.select(F.col("node").alias("src"))
        e = cut(e.join(inside, "src", "left_anti").join(inside.withColumnRenamed("src", "dst"), "dst", "left_anti").select("src", "dst"))
    else:
        raise RuntimeError("components did not settle")
    if not found:
        return nodes.sparkSession.createDataFrame([], "node long, comp long")
    out = found[0]
    for part in found[1:]:
        out = out.union(part)
    return out


def turned(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))


def trim(e: DataFrame, conf: EngineConf = DEFAULT) -> DataFrame:
    """Edges whose tails have in-edges and whose heads have out-edges, until no more go."""
    n = e.count()
    for _ in range(conf.max_rounds):
        heads, tails = e.select(F.col("dst").alias("src")).distinct(), e.select(F.col("src").alias("dst")).distinct()
        e = cut(e.join(heads, "src", "left_semi").join(tails, "dst", "left_semi").select("src", "dst"))
        left = e.count()
        if left == n:
            return e
        n = left
    raise RuntimeError("trimming did not settle")


def sweep(start: DataFrame, edges: DataFrame, conf: EngineConf = DEFAULT) -> DataFrame:
    """All nodes reachable from the start nodes, themselves included; semi-naive frontier."""
    seen = frontier = cut(start.select("node").distinct())
    for _ in range(conf.max_rounds):
        step = frontier.join(edges, F.col("node") == F.col("src")).select(F.col("dst").alias("node")).distinct()
        frontier = cut(step.join(seen, "node", "left_anti"))
        if empty(frontier):
            return seen
        seen = cut(seen.union(frontier))
    raise RuntimeError("sweep did not settle")


def coloured(e: DataFrame, conf: EngineConf = DEFAULT) -> DataFrame:
    """(node, comp): the component of each node that is the smallest to reach itself."""
    colours = cut(nodes_of(e).withColumn("colour", F.col("node")))
    changed = colours
    for _ in range(conf.max_rounds):
        offers = changed.join(e, F.col("node") == F.col("src")).groupBy(F.col("dst").alias("node")).agg(F.min("colour").alias("offer"))
        merged = cut(colours.join(offers, "node", "left").select("node", F.least("colour", F.coalesce("offer", "colour")).alias("colour"), (F.col("offer") < F.col("colour")).alias("moved")))
        colours, changed = merged.select("node", "colour"), merged.where("moved").select("node", "colour")
        if empty(changed):
            break
    a, b = colours.select(F.col("node").alias("src"), F.col("colour").alias("ca")), colours.select(F.col("node").alias("dst"), F.col("colour").alias("cb"))
    inside = cut(e.join(a, "src").join(b, "dst").where("ca = cb").select("src", "dst"))
    roots = colours.where("node = colour").select("node")
    return cut(sweep(roots, turned(inside), conf).join(colours, "node").select("node", F.col("colour").alias("comp")))


def component_sizes(membership: DataFrame) -> DataFrame:
    return membership.groupBy("comp").agg(F.count("*").alias("size")).withColumn("status", F.lit("current"))
