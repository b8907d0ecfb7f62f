"""Weakly connected parts: nothing that follows edges ever leaves one, so each part can go to a task of its own.

Graphs beyond what one task takes are contracted by sets first: every node points at its neighbour with the least random
number of the round, so that chains shrink as fast as stars do; what is left is united in one task.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from dynreach.conf import DEFAULT, EngineConf
from dynreach.operators.arrays import numbered, united
from dynreach.plans.loops import cut, fits

#: A task that only unites ends takes so many times the rows of one that searches: two numbers an edge and no objects.
PLAIN = 4
#: And one that hands the edges on to their bins, so many times.
DEALS = 2


def weak(edges: DataFrame, conf: EngineConf = DEFAULT) -> DataFrame:
    """(node, part) of all ends of edges(src, dst); a part is named by one of its nodes."""
    e = edges.where("src <> dst").select("src", "dst")
    maps, room = [], replace(conf, local_rows=PLAIN * conf.local_rows)
    for r in range(conf.max_rounds):
        if fits(room, e):
            break
        if not maps:
            e = cut(e.union(e.select("dst", "src")).distinct())
        rank = lambda c, r=r: F.struct(F.xxhash64(F.lit(conf.seed + r), c).alias("h"), F.col(c).alias("up"))
        to = cut(e.groupBy("src").agg(F.min(rank("dst")).alias("low")).select(F.col("src").alias("node"), F.least(rank("src"), "low")["up"].alias("up")))
        maps.append(to)
        a, b = to.select(F.col("node").alias("src"), F.col("up").alias("s")), to.select(F.col("node").alias("dst"), F.col("up").alias("t"))
        e = cut(e.join(a, "src").join(b, "dst").where("s <> t").select(F.col("s").alias("src"), F.col("t").alias("dst")).distinct())
    else:
        raise RuntimeError("parts did not settle")
    named = cut(e.groupBy(F.lit("all")).applyInPandas(_united, "node long, part long"))
    for to in reversed(maps):  # what fell together with its neighbours has no edge left and stands for its part
        named = cut(to.join(named.withColumnRenamed("node", "up"), "up", "left").select("node", F.coalesce("part", "up").alias("part")))
    return named.union(edges.where("src = dst").select(F.col("src").alias("node")).distinct().join(named, "node", "left_anti").select("node", F.col("node").alias("part")))


def _united(group: pd.DataFrame) -> pd.DataFrame:
    ids, a, b = numbered(group["src"].to_numpy(), group["dst"].to_numpy())
    return pd.DataFrame({"node": ids, "part": ids[united(len(ids), a, b)]})


def shares(n: int, a: np.ndarray, b: np.ndarray, conf: EngineConf) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(part, bin, nodes of each bin) of the nodes below n, in one task and as dealt() has them; bin is -1 where a part is too large."""
    part = united(n, a, b)
    nodes = np.bincount(part, minlength=n)
    rows = nodes + np.bincount(part[a], minlength=n)
    share = max(1, conf.local_rows // 16)
    of = np.full(n, -1)
    small, large = np.flatnonzero((nodes > 0) & (rows <= share)), np.flatnonzero((rows > share) & (rows <= conf.local_rows))
    of[small] = (np.cumsum(rows[small]) - 1) // (4 * share)
    of[small] = np.unique(of[small], return_inverse=True)[1]
    of[large] = np.arange(len(large)) + of.max(initial=-1) + 1
    bins = of[part]
    return part, bins, np.bincount(bins[bins >= 0])


def dealt_edges(edges: DataFrame, conf: EngineConf = DEFAULT) -> DataFrame:
    """edges(src, dst) with `first`, which names a bin of dealt() and is where its labels begin; first is null where a part
    alone has more rows than a task takes. One task deals the edges while it takes them."""
    if fits(replace(conf, local_rows=DEALS * conf.local_rows), edges):

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            got = [(x.column(0).to_numpy(), x.column(1).to_numpy()) for x in batches]
            if not got:
                return
            src, dst = (np.concatenate(x) for x in zip(*got))
            ids, a, b = numbered(src, dst)
            _, bins, sizes = shares(len(ids), a, b, conf)
            firsts = np.append((np.cumsum(sizes) - sizes) * conf.slack, -1)[bins[a]]  # the last one is that of bin -1
            for i in range(0, len(src), 1 << 16):
                yield pa.RecordBatch.from_arrays([pa.array(x[i : i + (1 << 16)]) for x in (src, dst, firsts)], ["src", "dst", "first"])

        rows = edges.select("src", "dst").repartition(1).mapInArrow(run, "src long, dst long, first long")
        tasks = 2 * edges.sparkSession.sparkContext.defaultParallelism  # a count that is not coalesced, or one task would go on with all bins
        return rows.withColumn("first", F.when(F.col("first") >= 0, F.col("first"))).repartition(tasks, "first")
    bins = dealt(edges, conf)
    wide = bins.where("bin is not null").groupBy("bin").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)) * conf.slack
    firsts = cut(wide.select("bin", before.cast("long").alias("first")))  # a row a bin
    return edges.join(bins.join(F.broadcast(firsts), "bin", "left").select(F.col("node").alias("src"), "first"), "src").select("src", "dst", "first")


def dealt(edges: DataFrame, conf: EngineConf = DEFAULT) -> DataFrame:
    """(node, part, bin) of all ends of edges: the rows of a bin go to one task. Parts of many rows have a bin each,
    small ones share bins by a hash; bin is null where a part alone has more rows than a task takes."""
    if fits(replace(conf, local_rows=PLAIN * conf.local_rows), edges):

        def run(group: pd.DataFrame) -> pd.DataFrame:
            ids, a, b = numbered(group["src"].to_numpy(), group["dst"].to_numpy())
            part, bins, _ = shares(len(ids), a, b, conf)
            return pd.DataFrame({"node": ids, "part": ids[part], "bin": bins})

        found = edges.select("src", "dst").groupBy(F.lit("all")).applyInPandas(run, "node long, part long, bin long")
        return cut(found.withColumn("bin", F.when(F.col("bin") >= 0, F.col("bin"))))
    named = cut(weak(edges, conf))
    rows = edges.join(named.withColumnRenamed("node", "src"), "src").groupBy("part").agg(F.count("*").alias("edges"))
    sizes = cut(rows.join(named.groupBy("part").agg(F.count("*").alias("nodes")), "part").select("part", (F.col("edges") + F.col("nodes")).alias("rows")))
    share = max(1, conf.local_rows // 16)
    small = F.col("rows") <= share
    total = sizes.where(small).agg(F.sum("rows")).first()[0] or 0
    shared = F.pmod(F.xxhash64("part"), F.lit(max(1, total // (4 * share)))) - 2**40  # below all parts
    bins = F.when(small, shared).when(F.col("rows") <= conf.local_rows, F.col("part"))
    return cut(named.join(sizes.select("part", bins.alias("bin")), "part").select("node", "part", "bin"))
