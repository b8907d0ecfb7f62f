"""Random graphs, update sequences and pairs by arithmetic on row numbers: the same rows on any cluster."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dynreach.conf import DEFAULT, EngineConf
from dynreach.operators.plain import PlainGraph, drawn_operations
from dynreach.plans.loops import cut, empty, fits

#: An integer mix of 31 bits that SQL engines compute alike.
_A, _B, _M = 1103515245, 12345, 2147483648


def mix(x: Column, seed: int) -> Column:
    """A pseudo-random integer below 2**31 from a row number."""
    h = (x + seed * 7919 + 1) % _M
    for add in (_B, _B * 3 + 2, _B * 7 + 4):
        h = ((h * _A + add) % _M).bitwiseXOR(F.floor(h / 65536).cast("long"))
        h = h % _M
    return h


def mix_sql(x: str, seed: int) -> str:
    """The same in SQL, as an expression over an integer."""
    h = f"(({x} + {seed * 7919 + 1}) % {_M})"
    for add in (_B, _B * 3 + 2, _B * 7 + 4):
        h = f"(xor((({h}) * {_A} + {add}) % {_M}, ({h}) // 65536) % {_M})"
    return h


def er_graph(spark: SparkSession, n: int, m: int, seed: int = 1) -> DataFrame:
    """m edges with both ends uniform over n nodes; repeated draws fall together."""
    i = F.col("id")
    return spark.range(m).select((mix(i * 2, seed) % n).alias("src"), (mix(i * 2 + 1, seed) % n).alias("dst")).distinct()


def er_sql(n: int, m: int, seed: int = 1) -> str:
    return f"select distinct {mix_sql('(range*2)', seed)} % {n} src, {mix_sql('(range*2+1)', seed)} % {n} dst from range({m})"


def ba_graph(spark: SparkSession, n: int, d: int = 2, seed: int = 1, flip: float = 0.5) -> DataFrame:
    """Preferential attachment: 2d start nodes; each later node draws an out-degree in [1, 2d] and targets in
    proportion to degree; each edge is then turned with probability flip.

    A target is an earlier end slot chosen uniformly: even slots hold the new node itself, odd ones
    point on, so all slots resolve together by pointer jumping, a logarithm of rounds in expectation.
    """
    start = 2 * d
    grown = spark.range(start, n).select(F.col("id").alias("node"), (mix(F.col("id"), seed) % (2 * d) + 1).alias("deg"))
    ranges = grown.withColumn("part", F.floor(F.col("node") / 50_000))
    sums = ranges.groupBy("part").agg(F.sum("deg").alias("n"))
    ahead = sums.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("ahead"))
    run = F.sum("deg").over(Window.partitionBy("part").orderBy("node").rowsBetween(Window.unboundedPreceding, -1))
    firsts = ranges.withColumn("run", F.coalesce(run, F.lit(0))).join(F.broadcast(ahead), "part")  # a row per 50,000 nodes
    # each node's first slots are its start ring, so that start nodes have degree too
    edges = firsts.select("node", F.explode(F.sequence(F.lit(0), F.col("deg") - 1)).alias("j"), (F.col("ahead") + F.col("run")).alias("first"))
    edges = cut(edges.select((F.col("first") + F.col("j")).alias("edge"), "node", "first"))
    # slot 2i is the tail of edge i, slot 2i + 1 its head; ring slots below 0 stand for the start nodes
    choices = F.col("first") * 2 + start
    pick = mix(F.col("edge") + 1_000_003, seed + 1) % choices - start
    at = edges.select("edge", "node", pick.alias("slot"))
    tails = edges.select(F.col("edge").alias("of"), F.col("node").alias("tail"))
    found, links = None, cut(at.select(F.col("edge").alias("of2"), F.col("slot").alias("onward")))
    open_ = at
    for _ in range(64):
        own = open_.where("slot < 0").select("edge", "node", (F.col("slot") + start).alias("target"))
        even = open_.where("slot >= 0 and slot % 2 = 0").join(tails, F.floor(F.col("slot") / 2) == F.col("of")).select("edge", "node", F.col("tail").alias("target"))
        got = cut(own.union(even))
        found = got if found is None else found.union(got)
        odd = open_.where("slot >= 0 and slot % 2 = 1")
        open_ = cut(odd.join(links, F.floor(F.col("slot") / 2) == F.col("of2")).select("edge", "node", F.col("onward").alias("slot")))
        if empty(open_):
            break
    else:
        raise RuntimeError("slots did not resolve")
    turn = mix(F.col("edge") + 2_000_003, seed + 2) % 1000 < int(flip * 1000)
    a, b = F.when(turn, F.col("target")).otherwise(F.col("node")), F.when(turn, F.col("node")).otherwise(F.col("target"))
    return found.where("node <> target").select(a.alias("src"), b.alias("dst")).distinct()


def update_sequence(edges: DataFrame, n_ops: int, mix_ratio: tuple[int, int, int, int] = (12, 3, 4, 1), seed: int = 3) -> DataFrame:
    """A valid sequence: insert_edge, delete_edge, insert_node, delete_node in the ratio given (of its sum).

    Targets are heads of existing edges at arithmetic ranks, and so in proportion to in-degree; an
    existing edge is deleted once at most; a new node gets ids above all others.
    """
    from dynreach.sources.graphs import nodes_of, ranks

    spark, total = edges.sparkSession, sum(mix_ratio)
    nodes = nodes_of(edges)
    n, m, top = nodes.count(), edges.count(), nodes.agg(F.max("node")).first()[0]
    bounds = [sum(mix_ratio[: i + 1]) for i in range(4)]
    i = F.col("op_id")
    kind = F.when(i % total < bounds[0], "insert_edge").when(i % total < bounds[1], "delete_edge").when(i % total < bounds[2], "insert_node").otherwise("delete_node")
    asked = spark.range(n_ops).select(
        F.col("id").alias("op_id"), (mix(F.col("id") * 4, seed) % n).alias("rank"), (mix(F.col("id") * 4 + 1, seed) % m).alias("e1"), (mix(F.col("id") * 4 + 2, seed) % m).alias("e2")
    ).withColumn("kind", kind)
    numbered = edge_ranks(edges)
    wanted = cut(asked)
    by_rank = ranks(nodes).withColumnRenamed("node", "picked")
    e1 = numbered.select(F.col("place").alias("e1"), F.col("src").alias("s1"), F.col("dst").alias("d1"))
    e2 = numbered.select(F.col("place").alias("e2"), F.col("src").alias("s2"), F.col("dst").alias("d2"))
    full = wanted.join(by_rank, "rank").join(e1, "e1").join(e2, "e2")
    fresh = F.lit(top + 1) + i
    u = F.when(F.col("kind") == "insert_edge", F.col("picked")).when(F.col("kind") == "delete_edge", F.col("s1")).when(F.col("kind") == "insert_node", fresh).otherwise(F.col("picked"))
    v = F.when(F.col("kind").isin("insert_edge", "delete_edge"), F.col("d1"))
    outs = F.when(F.col("kind") == "insert_node", F.array("d1"))
    ins = F.when(F.col("kind") == "insert_node", F.when(i % 2 == 0, F.array("d2")).otherwise(F.array().cast("array<long>")))
    ops = full.select("op_id", F.lit(None).cast("timestamp_ntz").alias("ts"), "kind", u.cast("long").alias("u"), v.cast("long").alias("v"), outs.alias("outs"), ins.alias("ins"))
    first = ops.where("kind = 'delete_edge'").groupBy("u", "v").agg(F.min("op_id").alias("op_id")).select("op_id")
    return ops.where("kind <> 'delete_edge'").union(ops.join(first, "op_id", "left_semi").select(*ops.columns)).orderBy("op_id")


def drawn_sequence(edges: DataFrame, n_ops: int, ratio: tuple[int, int, int, int] = (60, 15, 20, 5), most_degree: int = 4, seed: int = 3, conf: EngineConf = DEFAULT) -> DataFrame:
    """A random sequence: kinds in the ratio given, sources uniform and heads by in-degree, random in- and out-degrees of new
    nodes, deletions uniform over the edges and nodes that are there when their turn comes. One task draws it."""
    if not fits(conf, edges):
        raise ValueError("one task draws the sequence and can't hold this graph; update_sequence has no such bound")

    def run(group: pd.DataFrame) -> pd.DataFrame:
        links = sorted(zip(group["src"].tolist(), group["dst"].tolist()))
        rows = [(i, *op) for i, op in enumerate(drawn_operations(PlainGraph(links), n_ops, ratio, most_degree, seed))]
        return pd.DataFrame(rows, columns=["op_id", "kind", "u", "v", "outs", "ins"])

    found = edges.select("src", "dst").groupBy(F.lit("all")).applyInPandas(run, "op_id long, kind string, u long, v long, outs array<long>, ins array<long>")
    node = F.col("kind") == "insert_node"
    return found.select("op_id", F.lit(None).cast("timestamp_ntz").alias("ts"), "kind", "u", F.when(F.col("v") >= 0, F.col("v")).alias("v"), F.when(node, F.col("outs")).alias("outs"), F.when(node, F.col("ins")).alias("ins"))


def edge_ranks(edges: DataFrame) -> DataFrame:
    """(src, dst, place): place in the order by (dst, src)."""
    from dynreach.sources.graphs import ordered

    return ordered(edges.select("src", "dst"), "dst", "src", name="place")


def query_pairs(nodes: DataFrame, n: int, seed: int = 9) -> DataFrame:
    """(qid, u, v) with uniform ends."""
    from dynreach.sources.graphs import ranks

    total = nodes.count()
    asked = nodes.sparkSession.range(n).select(F.col("id").alias("qid"), (mix(F.col("id") * 2, seed) % total).alias("ru"), (mix(F.col("id") * 2 + 1, seed) % total).alias("rv"))
    at = ranks(nodes)
    u, v = at.select(F.col("rank").alias("ru"), F.col("node").alias("u")), at.select(F.col("rank").alias("rv"), F.col("node").alias("v"))
    return asked.join(u, "ru").join(v, "rv").select("qid", "u", "v")


def evolution(edge_events: DataFrame, cut_at) -> tuple[DataFrame, DataFrame]:
    """(snapshot edges, later changes) from versions (src, dst, ts, present): a change is where presence differs from the version before."""
    w = Window.partitionBy("src", "dst").orderBy("ts")
    changed = edge_events.withColumn("before", F.coalesce(F.lag("present").over(w), F.lit(False))).where("present <> before")
    early = changed.where(F.col("ts") < cut_at)
    snapshot = early.groupBy("src", "dst").agg(F.max_by("present", "ts").alias("present")).where("present").select("src", "dst")
    later = changed.where(F.col("ts") >= cut_at).select("ts", F.when(F.col("present"), "insert_edge").otherwise("delete_edge").alias("kind"), F.col("src").alias("u"), F.col("dst").alias("v"))
    return snapshot, later
