"""Workloads: update sequences on the given tables, with interleaved questions, and what they cost."""

from __future__ import annotations

import random
import time
import zlib

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dynreach.conf import DEFAULT, EngineConf
from dynreach.operators.generators import drawn_sequence
from dynreach.operators.kernel import DynamicIndex
from dynreach.operators.plain import PlainGraph
from dynreach.operators.updates import NONE, TASK_OPS, _rows
from dynreach.plans.loops import cut, fits
from dynreach.sources import graphs as G

NO_IDS = "cast(null as array<long>)"


def ops_wiki_like(spark: SparkSession, d: str, most: int = 1000) -> tuple[DataFrame, DataFrame]:
    """(snapshot edges, ops) of the goods graph in ship order, from its 95th percentile on.

    An order's first line inserts it as a node with that edge, later ones insert edges; returned parts insert
    edges back; `A` lines lose theirs after 90 days; some finished orders go 30 days after their last line.
    """
    lines, orders = G.read(spark, d, "lineitem"), G.read(spark, d, "orders")
    dates = lines.groupBy(F.col("l_shipdate").alias("t0")).count()  # a row a date
    running = F.sum("count").over(Window.orderBy("t0"))
    t0 = dates.select("t0", running.alias("upto"), F.sum("count").over(Window.partitionBy()).alias("all")).where("upto >= 0.95 * `all`").agg(F.min("t0").alias("t0"))
    dated = lines.select("l_orderkey", "l_partkey", "l_shipdate", "l_quantity", "l_returnflag", "l_discount").join(F.broadcast(t0))  # one row
    o, p = G.node("l_orderkey", G.ORDER), G.node("l_partkey", G.PART)
    out, back = F.col("l_quantity") <= 40, (F.col("l_returnflag") == "R") & (F.col("l_discount") >= 0.095)
    early = dated.where("l_shipdate < t0")
    snapshot = G.pairs(early.where(out), o, p).union(G.pairs(early.where(back), p, o)).distinct()
    spans = lines.groupBy("l_orderkey").agg(F.min("l_shipdate").alias("first"), F.max("l_shipdate").alias("last"))
    late = dated.where("l_shipdate >= t0")
    forward = late.where(out).join(spans, "l_orderkey").select(F.col("l_shipdate").alias("ts"), F.when(F.col("l_shipdate") == F.col("first"), "insert_node").otherwise("insert_edge").alias("kind"), o.alias("u"), p.alias("v"))
    backward = late.where(back).select(F.col("l_shipdate").alias("ts"), F.lit("insert_edge").alias("kind"), p.alias("u"), o.alias("v"))
    drop_at = F.expr("l_shipdate + interval 90 days")
    gone = dated.where(out & (F.col("l_returnflag") == "A")).where(drop_at >= F.col("t0")).select(drop_at.alias("ts"), F.lit("delete_edge").alias("kind"), o.alias("u"), p.alias("v"))
    ended = orders.where("o_orderstatus = 'F' and o_orderkey % 10 = 0").join(spans, F.col("o_orderkey") == F.col("l_orderkey")).join(F.broadcast(t0))
    at = F.expr("last + interval 30 days")
    dead = ended.where(at >= F.col("t0")).select(at.alias("ts"), F.lit("delete_node").alias("kind"), G.node("o_orderkey", G.ORDER).alias("u"), F.lit(None).cast("long").alias("v"))
    events = forward.union(backward).union(gone).union(dead).distinct()
    return snapshot, numbered(events, most)


def numbered(events: DataFrame, most: int | None = None) -> DataFrame:
    """ops from (ts, kind, u, v), in that order; the v of an insert_node becomes its out-edge. A cap keeps the first ones."""
    order = ["ts", "kind", "u", F.col("v").asc_nulls_last()]
    if most is not None:  # the feature: a bounded sequence
        events = events.orderBy(*order).limit(most)
    rows = G.ordered(events, *order, name="op_id")
    node = F.col("kind") == "insert_node"
    outs = F.when(node & F.col("v").isNotNull(), F.array("v"))
    return rows.select("op_id", "ts", "kind", "u", F.when(~node, F.col("v")).alias("v"), outs.alias("outs"), F.expr(NO_IDS).alias("ins"))


def ops_citation(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """(snapshot edges, ops): the first 85.8 % of orders by date are there, the others come as nodes with out-edges."""
    orders = G.read(spark, d, "orders").select("o_orderkey", "o_orderdate")
    ranked = cut(G.ordered(orders, "o_orderdate", "o_orderkey").select("o_orderkey", (F.col("rank") + 1).alias("rank")))
    n = ranked.count()
    early = ranked.where(F.col("rank") <= int(0.858 * n)).select(F.col("o_orderkey").alias("src"))
    edges = G.order_citation(spark, d)
    snapshot = edges.join(early, "src", "left_semi").select("src", "dst")
    later = ranked.where(F.col("rank") > int(0.858 * n))
    cited = edges.groupBy("src").agg(F.array_sort(F.collect_set("dst")).alias("outs"))
    ops = later.join(cited, F.col("o_orderkey") == F.col("src"), "left").select(
        (F.col("rank") - int(0.858 * n) - 1).cast("long").alias("op_id"), F.lit(None).cast("timestamp_ntz").alias("ts"), F.lit("insert_node").alias("kind"), F.col("o_orderkey").alias("u"), F.lit(None).cast("long").alias("v"), "outs", F.expr(NO_IDS).alias("ins")
    )
    return snapshot, ops


def ops_events(spark: SparkSession, d: str) -> DataFrame:
    """Events as operations on states: most insert the step, a purchase deletes the step before, some errors delete the state."""
    e = G.user_states(spark, d)
    error = F.col("event_type") == "error"
    kind = F.when(F.col("event_type").isin("view", "click", "signup"), "insert_edge").when(F.col("event_type") == "purchase", "delete_edge").when(error & (F.col("value") < 2), "delete_node")
    u = F.when(kind == "insert_edge", F.col("p")).when(kind == "delete_edge", F.col("pp")).otherwise(F.col("st"))
    v = F.when(kind == "insert_edge", F.col("st")).when(kind == "delete_edge", F.col("p"))
    rows = e.select("event_id", "ts", kind.alias("kind"), u.alias("u"), v.alias("v")).where("kind is not null and u is not null and (v is not null or kind = 'delete_node')")
    places = G.ordered(rows, "ts", "event_id", name="op_id")
    return places.select("op_id", "ts", "kind", "u", "v", F.expr(NO_IDS).alias("outs"), F.expr(NO_IDS).alias("ins"))


WORKLOADS = {
    "wiki_like": ops_wiki_like,
    "citation": ops_citation,
    "uniform": lambda spark, d: (e := cut(G.uniform_pairs(spark, d)), drawn_sequence(e, 1000)),
    "hub": lambda spark, d: (e := cut(G.goods_flow(spark, d)), drawn_sequence(e, 1000)),
}

TIMES = "method string, k int, measure string, n long, total_ms double, avg_ms double, expanded double, reached long, answers long"


def _task_rows(edges: DataFrame, ops: DataFrame, conf: EngineConf) -> DataFrame:
    if not fits(conf, edges):
        raise ValueError("times are taken in one task, which can't hold this graph")
    return edges.selectExpr("1 tag", "-1L op_id", "'' kind", "src u", "dst v", f"{NONE} outs", f"{NONE} ins").union(ops.selectExpr("2", *TASK_OPS))


def _methods(spark: SparkSession, ks: tuple[int, ...]) -> DataFrame:
    return spark.createDataFrame([(-1,), *((k,) for k in ks)], "k int")


def _replay(key: tuple, group: pd.DataFrame, most_ops: int | None, seed: int) -> tuple[int, DynamicIndex | None, PlainGraph, list[tuple]]:
    k, of = int(key[0]), lambda tag: group[group["tag"] == tag]
    links = sorted(zip(of(1)["u"].tolist(), of(1)["v"].tolist()))  # one order for every method
    return k, None if k < 0 else DynamicIndex((), links, k=k, seed=seed), PlainGraph(links), list(_rows(of(2)))[:most_ops]


def op_times(edges: DataFrame, ops: DataFrame, ks: tuple[int, ...] = (0, 1, 2), questions: int = 8, most_ops: int | None = None, conf: EngineConf = DEFAULT, seed: int = 42) -> DataFrame:
    """Times of questions and of each kind of operation, for plain search and for idx(k); one task a method.

    After every operation `questions` pairs are drawn uniformly from the nodes there are then, the same for all methods, on
    the same graph: the graph of plain search takes all operations as well, which costs it nothing. Rows: Q over all
    questions, Q1, Q2, ... over the first, second, ... question after each operation, and one for each kind of
    operation. `reached` and `answers` (a checksum in order) are what the method said; they agree between methods.
    """
    rows = _task_rows(edges, ops, conf)

    def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        k, ix, graph, sequence = _replay(key, group, most_ops, seed)
        rng, clock = random.Random(seed), time.perf_counter
        asked, spent = [[0.0, 0] for _ in range(questions)], {}
        expanded, said = 0, bytearray()
        for _, kind, u, v, outs, ins in sequence:
            graph.apply(kind, u, v, outs, ins)
            if ix is not None:
                n, ms = spent.get(kind, (0, 0.0))
                spent[kind] = n + 1, ms + ix.apply(kind, u, v, outs, ins)["ms"]
            for slot in asked if len(graph.nodes) else ():
                a, b = graph.nodes.draw(rng), graph.nodes.draw(rng)
                start = clock()
                hit, n = graph.search(a, b) if ix is None else ix.query(a, b)[::2]
                slot[0] += (clock() - start) * 1000
                slot[1] += 1
                expanded += n
                said.append(hit)
        name = "search" if k < 0 else f"idx({k})"
        total, count = sum(ms for ms, _ in asked), sum(n for _, n in asked)
        out = [(name, k, "Q", count, total, total / max(1, count), expanded / max(1, count), sum(said), zlib.crc32(bytes(said)))]
        out += [(name, k, f"Q{j}", n, ms, ms / max(1, n), None, None, None) for j, (ms, n) in enumerate(asked, 1)]
        out += [(name, k, kind, n, ms, ms / n, None, None, None) for kind, (n, ms) in spent.items()]
        frame = pd.DataFrame(out, columns=[f.split(" ")[0] for f in TIMES.split(", ")])
        return frame.astype({"reached": "Int64", "answers": "Int64"})

    return rows.crossJoin(F.broadcast(_methods(edges.sparkSession, ks))).groupBy("k").applyInPandas(run, TIMES)  # a row a method


def answers_of_methods(edges: DataFrame, ops: DataFrame, pairs: DataFrame, ks: tuple[int, ...] = (0, 1, 2), conf: EngineConf = DEFAULT, seed: int = 42) -> DataFrame:
    """(method, qid, u, v, reachable): what plain search and each idx(k) say of the pairs after all operations one by one."""
    rows = _task_rows(edges, ops, conf).union(pairs.selectExpr("3", "qid", "''", "u", "v", NONE, NONE))

    def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        k, ix, graph, sequence = _replay(key, group, None, seed)
        for _, kind, u, v, outs, ins in sequence:
            graph.apply(kind, u, v, outs, ins) if ix is None else ix.apply(kind, u, v, outs, ins)
        asked = group[group["tag"] == 3]
        said = [(graph.search(u, v) if ix is None else ix.query(u, v))[0] for u, v in zip(asked["u"].tolist(), asked["v"].tolist())]
        return pd.DataFrame({"method": "search" if k < 0 else f"idx({k})", "qid": asked["op_id"], "u": asked["u"], "v": asked["v"], "reachable": said})

    return rows.crossJoin(F.broadcast(_methods(edges.sparkSession, ks))).groupBy("k").applyInPandas(run, "method string, qid long, u long, v long, reachable boolean")


def sweep(times: DataFrame) -> DataFrame:
    """(method, q, total_ms): what the sequence took with q questions after every operation, for as many q as were asked:
    the operations, and the first q questions after each."""
    updates = times.where("not measure like 'Q%'").groupBy("method").agg(F.sum("total_ms").alias("updates"))
    asked = times.where("measure rlike '^Q[0-9]+$'").select("method", F.substring("measure", 2, 9).cast("int").alias("q"), "total_ms")
    upto = F.sum("total_ms").over(Window.partitionBy("method").orderBy("q").rowsBetween(Window.unboundedPreceding, 0))
    return asked.withColumn("upto", upto).join(updates, "method", "left").select("method", "q", (F.coalesce("updates", F.lit(0.0)) + F.col("upto")).alias("total_ms"))


def break_even(totals: DataFrame) -> DataFrame:
    """(method, q): the fewest questions an operation at which a method costs less than plain search; null if never."""
    base = totals.where("method = 'search'").select("q", F.col("total_ms").alias("base"))
    rows = totals.where("method <> 'search'").join(base, "q")
    return rows.groupBy("method").agg(F.min(F.when(F.col("total_ms") < F.col("base"), F.col("q"))).alias("q"))
