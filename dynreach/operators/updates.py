"""Updates of an index: edges and nodes, inserted and deleted, as sets or one by one."""

from __future__ import annotations

from collections.abc import Iterable

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dynreach.conf import DEFAULT, EngineConf
from dynreach.model import OP_LOG, Index
from dynreach.operators import condense, index as I, scc
from dynreach.operators.kernel import DynamicIndex
from dynreach.plans import batch
from dynreach.plans.loops import cut, empty, fits

NONE = "cast(array() as array<long>)"


def insert_edges(index: Index, rows: DataFrame, **more) -> Index:
    """rows(u, v)."""
    return batch.apply(index, batch.ops_frame(rows, "insert_edge", u=F.col("u"), v=F.col("v")), **more)


def delete_edges(index: Index, rows: DataFrame, **more) -> Index:
    return batch.apply(index, batch.ops_frame(rows, "delete_edge", u=F.col("u"), v=F.col("v")), **more)


def insert_nodes(index: Index, rows: DataFrame, outs_only: bool = False, **more) -> Index:
    """rows(u, outs, ins); with outs_only, ins are not looked at and no cycle can come, if ends are not inserted later."""
    ins = F.lit(None) if outs_only or "ins" not in rows.columns else F.col("ins")
    return batch.apply(index, batch.ops_frame(rows, "insert_node", u=F.col("u"), outs=F.col("outs"), ins=ins), **more)


def delete_nodes(index: Index, rows: DataFrame, **more) -> Index:
    """rows(u)."""
    return batch.apply(index, batch.ops_frame(rows, "delete_node", u=F.col("u")), **more)


def apply(index: Index, ops: DataFrame, mode: str = "auto", conf: EngineConf = DEFAULT) -> Index:
    """mode: auto and batch take the operations as a set, sequential one by one, rebuild anew."""
    return batch.apply(index, ops, "batch" if mode == "auto" else mode, conf)


def _rows(ops: pd.DataFrame) -> Iterable[tuple]:
    """(op_id, kind, u, v, outs, ins) in order; -1 stands for no v, and arrays are not null, so that ids stay whole numbers."""
    for r in ops.sort_values("op_id").itertuples(index=False):
        yield int(r.op_id), r.kind, int(r.u), None if r.v < 0 else int(r.v), [int(x) for x in r.outs], [int(x) for x in r.ins]


#: Columns of operations as a task takes them.
TASK_OPS = ("op_id", "kind", "u", "coalesce(v, -1L) v", f"filter(coalesce(outs, {NONE}), x -> x is not null) outs", f"filter(coalesce(ins, {NONE}), x -> x is not null) ins")


def sequential(nodes: DataFrame, edges: DataFrame, ops: DataFrame, k: int = 1, conf: EngineConf = DEFAULT, seed: int = 42, **modes) -> tuple[DataFrame, DataFrame]:
    """(op_log, membership) after the operations in order, by the kernel in one task; the edges are counted first.

    modes: propagate, split, shrink and order of the kernel.
    """
    if not fits(conf, edges, nodes):
        raise ValueError("one task can't hold the graph; take mode='batch'")
    rows = (
        nodes.selectExpr("0 tag", "-1L op_id", "'' kind", "node u", "-1L v", f"{NONE} outs", f"{NONE} ins")
        .union(edges.selectExpr("1", "-1L", "''", "src", "dst", NONE, NONE))
        .union(ops.where("u is not null and (v is not null or kind like '%node')").selectExpr("2", *TASK_OPS))
    )
    slack = conf.slack

    def run(group: pd.DataFrame) -> pd.DataFrame:
        of = lambda tag: group[group["tag"] == tag]
        ix = DynamicIndex(of(0)["u"].tolist(), zip(of(1)["u"].tolist(), of(1)["v"].tolist()), k=k, seed=seed, slack=slack, **modes)
        log = [{"op_id": op_id, **ix.apply(kind, u, v, outs, ins), "node": None, "comp": None} for op_id, kind, u, v, outs, ins in _rows(of(2))]
        if bad := ix.violations():
            raise AssertionError(f"labels broken at {bad[:3]}")
        log += [{"op_id": None, "kind": None, "case": None, "comps_touched": None, "labels_changed": None, "rounds": None, "ms": None, "node": n, "comp": c} for n, c in ix.membership().items()]
        columns = ["op_id", "kind", "case", "comps_touched", "labels_changed", "rounds", "ms", "node", "comp"]
        whole = lambda c: pd.array([r[c] for r in log], dtype="Int64")
        return pd.DataFrame({c: [r[c] for r in log] if c in ("kind", "case", "ms") else whole(c) for c in columns})

    both = cut(rows.groupBy(F.lit("all")).applyInPandas(run, OP_LOG + ", node long, comp long"))
    return both.where("op_id is not null").drop("node", "comp"), both.where("node is not null").select("node", "comp")


def sequential_index(index: Index, ops: DataFrame, conf: EngineConf = DEFAULT, seed: int = 42) -> Index:
    nodes, edges = (cut(x) for x in batch.final_state(index.nodes, index.edges, ops))
    if fits(conf, index.edges, index.nodes):
        _, membership = sequential(index.nodes, index.edges, ops, index.k, conf, seed)
    else:
        membership = cut(sequential_by_components(nodes, index.edges, ops, index.k, conf, seed))
    return I.assemble(nodes, edges, membership, index.k, seed, conf=conf, version=index.version + 1)


def sequential_by_components(there: DataFrame, edges: DataFrame, ops: DataFrame, k: int = 1, conf: EngineConf = DEFAULT, seed: int = 42) -> DataFrame:
    """membership of the nodes there after the operations in order, for graphs that no task takes.

    With all edges that are ever inserted, the graph has components that no cycle leaves at any time. Each of them that an
    operation changes inside goes to a task of its own, where the kernel takes its operations one by one; others stay as they are.
    """
    events = cut(batch.edge_events(ops))
    ever = cut(edges.select("src", "dst").union(events.where("insert").select("src", "dst")).distinct())
    several = cut(condense.compact(scc.strongly_connected(None, ever, conf=conf)))
    a, b = several.select(F.col("node").alias("src"), "comp"), several.select(F.col("node").alias("dst"), F.col("comp").alias("other"))
    within = lambda rows: rows.join(a, "src").join(b, "dst").where("comp = other").drop("other")
    kills = ops.where("kind = 'delete_node'").select("op_id", F.col("u").alias("node")).join(several, "node")
    inside = within(events).select("comp", "op_id", F.when(F.col("insert"), "insert_edge").otherwise("delete_edge").alias("kind"), "src", "dst")
    steps = cut(inside.union(kills.select("comp", "op_id", F.lit("delete_node"), "node", F.lit(-1).cast("long"))))
    touched = cut(steps.select("comp").distinct())
    links = cut(within(edges.select("src", "dst")).join(touched, "comp", "left_semi").select("comp", F.lit(-1).cast("long").alias("op_id"), F.lit("").alias("kind"), "src", "dst"))
    sizes = links.select("comp").union(several.join(touched, "comp", "left_semi").select("comp")).groupBy("comp").count()
    if not empty(sizes.where(F.col("count") > conf.local_rows)):
        raise ValueError("one task can't hold a component that operations change one by one; take mode='batch'")
    slack = conf.slack

    def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        base, later = group[group["op_id"] < 0], group[group["op_id"] >= 0].sort_values("op_id", kind="stable")
        ix = DynamicIndex((), zip(base["src"].tolist(), base["dst"].tolist()), k=k, seed=seed, slack=slack)
        for kind, u, v in zip(later["kind"], later["src"].tolist(), later["dst"].tolist()):
            ix.apply(kind, u, None if kind == "delete_node" else v)
        if bad := ix.violations():
            raise AssertionError(f"labels broken at {bad[:3]}")
        found = ix.membership()
        return pd.DataFrame({"node": list(found), "comp": list(found.values())}, dtype="int64")

    found = cut(links.union(steps).groupBy("comp").applyInPandas(run, "node long, comp long"))
    same = several.join(touched, "comp", "left_anti").select("node", "comp")
    return there.select("node").join(found.union(same), "node", "left").select("node", F.coalesce("comp", "node").alias("comp"))
