"""Batches of operations: net effect, classes, and one pass over the index for each class.

A batch is first reduced to what it changes: an operation undone later in the batch costs nothing. What is left falls into
four classes by the components of its ends. Edges within components need no work; edges that go between
components only change multiplicities; new edges between components are added together, their cycles found in the
part of the condensation that lies below a head and above a tail, and one upward pass repairs all labels. Deletions
within components decompose only the components they touch. A batch that changes a large share of the
edges rebuilds the index instead.
"""

from __future__ import annotations

from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dynreach.conf import DEFAULT, EngineConf
from dynreach.functions.intervals import label_hull
from dynreach.model import OPS, Index
from dynreach.operators import condense, containment, labels as L, scc, splits
from dynreach.operators import index as I
from dynreach.operators.kernel import repaired
from dynreach.operators.scc import turned
from dynreach.plans.loops import cut, empty, fits

NEVER = -1


def edge_events(ops: DataFrame) -> DataFrame:
    """(op_id, insert, src, dst) of all edges that operations name."""
    of = lambda kind: ops.where(F.col("kind") == kind)
    one = of("insert_edge").select("op_id", F.lit(True).alias("insert"), F.col("u").alias("src"), F.col("v").alias("dst"))
    gone = of("delete_edge").select("op_id", F.lit(False), "u", "v")
    new = of("insert_node")
    outs = new.select("op_id", F.lit(True), "u", F.explode("outs"))
    ins = new.select("op_id", F.lit(True), F.explode("ins").alias("i"), "u")
    return one.union(gone).union(outs).union(ins).where("src is not null and dst is not null")


def final_state(nodes: DataFrame, edges: DataFrame, ops: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(nodes, edges) after all operations in order of op_id."""
    events = edge_events(ops).union(edges.select(F.lit(NEVER).cast("long"), F.lit(True), "src", "dst"))
    last = events.groupBy("src", "dst").agg(F.max("op_id").alias("at"), F.max_by("insert", "op_id").alias("there")).where("there")
    kills = ops.where("kind = 'delete_node'").groupBy(F.col("u").alias("node")).agg(F.max("op_id").alias("killed"))
    alive = last.join(kills.select(F.col("node").alias("src"), F.col("killed").alias("ks")), "src", "left").join(kills.select(F.col("node").alias("dst"), F.col("killed").alias("kd")), "dst", "left")
    alive = alive.where("at > coalesce(ks, -2) and at > coalesce(kd, -2)").select("src", "dst")
    inserts = edge_events(ops).where("insert")
    named = (
        nodes.select("node", F.lit(NEVER).cast("long").alias("op_id"))
        .union(inserts.select(F.col("src"), "op_id"))
        .union(inserts.select(F.col("dst"), "op_id"))
        .union(ops.where("kind = 'insert_node'").select("u", "op_id"))
    )
    there = named.groupBy("node").agg(F.max("op_id").alias("at")).join(kills, "node", "left").where("at > coalesce(killed, -2)").select("node")
    return there, alive


def nearby(nodes: DataFrame, edges: DataFrame, ops: DataFrame, conf: EngineConf = DEFAULT) -> tuple[DataFrame, DataFrame]:
    """The nodes and edges that the operations can touch: edges they name, edges at nodes they delete, and all ends."""
    few = ops.limit(conf.broadcast_rows + 1).count() <= conf.broadcast_rows
    named = edge_events(ops).select("src", "dst").distinct().withColumn("named", F.lit(True))
    killed = ops.where("kind = 'delete_node'").select(F.col("u").alias("node")).distinct().withColumn("dead", F.lit(True))
    small = F.broadcast if few else (lambda df: df)  # as many rows as the operations name edges
    marked = edges.join(small(named), ["src", "dst"], "left")
    for end in ("src", "dst"):
        marked = marked.join(small(killed.select(F.col("node").alias(end), F.col("dead").alias(f"dead_{end}"))), end, "left")
    near = cut(marked.where("named or dead_src or dead_dst").select("src", "dst"))
    ends = edge_events(ops).select("src", "dst").union(near)
    ids = ends.select(F.col("src").alias("node")).union(ends.select("dst")).union(ops.where("kind like '%node'").select("u")).distinct()
    return cut(nodes.join(ids, "node", "left_semi")), near


def prune(nodes: DataFrame, edges: DataFrame, ops: DataFrame, conf: EngineConf = DEFAULT) -> DataFrame:
    """The net effect as (kind, u, v): the operations that change the graph, each at most once."""
    nodes, edges = nearby(nodes, edges, ops, conf)
    there, alive = final_state(nodes, edges, ops)
    flat = lambda df, kind, cols: df.select(F.lit(kind).alias("kind"), F.col(cols[0]).alias("u"), (F.col(cols[1]) if len(cols) > 1 else F.lit(None).cast("long")).alias("v"))
    return (
        flat(alive.join(edges, ["src", "dst"], "left_anti"), "insert_edge", ("src", "dst"))
        .union(flat(edges.select("src", "dst").join(alive, ["src", "dst"], "left_anti"), "delete_edge", ("src", "dst")))
        .union(flat(there.join(nodes, "node", "left_anti"), "insert_node", ("node",)))
        .union(flat(nodes.select("node").join(there, "node", "left_anti"), "delete_node", ("node",)))
    )


def classify(net: DataFrame, membership: DataFrame) -> DataFrame:
    """Edge operations with s, t and class: ins_intra, ins_inter, del_intra, del_inter. membership may hold their ends only."""
    rows = net.where("kind in ('insert_edge', 'delete_edge')").select("kind", F.col("u").alias("src"), F.col("v").alias("dst"))
    side = F.when(F.col("s") == F.col("t"), "_intra").otherwise("_inter")
    return condense.ends(rows, membership).select("kind", F.col("src").alias("u"), F.col("dst").alias("v"), "s", "t", F.concat(F.substring("kind", 1, 3), side).alias("class"))


def ends_of(rows: DataFrame, a: str = "src", b: str = "dst") -> DataFrame:
    return rows.select(F.col(a).alias("node")).union(rows.select(b)).distinct()


def condense_ops(net: DataFrame, conf: EngineConf = DEFAULT) -> DataFrame:
    """(node, comp): components of the inserted edges alone; a merge of several nodes by the batch itself is found once."""
    inserted = net.where("kind = 'insert_edge'").select(F.col("u").alias("src"), F.col("v").alias("dst"))
    return scc.strongly_connected(None, inserted, conf=conf)


def apply(index: Index, ops: DataFrame, mode: str = "batch", conf: EngineConf = DEFAULT, seed: int = 42) -> Index:
    """The index after the batch; facts hold the number of operations of each class, whether it was rebuilt, and what a split touched."""
    if mode == "sequential":
        from dynreach.operators.updates import sequential_index

        return sequential_index(index, ops, conf, seed)
    net = cut(prune(index.nodes, index.edges, ops, conf))
    changes = net.where("kind like '%edge'").select(F.col("u").alias("src"), F.col("v").alias("dst"))
    classes = cut(classify(net, index.lookup(ends_of(changes))))
    counts = {r[0]: r[1] for r in classes.groupBy("class").count().collect()}
    kinds = {r[0]: r[1] for r in net.groupBy("kind").count().collect()}
    total = sum(counts.values())
    facts = counts | {"net": total, "rebuilt": False}
    if not kinds:
        return index.next(facts=facts)
    new_nodes, gone_nodes = (net.where(F.col("kind") == k).select(F.col("u").alias("node")) for k in ("insert_node", "delete_node"))
    few = total <= conf.broadcast_rows
    small = F.broadcast if few else (lambda df: df)
    edges, nodes = index.edges.select("src", "dst"), index.nodes
    if "delete_edge" in kinds:
        edges = edges.join(small(classes.where("kind = 'delete_edge'").select(F.col("u").alias("src"), F.col("v").alias("dst"))), ["src", "dst"], "left_anti")
    if "insert_edge" in kinds:
        edges = edges.union(classes.where("kind = 'insert_edge'").select("u", "v"))
    if "delete_node" in kinds:
        nodes = nodes.join(small(gone_nodes), "node", "left_anti")
    if "insert_node" in kinds:
        nodes = nodes.union(new_nodes)
    edges, nodes = cut(edges.coalesce(_tasks(index.edges))) if total else edges, cut(nodes.coalesce(_tasks(index.nodes)))
    if mode == "rebuild" or total > conf.rebuild_ratio * max(1, index.edges.count()):
        membership = cut(scc.strongly_connected(nodes, edges, conf=conf))
        fresh = I.assemble(nodes, edges, membership, index.k, seed, conf=conf, version=index.version + 1)
        return replace(fresh, facts=facts | {"rebuilt": True})
    work = _Work(index, conf, seed)
    work.between_components(classes.where("class like '%_inter'"))
    work.insert(new_nodes, classes, kinds, counts)
    if counts.get("del_intra"):
        work.split(edges, classes.where("class = 'del_intra' and u <> v").select(F.col("u").alias("src"), F.col("v").alias("dst")))
    if "delete_node" in kinds:
        work.drop_nodes(gone_nodes)
    return index.next(nodes=nodes, edges=edges, components=work.components, dag_edges=work.dag, labels=work.labels, containment=work.containment, depth=work.depth, facts=facts | work.facts)


def _tasks(before: DataFrame) -> int:
    """Partitions for what comes out of a table: unions add them up, and a batch after a batch must not."""
    conf, sc = before.sparkSession.conf, before.sparkSession.sparkContext
    return max(sc.defaultParallelism, int(conf.get("spark.sql.shuffle.partitions")), before.rdd.getNumPartitions())


class _Work:
    """The parts of an index while a batch passes over them."""

    def __init__(self, index: Index, conf: EngineConf, seed: int):
        self.k, self.conf, self.epoch, self.seed, self.depth = index.k, conf, index.version + 1, seed, index.depth
        self.dag, self.labels, self.containment, self.components = index.dag_edges, index.labels, index.containment, index.components
        self.facts: dict = {}

    def lookup(self, nodes: DataFrame) -> DataFrame:
        return containment.find(self.containment, nodes, self.depth)

    def between_components(self, inter: DataFrame) -> None:
        """Multiplicities change by sums of the batch; pairs that reach zero go. Deletions leave labels as they are."""
        delta = inter.groupBy("s", "t").agg(F.sum(F.when(F.col("kind") == "insert_edge", 1).otherwise(-1)).alias("mult"))
        self._add(delta)

    def _add(self, delta: DataFrame) -> None:
        """Only the condensation edges that the delta names are summed again."""
        delta = cut(delta.where("mult <> 0"))
        if empty(delta):
            return
        few = delta.limit(self.conf.broadcast_rows + 1).count() <= self.conf.broadcast_rows
        small = F.broadcast if few else (lambda df: df)
        marked = self.dag.join(small(delta.withColumnRenamed("mult", "more")), ["s", "t"], "left")
        kept = marked.select("s", "t", (F.col("mult") + F.coalesce("more", F.lit(0))).alias("mult")).where("mult > 0")
        new = delta.join(self.dag.join(small(delta.select("s", "t")), ["s", "t"], "left_semi"), ["s", "t"], "left_anti").select("s", "t", "mult")
        dag = kept.union(new)
        self.dag = cut(dag.coalesce(_tasks(self.dag)))

    def insert(self, new: DataFrame, classes: DataFrame, kinds: dict, counts: dict) -> None:
        """New nodes are components of their own; cycles that new edges close are merged, and labels are raised."""
        if "insert_node" in kinds:
            self.components = self.components.union(new.select("node", F.lit(1).cast("long"), F.lit("current")))
        inserted = classes.where("class = 'ins_inter'").select("s", "t").distinct()
        if not counts.get("ins_inter") and "insert_node" not in kinds:
            return
        if fits(self.conf, self.dag, self.components):
            self._insert_here(new, inserted)
        else:
            self._add_labels(new, inserted)
            if counts.get("ins_inter"):
                self._merge(inserted)
        self.components = cut(self.components)

    def _insert_here(self, new: DataFrame, inserted: DataFrame) -> None:
        """One task takes the condensation and its labels, whose rows are counted, and says what merges and which labels change."""
        flat = F.flatten(F.transform("iv", lambda x: F.array(x["b"], x["e"])))
        none, k = F.array().cast("array<long>"), self.k
        rows = (
            self.dag.select(F.lit(0).alias("tag"), "s", "t", none.alias("iv"))
            .union(self.labels.select(F.lit(1), "comp", F.lit(-1).cast("long"), flat))
            .union(inserted.select(F.lit(2), "s", "t", none))
            .union(new.select(F.lit(3), "node", F.lit(-1).cast("long"), none))
        )

        def run(group: pd.DataFrame) -> pd.DataFrame:
            tag, s, t = (group[c].to_numpy() for c in ("tag", "s", "t"))
            of = lambda x: list(zip(s[tag == x].tolist(), t[tag == x].tolist()))
            labels = {c: list(zip(iv[::2].tolist(), iv[1::2].tolist())) for c, iv in zip(s[tag == 1].tolist(), group["iv"][tag == 1])}
            merged, changed = repaired(of(0), labels, of(2), s[tag == 3].tolist(), k)
            out = [(c, rep, []) for c, rep in merged.items()] + [(c, -1, [x for iv in ivs for x in iv]) for c, ivs in changed.items()]
            return pd.DataFrame({"comp": pd.array([r[0] for r in out], dtype="int64"), "rep": pd.array([r[1] for r in out], dtype="int64"), "iv": [r[2] for r in out]})

        found = cut(rows.groupBy(F.lit("all")).applyInPandas(run, "comp long, rep long, iv array<long>"))
        merged = found.where("rep >= 0").select("comp", "rep")
        if not empty(merged):
            self._rename(merged)
        labels = found.where("rep < 0").select("comp", L.paired(F.col("iv"), k).alias("iv"))
        self._relabel(found.select("comp").distinct(), labels)

    def _relabel(self, old: DataFrame, labels: DataFrame) -> None:
        all_ = self.labels.join(old, "comp", "left_anti").unionByName(labels)
        self.labels = cut(all_.coalesce(_tasks(self.labels)))

    def _add_labels(self, new: DataFrame, inserted: DataFrame) -> None:
        """By sets: a new component's label is just above its children's, or past the largest end in use."""
        if empty(new):
            return
        if not self.k:
            self.labels = cut(self.labels.union(L.none(new.select(F.col("node").alias("comp")))))
            return
        top = L.unpack(self.labels).agg(F.max("e")).first()[0] or 0
        fresh = F.array_repeat(F.struct(F.lit(top).cast("long").alias("b"), F.lit(top + 1).cast("long").alias("e")), self.k)
        below = inserted.select(F.col("s").alias("node"), F.col("t").alias("comp")).join(new, "node", "left_semi").join(self.labels, "comp")
        hull = below.groupBy("node").agg(label_hull(F.col("iv"), self.k).alias("iv")).select("node", F.transform("iv", lambda x: F.struct(x["b"].alias("b"), (x["e"] + 1).alias("e"))).alias("iv"))
        self.labels = cut(self.labels.union(new.join(hull, "node", "left").select(F.col("node").alias("comp"), F.coalesce("iv", fresh).alias("iv"))))

    def _merge(self, inserted: DataFrame) -> None:
        """By sets. Inserted edges are condensed among themselves first, so that cycles they close alone are one component
        before anything is searched; any other cycle lies above the inserted tails, and new nodes have little above them."""
        alone = inserted.select(F.col("s").alias("src"), F.col("t").alias("dst"))
        self._absorb(cut(condense.compact(scc.strongly_connected(None, alone, conf=self.conf)).select(F.col("node").alias("comp"), F.col("comp").alias("rep"))))
        up = scc.sweep(inserted.join(self.moved, F.col("s") == F.col("comp"), "left").select(F.coalesce("rep", "s").alias("node")), turned(self._plain()), self.conf)
        e = self._plain()
        inner = e.join(up.withColumnRenamed("node", "src"), "src", "left_semi").join(up.withColumnRenamed("node", "dst"), "dst", "left_semi").select("src", "dst")
        first = self.moved
        self._absorb(cut(condense.compact(scc.strongly_connected(None, inner, conf=self.conf)).select(F.col("node").alias("comp"), F.col("comp").alias("rep"))))
        if self.k:
            seeds = inserted.select(F.col("t").alias("comp")).union(first.select("rep")).distinct()
            for moved in (first, self.moved):
                seeds = seeds.join(moved, "comp", "left").select(F.coalesce("rep", "comp").alias("comp")).union(moved.select("rep")).distinct()
            self.labels = L.propagate_up(self.labels, self.dag, seeds.join(self.labels, "comp", "left_semi").select("comp"), self.conf)[0]

    def _plain(self) -> DataFrame:
        return cut(self.dag.select(F.col("s").alias("src"), F.col("t").alias("dst")))

    def _absorb(self, merged: DataFrame) -> None:
        self.moved = merged
        if not empty(merged):
            hulls = self.labels.join(merged, "comp").groupBy("rep").agg(label_hull(F.col("iv"), self.k).alias("iv")).select(F.col("rep").alias("comp"), "iv")
            labels = cut(hulls)
            self._rename(merged)
            self._relabel(merged.select("comp"), labels)

    def _rename(self, merged: DataFrame) -> None:
        """Merged components take the name of what they are part of: one row of the forest for each that is absorbed, and the
        condensation edges at them. No row of a node changes."""
        few = merged.limit(self.conf.broadcast_rows + 1).count() <= self.conf.broadcast_rows
        small = F.broadcast if few else (lambda df: df)
        a, b = small(merged.select(F.col("comp").alias("s"), F.col("rep").alias("rs"))), small(merged.select(F.col("comp").alias("t"), F.col("rep").alias("rt")))
        ends = cut(self.dag.join(a, "s", "left").join(b, "t", "left").select("s", "t", "mult", "rs", "rt"))
        moved = ends.where("rs is not null or rt is not null").select(F.coalesce("rs", "s").alias("s"), F.coalesce("rt", "t").alias("t"), "mult")
        # both ends of what a moved edge falls together with have an end that is a new name, so they moved as well
        dag = ends.where("rs is null and rt is null").select("s", "t", "mult").union(moved.where("s <> t").groupBy("s", "t").agg(F.sum("mult").alias("mult")))
        self.dag = cut(dag.coalesce(_tasks(self.dag)))
        absorbed = merged.where("comp <> rep").select(F.col("comp").alias("child"), F.col("rep").alias("parent"), F.lit(self.epoch).cast("long").alias("epoch"))
        self.containment, self.depth = cut(self.containment.union(absorbed)), self.depth + 1
        if self.depth > self.conf.forest_depth:
            self._compress()
        sizes = self.components.join(small(merged), "comp").groupBy(F.col("rep").alias("comp")).agg(F.sum("size").alias("size")).withColumn("status", F.lit("current"))
        self.components = cut(self.components.join(small(merged.select("comp")), "comp", "left_anti").unionByName(sizes))

    def _compress(self) -> None:
        """Rows point at current components again."""
        found = self.lookup(self.containment.select(F.col("child").alias("node")))
        self.containment = cut(self.containment.join(found, F.col("child") == F.col("node")).select("child", F.col("comp").alias("parent"), "epoch"))
        self.depth = 1

    def split(self, edges: DataFrame, deleted: DataFrame) -> None:
        """Decomposes components that lost an inner edge. What stays with the component's name keeps all its rows."""
        conf = self.conf
        lost = cut(condense.ends(deleted, self.lookup(ends_of(deleted))).where("s = t and src <> dst").select("src", "dst", F.col("s").alias("comp")))
        if empty(lost):
            return
        comps = cut(lost.select("comp").distinct())
        members = cut(containment.members(self.containment, comps, self.depth))
        extract = conf.split == "extract" or (conf.split == "auto" and not fits(conf, members))
        leavers, seen, middle = splits.leavers(edges, members, lost, conf) if extract else (members.select("node", F.lit(None).cast("int").alias("height")), None, 0)
        if seen is not None and empty(leavers):
            self.facts |= {"split": "none", "touched": seen}
            return
        there = cut(members.join(leavers, "node").select("node", "comp", "height"))
        moved, searched = there.where("height is not null").select("node", "comp", F.col("node").alias("piece"), "height"), there.where("height is null")
        inner = splits.inner(edges, searched)
        if not empty(searched):  # what was peeled off is a piece by itself
            fresh = scc.strongly_connected(searched.select("node"), inner, conf=conf).withColumnRenamed("comp", "piece")
            moved = moved.union(searched.join(fresh, "node").select("node", "comp", "piece", F.lit(middle)))
        moved = cut(moved.where("comp <> piece"))
        self.facts |= {"split": "naive" if seen is None else "extract", "touched": seen if seen is not None else inner.count(), "left": moved.count()}
        if not self.facts["left"]:
            return
        if self.depth > 1:  # paths through what leaves must not go with it
            self._compress()
        at = cut(splits.incident(edges, moved))
        before = condense.build(at, cut(self.lookup(ends_of(at)))).withColumn("mult", -F.col("mult"))
        there = self.containment.join(moved.select(F.col("node").alias("child")), "child", "left_anti").select("child", "parent", "epoch")
        rows = there.union(moved.where("node <> piece").select("node", "piece", F.lit(self.epoch).cast("long")))
        delta = cut(before)
        self.containment = cut(rows.coalesce(_tasks(self.containment)))
        after = condense.build(at, cut(self.lookup(ends_of(at))))
        self._add(delta.union(after).groupBy("s", "t").agg(F.sum("mult").alias("mult")))
        sizes = moved.groupBy("comp", F.col("piece")).agg(F.count("*").alias("size"), F.max("height").alias("height"))
        parted = cut(sizes.groupBy("comp").agg(F.sum("size").alias("gone")))
        rest = self.components.join(parted, "comp").select("comp", (F.col("size") - F.col("gone")).alias("size"), "status")
        new = sizes.select(F.col("piece").alias("comp"), "size", F.lit("current").alias("status"))
        self.components = cut(self.components.join(parted.select("comp"), "comp", "left_anti").unionByName(rest).unionByName(new))
        names = cut(sizes.select(F.col("comp").alias("of"), F.col("piece").alias("comp"), "height").union(parted.select(F.col("comp").alias("of"), "comp", F.lit(middle))))
        if not self.k:
            self.labels = cut(self.labels.unionByName(L.none(new.select("comp"))))
            return
        old = self.labels.join(parted.select("comp"), "comp", "left_semi").select(F.col("comp").alias("of"), "iv")
        drawn = cut(splits.labels(names, old, self.components, self.dag, self.labels, self.k, self.seed + self.epoch, conf))
        self._relabel(names.select("comp"), drawn)
        self.labels = L.propagate_up(self.labels, self.dag, names.select("comp"), conf)[0]

    def drop_nodes(self, gone: DataFrame) -> None:
        """Nodes that have lost their edges leave every table."""
        comps = gone.withColumnRenamed("node", "comp")
        self.labels = cut(self.labels.join(comps, "comp", "left_anti"))
        self.components = cut(self.components.join(comps, "comp", "left_anti"))
        self.containment = cut(self.containment.join(gone.withColumnRenamed("node", "child"), "child", "left_anti").select("child", "parent", "epoch"))


def ops_frame(like: DataFrame, kind: str, **columns) -> DataFrame:
    """ops rows of one kind from a frame; op_id numbers are the same, as one kind needs no order."""
    names = [f.split(" ")[0] for f in OPS.split(", ")]
    kinds = dict(f.split(" ") for f in OPS.split(", "))
    given = {"op_id": F.lit(0), "kind": F.lit(kind)} | columns
    return like.select(*[given.get(n, F.lit(None)).cast(kinds[n]).alias(n) for n in names])
