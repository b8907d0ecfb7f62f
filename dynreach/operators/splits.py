"""Components that fall apart, by sets: what leaves, found without reading what stays, and labels of the pieces.

A component keeps the piece of the node that it is named by. Nodes leave in two ways: they no longer reach that node, or
it no longer reaches them. If a deleted edge's tail still reaches it, so does all that came through that edge. So only
tails, and heads the other way round, are searched from, each until the name is met; a search that ends without meeting it
has found leavers, and what lies before leavers is searched next. The piece that stays is read only where these searches run.

Before that, what can lie on no cycle is peeled off, all ends of a round at once: members with no edge left to, or from, a member that is
still there. Each is a piece of its own, so a component that falls apart into single nodes is neither searched nor decomposed again, and
the round it went in tells how far above the old end its label has to end.
"""

from __future__ import annotations

import random

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dynreach.conf import DEFAULT, EngineConf
from dynreach.functions.intervals import label_hull
from dynreach.operators import labels as L
from dynreach.operators.kernel import walk
from dynreach.operators.scc import turned
from dynreach.plans.loops import cut, empty, fits


def incident(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """Edges with an end among nodes(node)."""
    at = nodes.select("node").distinct()
    out = edges.join(at.withColumnRenamed("node", "src"), "src", "left_semi").select("src", "dst")
    return out.union(edges.join(at.withColumnRenamed("node", "dst"), "dst", "left_semi").select("src", "dst")).distinct()


def inner(edges: DataFrame, members: DataFrame) -> DataFrame:
    """Edges between members(node, comp) of one component."""
    a, b = members.select(F.col("node").alias("src"), F.col("comp").alias("a")), members.select(F.col("node").alias("dst"), F.col("comp").alias("b"))
    return edges.join(a, "src").join(b, "dst").where("a = b").select("src", "dst")


def leavers(edges: DataFrame, members: DataFrame, lost: DataFrame, conf: EngineConf = DEFAULT) -> tuple[DataFrame, int, int]:
    """(node, height) that leave the piece of the component's name, how many rows the searches met, and the height of what was
    not peeled off. height is null for what was found by a search; an edge between nodes with heights always leads down."""
    gone, rounds, n = peeled(edges, members, lost, conf)
    bad = gone.select("node")
    found = []
    for e, end in ((edges, "src"), (turned(edges), "dst")):
        before = e.join(bad.withColumnRenamed("node", "dst"), "dst", "left_semi").select(F.col("src").alias("node")).join(members, "node").select("node", "comp")
        starts = lost.select(F.col(end).alias("node"), "comp").union(before).distinct().join(bad, "node", "left_anti").select("node", "comp")
        part, m = _cut_off(e, members, starts, conf, bad)
        found.append(part)
        n += m
    height = F.when(F.col("up"), 2 * rounds - F.col("round")).otherwise(F.col("round"))
    return cut(found[0].union(found[1]).distinct().join(gone.select("node", height.alias("height")), "node", "left")), n, rounds


def peeled(edges: DataFrame, members: DataFrame, lost: DataFrame, conf: EngineConf = DEFAULT) -> tuple[DataFrame, int, int]:
    """(node, up, round) of the members on no cycle that follow from the lost edges, without the nodes that name components; the rounds; the rows met.

    A round takes members without an edge to a member still there, or, with up, without one from such a member; then only
    their neighbours can follow. So what is below a node taken without up went in an earlier round, as did what is above one taken with up.
    """
    a, b = members.select(F.col("node").alias("src"), "comp"), members.select(F.col("node").alias("dst"), F.col("comp").alias("of"))
    inside = edges.where("src <> dst").join(a, "src").join(b, "dst").where("comp = of")
    side = lambda up, x, y: inside.select(F.lit(up).alias("up"), F.col(x).alias("node"), F.col(y).alias("next"), "comp")
    steps = cut(side(False, "src", "dst").union(side(True, "dst", "src")))
    todo = lost.select(F.lit(False).alias("up"), F.col("src").alias("node"), "comp").union(lost.select(F.lit(True), "dst", "comp"))
    gone, met = lost.select(F.col("src").alias("node"), F.lit(False).alias("up"), F.lit(0).alias("round")).limit(0), 0
    for r in range(conf.max_rounds):
        todo = todo.where("node <> comp").select("up", "node").distinct().join(gone.select("node"), "node", "left_anti")
        left = steps.join(todo, ["up", "node"], "left_semi").join(gone.select(F.col("node").alias("next")), "next", "left_anti").select("up", "node").distinct().withColumn("holds", F.lit(True))
        tried = cut(todo.join(left, ["up", "node"], "left").groupBy("node").agg(F.count("*").alias("n"), F.min(F.when(F.col("holds").isNull(), F.col("up"))).alias("up")))
        n, taken = tried.agg(F.sum("n"), F.count("up")).first()
        met += n or 0
        if not taken:
            return cut(gone), r, met
        now = tried.where("up is not null").select("node", "up", F.lit(r).alias("round"))
        todo = steps.join(now.select(F.col("node").alias("next")), "next", "left_semi").select("up", "node", "comp")
        gone = gone.union(now)
        if r % conf.checkpoint_every == conf.checkpoint_every - 1:
            gone = cut(gone)
    raise RuntimeError("peeling did not settle")


def _cut_off(edges: DataFrame, members: DataFrame, starts: DataFrame, conf: EngineConf, bad: DataFrame) -> tuple[DataFrame, int]:
    """Members with no path along edges to their component's name, those in bad included, which leave in any case, given that
    all others reach one of the starts or it."""
    own = members.select(F.col("node").alias("dst"), F.col("comp").alias("of"))
    good, touched = starts.limit(0).select("node"), 0
    starts = cut(starts)
    for _ in range(conf.max_rounds):
        if empty(starts):
            return bad, touched
        seen = frontier = cut(starts.select(F.col("node").alias("root"), "node", "comp"))
        hit = cut(frontier.where("node = comp").select("root").distinct())
        frontier = frontier.join(hit, "root", "left_anti")
        for r in range(conf.max_rounds):
            step = frontier.join(edges, F.col("node") == F.col("src")).join(own, "dst").where("of = comp").select("root", F.col("dst").alias("node"), "comp").distinct()
            step = cut(step.join(bad, "node", "left_anti").join(seen, ["root", "node"], "left_anti").select("root", "node", "comp"))
            if empty(step):
                break
            met = step.where("node = comp").select("root").union(step.join(good, "node", "left_semi").select("root")).distinct()
            hit = cut(hit.union(met).distinct())
            seen = seen.union(step)
            if r % conf.checkpoint_every == conf.checkpoint_every - 1:
                seen = cut(seen)
            frontier = cut(step.join(hit, "root", "left_anti").select("root", "node", "comp"))
            if empty(frontier):
                break
        touched += seen.count()
        good = cut(good.union(hit.select(F.col("root").alias("node"))).distinct())
        gone = cut(seen.join(hit, "root", "left_anti").select("node").distinct())
        bad = cut(bad.union(gone).distinct())
        before = edges.join(gone.withColumnRenamed("node", "dst"), "dst", "left_semi").select(F.col("src").alias("node")).distinct()
        starts = cut(before.join(members, "node").join(bad, "node", "left_anti").join(good, "node", "left_anti").select("node", "comp"))
    raise RuntimeError("extraction did not settle")


def labels(names: DataFrame, old: DataFrame, components: DataFrame, dag: DataFrame, drawn: DataFrame, k: int, seed: int, conf: EngineConf = DEFAULT) -> DataFrame:
    """Labels of the pieces, names(of, comp, height): a walk over each component's pieces from its old begin, the counter
    moving on by their sizes, ends above all children's. Pieces that no task holds take the old interval, its end moved up by their height."""
    pieces = cut(names.join(components.select("comp", "size"), "comp"))
    if not fits(conf, pieces):
        return names.join(old, "of").select("comp", F.transform("iv", lambda x: F.struct(x["b"].alias("b"), (x["e"] + F.col("height")).alias("e"))).alias("iv"))
    a, b = names.select(F.col("comp").alias("s"), "of"), names.select(F.col("comp").alias("t"), F.col("of").alias("same"))
    out = cut(dag.join(a, "s").join(b, "t", "left").select("of", "s", "t", F.coalesce(F.col("of") == F.col("same"), F.lit(False)).alias("inside")))
    flat = lambda c: F.flatten(F.transform(c, lambda x: F.array(x["b"], x["e"])))
    none = F.array().cast("array<long>")
    outside = out.where("not inside").join(drawn.withColumnRenamed("comp", "t"), "t").groupBy("of", "s").agg(label_hull(F.col("iv"), k).alias("iv"))
    rows = (
        pieces.select("of", F.lit(0).alias("tag"), F.col("comp").alias("s"), F.col("size").alias("t"), none.alias("iv"))
        .union(out.where("inside").select("of", F.lit(1), "s", "t", none))
        .union(outside.select("of", F.lit(2), "s", F.lit(-1).cast("long"), flat("iv")))
        .union(old.select("of", F.lit(3), "of", F.lit(-1).cast("long"), flat("iv")))
    )

    def run(group: pd.DataFrame) -> pd.DataFrame:
        tag, s, t = (group[c].to_numpy() for c in ("tag", "s", "t"))
        size = dict(zip(s[tag == 0].tolist(), t[tag == 0].tolist()))
        kids: dict[int, list[int]] = {c: [] for c in size}
        for x, y in zip(s[tag == 1].tolist(), t[tag == 1].tolist()):
            kids[x].append(y)
        hulls = {c: iv.tolist() for c, iv in zip(s[tag == 2].tolist(), group["iv"][tag == 2])}
        start = group["iv"][tag == 3].iloc[0].tolist()
        below = {y for ys in kids.values() for y in ys}
        rng = random.Random(seed)
        arranged = lambda xs: rng.sample(sorted(xs), len(xs))
        found: dict[int, list[int]] = {c: [] for c in size}
        for d in range(k):
            # what lies outside stands as one child below each piece, numbered below all ids
            known = lambda c, d=d: tuple(hulls[-c - 2][2 * d : 2 * d + 2]) if c < 0 else None
            step = lambda c: arranged(kids[c]) + ([-c - 2] if c in hulls else [])
            for c, (b, e) in walk(arranged([c for c in size if c not in below]), step, size.__getitem__, start[2 * d], known).items():
                found[c] += [b, e]
        return pd.DataFrame({"comp": list(found), "iv": list(found.values())}).astype({"comp": "int64"})

    made = rows.groupBy("of").applyInPandas(run, "comp long, iv array<long>")
    return made.select("comp", L.paired(F.col("iv"), k).alias("iv"))
