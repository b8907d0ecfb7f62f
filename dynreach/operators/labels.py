"""Interval labels: k per component, such that reaching implies containment, strictly at the end.

`postorder` draws them by walks, one task per dimension, for condensations that fit a task; `by_parts` does so for
each weakly connected part of a larger one, the parts side by side.
`bulk` draws them by sets: a random spanning forest, subtree widths from the leaves up,
offsets from the roots down, then the upward fixpoint. `propagate_up` is that fixpoint: begins
take the least begin below, ends pass the greatest end below, in semi-naive rounds.
"""

from __future__ import annotations

import random

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from dynreach.conf import DEFAULT, EngineConf
from dynreach.functions.intervals import IV, label_covers
from dynreach.operators.kernel import walk
from dynreach.plans.loops import cut, empty, fits

LONG = "comp long, dim int, b long, e long"


def width(size, slack: int = 1):
    """A label is as wide as its component's nodes times the slack, so the pieces of a split fit in it."""
    return size * slack


def pack(long_form: DataFrame) -> DataFrame:
    """labels(comp, iv) from (comp, dim, b, e)."""
    rows = long_form.groupBy("comp").agg(F.array_sort(F.collect_list(F.struct("dim", F.struct("b", "e").alias("x")))).alias("rows"))
    return rows.select("comp", F.transform("rows", lambda r: r["x"]).alias("iv"))


def unpack(labels: DataFrame) -> DataFrame:
    return labels.select("comp", F.posexplode("iv").alias("dim", "x")).select("comp", "dim", F.col("x.b").alias("b"), F.col("x.e").alias("e"))


def paired(flat, k: int):
    """Intervals from an array of b and e in turn."""
    if not k:
        return F.array().cast(IV)
    return F.array(*[F.struct(F.element_at(flat, 2 * d + 1).alias("b"), F.element_at(flat, 2 * d + 2).alias("e")) for d in range(k)])


def none(components: DataFrame) -> DataFrame:
    """k = 0: empty labels, which cover everything."""
    return components.select("comp", F.array().cast("array<struct<b:long,e:long>>").alias("iv"))


def postorder(dag_edges: DataFrame, components: DataFrame, k: int = 1, seed: int = 42, order: str = "random", slack: int = 1, conf: EngineConf = DEFAULT) -> DataFrame:
    """labels by k walks; children and roots are visited in random order, or by id up (asc) or down (desc)."""
    if not k:
        return none(components)
    if not fits(conf, dag_edges, components):
        raise ValueError("the condensation is too large for one task; use bulk")
    # -1 stands for no edge: a null would make pandas turn the ids into floats, which can't hold large ones
    rows = components.select(F.lit(0).cast("long").alias("first"), F.col("comp").alias("s"), F.lit(-1).cast("long").alias("t"), "size").union(dag_edges.select(F.lit(0).cast("long"), "s", "t", F.lit(0).cast("long")))
    return _walked(rows, k, seed, order, slack)


def _walked(rows: DataFrame, k: int, seed: int, order: str, slack: int) -> DataFrame:
    """rows(first, s, t, size) of components (t = -1) and edges; those with one value of `first` are walked from there."""
    dims = rows.sparkSession.range(k).select(F.col("id").cast("int").alias("dim"))

    def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        first, dim = int(key[0]), int(key[1])
        of_node = group["t"] < 0
        sizes = dict(zip(group["s"][of_node].tolist(), group["size"][of_node].tolist()))
        out: dict[int, list[int]] = {}
        links = group[~of_node]
        for s, t in zip(links["s"].tolist(), links["t"].tolist()):
            out.setdefault(s, []).append(t)
        below = {t for ts in out.values() for t in ts}
        rng = random.Random(seed * 1009 + dim)
        arranged = (lambda xs: rng.sample(sorted(xs), len(xs))) if order == "random" else (lambda xs: sorted(xs, reverse=order == "desc"))
        found = walk(arranged([c for c in sizes if c not in below]), lambda c: arranged(out.get(c, [])), lambda c: width(sizes[c], slack), first)
        return pd.DataFrame([(c, dim, b, e) for c, (b, e) in found.items()], columns=["comp", "dim", "b", "e"])

    return pack(rows.crossJoin(F.broadcast(dims)).groupBy("first", "dim").applyInPandas(run, LONG))  # k rows


def by_parts(dag_edges: DataFrame, components: DataFrame, k: int = 1, seed: int = 42, order: str = "random", slack: int = 1, conf: EngineConf = DEFAULT, bins: DataFrame | None = None) -> DataFrame:
    """labels of a condensation that no task takes, by walks over its weakly connected parts; a component without edges
    is a part of its own. If one part alone is too large, all are labelled in bulk."""
    from dynreach.operators import parts

    if not k:
        return none(components)
    bins = parts.dealt(dag_edges.select(F.col("s").alias("src"), F.col("t").alias("dst")), conf) if bins is None else bins
    bins = bins.select(F.col("node").alias("comp"), "part", "bin")
    alone = F.pmod(F.xxhash64("comp"), F.lit(64)) - 2**41  # below all bins
    at = cut(components.join(bins, "comp", "left").select("comp", "size", F.when(F.col("part").isNull(), alone).otherwise(F.col("bin")).alias("bin")))
    if not empty(at.where("bin is null")):
        return bulk(dag_edges, components, k, seed, slack, conf)
    # each bin begins where the widths of those before it end
    wide = at.groupBy("bin").agg(F.sum(F.col("size") * slack).alias("n"))
    before = F.coalesce(F.sum("n").over(Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).cast("long")
    firsts = cut(wide.select("bin", before.alias("first")))  # a row a bin
    here = cut(at.join(F.broadcast(firsts), "bin"))
    inner = dag_edges.join(here.select(F.col("comp").alias("s"), "first"), "s").select("first", "s", "t", F.lit(0).cast("long"))
    return _walked(here.select("first", F.col("comp").alias("s"), F.lit(-1).cast("long").alias("t"), "size").union(inner), k, seed, order, slack)



def layers(dag_edges: DataFrame, components: DataFrame, conf: EngineConf = DEFAULT) -> DataFrame:
    """(comp, layer): longest path from a root, by peeling roots."""
    left, e = cut(components.select("comp")), cut(dag_edges.select("s", "t"))
    out = None
    for layer in range(conf.max_rounds):
        if empty(left):
            return out if out is not None else left.withColumn("layer", F.lit(0))
        roots = cut(left.join(e.select(F.col("t").alias("comp")).distinct(), "comp", "left_anti"))
        part = roots.withColumn("layer", F.lit(layer))
        out = part if out is None else out.union(part)
        if layer % conf.checkpoint_every == conf.checkpoint_every - 1:
            out = cut(out)
        left, e = cut(left.join(roots, "comp", "left_anti")), cut(e.join(roots.withColumnRenamed("comp", "s"), "s", "left_anti"))
    raise RuntimeError("the condensation has a cycle")


def bulk(dag_edges: DataFrame, components: DataFrame, k: int = 1, seed: int = 42, slack: int = 1, conf: EngineConf = DEFAULT) -> DataFrame:
    """labels by sets; as many rounds as the condensation is deep."""
    if not k:
        return none(components)
    layered = cut(layers(dag_edges, components, conf))
    deepest = layered.agg(F.max("layer")).first()[0] or 0
    at = layered.select(F.col("comp").alias("s"), F.col("layer").alias("ls"))
    parts = None
    for dim in range(k):
        salt = F.lit(seed * 1009 + dim)
        # the parent in the forest is a random one among those a layer above, so layers are forest depths
        below = layered.select(F.col("comp").alias("t"), F.col("layer").alias("lt"))
        offers = dag_edges.join(at, "s").join(below, "t").where("ls = lt - 1")
        tree = cut(offers.groupBy("t").agg(F.min_by("s", F.xxhash64(salt, "s", "t")).alias("parent")))
        widths = cut(layered.join(components.select("comp", (F.col("size") * slack).alias("own")), "comp").withColumn("all", F.col("own")))
        for layer in range(deepest, 0, -1):
            sums = widths.where(F.col("layer") == layer).join(tree, F.col("comp") == F.col("t")).groupBy("parent").agg(F.sum("all").alias("more"))
            widths = widths.join(sums, F.col("comp") == F.col("parent"), "left").select("comp", "layer", "own", (F.col("all") + F.coalesce("more", F.lit(0))).alias("all"))
            if layer % conf.checkpoint_every == 0:
                widths = cut(widths)
        widths = cut(widths)
        placed = widths.where("layer = 0")
        first = _starts(placed.withColumn("group", F.pmod(F.xxhash64(salt, "comp"), F.lit(1024))))
        done = starts = cut(first)
        for layer in range(1, deepest + 1):
            kids = widths.where(F.col("layer") == layer).join(tree, F.col("comp") == F.col("t")).join(starts.select(F.col("comp").alias("parent"), "b"), "parent")
            run = F.coalesce(F.sum("all").over(Window.partitionBy("parent").orderBy(F.xxhash64(salt, "comp"), "comp").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
            starts = cut(kids.select("comp", (F.col("b") + run).alias("b")))
            done = done.union(starts)
        labelled = done.join(widths, "comp").select("comp", F.lit(dim).alias("dim"), "b", (F.col("b") + F.col("all")).alias("e"))
        parts = labelled if parts is None else parts.union(labelled)
    labels = cut(pack(parts))
    return propagate_up(labels, dag_edges, None, conf)[0]


def _starts(roots: DataFrame) -> DataFrame:
    """Begins of the roots: running widths in two levels, so that no window holds them all."""
    sums = roots.groupBy("group").agg(F.sum("all").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.orderBy("group").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ahead = F.broadcast(sums.select("group", before.alias("before")))  # 1024 rows at most
    inside = F.coalesce(F.sum("all").over(Window.partitionBy("group").orderBy("comp").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return roots.withColumn("inside", inside).join(ahead, "group").select("comp", (F.col("before") + F.col("inside")).alias("b"))


def propagate_up(labels: DataFrame, dag_edges: DataFrame, seeds: DataFrame | None = None, conf: EngineConf = DEFAULT) -> tuple[DataFrame, DataFrame]:
    """(labels, raised(comp, times)): the least labels above the given ones that satisfy the rule.

    seeds(comp): components whose labels are new; without seeds every edge is looked at once.
    """
    state = labels
    edges = cut(dag_edges.select("s", "t"))
    changed = state if seeds is None else cut(state.join(seeds.select("comp").distinct(), "comp", "left_semi"))
    raised, new = None, state.limit(0)  # new: labels that differ from the state; nothing else is written in a round
    for _ in range(conf.max_rounds):
        offers = edges.join(changed.select(F.col("comp").alias("t"), F.col("iv").alias("low")), "t")
        offers = offers.select("s", F.posexplode("low").alias("dim", "x")).groupBy("s", "dim").agg(F.min("x.b").alias("b"), (F.max("x.e") + 1).alias("e"))
        asked = pack(offers.withColumnRenamed("s", "comp")).withColumnRenamed("iv", "asked")
        now = asked.join(state, "comp").join(new.select("comp", F.col("iv").alias("newer")), "comp", "left").withColumn("old", F.coalesce("newer", "iv"))
        wider = F.zip_with("old", "asked", lambda a, b: F.struct(F.least(a["b"], b["b"]).alias("b"), F.greatest(a["e"], b["e"]).alias("e")))
        changed = cut(now.select("comp", wider.alias("iv"), "old").where("iv <> old").select("comp", "iv"))
        if empty(changed):
            if raised is None:
                return state, state.select("comp", F.lit(0).cast("long").alias("times")).limit(0)
            return cut(state.join(new, "comp", "left_anti").unionByName(new)), raised.groupBy("comp").agg(F.count("*").alias("times"))
        new = cut(new.join(changed, "comp", "left_anti").unionByName(changed))
        raised = changed.select("comp") if raised is None else raised.union(changed.select("comp"))
    raise RuntimeError("labels did not settle")


def violations(labels: DataFrame, dag_edges: DataFrame) -> DataFrame:
    """Condensation edges (s, t) whose labels break the rule: none in a sound index."""
    a, b = labels.select(F.col("comp").alias("s"), F.col("iv").alias("outer")), labels.select(F.col("comp").alias("t"), F.col("iv").alias("inner"))
    return dag_edges.join(a, "s").join(b, "t").where(~label_covers(F.col("outer"), F.col("inner"))).select("s", "t")


def drift(labels: DataFrame, nodes: int) -> float:
    """Largest end over the number of nodes: how loose updates have made the labels; draw anew beyond conf.relabel_drift."""
    top = unpack(labels).agg(F.max("e")).first()[0]
    return (top or 0) / max(1, nodes)
