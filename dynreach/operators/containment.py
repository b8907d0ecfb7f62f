"""The containment forest: node -> component -> absorbing component, as rows that are only appended.

Looking up follows parents by pointer doubling, so that a forest of any depth takes a logarithm of rounds.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dynreach.conf import DEFAULT, EngineConf
from dynreach.plans.loops import cut, empty


def build(membership: DataFrame, epoch: int = 0) -> DataFrame:
    """containment(child, parent, epoch) of the nodes in components named by another id."""
    return membership.where("node <> comp").select(F.col("node").alias("child"), F.col("comp").alias("parent"), F.lit(epoch).cast("long").alias("epoch"))


def attach(containment: DataFrame, merged: DataFrame, rep: int, epoch: int) -> DataFrame:
    """One row for each absorbed component: a merge costs as many rows as it has components."""
    rows = merged.where(F.col("comp") != rep).select(F.col("comp").alias("child"), F.lit(rep).cast("long").alias("parent"), F.lit(epoch).cast("long").alias("epoch"))
    return containment.union(rows)


def detach(containment: DataFrame, leaving: DataFrame) -> DataFrame:
    """Links of departing nodes go; links among expired components may stay."""
    return containment.join(leaving.select(F.col("node").alias("child")), "child", "left_anti").select("child", "parent", "epoch")


def find(containment: DataFrame, nodes: DataFrame, depth: int | None = None, conf: EngineConf = DEFAULT) -> DataFrame:
    """(node, comp) of the nodes asked for: only their paths are followed, so many joins as the forest is deep.

    Without a known depth, parents are doubled until nothing moves.
    """
    if depth is not None:
        at, links = nodes.select("node", F.col("node").alias("comp")), containment.select(F.col("child").alias("comp"), "parent")
        for _ in range(depth):
            at = at.join(links, "comp", "left").select("node", F.coalesce("parent", "comp").alias("comp"))
        return at
    at = cut(nodes.select("node", F.col("node").alias("comp")))
    links = containment.select(F.col("child").alias("comp"), "parent")
    for _ in range(conf.max_rounds):
        step = cut(at.join(links, "comp", "left").select("node", F.coalesce("parent", "comp").alias("comp"), F.col("parent").isNotNull().alias("moved")))
        if empty(step.where("moved")):
            return step.select("node", "comp")
        at = step.select("node", "comp")
        links = cut(double(links))
    raise RuntimeError("containment has a cycle")


def double(links: DataFrame) -> DataFrame:
    """Every link skips one: parents become grandparents where there are any."""
    up = links.select(F.col("comp").alias("parent"), F.col("parent").alias("above"))
    return links.join(up, "parent", "left").select("comp", F.coalesce("above", "parent").alias("parent"))


def compress(containment: DataFrame, conf: EngineConf = DEFAULT) -> DataFrame:
    """The same forest with every child directly below its current component."""
    found = find(containment, containment.select(F.col("child").alias("node")).distinct(), conf=conf)
    epochs = containment.select("child", "epoch")
    return found.join(epochs, F.col("node") == F.col("child")).select("child", F.col("comp").alias("parent"), "epoch")


def members(containment: DataFrame, comps: DataFrame, depth: int) -> DataFrame:
    """(node, comp) of all nodes of the components asked for, down the forest; rows of other components are not followed."""
    at = comps.select(F.col("comp").alias("node"), "comp")
    found, links = at, containment.select("child", F.col("parent").alias("node"))
    for _ in range(depth):
        at = at.join(links, "node").select(F.col("child").alias("node"), "comp")
        found = found.union(at)
    return found


def depth(containment: DataFrame, conf: EngineConf = DEFAULT) -> int:
    """Longest path to a current component."""
    n, below = 0, containment.select("child", "parent")
    at = below
    while not empty(at):
        n += 1
        at = cut(at.join(below.select(F.col("child").alias("parent"), F.col("parent").alias("next")), "parent").select("child", F.col("next").alias("parent")))
        if n > conf.max_rounds:
            raise RuntimeError("containment has a cycle")
    return n


def pick_representative(merged: DataFrame) -> DataFrame:
    """(rep, size): the largest of the merge list (comp, size) absorbs; ties go to the smaller id."""
    return merged.agg(F.max_by("comp", F.struct("size", -F.col("comp"))).alias("rep"), F.sum("size").alias("size"))


def flat_membership(membership: DataFrame, merged: DataFrame, rep: int) -> DataFrame:
    """The lookup table in place of the forest: rewrites the row of every node of every merged component."""
    hit = merged.select("comp", F.lit(rep).cast("long").alias("rep"))
    return membership.join(hit, "comp", "left").select("node", F.coalesce("rep", "comp").alias("comp"))
