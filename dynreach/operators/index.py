"""Building and storing whole index versions."""

from __future__ import annotations

import uuid
from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dynreach import model
from dynreach.conf import DEFAULT, EngineConf
from dynreach.model import Index, check_ids
from dynreach.operators import arrays, condense, containment, labels as L, parts, scc
from dynreach.plans.loops import cut, empty, fits
from dynreach.sources.graphs import nodes_of

#: Declared, as an empty table leaves no file to read a schema from.
TABLES = {"nodes": model.NODES, "edges": model.EDGES, "components": model.COMPONENTS, "dag_edges": model.DAG_EDGES, "labels": model.LABELS, "containment": model.CONTAINMENT}

POINTERS = "version long, folder string, k int, depth int, batch_id long"


def build(edges: DataFrame, nodes: DataFrame | None = None, k: int = 1, seed: int = 42, labeling: str = "auto", method: str = "auto", order: str = "random", conf: EngineConf = DEFAULT, as_is: bool = False) -> Index:
    """All parts of the index from the live graph; k = 0 keeps the condensation only. as_is: edges are distinct and kept already."""
    edges = edges.select("src", "dst") if as_is else cut(edges.select("src", "dst").distinct())
    check_ids(edges)
    if (method, labeling, order) == ("auto", "auto", "random") and conf.local_rows and not fits(replace(conf, local_rows=min(conf.driver_rows, conf.local_rows)), edges):
        whole = in_bins(edges, nodes, k, seed, conf)
        if whole is not None:
            return whole
    nodes = cut(nodes_of(edges) if nodes is None else nodes.select("node").union(nodes_of(edges)).distinct())
    # a part of the graph is one of its condensation as well, so a graph that is dealt out is dealt out once
    bins = parts.dealt(edges, conf) if method == "auto" and conf.local_rows and not fits(conf, edges) else None
    membership = cut(scc.strongly_connected(nodes, edges, method, conf, bins))
    return assemble(nodes, edges, membership, k, seed, labeling, order, conf, bins=bins)


def in_bins(edges: DataFrame, nodes: DataFrame | None, k: int, seed: int, conf: EngineConf) -> Index | None:
    """The index of a graph whose weakly connected parts fit a task each: the task that has a bin of parts works out their
    components, condensation and labels at once. None if one part is too large."""
    linked = edges
    if nodes is not None:  # a node without edges is a part of its own
        alone = nodes.select("node").distinct().join(nodes_of(edges), "node", "left_anti")
        linked = cut(edges.union(alone.select("node", F.col("node").alias("dst"))))

    def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        columns = ["tag", "x", "y", "n", "part", "bin", *(f"l{i}" for i in range(2 * k))]
        if pd.isna(key[0]):
            return pd.DataFrame([[2] + [0] * (len(columns) - 1)], columns=columns)
        first = int(key[0])
        ids, a, b = arrays.numbered(group["src"].to_numpy(), group["dst"].to_numpy())
        part, comp = arrays.united(len(ids), a, b), arrays.components(len(ids), a, b)
        names, at, sizes = np.unique(comp, return_inverse=True, return_counts=True)
        s, t, times = arrays.condensed(len(names), at[a], at[b])
        of_node, of_edge = {"tag": 0, "x": ids, "y": ids[comp], "n": sizes[at], "part": ids[part], "bin": first}, {"tag": 1, "x": ids[names[s]], "y": ids[names[t]], "n": times, "part": 0, "bin": first}
        for dim in range(k):
            spans = arrays.walked(len(names), s, t, L.width(sizes, conf.slack), first, np.random.default_rng([seed, dim, first]))
            for i, ends in enumerate(spans):
                of_node[f"l{2 * dim + i}"], of_edge[f"l{2 * dim + i}"] = np.array(ends, dtype="int64")[at], 0
        return pd.concat([pd.DataFrame(of_node, columns=columns), pd.DataFrame(of_edge, columns=columns)])

    longs = "".join(f", l{i} long" for i in range(2 * k))
    found = cut(parts.dealt_edges(linked, conf).groupBy("first").applyInPandas(run, f"tag int, x long, y long, n long, part long, bin long{longs}"))
    if not empty(found.where("tag = 2")):
        return None
    of_node, of_comp, of_edge = found.where("tag = 0"), found.where("tag = 0 and x = y"), found.where("tag = 1")
    membership = of_node.select(F.col("x").alias("node"), F.col("y").alias("comp"))
    spans = F.array(*[F.struct(F.col(f"l{2 * d}").alias("b"), F.col(f"l{2 * d + 1}").alias("e")) for d in range(k)]) if k else F.array().cast("array<struct<b:long,e:long>>")
    labels, dag = of_comp.select(F.col("x").alias("comp"), spans.alias("iv")), of_edge.select(F.col("x").alias("s"), F.col("y").alias("t"), F.col("n").alias("mult"))
    # what questions read: nodes with component and label, and the condensation with its bins
    named = of_node.select(F.col("x").alias("node"), F.col("y").alias("comp"), spans.alias("iv"))
    linked = {"at": of_edge.select(F.col("x").alias("src"), F.col("y").alias("dst"), "bin"), "ends": of_comp.select(F.col("x").alias("node"), "part", "bin"), "labelled": of_comp.select(F.col("x").alias("comp"), "bin", spans.alias("iv"))}
    components = of_comp.select(F.col("x").alias("comp"), F.col("n").alias("size"), F.lit("current").alias("status"))
    return Index(membership.select("node"), edges, components, dag, labels, containment.build(membership), k, kept={"membership": membership, "named": named, "linked": linked})


def assemble(nodes: DataFrame, edges: DataFrame, membership: DataFrame, k: int, seed: int = 42, labeling: str = "auto", order: str = "random", conf: EngineConf = DEFAULT, version: int = 0, bins: DataFrame | None = None) -> Index:
    components = cut(scc.component_sizes(membership))
    dag = cut(condense.build(edges, membership))
    if labeling == "auto":
        labeling = "postorder" if fits(conf, dag, components) else "parts" if conf.local_rows else "bulk"
    if labeling == "bulk":
        drawn = L.bulk(dag, components, k, seed, conf.slack, conf)
    elif labeling == "parts":
        bins = parts.dealt(dag.select(F.col("s").alias("src"), F.col("t").alias("dst")), conf) if bins is None else bins
        drawn = L.by_parts(dag, components, k, seed, order, conf.slack, conf, bins)
    else:
        drawn = L.postorder(dag, components, k, seed, order, conf.slack, conf)
    return Index(nodes, edges, components, dag, cut(drawn), cut(containment.build(membership)), k, version, kept={"membership": membership} | ({} if bins is None else {"linked": placed(dag, bins)}))


def placed(dag: DataFrame, bins: DataFrame) -> dict[str, DataFrame]:
    """The condensation's edges with the bins that its graph was dealt to, and those bins, as query.in_parts reads them."""
    at = dag.select(F.col("s").alias("src"), F.col("t").alias("dst")).join(bins.select(F.col("node").alias("src"), "bin"), "src")
    return {"at": at.select("src", "dst", "bin"), "ends": bins}


def commit(index: Index, path: str, ledger_id: int | None = None, buckets: int = 16) -> str:
    """Writes a version below path and then a pointer row; readers follow the newest pointer. Returns the version's folder."""
    folder = f"{path}/v{index.version}-{uuid.uuid4().hex[:8]}"
    for name in TABLES:
        table: DataFrame = getattr(index, name)
        key = table.columns[0]
        table.withColumn("bucket", F.pmod(F.xxhash64(key), F.lit(buckets)).cast("int")).write.partitionBy("bucket").parquet(f"{folder}/{name}")
    pointer = index.spark.createDataFrame([(index.version, folder, index.k, index.depth, -1 if ledger_id is None else ledger_id)], POINTERS)
    pointer.coalesce(1).write.mode("append").parquet(f"{path}/pointers")
    return folder


def versions(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(POINTERS).parquet(f"{path}/pointers")


def load(spark: SparkSession, path: str, version: int | None = None) -> Index:
    """A committed version, the newest unless named."""
    rows = versions(spark, path)
    row = (rows if version is None else rows.where(F.col("version") == version)).orderBy(F.desc("version")).first()
    tables = {name: spark.read.schema(f"{columns}, bucket int").parquet(f"{row.folder}/{name}").drop("bucket") for name, columns in TABLES.items()}
    return Index(**tables, k=row.k, version=row.version, depth=row.depth)
