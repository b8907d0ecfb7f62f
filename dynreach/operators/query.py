"""Reachability for batches of pairs.

Ends map to components; equal ones and pairs whose labels are not nested are decided without a
search. The rest share one search: the state is a set of (question, component) rows, a round joins
it with the condensation, drops rows whose label does not contain the goal's, rows seen before and
rows of questions that are decided. Small condensations (rows counted first) are searched in
the tasks that hold the questions, as they are or, where the driver should not gather them, sent there by a shuffle; of larger
ones a task takes whole weakly connected parts with their questions.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dynreach.conf import DEFAULT, EngineConf
from dynreach.functions.intervals import label_covers
from dynreach.model import ANSWERS, Index
from dynreach.operators.arrays import numbered, starts
from dynreach.operators.scc import turned
from dynreach.plans.loops import cut, empty, hinted

STRATEGIES = ("auto", "local", "parts", "forward", "bidirectional")


def resolve(index: Index, pairs: DataFrame) -> DataFrame:
    """(qid, u, v, s, t, ls, lt): components and labels of both ends, null for unknown nodes."""
    rows = pairs.select("qid", "u", "v")
    asked = rows.select(F.col("u").alias("node")).union(rows.select("v")).distinct()
    if "named" in index.kept:  # one pass over the nodes, and nothing of them is shuffled for a few questions
        ends = cut(index.kept["named"].join(hinted(cut(asked)), "node"))
    else:
        ends = cut(index.lookup(asked.join(index.nodes, "node", "left_semi")).join(index.labels, "comp").select("node", "comp", "iv"))  # of the nodes asked for only
    a = ends.select(F.col("node").alias("u"), F.col("comp").alias("s"), F.col("iv").alias("ls"))
    b = ends.select(F.col("node").alias("v"), F.col("comp").alias("t"), F.col("iv").alias("lt"))
    return rows.join(a, "u", "left").join(b, "v", "left").select("qid", "u", "v", "s", "t", "ls", "lt")


def label_reject(index: Index, pairs: DataFrame) -> DataFrame:
    """pairs with `rejected`: different components whose labels are not nested, so no path can be."""
    known = resolve(index, pairs).where("s is not null and t is not null")
    return known.select("qid", "u", "v", ((F.col("s") != F.col("t")) & ~label_covers(F.col("ls"), F.col("lt"))).alias("rejected"))


def decided(rows: DataFrame, prune: bool = True) -> DataFrame:
    """resolve()'s rows with decided_by; null where a search must decide."""
    rejected = ~label_covers(F.col("ls"), F.col("lt")) if prune else F.lit(False)
    how = F.when(F.col("s").isNull() | F.col("t").isNull(), "unknown_node").when(F.col("s") == F.col("t"), "same_comp").when(rejected, "labels")
    return rows.withColumn("decided_by", how)


def reach_batch(index: Index, pairs: DataFrame, prune: bool = True, strategy: str = "auto", conf: EngineConf = DEFAULT) -> DataFrame:
    """answers(qid, u, v, reachable, decided_by, expanded)."""
    if strategy not in STRATEGIES:
        raise ValueError(f"strategy is one of {STRATEGIES}")
    if strategy == "auto":
        few = min(conf.driver_rows, conf.local_rows)
        strategy = "local" if index.dag_edges.limit(few + 1).count() <= few else "parts" if conf.local_rows else "forward"
    rows = cut(decided(resolve(index, pairs), prune))
    done = rows.where("decided_by is not null").select("qid", "u", "v", (F.col("decided_by") == "same_comp").alias("reachable"), "decided_by", F.lit(0).cast("long").alias("expanded"))
    open_ = rows.where("decided_by is null")
    if strategy == "local":
        return done.union(_local(index, open_, prune))
    if strategy == "parts":
        dag = index.dag_edges.select(F.col("s").alias("src"), F.col("t").alias("dst"))
        found, open_ = in_parts(dag, open_.select("qid", F.col("s").alias("a"), F.col("t").alias("b"), "ls", "lt", "u", "v", "s", "t"), conf, index.labels if prune else None, index.k, **index.kept.get("linked", {}))
        done = done.union(found)
        if empty(open_):
            return done
    found = (_forward if strategy in ("parts", "forward") else _bidirectional)(index, open_, prune, conf)
    searched = open_.join(found, "qid", "left").select("qid", "u", "v", F.coalesce("reachable", F.lit(False)).alias("reachable"), F.lit("search").alias("decided_by"), F.coalesce("expanded", F.lit(0)).cast("long").alias("expanded"))
    return done.union(searched)


def _local(index: Index, open_: DataFrame, prune: bool) -> DataFrame:
    """The condensation and the labels of components with edges go to every task; its rows were counted before, and
    there are two such components an edge at most."""
    linked = index.dag_edges.select(F.col("s").alias("comp")).union(index.dag_edges.select("t")).distinct()
    dag, labels = index.dag_edges.select("s", "t").toPandas(), index.labels.join(linked, "comp", "left_semi").toPandas()
    out: dict[int, list[int]] = {}
    for s, t in zip(dag["s"].tolist(), dag["t"].tolist()):
        out.setdefault(s, []).append(t)
    iv = {c: tuple((x["b"], x["e"]) for x in xs) for c, xs in zip(labels["comp"].tolist(), labels["iv"])}
    shared = index.spark.sparkContext.broadcast((out, iv))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        out, iv = shared.value
        for frame in frames:
            rows = [_search(out, iv, s, t, prune) for s, t in zip(frame["s"].tolist(), frame["t"].tolist())]
            yield pd.DataFrame({"qid": frame["qid"], "u": frame["u"], "v": frame["v"], "reachable": [r for r, _ in rows], "decided_by": "search", "expanded": [n for _, n in rows]})

    tasks = max(1, min(open_.count() // 64, 8 * index.spark.sparkContext.defaultParallelism))
    return open_.select("qid", "u", "v", "s", "t").repartition(tasks).mapInPandas(run, ANSWERS)


def placed(edges: DataFrame, conf: EngineConf) -> tuple[DataFrame, DataFrame]:
    """(src, dst, bin) of edges and (node, part, bin) of their ends, for in_parts(); here a part is all of its bin."""
    from dynreach.operators import parts

    at = cut(parts.dealt_edges(edges, conf).withColumnRenamed("first", "bin"))
    ends = at.select(F.col("src").alias("node"), "bin").union(at.select("dst", "bin"))
    return at, ends.select("node", F.coalesce("bin", F.lit(-1).cast("long")).alias("part"), "bin").distinct()


def in_parts(edges: DataFrame, asked: DataFrame, conf: EngineConf, labels: DataFrame | None = None, k: int = 0, at: DataFrame | None = None, ends: DataFrame | None = None, labelled: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(answers, rows left) of asked(qid, a, b, u, v, ...), a and b being nodes of edges(src, dst) or nodes without any edge.

    The edges of a bin of weakly connected parts, the labels(comp, iv) at
    their ends and the questions about them meet in one task; many questions are dealt over several tasks with a copy of
    the bin each. Ends in different parts are not connected. Rows left lie in parts that no task takes.
    at, ends, labelled: edges(src, dst, bin), (node, part, bin) of the nodes asked for at least and (comp, bin, iv), if known.
    """
    asked = cut(asked)
    if at is None:
        at, ends = placed(edges, conf)
    if labels is not None and labelled is None:
        labelled = ends.select(F.col("node").alias("comp"), "bin").join(labels, "comp")
    known = cut(ends.join(hinted(cut(asked.select(F.col("a").alias("node")).union(asked.select("b")).distinct()), conf), "node", "left_semi"))  # two rows a question
    placed_ = asked.join(known.select(F.col("node").alias("a"), F.col("part").alias("pa"), "bin"), "a", "left").join(known.select(F.col("node").alias("b"), F.col("part").alias("pb")), "b", "left")
    placed_ = cut(placed_.withColumn("apart", (F.col("a") != F.col("b")) & ~F.coalesce(F.col("pa") == F.col("pb"), F.lit(False))))
    left = placed_.where("not apart and a <> b and bin is null").select(*asked.columns)
    placed_ = placed_.withColumn("apart", F.col("apart") | (F.col("a") == F.col("b"))).where("apart or bin is not null")
    at = at.where("bin is not null").select("src", "dst", "bin")
    open_ = cut(placed_.where("not apart").select("qid", "a", "b", "u", "v", "bin"))
    done = placed_.where("apart").select("qid", "u", "v", (F.col("a") == F.col("b")).alias("reachable"), F.lit("search").alias("decided_by"), F.lit(0).cast("long").alias("expanded"))
    bins = cut(open_.groupBy("bin").agg(F.count("*").alias("n")))
    most = edges.sparkSession.sparkContext.defaultParallelism
    copies = bins.select("bin", F.explode(F.sequence(F.lit(0), F.least(F.lit(most), F.ceil(F.col("n") / 64)).cast("int") - 1)).alias("copy"))
    copies = copies.join(bins.select("bin", F.least(F.lit(most), F.ceil(F.col("n") / 64)).cast("int").alias("of")), "bin")
    none = [F.lit(0).cast("long")] * (2 * k)
    rows = at.select("bin", F.lit(0).alias("tag"), F.lit(0).cast("long").alias("qid"), F.col("src").alias("x"), F.col("dst").alias("y"), *none)
    if labels is not None and k:
        rows = rows.union(labelled.where("bin is not null").select("bin", F.lit(1), F.lit(0), "comp", F.lit(-1), *[F.col("iv")[d][end] for d in range(k) for end in ("b", "e")]))
    rows = rows.join(F.broadcast(copies), "bin").drop("of")  # as few rows as there are questions
    names = ["bin", "tag", "qid", "x", "y", *[f"l{i}" for i in range(2 * k)], "copy"]
    with_ends = open_.join(F.broadcast(bins.select("bin", F.least(F.lit(most), F.ceil(F.col("n") / 64)).cast("int").alias("of"))), "bin")
    asks = with_ends.select("bin", F.lit(2), "qid", "a", "b", *none, F.pmod("qid", "of").cast("int"))
    pruned = labels is not None and k > 0

    def run(group: pd.DataFrame) -> pd.DataFrame:
        tag, x, y = (group[c].to_numpy() for c in ("tag", "x", "y"))
        ids, src, heads = numbered(x[tag == 0], y[tag == 0])
        heads, first = heads[np.argsort(src, kind="stable")].tolist(), starts(len(ids), src).tolist()
        spans = []
        if pruned:
            named = np.flatnonzero(tag == 1)
            place = np.searchsorted(ids, x[named])
            there = place < len(ids)
            there[there] = ids[place[there]] == x[named[there]]  # components that no edge links are not searched
            for i in range(2 * k):
                column = np.zeros(len(ids), dtype="int64")
                column[place[there]] = group[f"l{i}"].to_numpy()[named[there]]
                spans.append(column.tolist())
        dims = [(spans[2 * d], spans[2 * d + 1]) for d in range(len(spans) // 2)]
        wanted = tag == 2
        out = []
        for qid, a, b in zip(group["qid"].to_numpy()[wanted].tolist(), x[wanted].tolist(), y[wanted].tolist()):
            s, t = np.searchsorted(ids, (a, b)).tolist()
            if a == b or s == len(ids) or t == len(ids) or ids[s] != a or ids[t] != b:
                out.append((qid, a == b, 0))  # no edge leads from it, or to it
                continue
            seen, stack, n = bytearray(len(ids)), [s], 0
            seen[s] = 1
            goal = [(bs, es, bs[t], es[t]) for bs, es in dims]
            while stack and not seen[t]:
                n += 1
                z = stack.pop()
                for c in heads[first[z] : first[z + 1]]:
                    if not seen[c]:
                        seen[c] = 1
                        for bs, es, low, high in goal:
                            if bs[c] > low or es[c] <= high:
                                break
                        else:
                            stack.append(c)
            out.append((qid, bool(seen[t]), n))
        return pd.DataFrame(out, columns=["qid", "reachable", "expanded"])

    found = rows.toDF(*names).union(asks).groupBy("bin", "copy").applyInPandas(run, "qid long, reachable boolean, expanded long")
    answers = open_.join(found, "qid").select("qid", "u", "v", "reachable", F.lit("search").alias("decided_by"), "expanded")
    return done.union(answers), left


def _search(out: dict, iv: dict, s: int, t: int, prune: bool) -> tuple[bool, int]:
    if t not in iv:  # no edge leads to it
        return False, 0
    goal, seen, stack, expanded = iv[t], {s}, [s], 0
    while stack:
        expanded += 1
        for y in out.get(stack.pop(), ()):
            if y == t:
                return True, expanded
            if y not in seen and (not prune or all(a[0] <= b[0] and b[1] < a[1] for a, b in zip(iv[y], goal))):
                seen.add(y)
                stack.append(y)
    return False, expanded


def _labelled(index: Index, forward: bool = True) -> DataFrame:
    """Condensation edges (at, next, iv of next), in either direction."""
    lab = index.labels.select(F.col("comp").alias("next"), "iv")
    e = index.dag_edges.select(F.col("s" if forward else "t").alias("at"), F.col("t" if forward else "s").alias("next"))
    return cut(e.join(lab, "next"))


def _step(frontier: DataFrame, edges: DataFrame, seen: DataFrame, keep) -> DataFrame:
    step = frontier.join(edges, "at").where(keep).select("qid", F.col("next").alias("at"), "s", "t", "ls", "lt").dropDuplicates(["qid", "at"])
    return cut(step.join(seen, ["qid", "at"], "left_anti"))


def _forward(index: Index, open_: DataFrame, prune: bool, conf: EngineConf) -> DataFrame:
    """(qid, reachable, expanded)."""
    edges = _labelled(index)
    frontier = cut(open_.select("qid", F.col("s").alias("at"), "s", "t", "ls", "lt"))
    seen = frontier.select("qid", "at")
    hits = None
    keep = (label_covers(F.col("iv"), F.col("lt")) if prune else F.lit(True)) | (F.col("next") == F.col("t"))
    for r in range(conf.max_rounds):
        if empty(frontier):
            break
        frontier = _step(frontier, edges, seen, keep)
        hit = cut(frontier.where("at = t").select("qid"))
        hits = hit if hits is None else hits.union(hit)
        frontier = frontier.join(hit, "qid", "left_anti")
        seen = seen.union(frontier.select("qid", "at"))
        if r % conf.checkpoint_every == conf.checkpoint_every - 1:
            seen = cut(seen)
    else:
        raise RuntimeError("search did not settle")
    expanded = seen.groupBy("qid").agg(F.count("*").alias("expanded"))
    if hits is None:
        return expanded.withColumn("reachable", F.lit(False))
    return expanded.join(hits.withColumn("reachable", F.lit(True)), "qid", "left").select("qid", F.coalesce("reachable", F.lit(False)).alias("reachable"), "expanded")


def _bidirectional(index: Index, open_: DataFrame, prune: bool, conf: EngineConf) -> DataFrame:
    """Grows the smaller of two frontiers, from the sources down or from the goals up, until they meet."""
    sides = {}
    for forward in (True, False):
        start = cut(open_.select("qid", F.col("s" if forward else "t").alias("at"), "s", "t", "ls", "lt"))
        bound = label_covers(F.col("iv"), F.col("lt")) if forward else label_covers(F.col("ls"), F.col("iv"))
        keep = bound | (F.col("next") == F.col("t" if forward else "s")) if prune else F.lit(True)
        sides[forward] = {"frontier": start, "seen": start.select("qid", "at"), "edges": _labelled(index, forward), "keep": keep, "n": 0}
    hits, undecided = None, open_.count()
    for _ in range(conf.max_rounds):
        counts = {f: x["frontier"].count() for f, x in sides.items()}
        if not undecided or not min(counts.values()):
            break
        f = min(counts, key=counts.get)
        side, other = sides[f], sides[not f]
        side["frontier"] = _step(side["frontier"], side["edges"], side["seen"], side["keep"])
        side["seen"] = cut(side["seen"].union(side["frontier"].select("qid", "at")))
        hit = cut(side["frontier"].join(other["seen"], ["qid", "at"]).select("qid").distinct())
        hits = hit if hits is None else cut(hits.union(hit))
        for x in sides.values():
            x["frontier"] = cut(x["frontier"].join(hit, "qid", "left_anti"))
    else:
        raise RuntimeError("search did not settle")
    # a question of which one frontier has run dry without a meeting is answered: no path
    expanded = sides[True]["seen"].union(sides[False]["seen"]).groupBy("qid").agg(F.count("*").alias("expanded"))
    if hits is None:
        return expanded.withColumn("reachable", F.lit(False))
    # where frontiers ran dry on one side for all questions, those undecided on the other are negative as well
    return expanded.join(hits.distinct().withColumn("reachable", F.lit(True)), "qid", "left").select("qid", F.coalesce("reachable", F.lit(False)).alias("reachable"), "expanded")


def reaches(index: Index, u: int, v: int, conf: EngineConf = DEFAULT) -> bool:
    """One question, by frontier joins: no table is gathered, and labels cut the search short."""
    pair = index.spark.createDataFrame([(0, u, v)], "qid long, u long, v long")
    return reach_batch(index, pair, strategy="forward", conf=conf).first().reachable


def grow(start: DataFrame, edges: DataFrame, conf: EngineConf = DEFAULT) -> DataFrame:
    """(root, comp): everything reachable from each root over edges (src, dst), the root itself included."""
    seen = frontier = cut(start.select(F.col("comp").alias("root"), "comp").distinct())
    for r in range(conf.max_rounds):
        step = frontier.join(edges, F.col("comp") == F.col("src")).select("root", F.col("dst").alias("comp")).distinct()
        frontier = cut(step.join(seen, ["root", "comp"], "left_anti"))
        if empty(frontier):
            return seen
        seen = seen.union(frontier)
        if r % conf.checkpoint_every == conf.checkpoint_every - 1:
            seen = cut(seen)
    raise RuntimeError("search did not settle")


def _plain(index: Index) -> DataFrame:
    return cut(index.dag_edges.select(F.col("s").alias("src"), F.col("t").alias("dst")))


def descendants(index: Index, comps: DataFrame, conf: EngineConf = DEFAULT) -> DataFrame:
    return grow(comps, _plain(index), conf)


def ancestors(index: Index, comps: DataFrame, conf: EngineConf = DEFAULT) -> DataFrame:
    return grow(comps, turned(_plain(index)), conf)


def between(index: Index, t: int, s: int, conf: EngineConf = DEFAULT) -> DataFrame:
    """(comp): components on paths from t to s. Both sweeps keep to labels that contain s, or lie in t."""
    spark = index.spark
    goal = index.labels.where(F.col("comp") == s).select(F.col("iv").alias("goal"))
    around = index.labels.join(F.broadcast(goal)).where(label_covers(F.col("iv"), F.col("goal")) | (F.col("comp") == s)).select("comp")  # one row
    e = _plain(index).join(around.select(F.col("comp").alias("src")), "src", "left_semi").join(around.select(F.col("comp").alias("dst")), "dst", "left_semi")
    e = cut(e.select("src", "dst"))
    one = lambda c: spark.createDataFrame([(c,)], "comp long")
    down, up = grow(one(t), e, conf), grow(one(s), turned(e), conf)
    return down.join(up.select("comp"), "comp", "left_semi").select("comp")


def reach_as_of(versions: dict[int, Index], pairs: DataFrame, conf: EngineConf = DEFAULT) -> DataFrame:
    """answers of pairs (qid, op_id, u, v), each by the newest version whose operation is not after the pair's."""
    marks = sorted(versions)
    out = None
    for i, mark in enumerate(marks):
        upto = F.col("op_id") < marks[i + 1] if i + 1 < len(marks) else F.lit(True)
        part = reach_batch(versions[mark], pairs.where((F.col("op_id") >= mark) & upto), conf=conf)
        out = part if out is None else out.union(part)
    return out
