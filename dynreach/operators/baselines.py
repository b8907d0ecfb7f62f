"""What the index is compared with: search on the live graph, closure, rebuilds, and static indexes."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from dynreach.conf import DEFAULT, EngineConf
from dynreach.model import ANSWERS, Index
from dynreach.operators import index as I
from dynreach.operators.kernel import index_of, strongly_connected
from dynreach.operators.query import grow, in_parts, placed
from dynreach.plans.loops import cut, empty, fits, hinted
from dynreach.sources.graphs import nodes_of


def search(edges: DataFrame, pairs: DataFrame, kernel: str = "auto", conf: EngineConf = DEFAULT) -> DataFrame:
    """answers by plain search on the input graph: no components, no labels, nothing to keep current."""
    if kernel == "auto":
        few = min(conf.driver_rows, conf.local_rows)
        kernel = "local" if edges.limit(few + 1).count() <= few else "parts" if conf.local_rows else "frontier"
    if kernel == "local":
        return _local_search(edges, pairs)
    if kernel == "parts":
        at, ends = placed(edges.select("src", "dst"), conf)
        wanted = cut(pairs.select(F.col("u").alias("node")).union(pairs.select("v")).distinct())
        known = cut(ends.join(hinted(wanted, conf), "node", "left_semi"))
        asked = cut(pairs.select("qid", "u", "v").join(known.select(F.col("node").alias("u")), "u", "left_semi").join(known.select(F.col("node").alias("v")), "v", "left_semi").select("qid", "u", "v"))
        answers, left = in_parts(edges.select("src", "dst"), asked.select("qid", F.col("u").alias("a"), F.col("v").alias("b"), "u", "v"), conf, at=at, ends=known)
        unknown = pairs.join(asked, "qid", "left_anti").select("qid", "u", "v", F.lit(False), F.lit("unknown_node"), F.lit(0).cast("long"))
        answers = answers.union(unknown)
        return answers if empty(left) else answers.union(search(edges, left.select("qid", "u", "v"), "frontier", conf))
    known = nodes_of(edges)
    rows = pairs.join(known.withColumnRenamed("node", "u"), "u", "left_semi").join(known.withColumnRenamed("node", "v"), "v", "left_semi")
    frontier = cut(rows.select("qid", F.col("u").alias("at"), "v"))
    seen, hits = frontier.select("qid", "at"), frontier.where("at = v").select("qid")
    edges = cut(edges)
    for r in range(conf.max_rounds):
        frontier = frontier.join(hits, "qid", "left_anti")
        step = frontier.join(edges, F.col("at") == F.col("src")).select("qid", F.col("dst").alias("at"), "v").distinct()
        frontier = cut(step.join(seen, ["qid", "at"], "left_anti"))
        if empty(frontier):
            break
        seen, hits = seen.union(frontier.select("qid", "at")), cut(hits.union(frontier.where("at = v").select("qid")))
        if r % conf.checkpoint_every == conf.checkpoint_every - 1:
            seen = cut(seen)
    counted = seen.groupBy("qid").agg(F.count("*").alias("expanded"))
    out = pairs.select("qid", "u", "v").join(counted, "qid", "left").join(hits.distinct().withColumn("reachable", F.lit(True)), "qid", "left")
    how = F.when(F.col("expanded").isNull(), "unknown_node").otherwise("search")
    return out.select("qid", "u", "v", F.coalesce("reachable", F.lit(False)).alias("reachable"), how.alias("decided_by"), F.coalesce("expanded", F.lit(0)).cast("long").alias("expanded"))


def _local_search(edges: DataFrame, pairs: DataFrame) -> DataFrame:
    table = edges.toPandas()  # its rows were counted before
    shared = edges.sparkSession.sparkContext.broadcast((dict(index_of(zip(table["src"].tolist(), table["dst"].tolist()))), set(table["src"]) | set(table["dst"])))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        out, nodes = shared.value
        for frame in frames:
            rows = []
            for u, v in zip(frame["u"].tolist(), frame["v"].tolist()):
                if u not in nodes or v not in nodes:
                    rows.append((False, "unknown_node", 0))
                    continue
                seen, stack, n, hit = {u}, [u], 0, False
                while stack and not hit:
                    x = stack.pop()
                    n += 1
                    hit = x == v
                    for y in out.get(x, ()):
                        if y not in seen:
                            seen.add(y)
                            stack.append(y)
                rows.append((hit, "search", n))
            yield pd.DataFrame({"qid": frame["qid"], "u": frame["u"], "v": frame["v"], "reachable": [r[0] for r in rows], "decided_by": [r[1] for r in rows], "expanded": [r[2] for r in rows]})

    tasks = max(1, min(pairs.count() // 64, 8 * edges.sparkSession.sparkContext.defaultParallelism))
    return pairs.select("qid", "u", "v").repartition(tasks).mapInPandas(run, ANSWERS)


def closure(edges: DataFrame, conf: EngineConf = DEFAULT) -> DataFrame:
    """(src, dst) of all pairs with a path of length one or more: quadratic, for small graphs.

    Up to conf.driver_rows edges, tasks search the condensation from a component each and write its pairs as they go, so nothing
    of the closure is kept, shuffled or checkpointed; beyond, it grows by joins.
    """
    seen = frontier = cut(edges.select("src", "dst").distinct())
    few = min(conf.driver_rows, conf.local_rows)
    if seen.limit(few + 1).count() <= few:
        return _closure_in_tasks(seen)
    step = edges.select(F.col("src").alias("mid"), F.col("dst").alias("to"))
    for _ in range(conf.max_rounds):
        frontier = cut(frontier.join(step, F.col("dst") == F.col("mid")).select("src", F.col("to").alias("dst")).distinct().join(seen, ["src", "dst"], "left_anti"))
        if empty(frontier):
            return seen
        seen = cut(seen.union(frontier))
    raise RuntimeError("closure did not settle")


#: Nodes of a component that one row of a task's output stands for.
SOURCES = 64


def _closure_in_tasks(edges: DataFrame) -> DataFrame:
    table = edges.toPandas()  # its rows were counted before
    links = list(zip(table["src"].tolist(), table["dst"].tolist()))
    out = index_of(links)
    members = [np.array(sorted(part), dtype="int64") for part in strongly_connected(sorted(out), lambda x: out.get(x, ()))]
    of = {n: c for c, part in enumerate(members) for n in part.tolist()}
    below: list[set[int]] = [set() for _ in members]
    for a, b in links:
        below[of[a]].add(of[b])  # itself, if a path leads back
    chunks = [(c, first) for c, part in enumerate(members) if below[c] for first in range(0, len(part), SOURCES)]
    spark = edges.sparkSession
    tasks = max(1, min(len(chunks), 8 * spark.sparkContext.defaultParallelism))
    dealt = [chunk for task in range(tasks) for chunk in chunks[task::tasks]]  # a large component goes to all tasks
    shared = spark.sparkContext.broadcast((members, below, dealt))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        members, below, dealt = shared.value
        known, reached = -1, None
        for frame in frames:
            for i in frame["id"].tolist():
                c, first = dealt[i]
                if c != known:
                    seen, stack = set(below[c]), list(below[c])
                    while stack:
                        new = below[stack.pop()] - seen
                        seen |= new
                        stack += new
                    known, reached = c, np.concatenate([members[x] for x in seen])
                yield pd.DataFrame({"srcs": [members[c][first : first + SOURCES]], "dsts": [reached]})

    pairs = spark.range(0, len(dealt), 1, tasks).mapInPandas(run, "srcs array<long>, dsts array<long>")
    return pairs.select(F.explode("srcs").alias("src"), "dsts").select("src", F.explode("dsts").alias("dst"))


def rebuild_each(index: Index, states: list[DataFrame], conf: EngineConf = DEFAULT) -> list[Index]:
    """A fresh index for every state of the edges."""
    return [I.build(edges, k=index.k, conf=conf) for edges in states]


def tree_cover(dag_edges: DataFrame, components: DataFrame, conf: EngineConf = DEFAULT, of: DataFrame | None = None) -> DataFrame:
    """(comp, rank, ivs): static sets of intervals over ranks of a spanning forest, exact on acyclic graphs.

    One task walks the condensation, or each of its weakly connected parts if no task takes it, with ranks above those of
    the parts before; a node's intervals are its tree interval and those it inherits, joined where they touch. All rows of
    the cover grow with the square of the nodes; with of(comp), ivs are kept of these components only, and null elsewhere.
    """
    zero = F.lit(0).cast("long").alias("start")
    if fits(conf, dag_edges, components):
        rows = components.select(zero, F.col("comp").alias("s"), F.lit(-1).cast("long").alias("t")).union(dag_edges.select(zero, "s", "t"))
    else:
        rows = _placed(dag_edges, components, conf)
    if of is None:
        rows = rows.withColumn("asked", F.col("t") < 0)
    else:
        asked = of.select(F.col("comp").alias("s")).distinct().withColumn("mark", F.lit(True))
        rows = rows.join(asked, "s", "left").select("start", "s", "t", (F.col("mark").isNotNull() & (F.col("t") < 0)).alias("asked"))

    def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        start, s, t = int(key[0]), group["s"].to_numpy(), group["t"].to_numpy()
        ids = np.unique(s)
        src, dst = np.searchsorted(ids, s[t >= 0]), np.searchsorted(ids, t[t >= 0])
        rank, level = _postorder(len(ids), src, dst)
        wanted = np.searchsorted(ids, s[group["asked"].to_numpy()])
        at, b, e = _covers(rank, level, src, dst, wanted)
        first = np.searchsorted(at, np.arange(len(wanted) + 1))
        ivs: list = [None] * len(ids)
        for i, w in enumerate(wanted.tolist()):
            here = slice(first[i], first[i + 1])
            ivs[w] = [{"b": start + x, "e": start + y} for x, y in zip(b[here].tolist(), e[here].tolist())]
        return pd.DataFrame({"comp": ids, "rank": start + rank, "ivs": ivs})

    return rows.groupBy("start").applyInPandas(run, "comp long, rank long, ivs array<struct<b:long,e:long>>")


def _postorder(n: int, src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Ranks in which the nodes 0..n-1 are left by a walk from the roots, and longest paths to a leaf."""
    order = np.lexsort((dst, src))
    heads, first = dst[order].tolist(), np.searchsorted(src[order], np.arange(n + 1)).tolist()
    rank, level, count, place = [-1] * n, [0] * n, 0, first[:n]
    inner = np.zeros(n, bool)
    inner[dst] = True
    for root in np.flatnonzero(~inner).tolist():
        path = [root]
        while path:
            x = path[-1]
            while place[x] < first[x + 1] and rank[heads[place[x]]] >= 0:
                place[x] += 1
            if place[x] < first[x + 1]:
                path.append(heads[place[x]])
                continue
            path.pop()
            rank[x], count = count, count + 1
            level[x] = 1 + max((level[y] for y in heads[first[x] : first[x + 1]]), default=-1)
    return np.array(rank, dtype=np.int64), np.array(level, dtype=np.int64)


def _covers(rank: np.ndarray, level: np.ndarray, src: np.ndarray, dst: np.ndarray, wanted: np.ndarray, block_bytes: int = 48 << 20) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(place in wanted, begin, end) of the intervals that cover what each wanted node reaches, in order.

    Ranks are taken in blocks, so that the bits of all nodes for a block's ranks stay within block_bytes; sets are passed up
    from the leaves, a level at once.
    """
    n = len(rank)
    words = max(1, min(64, block_bytes // (8 * max(1, n))))
    order = np.lexsort((src, level[src]))
    src, dst = src[order], dst[order]
    by_rank = np.argsort(rank)
    found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    for low in range(0, n, 64 * words):
        here = by_rank[low : low + 64 * words]
        place = np.arange(len(here))
        bits = np.zeros((n, words), np.uint64)
        bits[here, place // 64] = np.uint64(1) << (place % 64).astype(np.uint64)
        use = rank[dst] >= low  # what lies lower reaches nothing here
        a, b = src[use], dst[use]
        starts = np.flatnonzero(np.r_[True, a[1:] != a[:-1]]) if len(a) else np.zeros(0, np.int64)
        tails = a[starts]
        steps = np.flatnonzero(np.r_[True, np.diff(level[tails]) != 0]).tolist() + [len(tails)] if len(tails) else []
        ends = np.r_[starts, len(a)]
        for i, j in zip(steps, steps[1:]):
            x, y = ends[i], ends[j]
            bits[tails[i:j]] |= np.bitwise_or.reduceat(bits[b[x:y]], starts[i:j] - x, axis=0)
        most = max(1, (32 << 20) // (64 * words))
        for i in range(0, len(wanted), most):
            rows = bits[wanted[i : i + most]]
            flat = np.zeros((len(rows), 64 * words + 2), np.int8)
            flat[:, 1:-1] = np.unpackbits(rows.astype("<u8").view(np.uint8), axis=1, bitorder="little")
            turns = np.diff(flat, axis=1)
            at, begin = np.nonzero(turns == 1)
            found.append((at + i, begin + low, np.nonzero(turns == -1)[1] + low - 1))
    if not found:
        return (np.zeros(0, np.int64),) * 3
    at, begin, end = (np.concatenate(x) for x in zip(*found))
    order = np.lexsort((begin, at))
    at, begin, end = at[order], begin[order], end[order]
    joins = (at[1:] == at[:-1]) & (begin[1:] == end[:-1] + 1)  # an interval that goes over the border of blocks
    first, last = np.r_[True, ~joins], np.r_[~joins, True]
    return at[first], begin[first], end[last]


def _placed(dag_edges: DataFrame, components: DataFrame, conf: EngineConf) -> DataFrame:
    """(start, s, t) of components (t = -1) and edges: start is the number of components in the bins of parts before."""
    from dynreach.operators import parts

    bins = parts.dealt(dag_edges.select(F.col("s").alias("src"), F.col("t").alias("dst")), conf).select(F.col("node").alias("comp"), "part", "bin")
    alone = F.pmod(F.xxhash64("comp"), F.lit(64)) - 2**41  # below all bins
    at = cut(components.join(bins, "comp", "left").select("comp", F.when(F.col("part").isNull(), alone).otherwise(F.col("bin")).alias("bin")))
    if not empty(at.where("bin is null")):
        raise ValueError("tree cover is built in one task for each weakly connected part, and one part is too large")
    before = F.coalesce(F.sum("n").over(Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).cast("long")
    starts = at.groupBy("bin").agg(F.count("*").alias("n")).select("bin", before.alias("start"))  # a row a bin
    here = cut(at.join(F.broadcast(starts), "bin").select("start", "comp"))
    inner = dag_edges.join(here.withColumnRenamed("comp", "s"), "s").select("start", "s", "t")
    return here.select("start", F.col("comp").alias("s"), F.lit(-1).cast("long").alias("t")).union(inner)


def tree_cover_reach(cover: DataFrame, pairs: DataFrame) -> DataFrame:
    """(qid, u, v, reachable) over components."""
    a, b = cover.select(F.col("comp").alias("u"), "ivs"), cover.select(F.col("comp").alias("v"), "rank")
    inside = F.exists("ivs", lambda iv: (iv["b"] <= F.col("rank")) & (F.col("rank") <= iv["e"]))
    return pairs.join(a, "u").join(b, "v").select("qid", "u", "v", inside.alias("reachable"))


def two_hop(dag_edges: DataFrame, components: DataFrame, conf: EngineConf = DEFAULT) -> DataFrame:
    """(comp, hubs_out, hubs_in): static two-hop labels by pruned sweeps from hubs in order of degree; one task."""
    if not fits(conf, dag_edges, components):
        raise ValueError("two-hop labels are built in one task")
    rows = components.select(F.col("comp").alias("s"), F.lit(-1).cast("long").alias("t")).union(dag_edges.select("s", "t"))

    def run(group: pd.DataFrame) -> pd.DataFrame:
        links = group[group["t"] >= 0]
        edges = list(zip(links["s"].tolist(), links["t"].tolist()))
        out, inn = index_of(edges), index_of((t, s) for s, t in edges)
        comps = sorted(set(group["s"].tolist()))
        hubs_out, hubs_in = {c: {c} for c in comps}, {c: {c} for c in comps}
        for hub in sorted(comps, key=lambda c: (-(len(out.get(c, ())) + 1) * (len(inn.get(c, ())) + 1), c)):
            for follow, mine, theirs in ((out, hubs_out, hubs_in), (inn, hubs_in, hubs_out)):
                stack, seen = list(follow.get(hub, ())), set()
                while stack:
                    x = stack.pop()
                    if x in seen or mine[hub] & theirs[x]:
                        continue
                    seen.add(x)
                    stack.extend(follow.get(x, ()))
                for x in seen:
                    theirs[x].add(hub)
        return pd.DataFrame({"comp": comps, "hubs_out": [sorted(hubs_out[c]) for c in comps], "hubs_in": [sorted(hubs_in[c]) for c in comps]})

    return rows.groupBy(F.lit("all")).applyInPandas(run, "comp long, hubs_out array<long>, hubs_in array<long>")


def two_hop_reach(hubs: DataFrame, pairs: DataFrame) -> DataFrame:
    a, b = hubs.select(F.col("comp").alias("u"), "hubs_out"), hubs.select(F.col("comp").alias("v"), "hubs_in")
    return pairs.join(a, "u").join(b, "v").select("qid", "u", "v", F.arrays_overlap("hubs_out", "hubs_in").alias("reachable"))


def everything_below(edges: DataFrame, starts: DataFrame, conf: EngineConf = DEFAULT) -> DataFrame:
    """(root, node) over the live graph."""
    return grow(starts.select(F.col("node").alias("comp")), edges, conf).select("root", F.col("comp").alias("node"))
