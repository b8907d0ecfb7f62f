"""Graphs beyond what one task takes: weakly connected parts, each in its own task."""

import random

import pytest
from pyspark.sql import functions as F

from dynreach.conf import EngineConf
from dynreach.operators import baselines as B
from dynreach.operators import index as I
from dynreach.operators import labels as L
from dynreach.operators import parts, query as Q, scc

# a graph of eight parts does not fit a task, a part does; and a graph of which one part does not
CONFS = {"each part fits": (EngineConf(local_rows=120, driver_rows=0), 2), "one part is too large": (EngineConf(local_rows=70, driver_rows=0), 0)}


def linked(seed):
    rng, out = random.Random(seed), set()
    for p in range(8):
        n = 40 if p == 3 else 20
        out |= {(1000 * p + rng.randrange(n), 1000 * p + rng.randrange(n)) for _ in range(60 if p == 3 else 24)}
    return sorted(out | {(9000, 9000)})


def below(edges, u):
    seen, stack = {u}, [u]
    while stack:
        x = stack.pop()
        for a, b in edges:
            if a == x and b not in seen:
                seen.add(b)
                stack.append(b)
    return seen


@pytest.mark.parametrize("conf, k", CONFS.values(), ids=CONFS)
def test_parts_answer_as_one_task_does(spark, conf, k):
    edges = linked(5)
    e = spark.createDataFrame(edges, "src long, dst long")
    nodes = sorted({x for edge in edges for x in edge})
    reach = {u: below(edges, u) for u in nodes}
    ix = I.build(e, k=k, conf=conf)
    assert {r.node: r.comp for r in ix.membership.collect()} == {u: min(v for v in reach[u] if u in reach[v]) for u in nodes}
    assert L.violations(ix.labels, ix.dag_edges).count() == 0 and ix.labels.count() == ix.components.count()
    rng = random.Random(7)
    asked = [(i, *((rng.choice(nodes), rng.choice(nodes)) if i % 2 else rng.choice([(u, v) for u in rng.sample(nodes, 5) for v in reach[u]]))) for i in range(150)] + [(150, 1, 77_777), (151, 9000, 9000)]
    pairs = spark.createDataFrame(asked, "qid long, u long, v long")
    want = {q: u in reach and v in reach[u] for q, u, v in asked}
    for prune in (True, False) if k else (True,):
        assert {r.qid: r.reachable for r in Q.reach_batch(ix, pairs, prune=prune, conf=conf).collect()} == want
    assert {r.qid: r.reachable for r in B.search(e, pairs, conf=conf).collect()} == want


def test_weak_parts_by_contraction(spark):
    chain = [(i, i + 1) for i in range(200)] + [(1000 + 7 * i % 50, 1000) for i in range(50)] + [(5, 5), (4000, 4000)]
    found = parts.weak(spark.createDataFrame(chain, "src long, dst long"), EngineConf(local_rows=1)).collect()
    groups = {}
    for r in found:
        groups.setdefault(r.part, set()).add(r.node)
    assert sorted(map(sorted, groups.values())) == [list(range(201)), list(range(1000, 1050)), [4000]]
    assert len(found) == 252


def test_tree_cover_of_parts(spark):
    edges = [(100 * p + i, 100 * p + j) for p in range(5) for i in range(8) for j in range(i + 1, 8) if (i * j + p) % 3 == 0]
    e = spark.createDataFrame(edges, "src long, dst long")
    ix = I.build(e)
    pairs = spark.createDataFrame([(i, 100 * (i % 5) + i % 8, 100 * (i % 4) + i % 7) for i in range(120)], "qid long, u long, v long").join(ix.nodes.withColumnRenamed("node", "u"), "u").join(ix.nodes.withColumnRenamed("node", "v"), "v").select("qid", "u", "v")
    cover = B.tree_cover(ix.dag_edges, ix.components, EngineConf(local_rows=40))
    want = {r.qid: r.v in below(edges, r.u) for r in pairs.collect()}
    assert {r.qid: r.reachable for r in B.tree_cover_reach(cover, pairs).collect()} == want
    assert cover.select(F.count_distinct("rank") == F.count("*")).first()[0]
