"""Queries that read given tables now, and limits that are no longer met."""

import random
import time

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as E
import tests.oracle as oracle
from dynreach.conf import EngineConf
from dynreach.model import OPS
from dynreach.operators import baselines as B, index as I, updates as U
from dynreach.plans import relational
from dynreach.sources import graphs as G
from dynreach.streaming import operations as S


@pytest.mark.parametrize("name", ["edges_example_graph", "condense_example_graph", "between_example"])
def test_moved_queries_match_sql_and_name_a_given_table(spark, sf_dir, name):
    sql = E.oracle_sql()[name]
    assert "events" in sql or "lineitem" in sql
    assert not oracle.compare(spark, name, E.queries()[name], sql, sf_dir, oracle.connect(sf_dir))


def test_gen_ba_grows_over_customers(spark, sf_dir):
    rows = E.queries()["gen_ba"](spark, sf_dir).collect()
    keys = {r[0] for r in duckdb.sql(f"select c_custkey from '{sf_dir}/customer.parquet'").fetchall()}
    assert {x for r in rows for x in r} <= keys and len({x for r in rows for x in r}) > 0.9 * len(keys)


def test_recursion_takes_more_rows_than_the_default_limit(spark, sf_dir):
    spark.conf.set("spark.sql.cteRecursionRowLimit", 10)
    try:
        got = {(r.root, r.n) for r in relational.cte_recursive_reach(spark, sf_dir).collect()}
        assert spark.conf.get("spark.sql.cteRecursionRowLimit") == "10"
    finally:
        spark.conf.unset("spark.sql.cteRecursionRowLimit")
    assert sum(n for _, n in got) == G.containment_tree(spark, sf_dir).count()


@pytest.mark.parametrize("mode", ["complete", "append"])
def test_stream_results_are_not_kept_by_the_driver(spark, tmp_path, mode):
    spark.createDataFrame([(i, i % 7) for i in range(50)], "id long, k long").repartition(3).write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema("id long, k long").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in")
    frame = stream.groupBy("k").count() if mode == "complete" else stream
    out = S.collected(frame, f"{tmp_path}/out", f"{tmp_path}/checkpoint", mode)
    files = out.inputFiles()
    assert files and all(f"{tmp_path}/out" in f for f in files)
    got = sorted(map(tuple, out.collect()))
    assert got == ([(k, len(range(k, 50, 7))) for k in range(7)] if mode == "complete" else [(i, i % 7) for i in range(50)])


@pytest.mark.parametrize("seed", [1, 2])
def test_cover_intervals_are_the_closure(seed):
    rng, n = random.Random(seed), 300
    edges = np.array(sorted({tuple(sorted(rng.sample(range(n), 2), reverse=True)) for _ in range(500)}))
    src, dst = edges[:, 0], edges[:, 1]
    rank, level = B._postorder(n, src, dst)
    assert sorted(rank.tolist()) == list(range(n)) and (rank[src] > rank[dst]).all() and (level[src] > level[dst]).all()
    below = {}
    for x in range(n):  # heads are smaller than tails
        below[x] = {x}.union(*(below[y] for y in dst[src == x].tolist()))
    wanted = np.array([5, 299, 150, 0, 298])
    for size in (1, 8 * n * 3, 48 << 20):  # blocks of 64 ranks, of 192, and one block
        at, b, e = B._covers(rank, level, src, dst, wanted, size)
        for i, x in enumerate(wanted.tolist()):
            spans = list(zip(b[at == i].tolist(), e[at == i].tolist()))
            assert {r for lo, hi in spans for r in range(lo, hi + 1)} == set(rank[list(below[x])].tolist())
            assert all(q[0] > p[1] + 1 for p, q in zip(spans, spans[1:]))


def test_cover_of_a_graph_with_many_inherited_intervals(spark):
    n = 20_000  # the sets of intervals of all nodes together would hold over 10^7
    rng = random.Random(3)
    edges = sorted({(x, rng.randrange(max(0, x - 3000), x)) for x in range(1, n) for _ in range(2)})
    e = spark.createDataFrame(pd.DataFrame(edges, columns=["s", "t"]))
    comps = spark.range(n).select(F.col("id").alias("comp"))
    pairs = spark.createDataFrame([(i, rng.randrange(n), rng.randrange(n)) for i in range(40)], "qid long, u long, v long")
    began = time.time()
    cover = B.tree_cover(e, comps, of=pairs.select(F.col("u").alias("comp")))
    got = {r.qid: r.reachable for r in B.tree_cover_reach(cover, pairs).collect()}
    assert time.time() - began < 20
    below, out = {}, {}
    for a, b in edges:
        out.setdefault(a, []).append(b)
    for r in pairs.collect():
        seen, stack = {r.u}, [r.u]
        while stack:
            for y in out.get(stack.pop(), ()):
                if y not in seen:
                    seen.add(y)
                    stack.append(y)
        below[r.qid] = r.v in seen
    assert got == below and len(set(got.values())) == 2


@pytest.mark.parametrize("seed", [3, 4])
def test_one_by_one_beyond_what_a_task_takes(spark, seed):
    rng = random.Random(seed)
    edges = {(100 * p + rng.randrange(12), 100 * p + rng.randrange(12)) for p in range(6) for _ in range(20)}
    ops, live = [], set(edges)
    nodes = lambda: sorted({x for e in edges for x in e})
    for i in range(30):
        kind = rng.choice(["insert_edge", "insert_edge", "delete_edge", "insert_node", "delete_node"])
        u, v, outs, ins = rng.choice(nodes()), None, None, None
        if kind == "insert_edge":
            v = rng.choice([x for x in nodes() if x // 100 == u // 100])
            live.add((u, v))
        elif kind == "delete_edge":
            u, v = rng.choice(sorted(live))
        elif kind == "insert_node":
            u, outs, ins = 7000 + i, [rng.choice(nodes())], [rng.choice(nodes())] if i % 2 else None
        ops.append((i, None, kind, u, v, outs, ins))
    frame = spark.createDataFrame(ops, OPS)
    ix = I.build(spark.createDataFrame(sorted(edges), "src long, dst long"))
    want = {r.node: r.comp for r in U.apply(ix, frame, "sequential").membership.collect()}
    got = U.apply(ix, frame, "sequential", EngineConf(local_rows=100, driver_rows=0)).membership.collect()
    assert {r.node: r.comp for r in got} == want and len(got) == len(want)
