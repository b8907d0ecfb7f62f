import datetime
import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

from dynreach.conf import EngineConf
from dynreach.model import OPS
from dynreach.operators import baselines, containment, generators, index as I, labels as L, query as Q, scc
from dynreach.operators.kernel import DynamicIndex
from dynreach.operators.plain import PlainGraph
from dynreach.plans import batch, workload
from dynreach.sources import graphs as G

BATCH = EngineConf(rebuild_ratio=1e9)
EXTRACT = EngineConf(rebuild_ratio=1e9, split="extract", forest_depth=2)
SETS = EngineConf(rebuild_ratio=1e9, local_rows=0)  # nothing fits a task
FAR = 2**62 + 1  # floats can't hold ids beside it


def frame(spark, edges):
    return spark.createDataFrame(sorted(edges), "src long, dst long")


def state(ix):
    return {r.node: r.comp for r in ix.membership.collect()}, {(r.s, r.t): r.mult for r in ix.dag_edges.collect()}


def holds(ix, kernel):
    members, dag = state(ix)
    assert members == kernel.membership() and dag == kernel.dag()
    assert L.violations(ix.labels, ix.dag_edges).count() == 0
    assert {r.comp for r in ix.labels.collect()} == set(members.values()) == {r.comp for r in ix.components.collect()}
    assert sum(r.size for r in ix.components.collect()) == len(members)


@pytest.mark.parametrize("seed, conf, far, n, steps", [(0, BATCH, 0, 16, 2), (1, EXTRACT, FAR, 16, 2), (2, SETS, FAR, 6, 1)])
def test_batches_match_the_kernel(spark, seed, conf, far, n, steps):
    rng = random.Random(seed)
    edges = {(far + rng.randrange(n), far + rng.randrange(n)) for _ in range(n * 3 // 2)}
    ix, kernel = I.build(frame(spark, edges), k=2), DynamicIndex((), edges, k=1)
    holds(ix, kernel)
    for step in range(steps):
        ops = []
        for i in range(n * 3 // 4):
            kind = rng.choices(("insert_edge", "delete_edge", "insert_node", "delete_node"), (5, 5, 2, 1))[0]
            u, v = far + rng.randrange(n + 4), far + rng.randrange(n + 4)
            lists = ([far + rng.randrange(n)], [far + rng.randrange(n)]) if kind == "insert_node" else (None, None)
            ops.append((i, None, kind, u, v if kind.endswith("edge") else None, *lists))
            kernel.apply(kind, u, v, lists[0] or (), lists[1] or ())
        ix = batch.apply(ix, spark.createDataFrame(ops, OPS), conf=conf)
        holds(ix, kernel)
        assert not ix.facts["rebuilt"] and containment.depth(ix.containment) <= ix.depth <= conf.forest_depth
    pairs = spark.createDataFrame([(i, far + rng.randrange(n + 6), far + rng.randrange(n + 6)) for i in range(40)], "qid long, u long, v long")
    want = {r.qid: kernel.query(r.u, r.v)[0] for r in pairs.collect()}
    for strategy in ("local", "forward", "bidirectional") if conf is BATCH else ("local",):
        assert {r.qid: r.reachable for r in Q.reach_batch(ix, pairs, strategy=strategy).collect()} == want
    assert {r.qid: r.reachable for r in baselines.search(ix.edges, pairs).collect()} == {q: a and q not in {r.qid for r in pairs.collect() if r.u == r.v and not ix.edges.where(f"src = {r.u} or dst = {r.u}").count()} for q, a in want.items()}


def test_sets_decompose_a_chain_a_cycle_and_nothing(spark):
    chain = frame(spark, [(i, i + 1) for i in range(12)])
    assert scc.strongly_connected(None, chain, "trim_color").where("node <> comp").count() == 0
    ring = frame(spark, [(i, (i + 1) % 7) for i in range(7)] + [(3, 3), (9, 0)])
    for method in ("trim_color", "fwbw", "local"):
        assert {(r.node, r.comp) for r in scc.strongly_connected(None, ring, method).collect()} == {(i, 0) for i in range(7)} | {(9, 9)}
    empty = I.build(frame(spark, [(0, 1)]).limit(0), k=1)
    assert Q.reach_batch(empty, spark.createDataFrame([(0, 1, 2)], "qid long, u long, v long")).first().decided_by == "unknown_node"
    with pytest.raises(ValueError):
        I.build(frame(spark, [(-1, 2)]))


def two_rings(far, n=40):
    """Two rings joined both ways; what hangs on the second leaves when the way back is cut."""
    first, second = [far + i for i in range(n)], [far + n + i for i in range(n)]
    ring = lambda xs: set(zip(xs, xs[1:] + xs[:1]))
    return ring(first) | ring(second) | {(first[0], second[0]), (second[1], first[1])}, (second[1], first[1])


def test_extraction_reads_what_leaves(spark):
    edges, back = two_rings(0)
    extra = {(200 + i, 200 + i + 1) for i in range(5)} | {(205, 1), (1, 200)}  # a loop through the first ring
    ix = I.build(frame(spark, edges | extra), k=2)
    kernel = DynamicIndex((), edges | extra, k=2)
    one = lambda u, v: spark.createDataFrame([(0, None, "delete_edge", u, v, None, None)], OPS)
    ix = batch.apply(ix, one(*back), conf=EXTRACT)
    kernel.delete_edge(*back)
    holds(ix, kernel)
    assert ix.facts["split"] == "extract" and ix.facts["left"] == 40
    ix2 = batch.apply(ix, one(201, 202), conf=EXTRACT)  # the loop opens: six nodes leave, the ring stays
    kernel.delete_edge(201, 202)
    holds(ix2, kernel)
    assert ix2.facts["left"] == 6
    naive = batch.apply(ix, one(201, 202), conf=EngineConf(rebuild_ratio=1e9, split="naive"))
    assert state(naive) == state(ix2) and ix2.facts["touched"] < naive.facts["touched"] + 46


def test_pieces_are_labelled_apart(spark):
    """After a split the labels prune as those of the kernel do: pieces don't all keep the old interval."""
    rng = random.Random(9)
    ring = {(i, (i + 1) % 60) for i in range(60)} | {(i, (i * 7) % 60) for i in range(0, 60, 9)}
    gone = [(i, (i + 1) % 60) for i in range(0, 60, 6)]
    ops = spark.createDataFrame([(i, None, "delete_edge", u, v, None, None) for i, (u, v) in enumerate(gone)], OPS)
    kernel = DynamicIndex((), ring, k=2)
    for e in gone:
        kernel.delete_edge(*e)
    pairs = [(rng.randrange(60), rng.randrange(60)) for _ in range(400)]
    asked = spark.createDataFrame([(i, u, v) for i, (u, v) in enumerate(pairs)], "qid long, u long, v long")
    def share(said):
        no = [how for hit, how in said if not hit and how != "unknown_node"]
        return sum(how == "search" for how in no) / len(no)
    theirs = share([kernel.query(u, v)[:2] for u, v in pairs])
    for conf in (BATCH, EXTRACT):
        ix = batch.apply(I.build(frame(spark, ring), k=2), ops, conf=conf)
        holds(ix, kernel)
        mine = share([(r.reachable, r.decided_by) for r in Q.reach_batch(ix, asked).collect()])
        assert mine <= theirs + 0.1


def test_large_ids_everywhere(spark):
    edges = {(FAR + a, FAR + b) for a, b in two_rings(0, 5)[0]} | {(FAR + 100, FAR), (FAR + 101, FAR + 100), (FAR + 300, FAR + 301)}
    ix = I.build(frame(spark, edges), k=2)
    kernel = DynamicIndex((), edges, k=2)
    holds(ix, kernel)
    pairs = spark.createDataFrame([(i, FAR + u, FAR + v) for i, (u, v) in enumerate([(101, 9), (9, 101), (3, 8), (300, 301), (301, 0)])], "qid long, u long, v long")
    want = {r.qid: kernel.query(r.u, r.v)[0] for r in pairs.collect()}
    for strategy in ("local", "forward"):
        assert {r.qid: r.reachable for r in Q.reach_batch(ix, pairs, strategy=strategy).collect()} == want
    ends = Q.resolve(ix, pairs).select("qid", F.col("s").alias("u"), F.col("t").alias("v"))
    for cover in (baselines.tree_cover_reach(baselines.tree_cover(ix.dag_edges, ix.components), ends), baselines.two_hop_reach(baselines.two_hop(ix.dag_edges, ix.components), ends)):
        assert {r.qid: r.reachable for r in cover.collect()} == want
    ops = spark.createDataFrame([(0, None, "insert_edge", FAR + 9, FAR + 101, None, None), (1, None, "insert_node", FAR + 500, None, [FAR + 3, None], None), (2, None, "delete_node", FAR + 300, None, None, None)], OPS)
    kernel.apply("insert_edge", FAR + 9, FAR + 101), kernel.apply("insert_node", FAR + 500, None, [FAR + 3]), kernel.apply("delete_node", FAR + 300)
    for mode in ("batch", "sequential"):
        holds(batch.apply(ix, ops, mode, BATCH), kernel)


def test_isolated_components_are_counted_and_not_gathered(spark):
    ix = I.build(frame(spark, [(0, 1)]), spark.range(50).withColumnRenamed("id", "node"), k=1, conf=EngineConf(local_rows=20))
    assert L.violations(ix.labels, ix.dag_edges).count() == 0 and ix.labels.count() == 50
    pairs = spark.createDataFrame([(0, 0, 1), (1, 0, 30), (2, 30, 30)], "qid long, u long, v long")
    assert [r.reachable for r in Q.reach_batch(ix, pairs, prune=False, strategy="local").orderBy("qid").collect()] == [True, False, True]


def test_methods_are_asked_the_same(spark):
    rng = random.Random(4)
    edges = frame(spark, {(rng.randrange(60), rng.randrange(60)) for _ in range(90)})
    ops = generators.drawn_sequence(edges, 200).cache()
    graph = PlainGraph(sorted((r.src, r.dst) for r in edges.collect()))
    kinds = Counter()
    for r in ops.orderBy("op_id").collect():
        kinds[r.kind] += 1
        if r.kind == "delete_edge":
            assert (r.u, r.v) in graph.edges  # it is there when its turn comes
        if r.kind == "delete_node":
            assert r.u in graph.nodes
        if r.kind == "insert_node":
            assert r.u not in graph.nodes and set(r.outs) | set(r.ins) <= set(graph.nodes.items)
        graph.apply(r.kind, r.u, r.v, r.outs or (), r.ins or ())
    assert kinds["insert_edge"] > kinds["insert_node"] > kinds["delete_node"] and sum(kinds.values()) == 200
    times = workload.op_times(edges, ops).cache()
    asked = times.where("measure = 'Q'").collect()
    assert len(asked) == 4 and len({(r.n, r.reached, r.answers) for r in asked}) == 1 and asked[0].n == 1600 and asked[0].reached > 0
    totals = {(r.method, r.q): r.total_ms for r in workload.sweep(times).collect()}
    assert len(totals) == 32 and all(totals[(m, q)] < totals[(m, q + 1)] for m, q in totals if q < 8)
    end = {(r.src, r.dst) for r in batch.final_state(G.nodes_of(edges), edges, ops)[1].collect()}
    assert end == set(graph.edges.items)


def test_order_by_places(spark):
    rows = [(i, (i * 7919) % 1000, 2**62 + i % 3) for i in range(1000)]
    got = G.ordered(spark.createDataFrame(rows, "i long, a long, b long").repartition(7), "b", "a", name="place").collect()
    assert [r.i for r in sorted(got, key=lambda r: r.place)] == [i for i, _, _ in sorted(rows, key=lambda r: (r[2], r[1]))]
    assert sorted(r.place for r in got) == list(range(1000))


def test_streams_put_operations_in_order(spark, tmp_path):
    from dynreach.streaming import operations as S

    day = lambda n: datetime.datetime(2024, 1, 1) + datetime.timedelta(days=n)
    chunks = [[(0, 0, 1, 2), (3, 9, 3, 4)], [(1, 5, 2, 1), (4, 12, 4, 3)], [(2, 1, 9, 9), (5, 20, 1, 3)]]  # op_id, day, u, v
    for rows in chunks:
        spark.createDataFrame([(i, day(t), "insert_edge", u, v, None, None) for i, t, u, v in rows], OPS).coalesce(1).write.mode("append").parquet(f"{tmp_path}/ops")
    I.commit(I.build(frame(spark, [(0, 1)]).limit(0)), f"{tmp_path}/ix")
    read = lambda: spark.readStream.schema(OPS).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/ops")
    for _ in range(2):
        S.run(read(), f"{tmp_path}/ix", f"{tmp_path}/c1", f"{tmp_path}/late", "5 days", BATCH).awaitTermination()
    ix = I.load(spark, f"{tmp_path}/ix")
    assert {(r.src, r.dst) for r in ix.edges.collect()} == {(1, 2), (2, 1), (3, 4), (4, 3)}
    late = spark.read.parquet(f"{tmp_path}/late").collect()
    assert [(r.op_id, r.batch_id) for r in late] == [(2, 2)]
    S.flush(spark, f"{tmp_path}/ix", BATCH)
    assert {(r.src, r.dst) for r in I.load(spark, f"{tmp_path}/ix").edges.collect()} == {(1, 2), (2, 1), (3, 4), (4, 3), (1, 3)}
    I.commit(I.build(frame(spark, [(0, 1)]).limit(0)), f"{tmp_path}/iy")
    with pytest.raises(Exception, match="give a watermark"):
        S.run(read(), f"{tmp_path}/iy", f"{tmp_path}/c2", conf=BATCH).awaitTermination()


def test_forest_lookup_of_any_depth(spark):
    deep = spark.createDataFrame([(i, i + 1, 0) for i in range(100, 140)], "child long, parent long, epoch long")
    nodes = spark.createDataFrame([(100,), (139,), (140,), (5,)], "node long")
    assert {(r.node, r.comp) for r in containment.find(deep, nodes).collect()} == {(100, 140), (139, 140), (140, 140), (5, 5)}
    assert containment.depth(containment.compress(deep)) == 1


def test_versions_survive_and_batches_apply_once(spark, sf_dir, tmp_path):
    from dynreach.streaming import operations as S

    ops = workload.ops_events(spark, sf_dir).limit(60).cache()
    ops.repartitionByRange(3, "op_id").write.parquet(f"{tmp_path}/ops")
    I.commit(I.build(frame(spark, [(0, 1)]).limit(0)), f"{tmp_path}/ix")
    for _ in range(2):  # the second run finds nothing new
        S.run(spark.readStream.schema(ops.schema).option("maxFilesPerTrigger", 3).parquet(f"{tmp_path}/ops"), f"{tmp_path}/ix", f"{tmp_path}/check").awaitTermination()
    ix = I.load(spark, f"{tmp_path}/ix")
    kernel = DynamicIndex()
    for r in ops.orderBy("op_id").collect():
        kernel.apply(r.kind, r.u, r.v)
    assert {(r.src, r.dst) for r in ix.edges.collect()} == kernel.edges()
    holds(ix, kernel)


def test_plans_stay_in_the_engine(spark, sf_dir):
    def plan(df):
        return df._jdf.queryExecution().executedPlan().toString()

    for graph in G.GRAPHS:
        if graph != "example_graph":
            text = plan(G.edges_of(spark, graph, sf_dir))
            assert "CartesianProduct" not in text and "Python" not in text
    assert "PushedFilters: [IsNotNull(l_quantity), LessThanOrEqual(l_quantity,18.0)]" in plan(G.uniform_pairs(spark, sf_dir))
    ix = I.build(G.part_hops(spark, sf_dir), k=2)
    rejected = plan(Q.label_reject(ix, G.pairs_fixed(ix.nodes, 10)))
    assert "Python" not in rejected and "CartesianProduct" not in rejected


def test_search_costs_fall_with_labels(spark, sf_dir):
    edges = G.goods_flow_light(spark, sf_dir)
    spent = {}
    for k in (0, 1, 2):
        ix = I.build(edges, k=k)
        spent[k] = sum(r.expanded for r in Q.reach_batch(ix, G.pairs_fixed(ix.nodes, 200)).collect())
    raw = sum(r.expanded for r in baselines.search(edges, G.pairs_fixed(G.nodes_of(edges), 200)).collect())
    assert spent[1] < spent[0] <= raw and spent[2] <= 1.1 * spent[1] + 10
