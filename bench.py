"""Headline times as one JSON line.

For each of the four workload graphs: building the index, answering the same pairs by idx(k) and by plain search, and a
large batch by idx(k); applying the first 1,000 operations of the workload as a batch; and operations one by one with
eight questions after each, the same for all methods. New nodes of the uniform and hub sequences come with in-edges too.
"""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
#: Pairs of a batch; pairs that every method answers, plain search too; operations of each sequence that are timed one by one,
#: as many as a plain search of 8 questions after each allows in a minute or two.
PAIRS, EQUAL_PAIRS = 100_000, 1_000
MOST_OPS = {"wiki_like": 400, "citation": 2_000, "uniform": 150, "hub": 60}
GRAPHS = {"wiki_like": "goods_flow_light", "citation": "order_citation", "uniform": "uniform_pairs", "hub": "goods_flow"}


def main() -> None:
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from dynreach.operators import baselines, generators, index, query
    from dynreach.plans import batch, workload
    from dynreach.plans.loops import cut
    from dynreach.sources import graphs

    seconds: dict[str, float] = {}
    shapes: dict[str, object] = {}

    def timed(name, make):
        start = time.time()
        out = make()
        seconds[name] = round(time.time() - start, 3)
        return out

    for name, graph in GRAPHS.items():
        edges = timed(f"{name}_edges", lambda: cut(graphs.edges_of(spark, graph, SF_DIR)))
        equal = None
        for k in (0, 1, 2):
            ix = timed(f"{name}_build_k{k}", lambda: index.build(edges, k=k))
            if equal is None:
                equal = cut(generators.query_pairs(ix.nodes, EQUAL_PAIRS))
                pairs = cut(generators.query_pairs(ix.nodes, PAIRS))
            hits = timed(f"{name}_equal_k{k}", lambda: query.reach_batch(ix, equal).where("reachable").count())
            shapes[f"{name}_equal_k{k}"] = {"pairs": EQUAL_PAIRS, "reachable": hits, "us_a_pair": round(seconds[f"{name}_equal_k{k}"] / EQUAL_PAIRS * 1e6, 1)}
            if k:
                hits = timed(f"{name}_reach_k{k}", lambda: query.reach_batch(ix, pairs).where("reachable").count())
                shapes[f"{name}_k{k}"] = {"pairs": PAIRS, "reachable": hits, "us_a_pair": round(seconds[f"{name}_reach_k{k}"] / PAIRS * 1e6, 1)}
        hits = timed(f"{name}_equal_search", lambda: baselines.search(edges, equal).where("reachable").count())
        shapes[f"{name}_equal_search"] = {"pairs": EQUAL_PAIRS, "reachable": hits, "us_a_pair": round(seconds[f"{name}_equal_search"] / EQUAL_PAIRS * 1e6, 1)}
        # the workload's own operations: the first 1,000 as a batch, and the first MOST_OPS one by one, with 8 questions after each
        base, ops = (cut(x) for x in workload.WORKLOADS[name](spark, SF_DIR))
        before = timed(f"{name}_snapshot_build", lambda: index.build(base, k=1))
        after = timed(f"{name}_batch_1000", lambda: batch.apply(before, ops.where("op_id < 1000")))
        shapes[f"{name}_batch_1000"] = after.facts
        times = timed(f"{name}_one_by_one", lambda: cut(workload.op_times(base, ops, most_ops=MOST_OPS[name])))
        rows = times.where("measure not rlike '^Q[0-9]'").orderBy("k", "measure").collect()
        shapes[f"{name}_avg_ms"] = {f"{r.method} {r.measure}": round(r.avg_ms, 4) for r in rows}
        asked = [r for r in rows if r.measure == "Q"]
        shapes[f"{name}_sequence"] = {"operations": sum(r.n for r in rows if r.method == "idx(1)" and r.measure != "Q"), "of": ops.count(), "questions": asked[0].n, "methods_agree": len({r.answers for r in asked}) == 1}
        totals = cut(workload.sweep(times))
        shapes[f"{name}_total_ms"] = {f"{r.method} q={r.q}": round(r.total_ms, 1) for r in totals.where("q in (1, 2, 4, 8)").orderBy("method", "q").collect()}
        shapes[f"{name}_break_even"] = {r.method: r.q for r in workload.break_even(totals).collect()}
    print(json.dumps({"metric": "headline queries, total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": SF_DIR.rsplit("sf", 1)[-1], "cpus": int(CPUS), "details": shapes}))
    spark.stop()


if __name__ == "__main__":
    main()
