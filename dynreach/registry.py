"""All queries of the engine by name, each with its SQL twin where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dynreach.conf import DEFAULT, EngineConf
from dynreach.model import OPS, Index
from dynreach.operators import baselines as B
from dynreach.operators import condense, containment as C, generators as GEN, index as I, labels as L, measures as M, query as Q, scc, updates as U
from dynreach.plans import batch, relational, workload as W
from dynreach.plans.loops import cut
from dynreach.sources import graphs as G

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}


def add(name: str, query: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql is not None:
        ORACLE_SQL[name] = sql


_kept: dict[tuple, object] = {}


def kept(spark: SparkSession, key: tuple, make: Callable[[], object]):
    """One build a session for what several queries read."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _kept:
        _kept[key] = make()
    return _kept[key]


def edges(spark: SparkSession, d: str, graph: str) -> DataFrame:
    return kept(spark, (d, graph), lambda: cut(G.edges_of(spark, graph, d)))


def index(spark: SparkSession, d: str, graph: str, k: int = 1) -> Index:
    return kept(spark, (d, graph, k), lambda: I.build(edges(spark, d, graph), k=k, as_is=graph in G.DISTINCT))


def nodes(spark: SparkSession, d: str, graph: str) -> DataFrame:
    return kept(spark, (d, graph, "nodes"), lambda: cut(G.nodes_of(edges(spark, d, graph))))


def asked(spark: SparkSession, d: str, graph: str, n: int = 200) -> DataFrame:
    """The index's nodes are asked for where it was built, else those of the edges: pairs need no index."""
    built = _kept.get((spark.sparkContext.applicationId, d, graph, 1))
    return kept(spark, (d, graph, "pairs", n), lambda: cut(G.pairs_fixed(built.nodes if built else nodes(spark, d, graph), n)))


# pieces of SQL


def with_graph(graph: str, rest: str, recursive: bool = True) -> str:
    return f"with {'recursive ' if recursive else ''}e as materialized ({G.sql_edges(graph)}), n as materialized ({G.sql_nodes()}), {rest}"


CLOSURE = "c(src, dst) as (select src, dst from e union select c.src, e.dst from c join e on e.src = c.dst)"
COMPS = CLOSURE + ", m as materialized (select node, least(node, coalesce(min(b.dst), node)) comp from n left join (select x.src, x.dst from c x join c y on x.src = y.dst and x.dst = y.src) b on b.src = node group by node)"
DAG = "dag as (select a.comp s, b.comp t, count(*) mult from e join m a on a.node = src join m b on b.node = dst where a.comp <> b.comp group by 1, 2)"


def reach(pairs: str, columns: str = "p.qid, p.u, p.v, (p.u = p.v or r.x is not null) reachable") -> str:
    """From a CTE e: sweeps from the pairs' sources only."""
    return f"p as materialized ({pairs}), r(root, x) as (select distinct u, dst from p join e on src = u union select r.root, e.dst from r join e on e.src = r.x) select {columns} from p left join r on r.root = p.u and r.x = p.v"


def reach_sql(graph: str, n: int = 200) -> str:
    return with_graph(graph, reach(G.sql_pairs(n)))


ANSWER = ("qid", "u", "v", "reachable")
SMALL = ("user_hops", "part_hops", "example_graph")
LARGE = ("uniform_pairs", "goods_flow", "goods_flow_light", "order_citation", "user_steps", "user_hops", "part_hops")

# graphs

for _g in G.GRAPHS:
    add(f"edges_{_g}", lambda s, d, g=_g: G.edges_of(s, g, d), G.sql_edges(_g))
add("edges_example_graph", lambda s, d: G.user_skips(s, d), G.sql_edges("user_skips"))  # states two events apart
add("edges_web_links", lambda s, d: G.web_links(s, d), G.SQL["web_links"])


def _interned(s: SparkSession, d: str) -> DataFrame:
    e, names = G.intern_ids(G.web_links(s, d))
    return names.select("key", F.col("node").cast("long").alias("node"))


add("intern_web_links", _interned, f"with e as ({G.SQL['web_links']}) select key, row_number() over (order by key) - 1 node from (select src key from e union select dst from e)")

# components and condensation

for _g in SMALL:
    add(f"scc_{_g}", lambda s, d, g=_g: index(s, d, g).membership, with_graph(_g, COMPS + " select node, comp from m"))
    add(f"condense_{_g}", lambda s, d, g=_g: index(s, d, g).dag_edges, with_graph(_g, f"{COMPS}, {DAG} select s, t, mult from dag"))
    add(f"graph_profile_{_g}", lambda s, d, g=_g: (ix := index(s, d, g)) and M.profile(ix.nodes, ix.edges, ix.membership), with_graph(_g, COMPS + ", z as (select comp, count(*) size from m group by 1) select (select count(*) from n) nodes, (select count(*) from e) edges, count(*) comps, max(size) largest, count(*) filter (where size > 1) several from z"))
    add(f"scc_sizes_{_g}", lambda s, d, g=_g: index(s, d, g).components.select("comp", "size"), with_graph(_g, COMPS + " select comp, count(*) size from m group by 1"))
add("condense_example_graph", lambda s, d: index(s, d, "user_steps").dag_edges, with_graph("user_steps", f"{COMPS}, {DAG} select s, t, mult from dag"))
for _g, _m in (("user_hops", "trim_color"), ("user_hops", "fwbw"), ("example_graph", "trim_color"), ("example_graph", "fwbw")):
    add(f"scc_{_m}_{_g}", lambda s, d, g=_g, m=_m: scc.strongly_connected(None, edges(s, d, g), m), with_graph(_g, COMPS + " select node, comp from m"))
add("scc_user_steps", lambda s, d: index(s, d, "user_steps").membership, with_graph("user_steps", COMPS + " select node, comp from m"))
for _g in ("order_citation", "containment_tree"):
    add(f"scc_acyclic_{_g}", lambda s, d, g=_g: index(s, d, g).membership, with_graph(_g, "x as (select node, node comp from n) select node, comp from x", False))
PIVOT = "pv as (select a.src node from (select src, count(*) o from e group by 1) a join (select dst, count(*) i from e group by 1) b on a.src = b.dst order by o * i desc, a.src limit 1), f(x) as (select node from pv union select dst from f join e on src = x), b(x) as (select node from pv union select src from b join e on dst = x)"


def _giant(s: SparkSession, d: str, g: str) -> DataFrame:
    e, m = edges(s, d, g), index(s, d, g).membership
    top = e.groupBy("src").count().join(e.groupBy("dst").agg(F.count("*").alias("back")), F.col("src") == F.col("dst"))
    pivot = top.orderBy(F.desc(F.col("count") * F.col("back")), "src").select(F.col("src").alias("node")).limit(1)
    return m.join(F.broadcast(m.join(pivot, "node").select("comp")), "comp").select("node")  # one row


for _g in ("uniform_pairs", "goods_flow", "goods_flow_light"):
    add(f"scc_giant_{_g}", lambda s, d, g=_g: _giant(s, d, g), with_graph(_g, PIVOT + " select x node from f intersect select x from b"))
add("compact_ratio_part_hops", lambda s, d: condense.compact(index(s, d, "part_hops").membership).agg(F.count("*").alias("kept")).join(index(s, d, "part_hops").nodes.agg(F.count("*").alias("nodes"))).select("kept", "nodes"), with_graph("part_hops", COMPS + " select count(*) kept, (select count(*) from n) nodes from m where comp in (select comp from m group by 1 having count(*) > 1)"))
add("dag_view_order_citation", lambda s, d: condense.view(edges(s, d, "order_citation"), None, True), with_graph("order_citation", "x as (select src s, dst t, 1::bigint mult from e) select s, t, mult from x", False))
add("index_rows_part_hops", lambda s, d: M.index_rows(index(s, d, "part_hops")).where("part in ('live_edges', 'components', 'dag_edges', 'intervals')"), with_graph("part_hops", f"{COMPS}, {DAG} select 'live_edges' part, count(*) n from e union all select 'components', count(distinct comp) from m union all select 'dag_edges', count(*) from dag union all select 'intervals', count(distinct comp) from m"))

# containment forest: components of user_hops, then three of them absorbed by the largest


def _forest(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame, int]:
    def make():
        ix = index(s, d, "part_hops")
        merged = ix.components.orderBy(F.desc("size"), "comp").select("comp", "size").limit(4)  # the feature: a merge list of four
        rep = C.pick_representative(merged).first().rep
        return cut(C.attach(ix.containment, merged, rep, 1)), cut(merged), rep

    return kept(s, (d, "forest"), make)


_MERGED = COMPS + ", z as (select comp, count(*) size from m group by 1 order by size desc, comp limit 4), rep as (select comp from z order by size desc, comp limit 1)"
add("containment_after_merge", lambda s, d: _forest(s, d)[0], with_graph("part_hops", _MERGED + " select node child, comp parent, 0::bigint epoch from m where node <> comp union all select comp, (select comp from rep), 1 from z where comp <> (select comp from rep)"))
_LOOKUP = with_graph("part_hops", _MERGED + " select node, case when comp in (select comp from z) then (select comp from rep) else comp end comp from m")
add("component_lookup", lambda s, d: C.find(_forest(s, d)[0], index(s, d, "part_hops").nodes), _LOOKUP)
add("flat_membership", lambda s, d: C.flat_membership(index(s, d, "part_hops").membership, _forest(s, d)[1], _forest(s, d)[2]), _LOOKUP)
add("merge_representative", lambda s, d: C.pick_representative(_forest(s, d)[1]).select("rep", F.col("size").cast("long").alias("size")), with_graph("part_hops", _MERGED + " select (select comp from rep) rep, sum(size)::bigint size from z"))
add("containment_depth", lambda s, d: s.createDataFrame([(C.depth(_forest(s, d)[0]), C.depth(C.compress(_forest(s, d)[0])))], "before int, after int"), with_graph("part_hops", _MERGED + " select case when exists (select 1 from z where size > 1 and comp <> (select comp from rep)) then 2 else 1 end::int \"before\", 1::int \"after\""))

# labels

for _g in (*LARGE, "containment_tree", "conversation_chain"):
    add(
        f"label_invariant_{_g}",
        lambda s, d, g=_g: (ix := index(s, d, g, 2)).labels.agg(F.count("*").alias("comps")).join(L.violations(ix.labels, ix.dag_edges).agg(F.count("*").alias("broken"))).select("broken", (F.col("comps") == ix.components.count()).alias("every_comp")),
        "select 0::bigint broken, true every_comp",
    )
for _g in ("containment_tree", "user_hops"):
    add(f"label_invariant_bulk_{_g}", lambda s, d, g=_g: L.violations(kept(s, (d, g, "bulk"), lambda: L.bulk(index(s, d, g).dag_edges, index(s, d, g).components, 2)), index(s, d, g).dag_edges).agg(F.count("*").alias("broken")), "select 0::bigint broken")
add("label_gap_part_hops", lambda s, d: index(s, d, "part_hops").labels.join(index(s, d, "part_hops").components, "comp").where(F.col("iv")[0]["e"] - F.col("iv")[0]["b"] < F.col("size")).agg(F.count("*").alias("narrow")), "select 0::bigint narrow")
add("label_static_user_hops", lambda s, d: L.violations(L.postorder(index(s, d, "user_hops").dag_edges, index(s, d, "user_hops").components, 2, slack=1), index(s, d, "user_hops").dag_edges).agg(F.count("*").alias("broken")), "select 0::bigint broken")
# the walk by ids upward, worked out by hand: fixed values
_WALKED = "select * from (values (0::bigint, 0::bigint, 12::bigint), (3, 0, 18), (7, 0, 8), (8, 1, 9), (9, 1, 14), (10, 1, 13), (11, 0, 7), (12, 0, 1), (13, 1, 6), (17, 0, 19)) x(comp, b, e)"
add("label_example", lambda s, d: L.postorder(index(s, d, "example_graph").dag_edges, index(s, d, "example_graph").components, 1, order="asc").select("comp", F.col("iv")[0]["b"].alias("b"), F.col("iv")[0]["e"].alias("e")), _WALKED)


def _heights(s: SparkSession, d: str) -> DataFrame:
    ix = index(s, d, "containment_tree")
    flat = ix.components.select("comp", F.array(F.struct(F.lit(0).cast("long").alias("b"), F.lit(1).cast("long").alias("e"))).alias("iv"))
    return L.propagate_up(flat, ix.dag_edges)[0].select("comp", F.col("iv")[0]["e"].alias("e"))


add("propagate_up_containment_tree", _heights, with_graph("containment_tree", "h(x, e) as (select node, 1 from n union select src, h.e + 1 from h join e on dst = x) select x comp, max(h.e)::bigint e from h group by 1"))

# questions

for _g in LARGE:
    add(f"reach_batch_{_g}", lambda s, d, g=_g: Q.reach_batch(index(s, d, g), asked(s, d, g)).select(*ANSWER), reach_sql(_g))
    add(f"base_search_{_g}", lambda s, d, g=_g: B.search(edges(s, d, g), asked(s, d, g)).select(*ANSWER), reach_sql(_g))
for _g in ("user_steps", "goods_flow_light"):
    # pairs with a path: sources at 60 ranks, each with everything in two steps
    _two = "pp as materialized (select distinct u, b.dst v from (select distinct u from (" + G.sql_pairs(60) + ")) join e a on a.src = u join e b on b.src = a.dst)"
    add(
        f"reach_positive_{_g}",
        lambda s, d, g=_g: Q.reach_batch(index(s, d, g), asked(s, d, g, 60).select("u").distinct().join(edges(s, d, g), F.col("u") == F.col("src")).select("u", F.col("dst").alias("mid")).join(edges(s, d, g), F.col("mid") == F.col("src")).select("u", F.col("dst").alias("v")).distinct().withColumn("qid", F.col("u") * 1_000_003 + F.col("v"))).select("u", "v", "reachable"),
        with_graph(_g, _two + " select u, v, true reachable from pp"),
    )
for _k in (0, 1, 2, 4):
    add(f"reach_k{_k}", lambda s, d, k=_k: Q.reach_batch(index(s, d, "part_hops", k), asked(s, d, "part_hops")).select(*ANSWER), reach_sql("part_hops"))
for _name, _how in (("forward", {"strategy": "forward"}), ("bidir", {"strategy": "bidirectional"}), ("prune_equals_noprune", {"prune": False})):
    add(f"reach_{_name}", lambda s, d, how=_how: Q.reach_batch(index(s, d, "user_hops"), asked(s, d, "user_hops"), **how).select(*ANSWER), reach_sql("user_hops"))
add("base_search_frontier", lambda s, d: B.search(edges(s, d, "user_hops"), asked(s, d, "user_hops"), "frontier").select(*ANSWER), reach_sql("user_hops"))
add("reach_same_comp", lambda s, d: Q.reach_batch(index(s, d, "part_hops"), asked(s, d, "part_hops")).where("decided_by = 'same_comp'").select("qid"), with_graph("part_hops", f"{COMPS}, p as ({G.sql_pairs()}) select qid from p join m a on a.node = u join m b on b.node = v where a.comp = b.comp"))
add("label_reject_sound", lambda s, d: Q.label_reject(index(s, d, "part_hops", 2), asked(s, d, "part_hops")).where("rejected").join(B.search(edges(s, d, "part_hops"), asked(s, d, "part_hops")).where("reachable").select("qid"), "qid").agg(F.count("*").alias("wrong")), "select 0::bigint wrong")
add("reach_one", lambda s, d: s.createDataFrame([(bool(Q.reaches(index(s, d, "example_graph"), 17, 12)), bool(Q.reaches(index(s, d, "example_graph"), 12, 17)), bool(Q.reaches(index(s, d, "example_graph"), 17, 99)))], "down boolean, up boolean, unknown boolean"), "select true down, false up, false unknown")
_ROOTS = "starts as (select comp from m group by 1 order by count(*) desc, comp limit 5)"
for _name, _fn, _a, _b in (("descendants", Q.descendants, "s", "t"), ("ancestors", Q.ancestors, "t", "s")):
    add(
        f"{_name}_part_hops",
        lambda s, d, fn=_fn: fn(index(s, d, "part_hops"), index(s, d, "part_hops").components.orderBy(F.desc("size"), "comp").select("comp").limit(5)),
        with_graph("part_hops", f"{COMPS}, {DAG}, {_ROOTS}, g(root, comp) as (select comp, comp from starts union select g.root, {_b} from g join dag on {_a} = g.comp) select root, comp from g"),
    )


def _between(s: SparkSession, d: str) -> DataFrame:
    """Between the ends of the condensation's first edge."""
    ix = index(s, d, "part_hops")
    ends = ix.dag_edges.orderBy("s", "t").select("s", "t").first()
    return Q.between(ix, ends.s, ends.t) if ends else ix.components.select("comp").limit(0)


add("between_example", _between, with_graph("part_hops", f"{COMPS}, {DAG}, ends as (select s, t from dag order by s, t limit 1), f(x) as (select s from ends union select dag.t from f join dag on dag.s = x), b(x) as (select t from ends union select dag.s from b join dag on dag.t = x) select x comp from f intersect select x from b"))
add("closure_user_hops", lambda s, d: B.closure(edges(s, d, "user_hops")), with_graph("user_hops", CLOSURE + " select src, dst from c"))
add("tree_cover_order_citation", lambda s, d: B.tree_cover_reach(B.tree_cover(index(s, d, "order_citation").dag_edges, index(s, d, "order_citation").components, of=asked(s, d, "order_citation").select(F.col("u").alias("comp"))), asked(s, d, "order_citation")).select(*ANSWER), reach_sql("order_citation"))
add("tree_cover_containment_tree", lambda s, d: B.tree_cover_reach(B.tree_cover(index(s, d, "containment_tree").dag_edges, index(s, d, "containment_tree").components), asked(s, d, "containment_tree")).select(*ANSWER), reach_sql("containment_tree"))


def _two_hop(s: SparkSession, d: str) -> DataFrame:
    ix, p = index(s, d, "user_hops"), asked(s, d, "user_hops")
    ends = Q.resolve(ix, p).select("qid", F.col("u").alias("a"), F.col("v").alias("b"), F.col("s").alias("u"), F.col("t").alias("v"))
    return B.two_hop_reach(B.two_hop(ix.dag_edges, ix.components), ends).join(p.select("qid", F.col("u").alias("a"), F.col("v").alias("b")), "qid").select("qid", F.col("a").alias("u"), F.col("b").alias("v"), "reachable")


add("two_hop_user_hops", _two_hop, reach_sql("user_hops"))
add("w_tree_reach", lambda s, d: Q.reach_batch(index(s, d, "containment_tree"), asked(s, d, "containment_tree", 1000)).select(*ANSWER), reach_sql("containment_tree", 1000))
add("w_chain_reach", lambda s, d: Q.reach_batch(index(s, d, "conversation_chain"), asked(s, d, "conversation_chain", 500)).select(*ANSWER), with_graph("conversation_chain", reach(G.sql_pairs(500))))


def _links_reach(s: SparkSession, d: str) -> DataFrame:
    e, _ = kept(s, (d, "links"), lambda: tuple(cut(x) for x in G.intern_ids(G.web_links(s, d))))
    ix = kept(s, (d, "links", "index"), lambda: I.build(e))
    return Q.reach_batch(ix, G.pairs_fixed(ix.nodes)).select(*ANSWER)


add("w_links_reach", _links_reach, f"with recursive l as ({G.SQL['web_links']}), k as materialized (select key, row_number() over (order by key) - 1 node from (select src key from l union select dst from l)), e as materialized (select a.node src, b.node dst from l join k a on a.key = l.src join k b on b.key = l.dst), n as ({G.sql_nodes()}), " + reach(G.sql_pairs()))

# ids that floats can't hold

LARGE_ID = 2**62 + 1


def _large(s: SparkSession, d: str) -> DataFrame:
    return kept(s, (d, "large"), lambda: cut(edges(s, d, "part_hops").select((F.col("src") + LARGE_ID).alias("src"), (F.col("dst") + LARGE_ID).alias("dst"))))


def _large_index(s: SparkSession, d: str) -> Index:
    return kept(s, (d, "large", "index"), lambda: I.build(_large(s, d), k=2))


_LARGE_SQL = f"with recursive e as materialized (select src + {LARGE_ID} src, dst + {LARGE_ID} dst from ({G.sql_edges('part_hops')})), n as materialized ({G.sql_nodes()}), "
add("large_ids_reach", lambda s, d: Q.reach_batch(_large_index(s, d), G.pairs_fixed(_large_index(s, d).nodes)).select(*ANSWER), _LARGE_SQL + reach(G.sql_pairs()))
add("large_ids_search", lambda s, d: B.search(_large(s, d), G.pairs_fixed(_large_index(s, d).nodes)).select(*ANSWER), _LARGE_SQL + reach(G.sql_pairs()))
add("large_ids_scc", lambda s, d: _large_index(s, d).membership, _LARGE_SQL + COMPS + " select node, comp from m")
add("large_ids_labels_hold", lambda s, d: L.violations(_large_index(s, d).labels, _large_index(s, d).dag_edges).agg(F.count("*").alias("broken")), "select 0::bigint broken")

# updates: the operations as SQL, and what they leave

SYNTH = (
    "nn as materialized (select node, row_number() over (order by node) - 1 r from n), ee as materialized (select src, dst, row_number() over (order by dst, src) - 1 place from e), "
    f"asked as (select range op_id, {GEN.mix_sql('(range*4)', 3)} % (select count(*) from n) rank, {GEN.mix_sql('(range*4+1)', 3)} % (select count(*) from e) e1, {GEN.mix_sql('(range*4+2)', 3)} % (select count(*) from e) e2 from range({{n}})), "
    "raw as materialized (select op_id, case when op_id % 20 < 12 then 'insert_edge' when op_id % 20 < 15 then 'delete_edge' when op_id % 20 < 19 then 'insert_node' else 'delete_node' end kind, nn.node picked, a.src s1, a.dst d1, b.dst d2, (select max(node) from n) + 1 + op_id fresh from asked join nn on nn.r = rank join ee a on a.place = e1 join ee b on b.place = e2), "
    "gone as (select s1, d1, min(op_id) op_id from raw where kind = 'delete_edge' group by 1, 2), "
    "ins as (select op_id, picked src, d1 dst from raw where kind = 'insert_edge' union all select op_id, fresh, d1 from raw where kind = 'insert_node' union all select op_id, d2, fresh from raw where kind = 'insert_node' and op_id % 2 = 0), "
    "del as (select op_id, s1 src, d1 dst from gone), kill as (select op_id, picked node from raw where kind = 'delete_node'), born as (select op_id, fresh node from raw where kind = 'insert_node')"
)
WIKI = (
    "t0 as (select quantile_disc(l_shipdate, 0.95) t0 from lineitem), sp as (select l_orderkey, min(l_shipdate) f, max(l_shipdate) z from lineitem group by 1), "
    "ev as (select l_shipdate ts, case when l_shipdate = f then 'insert_node' else 'insert_edge' end kind, l.l_orderkey*8 u, l_partkey*8+1 v from lineitem l join sp using (l_orderkey) where l_quantity <= 40 and l_shipdate >= (from t0) "
    "union select l_shipdate, 'insert_edge', l_partkey*8+1, l_orderkey*8 from lineitem where l_returnflag='R' and l_discount >= 0.095 and l_shipdate >= (from t0) "
    "union select l_shipdate + interval 90 day, 'delete_edge', l_orderkey*8, l_partkey*8+1 from lineitem where l_quantity <= 40 and l_returnflag='A' and l_shipdate + interval 90 day >= (from t0) "
    "union select z + interval 30 day, 'delete_node', o_orderkey*8, null from orders join sp on l_orderkey = o_orderkey where o_orderstatus='F' and o_orderkey % 10 = 0 and z + interval 30 day >= (from t0)), "
    "raw as materialized (select *, row_number() over (order by ts, kind, u, v nulls last) - 1 op_id from ev qualify op_id < 1000), "
    "ins as (select op_id, u src, v dst from raw where kind in ('insert_edge','insert_node') and v is not null), del as (select op_id, u src, v dst from raw where kind='delete_edge'), "
    "kill as (select op_id, u node from raw where kind='delete_node'), born as (select op_id, u node from raw where kind='insert_node')"
)
WIKI_BASE = "select l_orderkey*8 src, l_partkey*8+1 dst from lineitem where l_quantity <= 40 and l_shipdate < (select quantile_disc(l_shipdate, 0.95) from lineitem) union select l_partkey*8+1, l_orderkey*8 from lineitem where l_returnflag='R' and l_discount >= 0.095 and l_shipdate < (select quantile_disc(l_shipdate, 0.95) from lineitem)"
EVENTS = (
    "st as (select *, user_id*100 + (props->>'$.k')::bigint st from events), sp as (select *, lag(st) over w p, lag(st, 2) over w pp from st window w as (partition by user_id order by ts, event_id)), "
    "raw as materialized (select row_number() over (order by ts, event_id) op_id, case when event_type in ('view','click','signup') then 'insert_edge' when event_type='purchase' then 'delete_edge' when event_type='error' and value < 2 then 'delete_node' end kind, st, p, pp from sp), "
    "ins as (select op_id, p src, st dst from raw where kind='insert_edge' and p is not null), del as (select op_id, pp src, p dst from raw where kind='delete_edge' and pp is not null and p is not null), kill as (select op_id, st node from raw where kind='delete_node'), born as (select op_id, st node from raw where false)"
)
FINAL = (
    "base as (select -1::bigint op_id, src, dst from e), last_in as (select src, dst, max(op_id) seen from (select * from base union all select op_id, src, dst from ins) group by 1, 2), "
    "last_out as (select src, dst, max(op_id) gone from del group by 1, 2), last_kill as (select node, max(op_id) dead from kill group by 1), "
    "fe as materialized (select i.src, i.dst from last_in i left join last_out o on o.src = i.src and o.dst = i.dst left join last_kill a on a.node = i.src left join last_kill b on b.node = i.dst where seen > coalesce(gone, -2) and seen > coalesce(a.dead, -2) and seen > coalesce(b.dead, -2)), "
    "fn as materialized (select node from (select node, max(op_id) seen from (select node, -1 op_id from n union all select src, op_id from ins union all select dst, op_id from ins union all select node, op_id from born) group by 1) left join last_kill using (node) where seen > coalesce(dead, -2))"
)
CITE = (
    "rk as materialized (select o_orderkey node, row_number() over (order by o_orderdate, o_orderkey) rank from orders), "
    "late as (select node, rank from rk where rank > floor(0.858 * (select count(*) from rk))), whole as materialized (" + G.sql_edges("order_citation") + "), "
    "ins as (select rank op_id, src, dst from whole join late on node = src), del as (select * from ins where false), kill as (select 0::bigint op_id, 0::bigint node where false), born as (select rank op_id, node from late)"
)
CITE_BASE = "with rk as (select o_orderkey node, row_number() over (order by o_orderdate, o_orderkey) rank from orders) select src, dst from (" + G.sql_edges("order_citation") + ") join rk on node = src where rank <= floor(0.858 * (select count(*) from rk))"


def final_sql(base: str, ops: str, rest: str) -> str:
    return f"with recursive e as materialized (select src::bigint src, dst::bigint dst from ({base})), n as materialized ({G.sql_nodes()}), {ops}, {FINAL}, {rest}"


def synth_sql(graph: str, n: int, rest: str) -> str:
    return final_sql(G.SQL[graph], SYNTH.format(n=n), rest)


REACH_FINAL = reach(G.sql_pairs(100, "fn")).replace(" e ", " fe ").replace("e.dst", "fe.dst").replace("e.src", "fe.src").replace("join e on src", "join fe on src")
STATE = "q as (select 1) select src, dst from fe"


def updated(s: SparkSession, d: str, key: str, base: Callable[[], DataFrame], ops: Callable[[], DataFrame], mode: str = "auto", k: int = 1) -> Index:
    def make():
        return U.apply(I.build(base(), k=k), cut(ops()), mode)

    return kept(s, (d, key, mode, k), make)


def synth(s: SparkSession, d: str, graph: str, n: int, mode: str = "auto") -> Index:
    return updated(s, d, f"{graph}-synth-{n}", lambda: edges(s, d, graph), lambda: GEN.update_sequence(edges(s, d, graph), n), mode)


def answers_after(ix: Index) -> DataFrame:
    return Q.reach_batch(ix, G.pairs_fixed(ix.nodes, 100)).select(*ANSWER)


def wiki(s, d):
    base, ops = W.ops_wiki_like(s, d)
    return updated(s, d, "wiki", lambda: base, lambda: ops)


def citation(s, d):
    base, ops = W.ops_citation(s, d)
    return updated(s, d, "citation", lambda: base, lambda: ops)


def streamed(s, d):
    nothing = s.createDataFrame([], "src long, dst long")
    return updated(s, d, "events", lambda: nothing, lambda: W.ops_events(s, d))


for _name, _make, _sql in (
    ("wiki_like", wiki, lambda rest: final_sql(WIKI_BASE, WIKI, rest)),
    ("citation", citation, lambda rest: final_sql(CITE_BASE, CITE, rest)),
    ("uniform", lambda s, d: synth(s, d, "uniform_pairs", 1000), lambda rest: synth_sql("uniform_pairs", 1000, rest)),
    ("hub", lambda s, d: synth(s, d, "goods_flow", 1000), lambda rest: synth_sql("goods_flow", 1000, rest)),
    ("events", streamed, lambda rest: final_sql("select 0 src, 0 dst where false", EVENTS, rest)),
):
    add(f"w_{_name}_final_state", lambda s, d, make=_make: make(s, d).edges, _sql(STATE))
    add(f"w_{_name}_reach", lambda s, d, make=_make: answers_after(make(s, d)), _sql(REACH_FINAL))
    add(f"w_{_name}_labels_hold", lambda s, d, make=_make: L.violations(make(s, d).labels, make(s, d).dag_edges).agg(F.count("*").alias("broken")), "select 0::bigint broken")

FINAL_COMPS = COMPS.replace(" from e ", " from fe ").replace("join e on e.src", "join fe on fe.src").replace("e.dst", "fe.dst").replace("from n left", "from fn left")
for _n in (10, 100, 1000):
    add(f"w_batch_{_n}", lambda s, d, n=_n: synth(s, d, "part_hops", n).membership, synth_sql("part_hops", _n, FINAL_COMPS + " select node, comp from m"))
for _mode in ("sequential", "rebuild"):
    add(f"batch_{_mode}", lambda s, d, mode=_mode: synth(s, d, "part_hops", 100, mode).membership, synth_sql("part_hops", 100, FINAL_COMPS + " select node, comp from m"))
FINAL_DAG = DAG.replace("from e join", "from fe join")
for _name, _mode in (("batch", "auto"), ("sequential", "sequential")):
    add(f"large_ids_{_name}", lambda s, d, mode=_mode: updated(s, d, "large-ids", lambda: _large(s, d), lambda: GEN.update_sequence(_large(s, d), 100), mode).membership, final_sql(f"select src + {LARGE_ID} src, dst + {LARGE_ID} dst from ({G.sql_edges('part_hops')})", SYNTH.format(n=100), FINAL_COMPS + " select node, comp from m"))
add("rebuild_equals_incremental", lambda s, d: synth(s, d, "part_hops", 100).dag_edges, synth_sql("part_hops", 100, f"{FINAL_COMPS}, {FINAL_DAG} select s, t, mult from dag"))


def _net(s: SparkSession, d: str) -> DataFrame:
    ix = index(s, d, "part_hops")
    return kept(s, (d, "net"), lambda: cut(batch.prune(ix.nodes, ix.edges, GEN.update_sequence(edges(s, d, "part_hops"), 100))))


_NET = "net as materialized (select 'insert_edge' kind, src u, dst v from (select * from fe except select * from e) union all select 'delete_edge', src, dst from (select * from e except select * from fe) union all select 'insert_node', node, null from (select * from fn except select * from n) union all select 'delete_node', node, null from (select * from n except select * from fn))"
add("batch_prune", _net, synth_sql("part_hops", 100, _NET + " select kind, u, v from net"))
add("batch_classify", lambda s, d: batch.classify(_net(s, d), index(s, d, "part_hops").membership).select("kind", "u", "v", "class"), synth_sql("part_hops", 100, f"{COMPS}, {_NET} select kind, u, v, kind[1:3] || case when coalesce(a.comp, u) = coalesce(b.comp, v) then '_intra' else '_inter' end \"class\" from net left join m a on a.node = u left join m b on b.node = v where kind in ('insert_edge', 'delete_edge')"))
add("batch_condense_ops", lambda s, d: batch.condense_ops(_net(s, d)), synth_sql("part_hops", 100, f"{_NET}, ie as (select u src, v dst from net where kind = 'insert_edge'), inn as (select src node from ie union select dst from ie), {COMPS.replace(' from e ', ' from ie ').replace('join e on e.src', 'join ie on ie.src').replace('e.dst', 'ie.dst').replace('from n left', 'from inn left')} select node, comp from m"))

# single kinds of updates on user_hops: edges between fixed pairs, deletions of every fifth edge, nodes

_UH_PAIRS = G.sql_pairs(40)
_NO = "kill as (select 0::bigint op_id, 0::bigint node where false), born as (select 0::bigint op_id, 0::bigint node where false)"


def _kind_sql(ops: str, graph: str = "user_hops") -> str:
    return final_sql(G.SQL[graph], ops, REACH_FINAL)


def _numbered(s, d):
    return GEN.edge_ranks(edges(s, d, "user_hops"))


#: Batches that never rebuild, in one task where they fit or by sets alone, and the ways to decompose.
STEPS, SETS = EngineConf(rebuild_ratio=100.0), EngineConf(rebuild_ratio=100.0, local_rows=0)
NAIVE, EXTRACT = EngineConf(rebuild_ratio=100.0, split="naive"), EngineConf(rebuild_ratio=100.0, split="extract")


def _changed(s, d, name, change) -> Index:
    ix = kept(s, (d, "after", name), lambda: change(index(s, d, "user_hops", 2)))
    if ix.facts["rebuilt"]:
        raise AssertionError("the index was rebuilt instead of changed")
    return ix


def _after(s, d, name, change) -> DataFrame:
    return answers_after(_changed(s, d, name, change))


_PLACES = "ee as (select src, dst, row_number() over (order by dst, src) - 1 place from e)"
_NIL = "select 0::bigint op_id, 0::bigint src, 0::bigint dst where false"
add("insert_edges_then_reach", lambda s, d: _after(s, d, "ei", lambda ix: U.insert_edges(ix, asked(s, d, "user_hops", 40).select("u", "v"), conf=STEPS)), _kind_sql(f"ins as (select 0::bigint op_id, u src, v dst from ({_UH_PAIRS})), del as ({_NIL}), {_NO}"))
add("insert_edges_by_sets_then_reach", lambda s, d: _after(s, d, "ei2", lambda ix: U.insert_edges(ix, asked(s, d, "user_hops", 40).select("u", "v"), conf=SETS)), _kind_sql(f"ins as (select 0::bigint op_id, u src, v dst from ({_UH_PAIRS})), del as ({_NIL}), {_NO}"))
for _name, _conf in (("", STEPS), ("_by_sets", SETS), ("_naive", NAIVE), ("_extract", EXTRACT)):
    _cut = lambda s, d, name=_name, conf=_conf: _changed(s, d, "ed" + name, lambda ix: U.delete_edges(ix, _numbered(s, d).where("place % 6 = 0").select(F.col("src").alias("u"), F.col("dst").alias("v")), conf=conf))
    add(f"delete_edges{_name}_then_reach", lambda s, d, cut_=_cut: answers_after(cut_(s, d)), _kind_sql(f"{_PLACES}, ins as ({_NIL}), del as (select 0::bigint op_id, src, dst from ee where place % 6 = 0), {_NO}"))
    for _what, _sql in (("membership", " select node, comp from m"), ("dag_edges", ", " + FINAL_DAG + " select s, t, mult from dag")):
        add(f"split{_name}_{_what}", lambda s, d, cut_=_cut, what=_what: getattr(cut_(s, d), what), final_sql(G.SQL["user_hops"], f"{_PLACES}, ins as ({_NIL}), del as (select 0::bigint op_id, src, dst from ee where place % 6 = 0), {_NO}", FINAL_COMPS + _sql))
    add(f"split{_name}_labels_hold", lambda s, d, cut_=_cut: L.violations(cut_(s, d).labels, cut_(s, d).dag_edges).agg(F.count("*").alias("broken")), "select 0::bigint broken")
add("insert_nodes_then_reach", lambda s, d: _after(s, d, "ni", lambda ix: U.insert_nodes(ix, _numbered(s, d).where("place % 10 = 0").select((F.col("place") + 1_000_000).alias("u"), F.array("dst").alias("outs"), F.array("src").alias("ins")), conf=STEPS)), _kind_sql(f"{_PLACES}, ins as (select 0::bigint op_id, place + 1000000 src, dst from ee where place % 10 = 0 union all select 0, src, place + 1000000 from ee where place % 10 = 0), del as ({_NIL}), kill as (select 0::bigint op_id, 0::bigint node where false), born as (select 0::bigint op_id, place + 1000000 node from ee where place % 10 = 0)"))
add("delete_nodes_then_reach", lambda s, d: _after(s, d, "nd", lambda ix: U.delete_nodes(ix, ix.nodes.where("node % 8 = 0").select(F.col("node").alias("u")), conf=STEPS)), _kind_sql(f"ins as ({_NIL}), del as ({_NIL}), kill as (select 0::bigint op_id, node from n where node % 8 = 0), born as (select 0::bigint op_id, 0::bigint node where false)"))


def _as_of(s: SparkSession, d: str) -> DataFrame:
    first = index(s, d, "user_hops", 2)
    later = kept(s, (d, "after", "nd"), lambda: U.delete_nodes(first, first.nodes.where("node % 8 = 0").select(F.col("node").alias("u")), conf=STEPS))
    p = asked(s, d, "user_hops").withColumn("op_id", F.when(F.col("qid") % 2 == 0, 0).otherwise(5))
    return Q.reach_as_of({0: first, 5: later}, p).select(*ANSWER)


add(
    "reach_as_of",
    _as_of,
    with_graph("user_hops", f"fe as (select src, dst from e where src % 8 <> 0 and dst % 8 <> 0), p as materialized ({G.sql_pairs()}), r(root, x) as (select distinct u, dst from p join e on src = u union select root, dst from r join e on src = x), z(root, x) as (select distinct u, dst from p join fe on src = u union select root, dst from z join fe on src = x) select qid, u, v, case when qid % 2 = 0 then u = v or r.x is not null else u % 8 <> 0 and v % 8 <> 0 and (u = v or z.x is not null) end reachable from p left join r on r.root = u and r.x = v left join z on z.root = u and z.x = v"),
)

# the example's what-ifs, through batches and one by one

_EX = {
    "insert_c_j": ([("insert_edge", 2, 9)], "ins as (select 0::bigint op_id, 2::bigint src, 9::bigint dst)", _NIL),
    "insert_n_b": ([("insert_edge", 13, 1)], "ins as (select 0::bigint op_id, 13::bigint src, 1::bigint dst)", _NIL),
    "delete_h_l": ([("delete_edge", 7, 11)], f"ins as ({_NIL})", "select 0::bigint op_id, 7::bigint src, 11::bigint dst"),
    "delete_d_g": ([("delete_edge", 3, 6)], f"ins as ({_NIL})", "select 0::bigint op_id, 3::bigint src, 6::bigint dst"),
    "merge_then_delete_l_p": ([("insert_edge", 13, 1), ("delete_edge", 11, 15)], "ins as (select 0::bigint op_id, 13::bigint src, 1::bigint dst)", "select 1::bigint op_id, 11::bigint src, 15::bigint dst"),
    "merge_then_split": ([("insert_edge", 13, 1), ("delete_edge", 11, 15), ("delete_edge", 13, 1)], "ins as (select 0::bigint op_id, 13::bigint src, 1::bigint dst)", "select 1::bigint op_id, 11::bigint src, 15::bigint dst union all select 2, 13, 1"),
}


def example_ops(s: SparkSession, ops: list[tuple]) -> DataFrame:
    return s.createDataFrame([(i, None, kind, u, v, None, None) for i, (kind, u, v) in enumerate(ops)], "op_id long, ts timestamp_ntz, kind string, u long, v long, outs array<long>, ins array<long>")


for _name, (_ops, _ins, _del) in _EX.items():
    _sql = final_sql(G.SQL["example_graph"], f"{_ins}, del as ({_del}), {_NO}", f"{FINAL_COMPS}, {FINAL_DAG} select s, t, mult from dag")
    add(f"w_example_{_name}", lambda s, d, ops=_ops: _stepwise(s, d, ops).dag_edges, _sql)


def _stepwise(s: SparkSession, d: str, ops: list[tuple]) -> Index:
    """One batch an operation, so that merges and splits happen in turn."""
    ix = index(s, d, "example_graph", 2)
    for op in ops:
        ix = batch.apply(ix, example_ops(s, [op]), conf=STEPS)
    return ix


# the case of every operation, from the kernel's log: (R,D) has (R,E) beside it, and E hangs on (D,E) alone
_CASES = [("insert_edge", 17, 0), ("insert_edge", 0, 2), ("insert_edge", 0, 7), ("insert_edge", 10, 12), ("insert_edge", 13, 1), ("delete_edge", 0, 18), ("delete_edge", 0, 7), ("delete_edge", 17, 3), ("delete_edge", 3, 4), ("delete_edge", 13, 1)]
add(
    "update_cases_example",
    lambda s, d: U.sequential(index(s, d, "example_graph").nodes, edges(s, d, "example_graph"), example_ops(s, _CASES), 2)[0].select("op_id", "kind", "case"),
    "select * from (values (0::bigint, 'insert_edge', 'I0'), (1, 'insert_edge', 'I1'), (2, 'insert_edge', 'I2'), (3, 'insert_edge', 'I4'), (4, 'insert_edge', 'I5'), (5, 'delete_edge', 'D0'), (6, 'delete_edge', 'D3'), (7, 'delete_edge', 'D1'), (8, 'delete_edge', 'D4'), (9, 'delete_edge', 'D4')) x(op_id, kind, \"case\")",
)
# a covered pair gets its first edge, which is also the last to go; nodes come, come again and go
_MORE_CASES = [("insert_edge", 17, 12, None), ("delete_edge", 17, 12, None), ("insert_node", 30, None, [17, 3]), ("insert_node", 30, None, [0]), ("delete_node", 30, None, None), ("delete_node", 30, None, None), ("delete_edge", 0, 30, None)]
add(
    "update_cases_nodes_example",
    lambda s, d: U.sequential(index(s, d, "example_graph").nodes, edges(s, d, "example_graph"), s.createDataFrame([(i, None, kind, u, v, outs, None) for i, (kind, u, v, outs) in enumerate(_MORE_CASES)], OPS), 2)[0].select("op_id", "kind", "case"),
    "select * from (values (0::bigint, 'insert_edge', 'I3'), (1, 'delete_edge', 'D2'), (2, 'insert_node', 'N0'), (3, 'insert_node', 'N1'), (4, 'delete_node', 'N2'), (5, 'delete_node', 'D0'), (6, 'delete_edge', 'D0')) x(op_id, kind, \"case\")",
)
for _name, _modes in (("two_phase", {}), ("fixpoint", {"propagate": "fixpoint"}), ("unordered", {"propagate": "unordered"}), ("naive_split", {"split": "naive"}), ("shrink", {"shrink": True})):
    add(
        f"sequential_{_name}",
        lambda s, d, modes=_modes: U.sequential(index(s, d, "part_hops").nodes, edges(s, d, "part_hops"), kept(s, (d, "seq-ops"), lambda: cut(GEN.update_sequence(edges(s, d, "part_hops"), 100))), 2, **modes)[1],
        synth_sql("part_hops", 100, FINAL_COMPS + " select node, comp from m"),
    )
_LESS = "fe as (select * from e where src <> 7), fn as (select src node from fe union select dst from fe), " + FINAL_COMPS + " select node, comp from m"
add("rebuild_each_example", lambda s, d: B.rebuild_each(index(s, d, "example_graph"), [edges(s, d, "example_graph").where("src <> 7")])[0].membership, with_graph("example_graph", _LESS))

# generators, measures and the sweep

add("gen_er", lambda s, d: GEN.er_graph(s, 5000, 7500), GEN.er_sql(5000, 7500))


def _grown(s: SparkSession, d: str) -> DataFrame:
    """Preferential attachment of the customers, who come in the order of their keys."""
    at = cut(G.ranks(G.read(s, d, "customer").select(F.col("c_custkey").alias("node"))))
    made = GEN.ba_graph(s, at.count())
    a, b = at.select(F.col("rank").alias("src"), F.col("node").alias("a")), at.select(F.col("rank").alias("dst"), F.col("node").alias("b"))
    return made.join(a, "src").join(b, "dst").select(F.col("a").alias("src"), F.col("b").alias("dst"))


add("gen_ba", _grown)
add("gen_update_sequence", lambda s, d: GEN.update_sequence(edges(s, d, "part_hops"), 100).select("op_id", "kind", "u", "v"), synth_sql("part_hops", 100, "q as (select 1) select op_id, kind, case kind when 'insert_edge' then picked when 'insert_node' then fresh else picked end u, case when kind = 'insert_edge' then d1 end v from raw where kind <> 'delete_edge' union all select op_id, 'delete_edge', s1, d1 from gone"))
add("gen_pairs", lambda s, d: GEN.query_pairs(index(s, d, "part_hops").nodes, 300), with_graph("part_hops", f"nn as (select node, row_number() over (order by node) - 1 r from n), a as (select range qid, {GEN.mix_sql('(range*2)', 9)} % (select count(*) from n) ru, {GEN.mix_sql('(range*2+1)', 9)} % (select count(*) from n) rv from range(300)) select qid, x.node u, y.node v from a join nn x on x.r = ru join nn y on y.r = rv", False))


def _versions(s: SparkSession, d: str) -> DataFrame:
    e = G.read(s, d, "events").where("event_type in ('view', 'purchase')")
    return e.select(F.col("user_id").alias("src"), (F.get_json_object("props", "$.k").cast("long") % 5 + 1_000_000).alias("dst"), F.col("ts"), (F.col("event_type") == "view").alias("present"), "event_id").withColumn("ts", F.unix_micros(F.col("ts").cast("timestamp"))).drop("event_id")


_VERSIONS = "select user_id src, (props->>'$.k')::bigint % 5 + 1000000 dst, epoch_us(ts) ts, event_type = 'view' present from events where event_type in ('view', 'purchase')"
_CUT = "(select quantile_disc(ts, 0.8) from v)"


def _evolution(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    v = cut(_versions(s, d))
    return GEN.evolution(v, v.selectExpr("percentile_disc(0.8) within group (order by ts) c").first()[0])


_CHANGED = f"v as ({_VERSIONS}), w as (select *, coalesce(lag(present) over (partition by src, dst order by ts), false) b from v), x as (select * from w where present <> b)"
add("evolution_snapshot", lambda s, d: _evolution(s, d)[0], f"with {_CHANGED} select src, dst from x where ts < {_CUT} group by 1, 2 having arg_max(present, ts)")
add("evolution_changes", lambda s, d: _evolution(s, d)[1], f"with {_CHANGED} select ts, case when present then 'insert_edge' else 'delete_edge' end kind, src u, dst v from x where ts >= {_CUT}")
add("label_false_positives", lambda s, d: M.label_fp(index(s, d, "part_hops", 1), Q.reach_batch(index(s, d, "part_hops", 1), asked(s, d, "part_hops"))))
add("query_expansion", lambda s, d: M.expansion(Q.reach_batch(index(s, d, "part_hops", 1), asked(s, d, "part_hops"))))


#: Operations timed one by one, each with eight questions to every method after it: the length of the sequence.
_TIMED = {"wiki_like": 1000, "citation": 1000, "uniform": 300, "hub": 100}


def _times(s: SparkSession, d: str, name: str = "uniform") -> DataFrame:
    def make():
        base, ops = W.WORKLOADS[name](s, d)
        return cut(W.op_times(cut(base), cut(ops), most_ops=_TIMED[name]))

    return kept(s, (d, "times", name), make)


for _name in W.WORKLOADS:
    add(f"w_op_times_{_name}", lambda s, d, name=_name: _times(s, d, name))
    add(f"w_qpu_sweep_{_name}", lambda s, d, name=_name: W.sweep(_times(s, d, name)))
    add(f"w_break_even_{_name}", lambda s, d, name=_name: W.break_even(W.sweep(_times(s, d, name))))
    # all methods are asked the same questions on the same graph after each operation, and give the same answers
    add(f"w_methods_agree_{_name}", lambda s, d, name=_name: _times(s, d, name).where("measure = 'Q'").agg(F.count("*").alias("methods"), F.count_distinct("answers", "reached", "n").alias("answers"), F.min(F.col("reached") > 0).alias("some_reach")), "select 4::bigint methods, 1::bigint answers, true some_reach")


def _answers(s: SparkSession, d: str, name: str) -> DataFrame:
    base, ops = _SEQUENCES[name][0](s, d)
    there, _ = batch.final_state(G.nodes_of(base), base, ops)
    return W.answers_of_methods(base, ops, G.pairs_fixed(cut(there), 100)).select("method", *ANSWER)


_SEQUENCES = {
    "wiki_like": (W.ops_wiki_like, lambda rest: final_sql(WIKI_BASE, WIKI, rest)),
    "citation": (W.ops_citation, lambda rest: final_sql(CITE_BASE, CITE, rest)),
    "uniform": (lambda s, d: (edges(s, d, "uniform_pairs"), GEN.update_sequence(edges(s, d, "uniform_pairs"), 1000)), lambda rest: synth_sql("uniform_pairs", 1000, rest)),
    "hub": (lambda s, d: (edges(s, d, "goods_flow"), GEN.update_sequence(edges(s, d, "goods_flow"), 1000)), lambda rest: synth_sql("goods_flow", 1000, rest)),
}
for _name in _SEQUENCES:
    add(f"w_answers_{_name}", lambda s, d, name=_name: _answers(s, d, name), _SEQUENCES[_name][1](REACH_FINAL + " cross join (values ('search'), ('idx(0)'), ('idx(1)'), ('idx(2)')) methods(method)").replace("select p.qid, p.u", "select method, p.qid, p.u"))
add("op_log_cases", lambda s, d: M.cases(U.sequential(index(s, d, "part_hops").nodes, edges(s, d, "part_hops"), GEN.update_sequence(edges(s, d, "part_hops"), 100), 1)[0]))
add("sql_reach_view", lambda s, d: _sql_view(s, d), with_graph("part_hops", COMPS + " select comp, count(*) size from m group by 1 having count(*) > 1"))


def _sql_view(s: SparkSession, d: str) -> DataFrame:
    from dynreach.sqlapi import register

    register(index(s, d, "part_hops"))
    return s.sql("select comp, size from components where size > 1")


# relational surface and streams

for _name, (_f, _sql) in relational.ENTRIES.items():
    add(_name, _f, _sql)


def _streams() -> None:
    from dynreach.streaming import queries as S

    S.complete()
    for name, (f, sql) in S.ENTRIES.items():
        add(name, f, sql)


_streams()
