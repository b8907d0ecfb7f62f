"""The relational surface around the engine: each entry is a DataFrame query on the given tables with its SQL twin."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dynreach.plans.loops import cut
from dynreach.sources import graphs as G

ENTRIES: dict[str, tuple] = {}


def entry(sql: str):
    def keep(f):
        ENTRIES[f.__name__] = (f, sql)
        return f

    return keep


def t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return G.read(spark, d, name)


OC, UH, GF, GL, PH = (G.sql_edges(g) for g in ("order_citation", "user_hops", "goods_flow", "goods_flow_light", "part_hops"))


@entry(f"select count(*) n, min(src) low, max(dst) high from ({OC})")
def scan_edges(s, d):
    return G.order_citation(s, d).agg(F.count("*").alias("n"), F.min("src").alias("low"), F.max("dst").alias("high"))


@entry("select event_id, (props->>'$.k')::int k from events")
def scan_events_json(s, d):
    return t(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@entry("select page_id, (i-1)::int as \"position\", l[i] href from (select page_id, l, unnest(range(1, len(l)+1)) i from (select page_id, regexp_extract_all(html, '<a href=\"([^\"]*)\"', 1) l from pages))")
def scan_links(s, d):
    return G.links(s, d).select("page_id", F.col("position").cast("int").alias("position"), "href")


@entry(f"select src, dst from ({PH})")
def sink_roundtrip(s, d):
    """Written partitioned by bucket and read again with its schema, through the checkpoint folder all executors share."""
    import uuid

    from dynreach.plans.loops import ensure_checkpoint_dir

    ensure_checkpoint_dir(s)
    path = f"{s.sparkContext.getCheckpointDir()}/sink-{uuid.uuid4().hex}"
    G.part_hops(s, d).withColumn("bucket", F.pmod(F.xxhash64("src"), F.lit(8)).cast("int")).write.partitionBy("bucket").parquet(path)
    return s.read.schema("src long, dst long, bucket int").parquet(path).select("src", "dst")


@entry("select l_orderkey src, l_partkey dst, l_returnflag flag from lineitem")
def proj_edges(s, d):
    return t(s, d, "lineitem").select(F.col("l_orderkey").alias("src"), F.col("l_partkey").alias("dst"), F.col("l_returnflag").alias("flag"))


@entry("select l_orderkey, l_partkey, l_linenumber, l_suppkey, l_shipdate from lineitem where l_returnflag in ('R','N') and l_quantity between 5 and 12 and l_shipdate >= timestamp '1995-06-01'")
def filter_edges(s, d):
    rows = t(s, d, "lineitem").where(F.col("l_returnflag").isin("R", "N") & F.col("l_quantity").between(5, 12) & (F.col("l_shipdate") >= F.lit("1995-06-01").cast("timestamp_ntz")))
    return rows.select("l_orderkey", "l_partkey", "l_linenumber", "l_suppkey", "l_shipdate")


@entry("select event_id from (select event_id, event_type, lag(event_type) over (partition by user_id order by ts, event_id) b from events) where b is not distinct from event_type or b is null")
def filter_null_safe(s, d):
    before = F.lag("event_type").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    return t(s, d, "events").withColumn("b", before).where(F.col("b").eqNullSafe(F.col("event_type")) | F.col("b").isNull()).select("event_id")


@entry("select l_suppkey, count(*) n from lineitem join supplier on s_suppkey = l_suppkey where s_nationkey = 3 group by 1")
def join_broadcast_frontier(s, d):
    from dynreach.operators.joins import bounded

    few = bounded(t(s, d, "supplier").where("s_nationkey = 3").select("s_suppkey"))
    return t(s, d, "lineitem").select("l_suppkey").join(few, F.col("l_suppkey") == F.col("s_suppkey")).groupBy("l_suppkey").agg(F.count("*").alias("n"))


def _orders_of_lines(s, d, hint):
    lines = t(s, d, "lineitem").select("l_orderkey", "l_quantity")
    orders = t(s, d, "orders").select("o_orderkey", "o_custkey").hint(hint)
    return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_custkey").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("quantity"))


_LINES = "select o_custkey, count(*) n, sum(l_quantity::bigint)::bigint quantity from lineitem join orders on o_orderkey = l_orderkey group by 1"


@entry(_LINES)
def join_sortmerge_edges(s, d):
    return _orders_of_lines(s, d, "merge")


@entry(_LINES)
def join_shuffle_hash_edges(s, d):
    return _orders_of_lines(s, d, "shuffle_hash")


@entry("select a.p_partkey a, b.p_partkey b from part a join part b on a.p_brand = b.p_brand and b.p_size = a.p_size + 1 and a.p_retailprice < b.p_retailprice where a.p_brand = (select min(p_brand) from part)")
def join_theta_size(s, d):
    part = t(s, d, "part").select("p_partkey", "p_brand", "p_size", "p_retailprice")
    brand = part.agg(F.min("p_brand").alias("p_brand"))
    one = part.join(F.broadcast(brand), "p_brand")  # one row
    a, b = (one.select(F.col("p_partkey").alias(x), (F.col("p_size") + int(x == "a")).alias("size"), F.col("p_retailprice").alias(f"p{x}")) for x in "ab")
    return a.join(b, "size").where("pa < pb").select("a", "b")


_TREE = """region_iv as (select r_regionkey*8+5 node, r_regionkey*1000 b, r_regionkey*1000+999 e from region),
nation_iv as (select n_nationkey*8+4 node, n_regionkey*1000+n_nationkey*10 b, n_regionkey*1000+n_nationkey*10+9 e from nation),
iv as (select * from region_iv union all select * from nation_iv)"""


def tree_intervals(s, d) -> DataFrame:
    """(node, b, e): fixed labels of regions and nations."""
    r = t(s, d, "region").select((F.col("r_regionkey") * 8 + 5).cast("long").alias("node"), (F.col("r_regionkey") * 1000).cast("long").alias("b"), (F.col("r_regionkey") * 1000 + 999).cast("long").alias("e"))
    at = F.col("n_regionkey") * 1000 + F.col("n_nationkey") * 10
    return r.union(t(s, d, "nation").select((F.col("n_nationkey") * 8 + 4).cast("long"), at.cast("long"), (at + 9).cast("long")))


@entry(f"with {_TREE} select a.node::bigint above, b.node::bigint below from iv a join iv b on a.b <= b.b and b.e < a.e")
def join_label_range(s, d):
    from dynreach.operators.joins import range_join

    iv = tree_intervals(s, d)
    return range_join(iv, iv, width=100).select("above", "below")


@entry("select p.event_id purchase, (select v.event_id from events v where v.user_id = p.user_id and v.event_type = 'view' and (v.ts, v.event_id) < (p.ts, p.event_id) order by v.ts desc, v.event_id desc limit 1) as \"view\" from events p where p.event_type = 'purchase'")
def join_asof_ops(s, d):
    from dynreach.operators.joins import asof_last

    e = t(s, d, "events").select("event_id", "ts", "user_id", "event_type")
    return asof_last(e, "user_id", ["ts", "event_id"], F.col("event_type") == "view", F.col("event_type") == "purchase", "event_id").select(F.col("event_id").alias("purchase"), F.col("last").alias("view"))


@entry(f"with e as ({OC}), n as ({G.sql_nodes()}) select o_orderkey, coalesce(node is not null, false) linked from orders left join n on node = o_orderkey")
def join_left_membership(s, d):
    n = G.nodes_of(G.order_citation(s, d))
    return t(s, d, "orders").select("o_orderkey").join(n, F.col("o_orderkey") == F.col("node"), "left").select("o_orderkey", F.col("node").isNotNull().alias("linked"))


@entry(f"with e as ({PH}) select coalesce(a.src, b.dst) node, coalesce(o, 0) outs, coalesce(i, 0) ins from (select src, count(*) o from e group by 1) a full join (select dst, count(*) i from e group by 1) b on a.src = b.dst")
def join_full_degrees(s, d):
    e = G.part_hops(s, d)
    a, b = e.groupBy("src").agg(F.count("*").alias("o")), e.groupBy("dst").agg(F.count("*").alias("i"))
    return a.join(b, F.col("src") == F.col("dst"), "full").select(F.coalesce("src", "dst").alias("node"), F.coalesce("o", F.lit(0)).alias("outs"), F.coalesce("i", F.lit(0)).alias("ins"))


@entry(f"select p_partkey from part where p_partkey in (select src from ({PH}))")
def semi_reached(s, d):
    return t(s, d, "part").select("p_partkey").join(G.part_hops(s, d), F.col("p_partkey") == F.col("src"), "left_semi")


@entry(f"select p_partkey from part where p_partkey not in (select src from ({PH}))")
def anti_unvisited(s, d):
    return t(s, d, "part").select("p_partkey").join(G.part_hops(s, d), F.col("p_partkey") == F.col("src"), "left_anti")


@entry(f"with e as ({UH}) select distinct a.src, b.dst from e a join e b on a.dst = b.src")
def join_two_hop(s, d):
    e = cut(G.user_hops(s, d))
    return e.select("src", F.col("dst").alias("mid")).join(e.select(F.col("src").alias("mid"), "dst"), "mid").select("src", "dst").distinct()


@entry("select c_custkey, o_orderkey from (select o_custkey c_custkey, o_orderkey, row_number() over (partition by o_custkey order by o_orderdate desc, o_orderkey desc) r from orders) where r <= 2")
def lateral_topn(s, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_orderdate"), F.desc("o_orderkey"))
    return t(s, d, "orders").withColumn("r", F.row_number().over(w)).where("r <= 2").select(F.col("o_custkey").alias("c_custkey"), "o_orderkey")


@entry(f"select src, count(*) degree from ({GL}) group by 1")
def agg_degree(s, d):
    return G.goods_flow_light(s, d).groupBy("src").agg(F.count("*").alias("degree"))


@entry("select c_nationkey::int nation, l_suppkey, count(*) mult from lineitem join orders on o_orderkey = l_orderkey join customer on c_custkey = o_custkey group by 1, 2")
def agg_multiplicity(s, d):
    lines, orders, customer = t(s, d, "lineitem").select("l_orderkey", "l_suppkey"), t(s, d, "orders").select("o_orderkey", "o_custkey"), t(s, d, "customer").select("c_custkey", "c_nationkey")
    rows = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))
    return rows.groupBy(F.col("c_nationkey").alias("nation"), "l_suppkey").agg(F.count("*").alias("mult"))


@entry("select l_orderkey, count(distinct l_partkey) parts from lineitem group by 1")
def agg_distinct_targets(s, d):
    return t(s, d, "lineitem").groupBy("l_orderkey").agg(F.count_distinct("l_partkey").alias("parts"))


@entry("with g as (select l_suppkey, count(*) n from lineitem group by 1) select l_suppkey, n from g where n * (select count(*) from g) > (select sum(n) from g)")
def agg_having_hubs(s, d):
    g = t(s, d, "lineitem").groupBy("l_suppkey").agg(F.count("*").alias("n"))
    whole = g.agg(F.sum("n").alias("total"), F.count("*").alias("groups"))
    return g.join(F.broadcast(whole)).where("n * groups > total").select("l_suppkey", "n")  # one row


@entry("select l_linenumber, count(*) filter (where l_returnflag = 'R') r, count(*) filter (where l_linestatus = 'O') o from lineitem group by 1")
def agg_filter_clause(s, d):
    return t(s, d, "lineitem").groupBy("l_linenumber").agg(F.count_if(F.col("l_returnflag") == "R").alias("r"), F.count_if(F.col("l_linestatus") == "O").alias("o"))


@entry(f"select quantile_disc(degree, 0.5)::bigint median from (select src, count(*) degree from ({GL}) group by 1)")
def agg_percentile(s, d):
    return agg_degree(s, d).select(F.expr("percentile_disc(0.5) within group (order by degree)").cast("long").alias("median"))


@entry("select r_name, n_name, count(*) n from customer join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey group by rollup (r_name, n_name)")
def agg_rollup_geo(s, d):
    geo = t(s, d, "nation").join(t(s, d, "region"), F.col("r_regionkey") == F.col("n_regionkey")).select("n_nationkey", "n_name", "r_name")
    return t(s, d, "customer").select("c_nationkey").join(geo, F.col("n_nationkey") == F.col("c_nationkey")).rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@entry("select l_returnflag, l_linestatus, count(*) n from lineitem group by cube (l_returnflag, l_linestatus)")
def agg_cube_flags(s, d):
    return t(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@entry("select o_orderstatus, o_orderpriority, count(*) n from orders group by grouping sets ((o_orderstatus), (o_orderpriority))")
def agg_grouping_sets(s, d):
    status, priority = F.col("o_orderstatus"), F.col("o_orderpriority")
    return t(s, d, "orders").groupingSets([[status], [priority]], status, priority).agg(F.count("*").alias("n"))


_TYPES = ["view", "click", "purchase", "signup", "error"]


@entry("select user_id, " + ", ".join(f"count(*) filter (where event_type = '{x}') as \"{x}\"" for x in _TYPES) + " from events group by 1")
def pivot_event_types(s, d):
    return t(s, d, "events").groupBy("user_id").pivot("event_type", _TYPES).count().na.fill(0)


@entry(f"with e as ({PH}), g as (select coalesce(a.src, b.dst) node, coalesce(o, 0) outs, coalesce(i, 0) ins from (select src, count(*) o from e group by 1) a full join (select dst, count(*) i from e group by 1) b on a.src = b.dst) select node, 'outs' side, outs n from g union all select node, 'ins', ins from g")
def unpivot_degrees(s, d):
    return join_full_degrees(s, d).unpivot("node", ["outs", "ins"], "side", "n")


@entry(f"select src, rank() over (order by degree desc) rk, dense_rank() over (order by degree desc) dr, row_number() over (order by degree desc, src) rn from (select src, count(*) degree from ({PH}) group by 1)")
def win_rank_hubs(s, d):
    g = G.part_hops(s, d).groupBy("src").agg(F.count("*").alias("degree"))
    w = Window.orderBy(F.desc("degree"))
    return g.select("src", F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.row_number().over(Window.orderBy(F.desc("degree"), "src")).alias("rn"))


@entry("select p_partkey, ntile(4) over (partition by p_brand order by p_retailprice, p_partkey) quartile from part")
def win_ntile(s, d):
    return t(s, d, "part").select("p_partkey", F.ntile(4).over(Window.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")).alias("quartile"))


@entry("select o_orderkey, lag(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey) prev from orders")
def win_lag_prev_order(s, d):
    return t(s, d, "orders").select("o_orderkey", F.lag("o_orderkey").over(Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")).alias("prev"))


@entry("select event_id, count(*) over (partition by user_id order by ts, event_id rows unbounded preceding) n from events")
def win_running_edges(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return t(s, d, "events").select("event_id", F.count("*").over(w).alias("n"))


@entry("select event_id, count(*) over (partition by user_id order by epoch(ts)::bigint range between 604800 preceding and current row) n from (select event_id, user_id, date_trunc('second', ts) ts from events)")
def win_range_7d(s, d):
    w = Window.partitionBy("user_id").orderBy("at").rangeBetween(-604800, 0)
    at = F.unix_seconds(F.date_trunc("second", F.col("ts").cast("timestamp")))
    return t(s, d, "events").select("event_id", "user_id", at.alias("at")).select("event_id", F.count("*").over(w).alias("n"))


@entry(f"select dst, count(*) degree from ({GL}) group by 1 order by degree desc, dst limit 10")
def topk_hubs(s, d):
    return G.goods_flow_light(s, d).groupBy("dst").agg(F.count("*").alias("degree")).orderBy(F.desc("degree"), "dst").limit(10)


@entry("select p_brand, p_partkey from (select p_brand, p_partkey, row_number() over (partition by p_brand order by p_retailprice desc, p_partkey) r from part) where r <= 3")
def topk_per_group(s, d):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return t(s, d, "part").withColumn("r", F.row_number().over(w)).where("r <= 3").select("p_brand", "p_partkey")


@entry("select event_id, row_number() over (order by b nulls last, event_id desc) as \"place\" from (select event_id, lag(event_type) over (partition by user_id order by ts, event_id) b from events)")
def sort_multi(s, d):
    b = F.lag("event_type").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    rows = t(s, d, "events").select("event_id", b.alias("b"))
    return rows.select("event_id", F.row_number().over(Window.orderBy(F.asc_nulls_last("b"), F.desc("event_id"))).alias("place"))


@entry(f"select src, dst from ({GF}) union select src, dst from ({GL})")
def set_union_edges(s, d):
    return G.goods_flow(s, d).union(G.goods_flow_light(s, d)).distinct()


@entry(f"select src, dst from ({GF}) intersect select src, dst from ({GL})")
def set_intersect(s, d):
    return G.goods_flow(s, d).intersect(G.goods_flow_light(s, d))


@entry(f"select src, dst from ({GF}) except select src, dst from ({GL})")
def set_except(s, d):
    return G.goods_flow(s, d).exceptAll(G.goods_flow_light(s, d)).distinct()


@entry("select l_partkey node from lineitem where l_quantity <= 40 except all select l_partkey from lineitem where l_returnflag = 'R' and l_quantity <= 40")
def set_except_all(s, d):
    lines = t(s, d, "lineitem").where("l_quantity <= 40").select(F.col("l_partkey").alias("node"), "l_returnflag")
    return lines.select("node").exceptAll(lines.where("l_returnflag = 'R'").select("node"))


@entry("select o_orderkey from orders where exists (select 1 from lineitem where l_orderkey = o_orderkey and l_returnflag = 'R')")
def subq_exists(s, d):
    t(s, d, "orders").createOrReplaceTempView("rel_orders")
    t(s, d, "lineitem").createOrReplaceTempView("rel_lineitem")
    return s.sql("select o_orderkey from rel_orders where exists (select 1 from rel_lineitem where l_orderkey = o_orderkey and l_returnflag = 'R')")


@entry("select l_orderkey, count(*) n from lineitem where l_quantity > (select avg(l_quantity) from lineitem) group by 1")
def subq_scalar(s, d):
    t(s, d, "lineitem").createOrReplaceTempView("rel_lineitem")
    return s.sql("select l_orderkey, count(*) n from rel_lineitem where l_quantity > (select avg(l_quantity) from rel_lineitem) group by 1")


_RECURSIVE = "with recursive below(root, node, depth) as (select src, dst, 1 from {e} where src % 8 = 5 union all select root, dst, depth + 1 from below join {e} on src = node where depth < 4) select root, count(*) n from below group by 1"


@entry(_RECURSIVE.format(e=f"({G.sql_edges('containment_tree')})"))
def cte_recursive_reach(s, d):
    cut(G.containment_tree(s, d)).createOrReplaceTempView("rel_tree")
    limit = "spark.sql.cteRecursionRowLimit"  # the depth is bounded by the query, its rows are as many as the tree has below regions
    before = s.conf.get(limit)
    s.conf.set(limit, -1)
    try:
        return cut(s.sql(_RECURSIVE.format(e="rel_tree")))
    finally:
        s.conf.set(limit, before)


@entry("select page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) host, upper(substring(url, 1, 4)) scheme, len(string_split(url, '/')) parts from pages")
def fn_string(s, d):
    return t(s, d, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"), F.upper(F.substring("url", 1, 4)).alias("scheme"), F.size(F.split("url", "/", -1)).cast("long").alias("parts"))


@entry("select o_orderkey, strftime(o_orderdate, '%Y-%m') bucket, date_diff('day', date '1992-01-01', o_orderdate::date)::int as \"days\" from orders")
def fn_date(s, d):
    return t(s, d, "orders").select("o_orderkey", F.date_format("o_orderdate", "yyyy-MM").alias("bucket"), F.date_diff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("days"))


@entry(f"select src, (src % 7)::bigint modulo, floor(log2(degree))::bigint magnitude, greatest(degree, 3) at_least from (select src, count(*) degree from ({PH}) group by 1)")
def fn_math(s, d):
    g = G.part_hops(s, d).groupBy("src").agg(F.count("*").alias("degree"))
    return g.select("src", F.pmod("src", F.lit(7)).cast("long").alias("modulo"), F.floor(F.log2("degree")).alias("magnitude"), F.greatest("degree", F.lit(3)).cast("long").alias("at_least"))


@entry(f"select src, array_to_string(list_sort(list(dst)), ',') heads from ({PH}) group by 1")
def fn_adjacency_array(s, d):
    return G.part_hops(s, d).groupBy("src").agg(F.array_join(F.array_sort(F.collect_list("dst")).cast("array<string>"), ",").alias("heads"))


@entry(f"with g as (select src, list(dst) heads from ({UH}) group by 1) select src, len(list_filter(heads, lambda x: x % 2 = 0))::int evens, list_sum(list_transform(heads, lambda x: x * 2))::bigint doubled, len(list_intersect(heads, [src + 1, src - 1]))::int near from g")
def fn_higher_order(s, d):
    g = G.user_hops(s, d).groupBy("src").agg(F.collect_list("dst").alias("heads"))
    return g.select(
        "src",
        F.size(F.filter("heads", lambda x: x % 2 == 0)).alias("evens"),
        F.aggregate(F.transform("heads", lambda x: x * 2), F.lit(0).cast("long"), lambda a, x: a + x).alias("doubled"),
        F.size(F.array_intersect("heads", F.array(F.col("src") + 1, F.col("src") - 1))).alias("near"),
    )


@entry("select user_id, event_type as \"key\", count(*) n from events group by 1, 2")
def fn_map_degrees(s, d):
    g = t(s, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    maps = g.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return maps.select("user_id", F.explode("m").alias("key", "n"))


@entry("select event_id, '{\"k\":' || (props->>'$.k') || '}' json from events")
def fn_json_props(s, d):
    return t(s, d, "events").select("event_id", F.to_json(F.from_json("props", "k int")).alias("json"))


@entry("select c_custkey, try_cast(regexp_extract(c_name, '[0-9]+') as bigint) number, coalesce(nullif(c_nationkey, 3), -1)::int nation from customer")
def fn_cast_null(s, d):
    number = F.regexp_extract("c_name", "[0-9]+", 0).try_cast("long")
    return t(s, d, "customer").select("c_custkey", number.alias("number"), F.coalesce(F.nullif("c_nationkey", F.lit(3)), F.lit(-1)).alias("nation"))


@entry(f"with {_TREE} select a.node::bigint a, b.node::bigint b, a.b <= b.b and b.e < a.e covers from iv a cross join iv b where a.node % 8 = 5")
def udf_label_covers(s, d):
    from dynreach.functions.intervals import register

    register(s)
    tree_intervals(s, d).selectExpr("node", "array(named_struct('b', b, 'e', e)) iv").createOrReplaceTempView("rel_iv")
    return s.sql("select x.node a, y.node b, label_covers(x.iv, y.iv) covers from rel_iv x cross join rel_iv y where x.node % 8 = 5")  # 5 by 30 rows


@entry(f"with {_TREE}, kids as (select n_regionkey::bigint region, n_regionkey*1000+n_nationkey*10 b, n_regionkey*1000+n_nationkey*10+9 e from nation) select region, min(b)::bigint b, max(e)::bigint e from kids group by 1")
def udaf_interval_hull(s, d):
    from dynreach.functions.intervals import hull_in_groups

    at = F.col("n_regionkey") * 1000 + F.col("n_nationkey") * 10
    kids = t(s, d, "nation").select(F.col("n_regionkey").cast("long").alias("region"), at.cast("long").alias("b"), (at + 9).cast("long").alias("e"))
    return kids.groupBy("region").applyInPandas(hull_in_groups("region"), "region long, b long, e long")


@entry(f"with recursive e as ({G.sql_edges('conversation_chain')}), s0 as (select min(src) start from e group by src // 1000), r(start, step, node) as (select start, 1, start + 1 from s0 union all select start, step + 1, dst from r join e on src = node) select start, step::int step, node from r")
def udtf_path(s, d):
    from dynreach.functions.intervals import step_path

    e = G.conversation_chain(s, d)
    g = e.groupBy(F.floor(F.col("src") / 1000).alias("conv")).agg(F.min("src").alias("start"), F.collect_list("src").alias("heads"), F.collect_list("dst").alias("tails"))
    s.udtf.register("step_path", step_path())
    g.createOrReplaceTempView("rel_chains")
    return s.sql("select p.start, p.step, p.node from rel_chains g, lateral step_path(g.start, g.heads, g.tails) p")
