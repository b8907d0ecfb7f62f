"""Directed graphs read from the given tables, as DataFrames and as SQL for the oracle.

Mixed graphs number nodes 8 * key + tag; states are user_id * 100 + k; turns are conv_id * 1000 + turn.
Each edge set is distinct, and what it needs of a table is a pruned projection with pushed filters.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

ORDER, PART, CUSTOMER, SUPPLIER, NATION, REGION = range(6)


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def node(key: str, tag: int) -> Column:
    return (F.col(key).cast("long") * 8 + tag).cast("long")


def pairs(df: DataFrame, src: Column, dst: Column) -> DataFrame:
    return df.select(src.cast("long").alias("src"), dst.cast("long").alias("dst"))


def uniform_pairs(spark: SparkSession, d: str) -> DataFrame:
    n = read(spark, d, "orders").agg(F.count("*").alias("n"))
    lines = read(spark, d, "lineitem").where("l_quantity <= 18").join(F.broadcast(n))  # one row
    mixed = (F.col("l_partkey") * 97 + F.col("l_suppkey") * 31 + F.col("l_linenumber")) % F.col("n")
    return pairs(lines, F.col("l_orderkey"), mixed).distinct()


def goods_flow(spark: SparkSession, d: str) -> DataFrame:
    lines = read(spark, d, "lineitem")
    back = lines.where("l_returnflag = 'R' and l_linestatus = 'F'")
    return pairs(lines, node("l_orderkey", ORDER), node("l_partkey", PART)).union(pairs(back, node("l_partkey", PART), node("l_orderkey", ORDER))).distinct()


def goods_flow_light(spark: SparkSession, d: str) -> DataFrame:
    lines = read(spark, d, "lineitem")
    back = lines.where("l_returnflag = 'R' and l_discount >= 0.095")
    return pairs(lines.where("l_quantity <= 40"), node("l_orderkey", ORDER), node("l_partkey", PART)).union(pairs(back, node("l_partkey", PART), node("l_orderkey", ORDER))).distinct()


def order_citation(spark: SparkSession, d: str) -> DataFrame:
    orders = read(spark, d, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    lowest = read(spark, d, "lineitem").groupBy("l_orderkey").agg(F.min("l_partkey").alias("lowest"))
    before = lambda key: F.lag("o_orderkey").over(Window.partitionBy(key).orderBy("o_orderdate", "o_orderkey"))
    by_customer = pairs(orders.withColumn("p", before("o_custkey")), F.col("o_orderkey"), F.col("p"))
    by_part = pairs(orders.join(lowest, F.col("o_orderkey") == F.col("l_orderkey")).withColumn("p", before("lowest")), F.col("o_orderkey"), F.col("p"))
    return by_customer.union(by_part).where("dst is not null").distinct()


def user_states(spark: SparkSession, d: str) -> DataFrame:
    """event_id, ts, user_id, event_type, value, st and the states one and two events before."""
    e = read(spark, d, "events").where("user_id is not null")
    st = F.col("user_id") * 100 + F.get_json_object("props", "$.k").cast("long")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return e.withColumn("st", st).withColumns({"p": F.lag("st").over(w), "pp": F.lag("st", 2).over(w)})


def user_steps(spark: SparkSession, d: str) -> DataFrame:
    return pairs(user_states(spark, d).where("p is not null"), F.col("p"), F.col("st")).distinct()


def user_skips(spark: SparkSession, d: str) -> DataFrame:
    return pairs(user_states(spark, d).where("pp is not null"), F.col("pp"), F.col("st")).distinct()


def user_hops(spark: SparkSession, d: str) -> DataFrame:
    """Each event with the one after it in the global order, joined by place."""
    e = ordered(read(spark, d, "events").select("ts", "event_id", "user_id", "event_type", "value"), "ts", "event_id", name="place")
    e = e.join(e.select((F.col("place") - 1).alias("place"), F.col("user_id").alias("nxt")), "place")
    return pairs(e.where("event_type = 'purchase' and value < 8 and nxt is not null and nxt <> user_id"), F.col("user_id"), F.col("nxt")).distinct()


def part_hops(spark: SparkSession, d: str) -> DataFrame:
    lines = read(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_linenumber", "l_suppkey", "l_shipdate", "l_quantity")
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate")
    return pairs(lines.withColumn("nxt", F.lead("l_partkey").over(w)).where("l_quantity <= 3 and nxt is not null and nxt <> l_partkey"), F.col("l_partkey"), F.col("nxt")).distinct()


def containment_tree(spark: SparkSession, d: str) -> DataFrame:
    nation, customer, orders, supplier = (read(spark, d, t) for t in ("nation", "customer", "orders", "supplier"))
    return (
        pairs(nation, node("n_regionkey", REGION), node("n_nationkey", NATION))
        .union(pairs(customer, node("c_nationkey", NATION), node("c_custkey", CUSTOMER)))
        .union(pairs(orders, node("o_custkey", CUSTOMER), node("o_orderkey", ORDER)))
        .union(pairs(supplier, node("s_nationkey", NATION), node("s_suppkey", SUPPLIER)))
    )


def conversation_chain(spark: SparkSession, d: str) -> DataFrame:
    turns = read(spark, d, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("src"))
    later = turns.select((F.col("src") - 1).alias("prev"))
    return pairs(turns.join(later, F.col("src") == F.col("prev")), F.col("src"), F.col("src") + 1).distinct()


def links(spark: SparkSession, d: str) -> DataFrame:
    """(page_id, position, url, href): scheme and host of a page's address, then the address in each link."""
    pages = read(spark, d, "pages").select("page_id", "url", "html")
    return pages.select("page_id", "url", F.posexplode(F.regexp_extract_all("html", F.lit('<a href="([^"]*)"'), F.lit(1))).alias("position", "href"))


def web_links(spark: SparkSession, d: str) -> DataFrame:
    """String ends, still to be interned."""
    host = F.regexp_extract("url", "^([a-z]+://[^/]+)", 1)
    return links(spark, d).select(F.col("url").alias("src"), F.concat(host, "href").alias("dst")).distinct()


def ordered(rows: DataFrame, *keys: str, name: str = "rank") -> DataFrame:
    """rows with their place, from 0, in the order of the keys: sorted ranges and a count for each, so that no window and no
    task holds them all, however the keys cluster. Rows with equal keys fall in any order."""
    from dynreach.plans.loops import cut

    parts = cut(rows.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumns({"__part": F.spark_partition_id(), "__row": F.monotonically_increasing_id()}))
    starts = parts.groupBy("__part").agg(F.count("*").alias("n"), F.min("__row").alias("first"))  # a row a partition
    before = F.coalesce(F.sum("n").over(Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    place = F.col("before") + F.col("__row") - F.col("first")
    return parts.join(F.broadcast(starts.withColumn("before", before)), "__part").select(*rows.columns, place.cast("long").alias(name))


def intern_ids(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(edges, names): dense ids by sorted key."""
    keys = edges.select(F.col("src").alias("key")).union(edges.select("dst")).distinct()
    names = ordered(keys, "key", name="node")
    a, b = names.select(F.col("key").alias("src"), F.col("node").alias("a")), names.select(F.col("key").alias("dst"), F.col("node").alias("b"))
    return edges.join(a, "src").join(b, "dst").select(F.col("a").alias("src"), F.col("b").alias("dst")), names


def example_graph(spark: SparkSession, d: str = "") -> DataFrame:
    from dynreach.sources.example import EXAMPLE_EDGES, letter

    return spark.createDataFrame([(letter(a), letter(b)) for a, b in EXAMPLE_EDGES], "src long, dst long")


GRAPHS = {
    f.__name__: f for f in (uniform_pairs, goods_flow, goods_flow_light, order_citation, user_steps, user_hops, part_hops, containment_tree, conversation_chain, example_graph)
}

#: Graphs whose queries give each edge once; the others rely on the keys of the given tables.
DISTINCT = frozenset(GRAPHS) - {"containment_tree"}


def edges_of(spark: SparkSession, graph: str, sf_dir: str) -> DataFrame:
    return GRAPHS[graph](spark, sf_dir)


def nodes_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("node")).union(edges.select("dst")).distinct()


def pairs_fixed(nodes: DataFrame, n: int = 200) -> DataFrame:
    """qid 0..n-1 with ends at ranks of the nodes' order given by arithmetic on qid."""
    spark = nodes.sparkSession
    total = nodes.count()
    if not total:
        return spark.createDataFrame([], "qid long, u long, v long")
    asked = spark.range(n).select(F.col("id").alias("qid"), ((F.col("id") * 7919 + 13) % total).alias("ru"), ((F.col("id") * 104729 + 71) % total).alias("rv"))
    wanted = asked.select(F.col("ru").alias("rank")).union(asked.select("rv")).distinct()
    ranked = ranks(nodes).join(F.broadcast(wanted) if n <= 100_000 else wanted, "rank")  # two rows a question
    u, v = ranked.select(F.col("rank").alias("ru"), F.col("node").alias("u")), ranked.select(F.col("rank").alias("rv"), F.col("node").alias("v"))
    return asked.join(u, "ru").join(v, "rv").select("qid", "u", "v")


def ranks(nodes: DataFrame) -> DataFrame:
    """(node, rank): place in the order of ids."""
    return ordered(nodes.select("node"), "node")


SQL = {
    "uniform_pairs": "select distinct l_orderkey::bigint src, ((l_partkey*97 + l_suppkey*31 + l_linenumber) % (select count(*) from orders))::bigint dst from lineitem where l_quantity <= 18",
    "goods_flow": "select l_orderkey*8 src, l_partkey*8+1 dst from lineitem union select l_partkey*8+1, l_orderkey*8 from lineitem where l_returnflag='R' and l_linestatus='F'",
    "goods_flow_light": "select l_orderkey*8 src, l_partkey*8+1 dst from lineitem where l_quantity <= 40 union select l_partkey*8+1, l_orderkey*8 from lineitem where l_returnflag='R' and l_discount >= 0.095",
    "order_citation": "select src, dst from (select o_orderkey src, lag(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey) dst from orders union select o_orderkey, lag(o_orderkey) over (partition by lowest order by o_orderdate, o_orderkey) from orders join (select l_orderkey, min(l_partkey) lowest from lineitem group by 1) on l_orderkey = o_orderkey) where dst is not null",
    "user_steps": "select distinct p src, st dst from (select st, lag(st) over (partition by user_id order by ts, event_id) p from (select *, user_id*100 + (props->>'$.k')::bigint st from events)) where p is not null",
    "user_skips": "select distinct p src, st dst from (select st, lag(st, 2) over (partition by user_id order by ts, event_id) p from (select *, user_id*100 + (props->>'$.k')::bigint st from events)) where p is not null",
    "user_hops": "select distinct user_id src, nxt dst from (select *, lead(user_id) over (order by ts, event_id) nxt from events) where event_type='purchase' and value < 8 and nxt is not null and nxt <> user_id",
    "part_hops": "select distinct l_partkey src, nxt dst from (select l_partkey, l_quantity, lead(l_partkey) over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_shipdate) nxt from lineitem) where l_quantity <= 3 and nxt is not null and nxt <> l_partkey",
    "containment_tree": "select n_regionkey::bigint*8+5 src, n_nationkey::bigint*8+4 dst from nation union all select c_nationkey::bigint*8+4, c_custkey*8+2 from customer union all select o_custkey*8+2, o_orderkey*8 from orders union all select s_nationkey::bigint*8+4, s_suppkey*8+3 from supplier",
    "conversation_chain": "select distinct a.conv_id*1000+a.turn src, b.conv_id*1000+b.turn dst from conversations a join conversations b on a.conv_id=b.conv_id and b.turn=a.turn+1",
    "web_links": "select distinct url src, regexp_extract(url, '^([a-z]+://[^/]+)', 1) || href dst from (select url, unnest(regexp_extract_all(html, '<a href=\"([^\"]*)\"', 1)) href from pages)",
    "example_graph": "select ascii(e[1])-65 src, ascii(e[2])-65 dst from (select unnest(string_split('RA RD RE AB BC CA DE FD DG EF GF BH CI GJ DH HL JK LM KN IO LP NT OT PT TS SN SO SP', ' ')) e)",
}


def sql_edges(graph: str) -> str:
    """A CTE body with bigint src, dst."""
    return f"select src::bigint src, dst::bigint dst from ({SQL[graph]})"


def sql_nodes(edges: str = "e") -> str:
    return f"select src node from {edges} union select dst from {edges}"


def sql_pairs(n: int = 200, nodes: str = "n") -> str:
    return (
        f"select q.qid, a.node u, b.node v from (select range qid, (range*7919+13) % (select count(*) from {nodes}) ru, (range*104729+71) % (select count(*) from {nodes}) rv from range({n})) q "
        f"join (select node, row_number() over (order by node)-1 r from {nodes}) a on a.r=ru join (select node, row_number() over (order by node)-1 r from {nodes}) b on b.r=rv"
    )
