"""Streams run to the end of their input, each with a batch twin in SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dynreach.conf import EngineConf
from dynreach.model import OPS
from dynreach.operators import index as I
from dynreach.plans import batch
from dynreach.plans.loops import cut, ensure_checkpoint_dir
from dynreach.streaming import operations as S


def folder(spark: SparkSession) -> str:
    """A new folder that all executors share."""
    ensure_checkpoint_dir(spark)
    return f"{spark.sparkContext.getCheckpointDir()}/stream-{uuid.uuid4().hex}"


def events(spark: SparkSession, d: str) -> DataFrame:
    """The events table as a stream, in one micro-batch: nothing comes late."""
    return S.event_stream(spark, d, 1, "events.parquet")


def finished(frame: DataFrame, mode: str = "complete") -> DataFrame:
    return S.collected(frame, folder(frame.sparkSession), folder(frame.sparkSession), mode)


def tumbling(spark, d):
    return finished(S.tumbling(events(spark, d)))


def sliding(spark, d):
    return finished(S.sliding(events(spark, d)))


def sessions(spark, d):
    return finished(S.sessions(events(spark, d)))


def deduplicated(spark, d):
    return finished(S.deduplicated(events(spark, d), "3650 days").groupBy("event_type").agg(F.count("*").alias("n")))


def net_edges(spark, d):
    e = events(spark, d).where("event_type in ('view', 'purchase')")
    ops = e.select(F.col("user_id").alias("u"), (F.get_json_object("props", "$.k").cast("long") % 5).alias("v"), F.col("event_id").alias("op_id"), F.when(F.col("event_type") == "view", "insert_edge").otherwise("delete_edge").alias("kind"))
    out = finished(S.net_edges(ops), "update")
    return out.groupBy("u", "v").agg(F.max_by("kind", "op_id").alias("kind"), F.max("op_id").alias("op_id"))


def static_join(spark, d):
    from dynreach.registry import index

    ops = events(spark, d).select("event_id", F.col("user_id").alias("u"))
    return finished(S.with_components(ops, index(spark, d, "user_hops").membership).select("event_id", "comp"), "append")


def stream_join(spark, d):
    e = events(spark, d)
    return finished(S.purchases_after_views(e.where("event_type = 'purchase'"), events(spark, d).where("event_type = 'view'")), "append")


def _written(ops: DataFrame, chunk, chunks: int, path: str) -> DataFrame:
    """The operations as a stream of files, a chunk after the other and each a micro-batch."""
    kept = cut(ops.withColumn("chunk", chunk))
    for i in range(chunks):
        kept.where(F.col("chunk") == i).drop("chunk").coalesce(1).write.mode("append").parquet(path)
    return ops.sparkSession.readStream.schema(ops.schema).option("maxFilesPerTrigger", 1).parquet(path)


def index_after_stream(spark, d):
    """Operations on user states in three micro-batches onto an index that starts with the first tenth; the edges it ends with."""
    from dynreach.plans.workload import ops_events

    root, ops = folder(spark), cut(ops_events(spark, d))
    top = ops.agg(F.max("op_id")).first()[0] or 0
    first = F.col("op_id") <= top // 10
    nothing = spark.createDataFrame([], "src long, dst long")
    I.commit(batch.apply(I.build(nothing), ops.where(first)), f"{root}/index")
    stream = _written(ops.where(~first), F.least(F.lit(2), F.floor((F.col("op_id") - top // 10) * 3 / (top + 1 - top // 10))), 3, f"{root}/ops")
    S.run(stream, f"{root}/index", f"{root}/checkpoint", conf=EngineConf(rebuild_ratio=100.0)).awaitTermination()
    done = I.versions(spark, f"{root}/index").where("batch_id >= 0").count()
    if done != 3:
        raise AssertionError(f"{done} micro-batches instead of 3")
    return I.load(spark, f"{root}/index").edges.select("src", "dst")


CHUNKS, BEHIND = 4, "30 days"


def _disordered(spark, d):
    """Operations in four micro-batches, each over the whole time: most of the later ones are late. (final edges, late operations)."""
    from dynreach.plans.workload import ops_events
    from dynreach.registry import kept

    def make():
        root, ops = folder(spark), ops_events(spark, d)
        I.commit(I.build(spark.createDataFrame([], "src long, dst long")), f"{root}/index")
        stream = _written(ops, F.pmod(F.floor(F.col("op_id") / 7), F.lit(CHUNKS)), CHUNKS, f"{root}/ops")
        S.run(stream, f"{root}/index", f"{root}/checkpoint", f"{root}/late", BEHIND, EngineConf(rebuild_ratio=100.0)).awaitTermination()
        S.flush(spark, f"{root}/index")
        return I.load(spark, f"{root}/index").edges.select("src", "dst"), spark.read.schema(f"{OPS}, batch_id long").parquet(f"{root}/late")

    return kept(spark, (d, "disordered"), make)


def late(spark, d):
    """Operations that came after the watermark, counted by kind from the side table that the stream wrote."""
    return _disordered(spark, d)[1].groupBy("kind").agg(F.count("*").alias("n"))


def in_order(spark, d):
    """The edges after the operations that were not late, whatever order they came in."""
    return _disordered(spark, d)[0]


def _events_sql() -> str:
    from dynreach import registry as R

    return R.final_sql("select 0 src, 0 dst where false", R.EVENTS, R.STATE)


ENTRIES: dict[str, tuple] = {
    "stream_tumbling": (tumbling, "select date_trunc('day', ts)::timestamp start, event_type, count(*) n from events group by 1, 2"),
    "stream_sliding": (sliding, "select s::timestamp start, count(*) n from events, lateral (select unnest([date_trunc('day', ts) - interval 2 day, date_trunc('day', ts) - interval 1 day, date_trunc('day', ts)::timestamp]) s) where s <= ts and ts < s + interval 3 day group by 1"),
    "stream_session": (
        sessions,
        "select user_id, min(ts) start, max(ts) + interval 30 minute as \"stop\", count(*) n from (select *, sum(f) over (partition by user_id order by ts, event_id) g from (select *, case when ts - lag(ts) over (partition by user_id order by ts, event_id) < interval 30 minute then 0 else 1 end f from events)) group by user_id, g",
    ),
    "stream_dedup": (deduplicated, "select event_type, count(*) n from (select distinct user_id, (props->>'$.k')::int k, event_type from events) group by 1"),
    "stream_net_edge": (net_edges, "select user_id u, (props->>'$.k')::bigint % 5 v, arg_max(case when event_type = 'view' then 'insert_edge' else 'delete_edge' end, event_id) kind, max(event_id) op_id from events where event_type in ('view', 'purchase') group by 1, 2"),
    "stream_stream_join": (stream_join, "select p.event_id purchase, v.event_id as \"view\" from events p join events v on v.user_id = p.user_id and v.ts <= p.ts and v.ts >= p.ts - interval 1 hour where p.event_type = 'purchase' and v.event_type = 'view'"),
}


def complete() -> None:
    """Entries whose SQL is put together in the registry."""
    from dynreach import registry as R

    ENTRIES["stream_static_join"] = (static_join, R.with_graph("user_hops", R.COMPS + " select event_id, comp from events left join m on node = user_id"))
    # a micro-batch sees the newest time of the batches before it
    op = "op as (select row_number() over (order by ts, event_id) - 1 op_id, ts, kind, u, v from (select event_id, ts, kind, case kind when 'insert_edge' then p when 'delete_edge' then pp else st end u, case kind when 'insert_edge' then st when 'delete_edge' then p end v from kinds) where kind is not null and u is not null and (v is not null or kind = 'delete_node'))"
    kinds = R.EVENTS.split(", raw as")[0] + ", kinds as (select *, case when event_type in ('view','click','signup') then 'insert_edge' when event_type='purchase' then 'delete_edge' when event_type='error' and value < 2 then 'delete_node' end kind from sp)"
    marked = f"{kinds}, {op}, ch as (select *, (op_id // 7) % {CHUNKS} c from op), tops as (select c, max(ts) t from ch group by 1), lt as (select ch.*, coalesce(ts < (select max(t) from tops where tops.c < ch.c) - interval {BEHIND}, false) late from ch)"
    kept = "ins as (select op_id, u src, v dst from lt where kind='insert_edge' and not late), del as (select op_id, u src, v dst from lt where kind='delete_edge' and not late), kill as (select op_id, u node from lt where kind='delete_node' and not late), born as (select op_id, u node from lt where false)"
    ENTRIES["stream_late"] = (late, f"with {marked} select kind, count(*) n from lt where late group by 1")
    ENTRIES["stream_in_order_final_state"] = (in_order, R.final_sql("select 0 src, 0 dst where false", f"{marked}, {kept}", R.STATE))
    ENTRIES["w_stream_final_state"] = (index_after_stream, _events_sql())
