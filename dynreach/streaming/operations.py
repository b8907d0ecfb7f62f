"""Streams of update operations.

The index is global state, so it is kept by `foreachBatch`: each micro-batch is one batch of the
planner, committed as a new version with its batch id; a batch that a restart repeats is found in the
ledger and skipped. Operations that come after the watermark are set aside, never applied silently, and the others are
applied in order of time.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from dynreach.conf import DEFAULT, EngineConf
from dynreach.model import OPS
from dynreach.operators import index as I
from dynreach.plans import batch
from dynreach.plans.loops import cut, empty

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files: int = 1, pattern: str | None = None) -> DataFrame:
    """events as a stream of parquet files; ts becomes a timestamp for watermarks."""
    reader = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files)
    if pattern:
        reader = reader.option("pathGlobFilter", pattern)
    return reader.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


TIMES = "newest timestamp_ntz, last_op long"


def run(ops: DataFrame, path: str, checkpoint: str, late_path: str | None = None, watermark: str | None = None, conf: EngineConf = DEFAULT, mode: str = "batch") -> StreamingQuery:
    """Applies a stream of operations to the index committed at path; stops when what is there has been read.

    With a watermark, operations are put in order of time: those newer than the newest time seen less the watermark wait for
    a later batch (`flush` applies what waits at the end), and those older than what has been applied are late: they are
    written below late_path and never applied. Without one, operations must come in order of op_id over batches, or
    the stream fails. Everything a batch writes is named by its id, so a batch that is repeated writes the same again.
    """

    def step(rows: DataFrame, batch_id: int) -> None:
        spark = rows.sparkSession
        if I.versions(spark, path).where(F.col("batch_id") == batch_id).limit(1).count():
            return
        current, rows = I.load(spark, path), cut(rows)
        seen = _before(spark, f"{path}/times", TIMES, batch_id).agg(F.max("newest"), F.max("last_op")).first()
        here = rows.agg(F.max("ts"), F.min("op_id"), F.max("op_id")).first()
        newest = max((t for t in (seen[0], here[0]) if t is not None), default=None)
        if watermark is None:
            if seen[1] is not None and here[1] is not None and here[1] <= seen[1]:
                raise ValueError(f"operation {here[1]} comes after {seen[1]} was applied; give a watermark")
            ready = rows
        else:
            behind = lambda t: F.lit(t).cast("timestamp_ntz") - F.expr(f"interval {watermark}")
            late = F.coalesce(F.col("ts") < behind(seen[0]), F.lit(False))
            if late_path:
                rows.where(late).write.mode("overwrite").parquet(f"{late_path}/batch_id={batch_id}")
            waiting = _last(spark, f"{path}/waiting", OPS, batch_id)
            open_ = cut(waiting.unionByName(rows.where(~late).select(*waiting.columns)))
            due = F.coalesce(F.col("ts") < behind(newest), F.lit(False))
            ready = open_.where(due)
            open_.where(~due).write.mode("overwrite").parquet(f"{path}/waiting/batch_id={batch_id}")
        spark.createDataFrame([(newest, max((x for x in (seen[1], here[2]) if x is not None), default=None))], TIMES).coalesce(1).write.mode("overwrite").parquet(f"{path}/times/batch_id={batch_id}")
        I.commit(batch.apply(current, ready, mode, conf), path, batch_id)

    return ops.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def flush(spark: SparkSession, path: str, conf: EngineConf = DEFAULT, mode: str = "batch") -> None:
    """Applies the operations that still wait, when no more will come."""
    last = I.versions(spark, path).agg(F.max("batch_id")).first()[0]
    waiting = _last(spark, f"{path}/waiting", OPS, last + 1)
    if not empty(waiting):
        I.commit(batch.apply(I.load(spark, path), waiting, mode, conf), path, last + 1)


def _before(spark: SparkSession, path: str, schema: str, batch_id: int) -> DataFrame:
    """Rows that batches before this one wrote."""
    try:
        return spark.read.schema(f"{schema}, batch_id long").parquet(path).where(F.col("batch_id") < batch_id)
    except AnalysisException as e:  # no batch has written yet
        if "PATH_NOT_FOUND" in str(e):
            return spark.createDataFrame([], f"{schema}, batch_id long")
        raise


def _last(spark: SparkSession, path: str, schema: str, batch_id: int) -> DataFrame:
    rows = _before(spark, path, schema, batch_id)
    newest = I.versions(spark, path.rsplit("/", 1)[0]).where(F.col("batch_id") < batch_id).agg(F.max("batch_id")).first()[0]
    return rows.where(F.col("batch_id") == F.lit(newest)).drop("batch_id")


def tumbling(events: DataFrame, width: str = "1 day", late: str = "1 day") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type")
    return w.agg(F.count("*").alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


def sliding(events: DataFrame, width: str = "3 days", step: str = "1 day", late: str = "1 day") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", width, step))
    return w.agg(F.count("*").alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 day") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id")
    return w.agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), F.col("session_window.end").cast("timestamp_ntz").alias("stop"), "n")


def deduplicated(events: DataFrame, within: str = "1 day") -> DataFrame:
    """Repeated (user, k, type) within the watermark go."""
    keyed = events.withColumn("k", F.get_json_object("props", "$.k").cast("int"))
    return keyed.withWatermark("ts", within).dropDuplicatesWithinWatermark(["user_id", "k", "event_type"])


def net_edges(ops: DataFrame) -> DataFrame:
    """(u, v, op_id, kind): the newest edge operation of each edge, kept as state per edge; emits on each change."""

    def newest(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        best = state.get if state.exists else (-1, "")
        for frame in frames:
            row = frame.loc[frame["op_id"].idxmax()]
            if int(row["op_id"]) > best[0]:
                best = (int(row["op_id"]), row["kind"])
        state.update(best)
        yield pd.DataFrame({"u": [key[0]], "v": [key[1]], "op_id": [best[0]], "kind": [best[1]]})

    return ops.groupBy("u", "v").applyInPandasWithState(newest, "u long, v long, op_id long, kind string", "op_id long, kind string", "update", GroupStateTimeout.NoTimeout)


def with_components(ops: DataFrame, membership: DataFrame) -> DataFrame:
    """Stream-static join: each operation with the current component of its tail."""
    return ops.join(membership.select(F.col("node").alias("u"), "comp"), "u", "left")


def purchases_after_views(purchases: DataFrame, views: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream join: a purchase with the views of its user in the time before."""
    p = purchases.withWatermark("ts", within).select(F.col("user_id").alias("pu"), F.col("event_id").alias("purchase"), F.col("ts").alias("pt"))
    v = views.withWatermark("ts", within).select(F.col("user_id").alias("vu"), F.col("event_id").alias("view"), F.col("ts").alias("vt"))
    near = (F.col("pu") == F.col("vu")) & (F.col("vt") <= F.col("pt")) & (F.col("vt") >= F.col("pt") - F.expr(f"interval {within}"))
    return p.join(v, near).select("purchase", "view")


def collected(frame: DataFrame, folder: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Runs a stream to the end of its input and returns what it has written below folder, which all executors share: the rows
    of all micro-batches, or of the last one in complete mode. Nothing is gathered by the driver."""

    def write(rows: DataFrame, batch_id: int) -> None:
        rows.write.mode("overwrite").parquet(f"{folder}/{batch_id}")  # a batch that is tried again replaces its own rows
        done.append(batch_id)

    done: list[int] = []
    query = frame.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    wanted = sorted(set(done)) if mode != "complete" else [max(done)] if done else []
    if not wanted:
        return frame.sparkSession.createDataFrame([], frame.schema)
    return frame.sparkSession.read.schema(frame.schema).parquet(*(f"{folder}/{b}" for b in wanted))
