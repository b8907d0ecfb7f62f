"""Two-pass external shuffle into shards.

Pass one scatters records uniformly into buckets of a size that fits a task's memory, by a
seeded hash of the record and its row number, so copies of one record spread as well. Pass two
shuffles each bucket in memory (Fisher-Yates, seeded by bucket) and writes it. Buckets one after another
are the global order; only a count per bucket, and per shard, is needed to place a record.

Laws: `rows` deals the global order round, counts differ by one at most; `bytes` cuts it at equal
shares of the bytes; `key` places by id and shard count alone (jump hashing, so that one more shard
takes rows only into itself). Defined cases: null text has no bytes (size 1), equal rows get places of their
own, null ids go by the hash of the empty text, an empty table gives no rows.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from dynreach.llm.common import cut, seeded

LAWS = ("rows", "bytes", "key")
#: Buckets summed together, and bucket rows up to which their starts are broadcast (24 bytes or so each).
STRETCH, MOST_BROADCAST = 4_096, 100_000


def fisher_yates(n: int, seed: int, bucket: int) -> np.ndarray:
    """A uniform permutation by swapping each place with one at or below it."""
    order = np.arange(n)
    picks = (seeded((seed << 32) + bucket).random(n) * np.arange(1, n + 1)).astype(np.int64)
    for i in range(n - 1, 0, -1):
        j = picks[i]
        order[i], order[j] = order[j], order[i]
    return order


def jump_shard(key: int, shards: int) -> int:
    """Jump consistent hashing (a published method): moves a key only into added shards."""
    b, j = -1, 0
    while j < shards:
        b = j
        key = (key * 2862933555777941757 + 1) & 0xFFFFFFFFFFFFFFFF
        j = int((b + 1) * (float(1 << 31) / float((key >> 33) + 1)))
    return b


def key_of(doc_id: object, seed: int) -> int:
    text = "" if doc_id is None else str(doc_id)
    low, high = zlib.crc32(text.encode(), seed), zlib.crc32(text.encode() + b"#", seed ^ 0x5BD1E995)
    return (high << 32) | low


def bucket_count(docs: DataFrame, text_col: str, bucket_bytes: int) -> int:
    total = docs.agg(F.sum(F.octet_length(F.coalesce(text_col, F.lit(""))).cast("long") + 1)).first()[0]
    return max(1, -(-(total or 0) // bucket_bytes))


def shuffled(
    docs: DataFrame, shards: int = 8, law: str = "rows", seed: int = 7, bucket_bytes: int = 16 << 20, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ()
) -> DataFrame:
    """Both passes: id, size, text_crc32, bucket, rank (in the bucket), cum (bytes before it in the bucket),
    own (shard under `key`), own_rank, grown, and the columns asked for."""
    if law not in LAWS:
        raise ValueError(f"law is one of {LAWS}")
    buckets = bucket_count(docs, text_col, bucket_bytes)
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(
        F.col(id_col),
        text.alias("__text"),
        *[F.col(c).alias(f"__kept_{i}") for i, c in enumerate(keep)],
        F.xxhash64(F.lit(seed), F.col(id_col), F.crc32(text), F.monotonically_increasing_id()).alias("__hash"),
    ).withColumn("__bucket", F.pmod(F.shiftright("__hash", 8), F.lit(buckets)))
    kept = [f"__kept_{i}" for i in range(len(keep))]
    new = ["size", "text_crc32", "bucket", "rank", "cum", "own", "own_rank", "grown"]
    schema = StructType([docs.schema[id_col], *(StructField(c, LongType()) for c in new), *(StructField(k, docs.schema[c].dataType) for k, c in zip(kept, keep))])

    def second_pass(group: pa.Table) -> pa.Table:
        n, bucket = group.num_rows, group["__bucket"][0].as_py()
        order = np.argsort(group["__hash"].to_numpy(), kind="stable")[fisher_yates(n, seed, bucket)]
        group = group.take(pa.array(order))
        raw = [t.encode() for t in group["__text"].to_pylist()]
        size = np.fromiter((len(r) + 1 for r in raw), np.int64, n)
        own = own_rank = grown = np.zeros(n, np.int64)
        if law == "key":
            keys = [key_of(x, seed) for x in group[id_col].to_pylist()]
            own, grown = (np.array([jump_shard(k, s) for k in keys], np.int64) for s in (shards, shards + 1))
            own_rank = np.zeros(n, np.int64)
            for s in np.unique(own):
                own_rank[own == s] = np.arange((own == s).sum())
        columns = [size, np.fromiter(map(zlib.crc32, raw), np.int64, n), np.full(n, bucket), np.arange(n), np.cumsum(size) - size, own, own_rank, grown]
        return pa.table([group[id_col], *(pa.array(c, pa.int64()) for c in columns), *(group[k] for k in kept)], [id_col, *new, *kept])

    done = rows.groupBy("__bucket").applyInArrow(second_pass, schema)
    for k, c in zip(kept, keep):
        done = done.withColumnRenamed(k, c)
    return done


def starts(done: DataFrame) -> DataFrame:
    """(bucket, own, before, bytes_before, total): running sums in two levels, so that no window holds more than STRETCH
    buckets or a row for so many of them."""
    per = cut(done.groupBy("bucket", "own").agg(F.count("*").alias("n"), F.sum("size").alias("bytes")).withColumn("stretch", F.floor(F.col("bucket") / STRETCH)))
    upto = lambda c, w: F.coalesce(F.sum(c).over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    coarse, fine = Window.partitionBy("own").orderBy("stretch"), Window.partitionBy("own", "stretch").orderBy("bucket")
    sums = per.groupBy("own", "stretch").agg(F.sum("n").alias("n"), F.sum("bytes").alias("bytes"))
    ahead = sums.select("own", "stretch", upto("n", coarse).alias("n0"), upto("bytes", coarse).alias("b0"))
    inside = per.select("own", "stretch", "bucket", upto("n", fine).alias("n1"), upto("bytes", fine).alias("b1"))
    total = per.agg(F.sum("bytes").alias("total"))  # one row
    out = inside.join(ahead, ["own", "stretch"]).join(F.broadcast(total)).select("bucket", "own", (F.col("n0") + F.col("n1")).alias("before"), (F.col("b0") + F.col("b1")).alias("bytes_before"), "total")
    return F.broadcast(out) if per.count() <= MOST_BROADCAST else out


def place(done: DataFrame, shards: int, law: str) -> DataFrame:
    """Adds law, shard, slot, grown_shard. `done` is read several times: written or checkpointed rows."""
    placed = done.join(starts(done), ["bucket", "own"])
    if law == "key":
        shard, slot = F.col("own"), F.col("before") + F.col("own_rank")
    else:
        placed = placed.withColumn("position", F.col("before") + F.col("rank"))
        if law == "rows":
            shard, slot = F.col("position") % shards, F.floor(F.col("position") / shards)
        else:
            share = F.floor((F.col("bytes_before") + F.col("cum")).cast("decimal(38,0)") * shards / F.col("total"))
            placed = placed.withColumn("share", F.least(share, F.lit(shards - 1)).cast("long"))
            first = placed.groupBy("share").agg(F.min("position").alias("first"))  # a row a shard
            placed = placed.join(F.broadcast(first), "share")
            shard, slot = F.col("share"), F.col("position") - F.col("first")
    grown = F.col("grown").cast("int") if law == "key" else F.lit(None).cast("int")
    return placed.withColumns({"law": F.lit(law), "shard": shard.cast("int"), "slot": slot.cast("long"), "grown_shard": grown})


def assign_shards(docs: DataFrame, shards: int = 8, law: str = "rows", seed: int = 7, bucket_bytes: int = 16 << 20) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard of every row."""
    done = cut(shuffled(docs, shards, law, seed, bucket_bytes))
    return place(done, shards, law).select("doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard")


def write_shards(docs: DataFrame, path: str, shards: int = 8, law: str = "rows", seed: int = 7, bucket_bytes: int = 16 << 20) -> None:
    """Writes whole records below path: first the shuffled buckets, then shard=N folders in slot order."""
    spark, names = docs.sparkSession, [c for c in docs.columns if c != "doc_id"]
    shuffled(docs, shards, law, seed, bucket_bytes, keep=tuple(names)).write.mode("overwrite").parquet(f"{path}/buckets")
    placed = place(spark.read.parquet(f"{path}/buckets"), shards, law)
    placed.select("doc_id", *names, "shard", "slot").repartition(F.col("shard"), F.floor(F.col("slot") / 100_000)).sortWithinPartitions("shard", "slot").write.mode("overwrite").partitionBy("shard").parquet(f"{path}/shards")
