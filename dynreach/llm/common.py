"""Helpers shared by the training-data operators."""

from __future__ import annotations

import tempfile

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """The session's shared folder is kept; a folder of our own is set only where none is."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        shared = spark.conf.get("spark.checkpoint.dir", None)
        if shared is None and not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(shared or tempfile.mkdtemp(prefix="dynreach-checkpoint-"))


def cut(df: DataFrame, *, eager: bool = True) -> DataFrame:
    """Writes df to the shared checkpoint folder and reads it from there."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager)


def give_back() -> None:
    """Hands memory that a worker has freed back to the machine, where the C library can; workers outlive their tasks."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def id_residue(column: str, modulus: int):
    """crc32 of the id as text, modulo; null ids count as the empty text."""
    return F.crc32(F.coalesce(F.col(column).cast("string"), F.lit(""))) % modulus


#: Keys with more than one in so many rows are joined by broadcast: there are fewer than that.
HOT_SHARE = 2_000
#: Neighbours from which a node is a hub, however few rows there are, and tasks that a hub's neighbours are dealt to.
LEAST_HOT, SALTS = 500, 64


def hot_keys(rows: DataFrame, key: str) -> list:
    """Keys with over 1 / HOT_SHARE of the rows, so fewer than HOT_SHARE. rows is read: a checkpoint."""
    counts = rows.groupBy(key).agg(F.count("*").alias("n")).where(F.col("n") > LEAST_HOT)
    total = rows.count()
    return [r[0] for r in counts.where(F.col("n") * HOT_SHARE > total).select(key).limit(HOT_SHARE).collect()]


def spread_join(rows: DataFrame, classes: DataFrame, key: str, how: str = "inner", n: str = "n", total: int | None = None) -> DataFrame:
    """rows joined with classes (one row a key) on key; the rows of a key that many share stay where they are.

    n: rows of the key, as classes counts them. Keys with over 1 / HOT_SHARE of all, fewer than HOT_SHARE, are
    broadcast; what is shuffled holds no more than that share of a key. rows and classes are read twice.
    """
    if total is None:
        total = classes.agg(F.sum(n)).first()[0] or 0
    if total <= HOT_SHARE:
        return rows.join(classes, key, how)
    hot = F.col(n) * HOT_SHARE > total
    far = F.broadcast(classes.where(hot))  # fewer than HOT_SHARE rows
    rest = rows.join(far.select(key), key, "left_anti").select(*rows.columns)
    return rows.join(far, key).unionByName(rest.join(classes.where(~hot), key, how))


#: Words of 64 bits that are broadcast at most to tell which ids are asked for.
MOST_BITS = 1 << 18


def likely(rows: DataFrame, ids: DataFrame, key: str) -> DataFrame:
    """All rows whose key is among ids and a few others, told apart without a shuffle: an id sets one of 16 bits for each
    row of ids, up to MOST_BITS words, beyond which more of the others come through. The keys are whole numbers."""
    places = 64 * min(MOST_BITS, max(1, ids.count() // 4))
    place = F.pmod(F.xxhash64(F.lit(7), F.col(key).cast("long")), F.lit(places))
    at = ids.select(F.floor(place / 64).cast("int").alias("__word"), F.pmod(place, F.lit(64)).cast("int").alias("__bit"))
    bits = at.groupBy("__word").agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("__bit"))).alias("__bits"))
    found = rows.withColumn("__word", F.floor(place / 64).cast("int")).join(F.broadcast(bits), "__word")
    return found.where(F.getbit("__bits", F.pmod(place, F.lit(64)).cast("int")) == 1).select(*rows.columns)


def components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """Connected components of undirected edges as (node, component), component = smallest node.

    Alternating star contraction: every step hangs larger neighbours onto the smallest
    one and keeps connectivity, so any number of hubs or chain lengths is handled with
    partial aggregates and joins alone; neighbours of hubs are not brought together. Nodes without edges don't appear.
    """
    e = cut(
        edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct()
    )
    before = None
    for _ in range(max_rounds):
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        # neighbours of a hub are dealt over SALTS tasks; its own row goes to each of them
        hubs = hot_keys(e, "v")
        above = e.select(F.col("v").alias("u"), F.col("u").alias("v"))
        if hubs:
            hub = F.col("u").isin(hubs)
            above = above.withColumn("salt", F.when(hub, F.pmod(F.xxhash64("v"), F.lit(SALTS))).otherwise(F.lit(0)).cast("int"))
            low = low.withColumn("salt", F.explode(F.when(hub, F.sequence(F.lit(0), F.lit(SALTS - 1))).otherwise(F.array(F.lit(0)))))
        large = above.join(low, ["u", "salt"] if hubs else "u")
        large = large.select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        joined = large.join(low, "u")
        small = (
            joined.select(F.col("v").alias("u"), F.col("m").alias("v"))
            .union(low.select("u", F.col("m").alias("v")))
            .where("u <> v")
            .distinct()
        )
        e = cut(small)
        now = e.agg(
            F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))
        ).first()
        if before == tuple(now):
            break
        before = tuple(now)
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    roots = e.groupBy("v").agg(F.first("v").alias("component")).select(F.col("v").alias("node"), "component")
    return e.select(F.col("u").alias("node"), F.col("v").alias("component")).union(roots)


class Forest:
    """Union-find over small integers; root = smallest member."""

    def __init__(self, n: int):
        self.parent = list(range(n))

    def find(self, x: int) -> int:
        p = self.parent
        while p[x] != x:
            p[x] = p[p[x]]
            x = p[x]
        return x

    def join(self, x: int, y: int) -> bool:
        x, y = self.find(x), self.find(y)
        if x == y:
            return False
        self.parent[max(x, y)] = min(x, y)
        return True


def seeded(seed: int) -> np.random.Generator:
    return np.random.Generator(np.random.PCG64(seed))
