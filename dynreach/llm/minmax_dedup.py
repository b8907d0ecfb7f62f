"""Near-duplicate documents by min-max hashing, bands, and a check on full shingle sets.

Every permutation gives two values of a set, its smallest and its largest hash, so that a signature
of 2 * PERMUTATIONS values costs PERMUTATIONS hash evaluations per shingle. Bands of the signature
name buckets. Work after that:

1. Documents with equal sets are one class, held by its smallest id.
2. Each bucket points its classes to its smallest one; the connected parts of those pointers
   hold all pairs that share a bucket. In a part beyond a block of BLOCK classes each is compared with the smallest one first: those
   linked to it are connected, and no pair of them is looked at again, so a vast family of near copies costs its size.
   The rest is compared in blocks: each pair of blocks with a class that is not tied is a task of its own that checks all
   its pairs which share a bucket on their full sets and returns a spanning forest of the links it finds.
   Parts beyond PART classes are compared bucket by bucket in the same way; a pair then counts in its first common bucket.
3. Components of the links, by distributed star contraction.

Texts that no comparison asks for are left where they are: bits of the ids in question are broadcast, and only what they
let through is shuffled. No pair that shares a band is skipped, and no group is gathered whole. Defined cases: null texts and
texts without words have no shingles and link with nothing; texts under `width` words are one
shingle; rows that share an id are one document, null ids link with nothing; extra columns pass through `dedup`.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dynreach.llm.common import Forest, components, cut, give_back, likely, seeded, spread_join

WIDTH, PERCENT = 5, 85
PERMUTATIONS = 128
#: A pair at the threshold shares no band with this probability at most.
MISS = 1e-4
BLOCK, PART, PACK = 512, 20_000, 512
MOST_WORDS = 400_000
_STEP, _MIX = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)
_LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))
_WORD = r"[^\x09-\x0D\x20]"
_ODD = seeded(97).integers(0, 1 << 31, PERMUTATIONS, dtype=np.uint64).astype(np.uint32) * np.uint32(2) + np.uint32(1)


class _Words(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) >= MOST_WORDS:
            self.clear()
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


_WORDS = _Words()


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * _MIX
    return h ^ (h >> np.uint64(29))


def shingles(text: str | None, width: int = WIDTH) -> np.ndarray:
    """Distinct 64-bit shingle hashes in order; bytes of A-Z are folded, words part at ASCII white space."""
    words = (text or "").encode().translate(_LOWER).split()
    n = len(words)
    if not n:
        return np.zeros(0, np.uint64)
    w = np.fromiter(map(_WORDS.__getitem__, words), np.uint64, n)
    if n < width:
        return _mixed(np.array([_fold(w)], np.uint64))
    h = w[: n - width + 1]
    for k in range(1, width):
        h = h * _STEP + w[k : n - width + 1 + k]
    return np.unique(_mixed(h))


def _fold(w: np.ndarray) -> int:
    h = len(w)
    for x in w.tolist():
        h = (h * int(_STEP) + x) & 0xFFFFFFFFFFFFFFFF
    return h


def signature(hashes: np.ndarray) -> np.ndarray:
    """Smallest values under all permutations, then the largest ones."""
    x = (hashes >> np.uint64(32)).astype(np.uint32)[:, None]
    low, high = np.full(PERMUTATIONS, 0xFFFFFFFF, np.uint32), np.zeros(PERMUTATIONS, np.uint32)
    for k in range(0, len(x), 2048):
        moved = x[k : k + 2048] * _ODD
        np.minimum(low, moved.min(0), out=low)
        np.maximum(high, moved.max(0), out=high)
    return np.concatenate([low, high])


def band_rows(percent: int = PERCENT) -> int:
    """Values a band: the most that keep a pair at the threshold from sharing no band but with probability MISS."""
    return next((r for r in range(16, 1, -1) if (1 - (percent / 100) ** r) ** (2 * PERMUTATIONS // r) <= MISS), 1)


def band_keys(signatures: np.ndarray, rows: int) -> np.ndarray:
    """A 64-bit key for each band of each row; the band is part of the key."""
    bands = 2 * PERMUTATIONS // rows
    parts = signatures[:, : bands * rows].reshape(len(signatures), bands, rows).astype(np.uint64)
    keys = np.broadcast_to(np.arange(1, bands + 1, dtype=np.uint64) * _MIX, parts.shape[:2])
    for k in range(rows):
        keys = _mixed((keys ^ parts[:, :, k]) * _STEP)
    return keys.view(np.int64)


def sketches(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, percent: int = PERCENT) -> DataFrame:
    """(id, n_shingles, set_hash, bands) of every row; set_hash and bands are null for empty sets."""
    band = band_rows(percent)
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes, hashes, rows, keys = [], [], [], []
            for text in batch.column(1).to_pylist():
                s = shingles(text, width)
                sizes.append(len(s))
                hashes.append(xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None)
                if len(s):
                    rows.append(signature(s))
            keys = iter(band_keys(np.stack(rows), band)) if rows else iter(())
            bands = [next(keys) if n else None for n in sizes]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes, pa.int64()), pa.array(hashes, pa.binary()), pa.array(bands, pa.list_(pa.int64()))], [id_col, "n_shingles", "set_hash", "bands"])
        _WORDS.clear()  # the worker goes on to other operators
        give_back()

    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, n_shingles long, set_hash binary, bands array<long>")


def enough(common: np.ndarray, a: np.ndarray, b: np.ndarray, percent: int = PERCENT) -> np.ndarray:
    return 100 * common >= percent * (a + b - common)


def verified_links(sets: list[np.ndarray], bands: np.ndarray, cross: np.ndarray | None, first_key: int | None, percent: int = PERCENT) -> list[tuple[int, int]]:
    """A spanning forest of the links between sets that share a band.

    cross: only pairs whose sides differ in it. first_key: only pairs whose first common band has this key.
    """
    n = len(sets)
    shared = np.zeros((n, n), bool)
    if first_key is None:
        for k in range(bands.shape[1]):
            shared |= bands[:, k, None] == bands[None, :, k]
    else:
        open_ = np.ones((n, n), bool)
        for k in range(bands.shape[1]):
            same = open_ & (bands[:, k, None] == bands[None, :, k])
            shared |= same & (bands[:, k] == first_key)[:, None]
            open_ &= ~same
    if cross is not None:
        shared &= cross[:, None] != cross[None, :]
    sizes = np.fromiter(map(len, sets), np.int64, n)
    shared &= enough(np.minimum(sizes[:, None], sizes[None, :]), sizes[:, None], sizes[None, :], percent)
    a, b = np.nonzero(np.triu(shared, 1))
    forest, links = Forest(n), []
    if len(a) > 64 and (common := _products(sets)) is not None:
        good = enough(common[a, b], sizes[a], sizes[b], percent)
        return [(i, j) for i, j in zip(a[good].tolist(), b[good].tolist()) if forest.join(i, j)]
    for i, j in zip(a.tolist(), b.tolist()):
        if forest.find(i) != forest.find(j):
            common = len(np.intersect1d(sets[i], sets[j], assume_unique=True))
            if enough(common, sizes[i], sizes[j], percent):
                forest.join(i, j)
                links.append((i, j))
    return links


def _products(sets: list[np.ndarray], most_cells: int = 40_000_000) -> np.ndarray | None:
    """Sizes of all intersections by one product of 0/1 rows; None if those would not fit."""
    _, number, held = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    column = np.cumsum(held > 1) - 1
    width = int(column[-1]) + 1
    if width * len(sets) > most_cells:
        return None
    row, useful = np.repeat(np.arange(len(sets)), [len(s) for s in sets]), held[number] > 1
    ones = np.zeros((len(sets), width), np.float32)
    ones[row[useful], column[number[useful]]] = 1
    return (ones @ ones.T).astype(np.int64)


def star_links(texts: DataFrame, members: DataFrame, width: int = WIDTH, percent: int = PERCENT, block: int = BLOCK) -> DataFrame:
    """(a, b): links of the classes of parts beyond a block with their part's smallest class. Each text is shipped once,
    and the smallest class's to every block."""
    blocks = F.ceil(F.col("part_size") / block).cast("int")
    large = members.where(F.col("part_size") > block).select("rep", "component", blocks.alias("blocks"))
    centre = F.col("rep") == F.col("component")
    rows = large.where(~centre).select("rep", "component", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int").alias("at"), F.lit(False).alias("centre"))
    centres = large.where(centre).select("rep", "component", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("at"), F.lit(True).alias("centre"))

    texts = likely(texts, large.select("rep"), "rep")

    def check(group: pd.DataFrame) -> pd.DataFrame:
        group = group.drop_duplicates("rep")
        found, middle = [], shingles(group["text"][group["centre"]].iloc[0], width)
        for rep, text in zip(group["rep"][~group["centre"]].tolist(), group["text"][~group["centre"]]):
            s = shingles(text, width)
            if enough(len(np.intersect1d(s, middle, assume_unique=True)), len(s), len(middle), percent):
                found.append((rep, int(group["component"].iloc[0])))
        _WORDS.clear()
        return pd.DataFrame(found, columns=["a", "b"]).astype("int64")

    return texts.join(rows.union(centres), "rep").groupBy("component", "at").applyInPandas(check, "a long, b long")


def links(docs: DataFrame, sketched: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, percent: int = PERCENT, block: int = BLOCK, part: int = PART) -> DataFrame:
    """(a, b): links that connect all documents linked directly or through others."""
    full = sketched.where(F.col("set_hash").isNotNull() & F.col(id_col).isNotNull())
    by_set = full.groupBy("set_hash").agg(F.min(id_col).alias("rep"), F.first("bands").alias("bands"), F.count("*").alias("n"))
    several = cut(by_set.where("n > 1").select("set_hash", "rep", "n"))
    copies = spread_join(full.select(id_col, "set_hash"), several, "set_hash").where(F.col(id_col) != F.col("rep")).select(F.col(id_col).alias("a"), F.col("rep").alias("b"))

    exploded = by_set.select("rep", F.explode("bands").alias("key"))
    buckets = exploded.groupBy("key").agg(F.count("*").alias("n"), F.min("rep").alias("pivot")).where("n > 1").select("key", "pivot")
    pointers = exploded.join(buckets, "key").where("rep <> pivot").select(F.col("rep").alias("a"), F.col("pivot").alias("b"))
    loose = components(pointers)
    sizes = loose.groupBy("component").agg(F.count("*").alias("part_size"))
    members = cut(loose.join(sizes, "component").join(by_set.select("rep", "bands"), F.col("node") == F.col("rep")).select("rep", "bands", "component", "part_size"))
    texts, packs = docs.select(F.col(id_col).alias("rep"), F.col(text_col).alias("text")), max(1, members.count() // PACK)
    vast_parts = not members.where(F.col("part_size") > block).isEmpty()  # else texts are not shuffled for them
    stars = cut(star_links(texts, members, width, percent, block)) if vast_parts else docs.sparkSession.createDataFrame([], "a long, b long")
    tied = members.join(stars.select(F.col("a").alias("rep"), F.lit(True).alias("tied")), "rep", "left")
    # the classes tied to their part's smallest one are connected: only pairs with one that is not are still open
    members = tied.withColumn("tied", (F.col("part_size") > block) & (F.coalesce("tied", F.lit(False)) | (F.col("rep") == F.col("component"))))
    whole = members.where(F.col("part_size") <= part).select("rep", "bands", F.col("component").alias("unit"), F.lit(False).alias("by_bucket"), "tied")
    vast = members.where(F.col("part_size") > part).select("rep", "bands", F.explode("bands").alias("unit"), F.lit(True).alias("by_bucket"), "tied")
    units = whole.unionByName(vast)
    sizes = units.groupBy("by_bucket", "unit").agg(F.count_if(~F.col("tied")).alias("n_free"), F.count_if("tied").alias("n_tied")).where("n_free > 0 and n_free + n_tied > 1")
    units = units.join(sizes, ["by_bucket", "unit"])

    free = F.ceil(F.col("n_free") / block).cast("int")
    one = F.col("n_free") + F.col("n_tied") <= block
    kept = F.ceil(F.col("n_tied") / block).cast("int")
    own = F.when(one, 0).otherwise(F.when(F.col("tied"), F.col("free") + F.pmod(F.xxhash64("rep"), F.greatest(F.col("kept"), F.lit(1)))).otherwise(F.pmod(F.xxhash64("rep"), F.col("free")))).cast("int")
    # free blocks meet each other and the tied ones, tied blocks only free ones
    last = F.when(F.col("one"), 0).when(F.col("tied"), F.col("free") - 1).otherwise(F.col("free") + F.col("kept") - 1)
    dealt = (
        units.withColumns({"free": free, "kept": kept, "one": one})
        .withColumn("own", own)
        .withColumn("other", F.explode(F.sequence(F.lit(0), last)))
        .withColumns({"i": F.least("own", "other"), "j": F.greatest("own", "other")})
        .withColumn("task", F.when(F.col("one"), F.pmod(F.xxhash64("unit"), F.lit(packs))).otherwise(F.xxhash64("by_bucket", "unit", "i", "j")))
        .select("rep", "bands", "unit", "by_bucket", "own", "i", "j", "task")
    )
    shipped = likely(texts, units.select("rep"), "rep").join(dealt, "rep")

    def check(rows: pd.DataFrame) -> pd.DataFrame:
        found = []
        for (by_bucket, unit, i, j), group in rows.groupby(["by_bucket", "unit", "i", "j"], sort=False):
            group = group.drop_duplicates("rep")
            if len(group) < 2:
                continue
            ids = group["rep"].tolist()
            sets = [shingles(t, width) for t in group["text"]]
            own = group["own"].to_numpy() if i != j else None
            for x, y in verified_links(sets, np.stack(group["bands"].tolist()), own, int(unit) if by_bucket else None, percent):
                found.append((ids[x], ids[y]))
        _WORDS.clear()
        give_back()
        return pd.DataFrame(found, columns=["a", "b"]).astype("int64")

    near = shipped.groupBy("task").applyInPandas(check, "a long, b long")
    return copies.select(F.col("a").cast("long"), F.col("b").cast("long")).union(stars).union(near)


def dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, percent: int = PERCENT, block: int = BLOCK, part: int = PART) -> DataFrame:
    """id, n_shingles, component_id (smallest id reachable by links), kept, for every row."""
    sketched = cut(sketches(docs, id_col, text_col, width, percent))
    found = components(links(docs, sketched, id_col, text_col, width, percent, block, part))
    joined = sketched.join(found, F.col(id_col) == F.col("node"), "left")
    component = F.coalesce("component", F.col(id_col))
    return joined.select(id_col, "n_shingles", component.alias("component_id"), component.eqNullSafe(F.col(id_col)).alias("kept"))


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = PERCENT) -> DataFrame:
    """The documents kept, with their columns as they are; rows with shingles whose id and text are equal leave one row."""
    found = cut(dedup(docs, id_col, text_col, percent=percent))
    gone = found.where("not kept").select(id_col).distinct()
    repeated = found.where(F.col("kept") & (F.col("n_shingles") > 0) & F.col(id_col).isNotNull()).groupBy(id_col).count().where("count > 1").select(id_col)
    left = docs.join(gone, id_col, "left_anti").select(*docs.columns)
    if repeated.isEmpty():
        return left
    repeated = cut(repeated)
    several, worded = left.join(repeated, id_col, "left_semi"), F.coalesce(F.col(text_col).rlike(_WORD), F.lit(False))
    whole = F.struct(*[F.col(c) for c in docs.columns])
    once = several.where(worded).groupBy(id_col, text_col).agg(F.min_by(whole, F.to_json(whole)).alias("row")).select("row.*")
    return left.join(repeated, id_col, "left_anti").select(*docs.columns).union(once).union(several.where(~worded).select(*docs.columns))
