"""Near-duplicate vectors by spherical-cap filters from structured random product codes.

A filter is a direction made of one random codeword for each of two blocks of the rotated
coordinates; a vector passes if its product with the direction exceeds a threshold. Products with
the blocks' codewords are computed once, and all passing pairs of codewords are listed from them.
The threshold is set from random vectors so that a vector passes about `listed` filters of each code.
The number of codewords grows with the root of a label's own vectors, so a filter holds as many unlike vectors at any
size, and other labels change nothing. More codewords make a code miss more pairs, so codes are added until random pairs
at the cosine asked for share no filter with probability MISS at most: the codes are rotated independently,
so the shares they miss multiply, and each is measured on PAIRS such pairs and raised by three standard errors. Where
that takes more than MOST_TABLES codes, all vectors of a label are in one filter.

Vectors meet in the filters they share with equal labels: filters with one vector drop out before any vector is
moved, large ones are cut into blocks and every pair of blocks is a task of its own. A pair counts in its
smallest common filter only, so links are counted without listing pairs; tasks return
sums per vector and a spanning forest. Equal vectors are one vector with a multiplicity.

Defined cases: vectors that are null, empty, zero or hold null or non-finite components, and those with a null label
or id, link with nothing; vectors of other lengths aren't compared; repeated rows are one vector;
vectors of up to SHORT components are all in one filter; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dynreach.llm.common import Forest, components, cut, seeded
from dynreach.llm.vectors import rotation, usable

CODEWORDS, LISTED, SHORT = 256, 16, 8
MISS, PAIRS, MOST_TABLES, PROBES = 1e-4, 2000, 24, 16
#: Filters of a code for each vector of a label, so that unlike vectors rarely meet at any size.
FILTERS_A_VECTOR = 64
BLOCK, PACK = 512, 2048


@lru_cache(maxsize=64)
def code(d: int, table: int, listed: float, seed: int, codewords: int) -> tuple[np.ndarray, tuple[np.ndarray, np.ndarray], float]:
    """Rotation, codewords of both blocks, and the threshold."""
    turn = rotation(d, seed + table)
    rng = seeded(seed * 7919 + table * 31 + d)
    words = []
    for width in (d // 2, d - d // 2):
        w = rng.standard_normal((codewords, width))
        words.append(w / np.linalg.norm(w, axis=1, keepdims=True) / np.sqrt(2))
    probe = rng.standard_normal((PROBES, d))
    probe /= np.linalg.norm(probe, axis=1, keepdims=True)
    return turn, tuple(words), top_sum(probe[:, : d // 2] @ words[0].T, probe[:, d // 2 :] @ words[1].T, listed)


def top_sum(first: np.ndarray, second: np.ndarray, listed: float) -> float:
    """The value that `listed` of a row's sums first[r, i] + second[r, j] exceed, over all rows; only sums that can be among the top ones are made."""
    n = len(first)
    place = listed * (n - 1 / (first.shape[1] * second.shape[1]))  # from the top; between two sums as a rule
    most = int(np.ceil(place)) + 1
    a, b = -np.sort(-first, axis=1)[:, :most], -np.sort(-second, axis=1)[:, :most]
    # the sum of the i-th and j-th largest has i * j sums at least as large, itself among them
    sums = -np.sort(-np.concatenate([(a[:, i, None] + b[:, : most // (i + 1)]).ravel() for i in range(a.shape[1])]))
    low = min(int(place), len(sums) - 1)
    return float(sums[low] + (place - low) * (sums[min(low + 1, len(sums) - 1)] - sums[low]))


def passed_in(vectors: np.ndarray, table: int, listed: float, seed: int, codewords: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, number) of each filter of one code that a unit vector passes; its best one at least."""
    d = vectors.shape[1]
    turn, (first, second), least = code(d, table, listed, seed, codewords)
    x = vectors @ turn
    a, b = x[:, : d // 2] @ first.T, x[:, d // 2 :] @ second.T
    top = b.max(1)
    r, i = np.nonzero(a + top[:, None] >= np.minimum(least, a.max(1) + top)[:, None])
    k, j = np.nonzero(b[r] >= np.minimum(least - a[r, i], top[r])[:, None])
    return r[k], table * codewords**2 + i[k] * codewords + j


def missed(d: int, table: int, least: float, listed: float, seed: int, codewords: int, pairs: int = PAIRS) -> float:
    """Share of random pairs at cosine `least` that share no filter of a code."""
    rng = seeded(seed * 104_729 + table * 613 + d)
    apart = 0
    for k in range(0, pairs, 250):
        x, y = rng.standard_normal((2, min(250, pairs - k), d))
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        y -= (x * y).sum(1, keepdims=True) * x
        y = least * x + np.sqrt(1 - least * least) * y / np.linalg.norm(y, axis=1, keepdims=True)
        keys = [r * (MOST_TABLES * codewords**2) + f for r, f in (passed_in(v, table, listed, seed, codewords) for v in (x, y))]
        apart += len(x) - len(np.unique(np.intersect1d(*keys) // (MOST_TABLES * codewords**2)))
    return apart / pairs


@lru_cache(maxsize=256)
def tables_for(d: int, codewords: int, least: float, listed: float = LISTED, seed: int = 3) -> int:
    """Codes needed to miss no more than MISS; 0 for a single filter of all vectors."""
    if d <= SHORT:
        return 0
    miss = 1.0
    for table in range(MOST_TABLES):
        m = missed(d, table, least, listed, seed, codewords)
        miss *= min(1.0, max(m, 1 / PAIRS) + 3 * np.sqrt(max(m, 1 / PAIRS) * (1 - m) / PAIRS))
        if miss <= MISS:
            return table + 1
        if miss ** (MOST_TABLES / (table + 1)) > 2 * MISS:
            return 0
    return 0


def passed(vectors: np.ndarray, tables: int, listed: float = LISTED, seed: int = 3, codewords: int = CODEWORDS) -> list[np.ndarray]:
    """Sorted numbers of the filters that each unit vector passes, over all tables."""
    n = len(vectors)
    if not tables:
        return [np.zeros(1, np.int64)] * n
    rows, numbers = map(np.concatenate, zip(*(passed_in(vectors, t, listed, seed, codewords) for t in range(tables))))
    order = np.lexsort((numbers, rows))
    return np.split(numbers[order], np.cumsum(np.bincount(rows, minlength=n))[:-1])


def sized(reps: DataFrame) -> DataFrame:
    """reps with `d` and `codewords`, a power of two that grows with the vectors of equal label and length."""
    reps = reps.withColumn("d", F.size("embedding"))
    many = reps.groupBy("label", "d").count().where(F.col("count") * FILTERS_A_VECTOR > CODEWORDS**2)  # a row for a thousand vectors at most
    many = many.select("label", "d", F.pow(F.lit(2.0), F.ceil(F.log2(F.col("count") * FILTERS_A_VECTOR) / 2)).cast("int").alias("codewords"))
    return reps.join(F.broadcast(many), ["label", "d"], "left").withColumn("codewords", F.coalesce("codewords", F.lit(CODEWORDS)))


def listed_filters(reps: DataFrame, least: float, listed: float, seed: int) -> DataFrame:
    """(rep, filters) of every row."""
    rows = sized(reps).select("rep", "embedding", "d", "codewords")
    tables = {(r.d, r.codewords): tables_for(r.d, r.codewords, least, listed, seed) for r in rows.select("d", "codewords").distinct().collect()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            vectors = [np.array(v, float) for v in batch.column(1).to_pylist()]
            kinds = list(zip(batch.column(2).to_pylist(), batch.column(3).to_pylist()))
            out = [None] * len(vectors)
            for kind in set(kinds):
                at = [i for i, k in enumerate(kinds) if k == kind]
                for k in range(0, len(at), 256):
                    part = np.stack([vectors[i] for i in at[k : k + 256]])
                    part /= np.abs(part).max(1, keepdims=True)
                    part /= np.linalg.norm(part, axis=1, keepdims=True)
                    for i, f in zip(at[k : k + 256], passed(part, tables[kind], listed, seed, kind[1])):
                        out[i] = f
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.list_(pa.int64()))], ["rep", "filters"])

    return rows.mapInArrow(run, "rep long, filters array<long>")


def unit_rows(vectors: list) -> np.ndarray:
    x = np.stack([np.asarray(v, float) for v in vectors])
    scale = np.abs(x).max(1, keepdims=True)
    x = x / np.where((scale > 1e100) | (scale < 1e-100), scale, 1.0)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def counted_pairs(vectors: np.ndarray, filters: list, this: int, cross: np.ndarray | None, least: float) -> np.ndarray:
    """Upper matrix of pairs with enough cosine for which `this` is the smallest common filter."""
    n = len(vectors)
    good = np.triu(vectors @ vectors.T >= least, 1)
    if cross is not None:
        good &= cross[:, None] != cross[None, :]
    if good.any():
        row = np.repeat(np.arange(n), [len(f) for f in filters])
        number = np.concatenate([np.asarray(f, np.int64) for f in filters])
        row, number = row[number < this], number[number < this]
        _, column, held = np.unique(number, return_inverse=True, return_counts=True)
        useful = held[column] > 1 if len(number) else np.zeros(0, bool)
        if useful.any():
            seen = np.zeros((n, len(held)), np.float32)
            seen[row[useful], column[useful]] = 1
            good &= (seen @ seen.T) == 0
    return good


def near_duplicates(
    vectors: DataFrame, least: float = 0.93, listed: float = LISTED, seed: int = 3, block: int = BLOCK, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label"
) -> DataFrame:
    """id, n_links, component_id, kept of every row."""
    named = vectors.select(F.col(id_col).alias("id"), F.col(vector_col).alias("embedding"), F.col(label_col).alias("label"))
    sound = named.where(usable("embedding") & F.col("label").isNotNull() & F.col("id").isNotNull()).distinct()
    reps = cut(sound.groupBy("label", "embedding").agg(F.min("id").alias("rep"), F.count("*").alias("many")))
    listed_rows = cut(listed_filters(reps, least, listed, seed))

    keyed = reps.select("rep", "label", F.size("embedding").alias("d")).join(listed_rows, "rep")
    places = keyed.select("rep", F.xxhash64("label", "d").alias("kind"), F.explode("filters").alias("filter"))
    sizes = places.groupBy("kind", "filter").agg(F.count("*").alias("n")).where("n > 1")
    blocks = F.ceil(F.col("n") / block).cast("int")
    own = F.pmod(F.xxhash64("rep"), blocks).cast("int")
    dealt = cut(places.join(sizes, ["kind", "filter"]).select("rep", "kind", "filter", blocks.alias("blocks"), own.alias("own")))
    packs = max(1, dealt.count() // PACK)
    dealt = (
        dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
        .withColumns({"i": F.least("own", "other"), "j": F.greatest("own", "other")})
        .withColumn("task", F.when(F.col("blocks") == 1, F.pmod(F.xxhash64("kind", "filter"), F.lit(packs))).otherwise(F.xxhash64("kind", "filter", "i", "j")))
    )
    shipped = reps.select("rep", "many", "label", "embedding").join(listed_rows, "rep").join(dealt.select("rep", "kind", "filter", "own", "i", "j", "task"), "rep")

    def check(rows: pd.DataFrame) -> pd.DataFrame:
        counts, ends = [], []
        for (_, this, i, j, _, _), group in rows.groupby(["kind", "filter", "i", "j", "label", rows["embedding"].map(len)], sort=False):
            if len(group) < 2:
                continue
            x, ids, many = unit_rows(group["embedding"].tolist()), group["rep"].to_numpy(), group["many"].to_numpy()
            good = counted_pairs(x, group["filters"].tolist(), this, group["own"].to_numpy() if i != j else None, least)
            a, b = np.nonzero(good)
            if not len(a):
                continue
            found = np.bincount(a, many[b], len(ids)) + np.bincount(b, many[a], len(ids))
            counts += [(int(r), None, int(c)) for r, c in zip(ids, found) if c]
            forest = Forest(len(ids))
            ends += [(int(ids[p]), int(ids[q]), None) for p, q in zip(a.tolist(), b.tolist()) if forest.join(p, q)]
        return pd.DataFrame(counts + ends, columns=["a", "b", "links"]).astype({"a": "int64", "b": "Int64", "links": "Int64"})

    found = cut(shipped.groupBy("task").applyInPandas(check, "a long, b long, links long"))
    links = found.where("links is not null").groupBy("a").agg(F.sum("links").alias("links"))
    parts = components(found.where("b is not null").select("a", "b"))
    classes = reps.join(links, F.col("rep") == F.col("a"), "left").join(parts, F.col("rep") == F.col("node"), "left")
    classes = classes.select("label", "embedding", (F.coalesce("links", F.lit(0)) + F.col("many") - 1).alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    # equal vectors share all links, so what holds for the smallest id holds for each
    rows = named.withColumn("ok", usable("embedding") & F.col("label").isNotNull() & F.col("id").isNotNull())
    mine = rows.where("ok").join(classes, ["label", "embedding"]).select("id", "n_links", "component_id")
    rest = rows.where("not ok").select("id", F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component_id"))
    return mine.union(rest).select(F.col("id").alias(id_col), F.col("n_links").cast("long").alias("n_links"), "component_id", F.col("component_id").eqNullSafe(F.col("id")).alias("kept"))
