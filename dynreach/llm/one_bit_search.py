"""Nearest vectors by inner product, from randomly rotated one-bit codes.

The index keeps of each vector the signs of its rotated components, packed, with two scalars: its
norm, and the product of its unit vector with its code. A query is rounded to a few bits a component and taken apart into
planes, so that its product with a code is a sum of bit counts of packed words. From these the inner product with a
query is estimated without bias, and an error bound holds with a probability set by `trust`. Exact
products are computed only for vectors whose upper bound reaches the k-th best exact product found
so far. All rows are indexed; nothing is fitted.

Queries and rows meet in blocks: a task holds one block of rows and one of queries and returns k
rows for each query. Vectors travel with their codes: for a block of some thousand queries that is less than
fetching the candidates of each one. Defined cases: vectors that are null, empty, zero or hold null or non-finite
components, and null ids, take no part; vectors of other lengths aren't compared; repeated rows count once; ties go to the smaller id; with
fewer than k candidates all are returned.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from dynreach.llm.common import cut
from dynreach.llm.vectors import rotation, usable

ROW_BLOCK, QUERY_BLOCK, TRUST, SEED = 16_384, 4_096, 4.0, 29
#: Bits of a query's components.
PLANES = 8
#: Vectors of the largest estimates whose products are computed first: the k-th best of them is what bounds are held against.
FIRST = 256


def codes(vectors: np.ndarray, seed: int = SEED) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Packed signs, norms, and products of the unit vectors with their codes."""
    d = vectors.shape[1]
    norms = np.linalg.norm(vectors, axis=1)
    turned = vectors / norms[:, None] @ rotation(d, seed)
    return np.packbits(turned >= 0, axis=1), norms, np.abs(turned).sum(1) / np.sqrt(d)


def words(bits: np.ndarray) -> np.ndarray:
    """Packed bytes as 64-bit words, filled up with zeros."""
    return np.ascontiguousarray(np.pad(bits, ((0, 0), (0, -bits.shape[1] % 8)))).view(np.uint64)


def counted(columns: list[np.ndarray], plane: np.ndarray) -> np.ndarray:
    """Bits that each row's words have in common with the plane; columns hold the first words of all rows, the second ones, and so on."""
    if len(columns) == 1:
        return np.bitwise_count(columns[0] & plane[0])
    total = np.zeros(len(columns[0]), np.int32)
    for column, word in zip(columns, plane):
        total += np.bitwise_count(column & word)
    return total


def bit_planes(x: np.ndarray) -> tuple[np.ndarray, float, float, float, float]:
    """A query in PLANES bits a component, as packed planes from the lowest bit on, with the value of zero, the step, the
    sum of all components, and the length of what rounding takes away, by which products with unit vectors are off at most."""
    low, high = float(x.min()), float(x.max())
    step = (high - low) / ((1 << PLANES) - 1) or 1.0
    level = np.rint((x - low) / step).astype(np.int64)
    planes = np.packbits((level[None, :] >> np.arange(PLANES)[:, None] & 1).astype(np.uint8), axis=1)
    rounded = low + step * level
    return words(planes), low, step, float(rounded.sum()), float(np.linalg.norm(x - rounded))


def index(vectors: DataFrame, id_col: str, vector_col: str, seed: int = SEED) -> DataFrame:
    """(vec_id, embedding, bits, norm, fit) of every usable row."""
    rows = vectors.select(F.col(id_col).alias("vec_id"), F.col(vector_col).alias("embedding")).where(usable("embedding") & F.col("vec_id").isNotNull()).distinct()
    kind = rows.schema["embedding"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [np.array(v, float) for v in batch.column(1).to_pylist()]
            bits, norm, fit = [None] * len(found), np.zeros(len(found)), np.zeros(len(found))
            for d in {len(v) for v in found}:
                at = [i for i, v in enumerate(found) if len(v) == d]
                packed, norm[at], fit[at] = codes(np.stack([found[i] for i in at]), seed)
                for i, p in zip(at, packed):
                    bits[i] = p.tobytes()
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(bits, pa.binary()), pa.array(norm), pa.array(fit)], ["vec_id", "embedding", "bits", "norm", "fit"])

    return rows.mapInArrow(run, f"vec_id long, embedding {kind}, bits binary, norm double, fit double")


def best_of_block(
    queries: np.ndarray, query_ids: np.ndarray, vectors: np.ndarray, ids: np.ndarray, bits: np.ndarray, norms: np.ndarray, fits: np.ndarray, k: int, trust: float, seed: int = SEED
) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(query id, ids, products) of each query's k best vectors of a block."""
    d = vectors.shape[1]
    columns = [np.ascontiguousarray(c) for c in words(bits).T]
    held = counted(columns, [np.uint64(0xFFFFFFFFFFFFFFFF)] * len(columns))
    scale = norms / fits / np.sqrt(d)
    slack = norms * np.sqrt(np.maximum(1 - fits**2, 0)) / fits * trust / np.sqrt(max(d - 1, 1))
    loose, rounding = norms / fits, 1e-12 * d * norms.max(initial=0.0)
    turned = queries @ rotation(d, seed)
    lengths = np.linalg.norm(queries, axis=1)
    for q, x in enumerate(turned):
        planes, low, step, whole, error = bit_planes(x)
        # a component counts once where its bit is set and against it where not: twice the set ones less all
        weighted = np.zeros(len(ids), np.int64)
        for plane in planes[::-1]:
            weighted *= 2
            weighted += counted(columns, plane)
        estimate = (2 * (low * held + step * weighted) - whole) * scale
        if len(ids):
            upper = estimate + slack * lengths[q] + loose * error
            most = min(max(k + 1, FIRST), len(ids))  # the query itself may be among them
            first = np.argpartition(estimate, len(ids) - most)[len(ids) - most :]
            first = first[ids[first] != query_ids[q]]
            least = np.partition(vectors[first] @ queries[q], len(first) - k)[len(first) - k] if len(first) >= k else -np.inf
            chosen = np.flatnonzero(upper >= least - 1e-5 * abs(least)) if least > -np.inf else np.arange(len(ids))
            chosen = chosen[ids[chosen] != query_ids[q]]
            if len(chosen) > k:  # summed in any order first: what is off by more than rounding can't be among the k best
                rough = vectors[chosen] @ queries[q]
                chosen = chosen[~(rough < np.partition(rough, len(chosen) - k)[len(chosen) - k] - rounding * lengths[q])]
            products = np.cumsum(vectors[chosen] * queries[q], axis=1)[:, -1]  # summed in order, as SQL does
            order = np.lexsort((ids[chosen], -products))[:k]
            yield query_ids[q], ids[chosen][order], products[order]


def search(
    vectors: DataFrame, queries: DataFrame, k: int = 20, id_col: str = "vec_id", vector_col: str = "embedding", trust: float = TRUST, row_block: int = ROW_BLOCK, query_block: int = QUERY_BLOCK
) -> DataFrame:
    """query_id, rank, vec_id, score: each query's k best rows but itself, nearest first."""
    indexed = cut(index(vectors, id_col, vector_col))
    asked = queries.select(F.col(id_col).alias("query_id"), F.col(vector_col).alias("query")).where(usable("query") & F.col("query_id").isNotNull()).distinct()
    asked = cut(asked)
    row_blocks, query_blocks = max(1, -(-indexed.count() // row_block)), max(1, -(-asked.count() // query_block))
    rows = indexed.withColumns({"r": F.pmod(F.xxhash64("vec_id"), F.lit(row_blocks)).cast("int"), "q": F.explode(F.sequence(F.lit(0), F.lit(query_blocks - 1)))})
    wanted = asked.withColumns({"q": F.pmod(F.xxhash64("query_id"), F.lit(query_blocks)).cast("int"), "r": F.explode(F.sequence(F.lit(0), F.lit(row_blocks - 1)))})

    def meet(block: pd.DataFrame, those: pd.DataFrame) -> pd.DataFrame:
        out = []
        sizes, wants = block["embedding"].map(len).to_numpy(), those["query"].map(len).to_numpy()
        for d in set(sizes.tolist()) & set(wants.tolist()):
            b, t = block[sizes == d], those[wants == d]
            bits = np.stack([np.frombuffer(x, np.uint8) for x in b["bits"]])
            found = best_of_block(
                np.stack(t["query"].tolist()).astype(float), t["query_id"].to_numpy(), np.stack(b["embedding"].tolist()).astype(float), b["vec_id"].to_numpy(), bits, b["norm"].to_numpy(), b["fit"].to_numpy(), k, trust
            )
            out += [pd.DataFrame({"query_id": q, "vec_id": ids, "score": products}) for q, ids, products in found]
        return pd.concat(out) if out else pd.DataFrame({"query_id": [], "vec_id": [], "score": []})

    met = rows.groupBy("r", "q").cogroup(wanted.groupBy("r", "q")).applyInPandas(meet, "query_id long, vec_id long, score double")
    nearest = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return met.withColumn("rank", F.row_number().over(nearest)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
