"""Language identification by nearest centroid.

Texts become normalised TF-IDF vectors of hashed letter n-grams (one to three letters, runs of
anything else are one break). Each language has several centroids, clustered by spherical
k-means over a bounded sample; a text gets the language of the centroid with the largest
cosine. It is rejected if that cosine lies below what its length lets one expect: below
`slack` times the lowest cosine that sample texts of like length have.

The sample is bounded by SAMPLE_PER_LANGUAGE texts of each language, drawn by a hash of the id;
everything else reads all rows whole. Defined cases: null texts and texts without letters are `und` with
score 0 and are rejected; with nothing to learn from, all rows are `und`; equal rows get equal results; ties go to the
language first in order; extra columns pass through `classify` untouched.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, DoubleType, StringType, StructField, StructType

from dynreach.llm.common import seeded

#: About so many texts of each language are drawn to learn from.
SAMPLE_PER_LANGUAGE = 500
CENTROIDS, WIDTH, LENGTH_STEPS = 4, 4096, 24
_MULTIPLIERS = tuple(np.uint32(x) for x in (2654435761, 2246822519, 3266489917))


def _letters(kept: list = []) -> np.ndarray:  # noqa: B006  one per worker
    if not kept:
        kept.append(np.fromiter((chr(i).isalpha() for i in range(sys.maxunicode + 1)), bool, sys.maxunicode + 1))
    return kept[0]


def counts(text: str | None) -> np.ndarray | None:
    """Counts of hashed n-grams; None for a text without letters."""
    if not text:
        return None
    codes = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    letter = _letters()[codes]
    if not letter.any():
        return None
    codes = np.where(letter, codes, np.uint32(0))
    kept = np.ones(len(codes), bool)
    np.logical_or(letter[1:], letter[:-1], out=kept[1:])  # the first of a run that holds no letter
    codes = np.concatenate(([np.uint32(0)], codes[kept], [np.uint32(0)]))
    a, b, c = _MULTIPLIERS
    one = codes * a
    two = (one[:-1] ^ (codes[1:] * b)) * c
    three = (two[:-1] ^ (codes[2:] * a)) * b
    shift = np.uint32(32 - int(WIDTH).bit_length() + 1)
    out = np.zeros(WIDTH, np.float32)
    for grams in (one[codes != 0] * c, two, three):
        out += np.bincount(((grams ^ (grams >> np.uint32(15))) * a) >> shift, minlength=WIDTH)
    return out


@dataclass(frozen=True)
class Model:
    """names[i] is the language of centroids[i]; floor[length step] is the least cosine that isn't rejected."""

    names: tuple[str, ...]
    idf: np.ndarray
    centroids: np.ndarray
    floor: np.ndarray

    def vectors(self, rows: np.ndarray) -> np.ndarray:
        v = np.log1p(rows) * self.idf
        return v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-30)

    def predict(self, texts: list[str | None], batch: int = 256) -> tuple[list[str], list[float], list[bool]]:
        langs, scores, rejected = [], [], []
        for k in range(0, len(texts), batch):
            part = [counts(t) for t in texts[k : k + batch]]
            rows = [c for c in part if c is not None]
            if rows and self.names:
                rows = np.stack(rows)
                cosines = self.vectors(rows) @ self.centroids.T
                best, top = cosines.argmax(1), cosines.max(1)
                step = length_step(rows)
                answers = iter(zip(best, top, top < self.floor[step]))
            else:
                part, answers = [None] * len(part), iter(())
            for c in part:
                i, score, out = next(answers) if c is not None else (None, 0.0, True)
                langs.append("und" if i is None else self.names[i])
                scores.append(min(1.0, max(0.0, float(score))))
                rejected.append(bool(out))
        return langs, scores, rejected


def length_step(rows: np.ndarray) -> np.ndarray:
    """Base-2 logarithm of the number of n-grams, as a step."""
    return np.minimum(np.log2(np.maximum(rows.sum(1), 1)).astype(int), LENGTH_STEPS - 1)


def clusters(vectors: np.ndarray, k: int, seed: int, rounds: int = 12) -> np.ndarray:
    """Spherical k-means; empty clusters go."""
    rng = seeded(seed)
    centres = vectors[rng.choice(len(vectors), min(k, len(vectors)), replace=False)]
    for _ in range(rounds):
        own = (vectors @ centres.T).argmax(1)
        sums = np.stack([vectors[own == i].sum(0) for i in range(len(centres)) if (own == i).any()])
        centres = sums / np.linalg.norm(sums, axis=1, keepdims=True)
    return centres


def learn(
    labelled: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", per_language: int = SAMPLE_PER_LANGUAGE, k: int = CENTROIDS, slack: float = 0.5, seed: int = 11
) -> Model:
    """Fits the model on about per_language texts of each language; the rows' hashes alone decide which."""
    labelled = labelled.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull())
    totals = {r[0]: r[1] for r in labelled.groupBy(lang_col).count().collect()}
    rows: dict[str, list[np.ndarray]] = {}
    if totals:
        share = F.create_map(*[F.lit(x) for name, n in totals.items() for x in (name, min(1.0, per_language / n))])
        drawn = F.pmod(F.xxhash64(F.lit(seed), id_col), F.lit(1_000_003)) / 1_000_003 < share[F.col(lang_col)]

        def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                names, found = [], []
                for name, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                    if (c := counts(text)) is not None:
                        names.append(name)
                        found.append(np.minimum(c, 65535).astype(np.uint16).tobytes())
                yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(found, pa.binary())], ["lang", "counts"])

        for r in labelled.where(drawn).select(lang_col, text_col).mapInArrow(features, "lang string, counts binary").collect():
            rows.setdefault(r.lang, []).append(np.frombuffer(r.counts, np.uint16))
    return fit({name: np.stack(sorted(found, key=lambda c: c.tobytes())) for name, found in rows.items()}, k, slack, seed)


def fit(rows: dict[str, np.ndarray], k: int, slack: float, seed: int) -> Model:
    names = sorted(rows)
    if not names:
        return Model((), np.zeros(WIDTH, np.float32), np.zeros((0, WIDTH), np.float32), np.zeros(LENGTH_STEPS))
    n = sum(len(rows[x]) for x in names)
    held = sum((rows[x] > 0).sum(0) for x in names)
    idf = (np.log((1 + n) / (1 + held)) + 1).astype(np.float32)
    model = Model(tuple(names), idf, np.zeros((0, WIDTH), np.float32), np.zeros(LENGTH_STEPS))
    centres, owners, floor = [], [], np.ones(LENGTH_STEPS)
    for i, name in enumerate(names):
        found = clusters(model.vectors(rows[name].astype(np.float32)), k, seed + i)
        centres.append(found)
        owners += [name] * len(found)
    centroids = np.concatenate(centres).astype(np.float32)
    for name in names:
        top = (model.vectors(rows[name].astype(np.float32)) @ centroids.T).max(1)
        np.minimum.at(floor, length_step(rows[name]), top)
    seen = np.flatnonzero(floor < 1)
    if len(seen):  # steps without a sample text take the floor of the next shorter step, or 0
        for s in range(LENGTH_STEPS):
            if floor[s] >= 1:
                floor[s] = floor[s - 1] if s and s > seen[0] else 0.0
        floor = np.minimum.accumulate(floor[::-1])[::-1]  # longer texts may not be held to less
    return Model(tuple(owners), idf, centroids, floor * slack)


def classify(docs: DataFrame, model: Model, text_col: str = "text", names: tuple[str, str, str] = ("lang_pred", "score", "rejected"), keep: list[str] | None = None) -> DataFrame:
    """The columns kept (all, unless named) with the predicted language, its cosine, and whether it is rejected."""
    keep = docs.columns if keep is None else keep
    schema = StructType([docs.schema[c] for c in keep] + [StructField(names[0], StringType()), StructField(names[1], DoubleType()), StructField(names[2], BooleanType())])
    n = len(keep)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            langs, scores, rejected = model.predict(batch.column(n).to_pylist())
            yield pa.RecordBatch.from_arrays([*batch.columns[:n], pa.array(langs, pa.string()), pa.array(scores, pa.float64()), pa.array(rejected, pa.bool_())], [f.name for f in schema.fields])

    return docs.select(*keep, F.col(text_col).alias("__text")).mapInArrow(run, schema)


def held_out(id_column: str = "doc_id") -> Column:
    from dynreach.llm.common import id_residue

    return id_residue(id_column, 5) == 0


def identify(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score, rejected of every row, learnt from the rows not held out."""
    model = learn(docs.where(~held_out()))
    found = classify(docs.select("doc_id", "text"), model, keep=["doc_id"])
    return found.select("doc_id", held_out().alias("held_out"), "lang_pred", "score", "rejected")
