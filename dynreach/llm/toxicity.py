"""Toxicity by gradient-boosted trees over dense features, with isotonic calibration.

The features of a text are densities: of lexicon words, of lexicon words near a second-person
pronoun, of capitals, punctuation, and obfuscated words. The lexicon is learnt: whole words and word stems
that labelled texts with label 1 hold far more often than the others, counted by an aggregate.
Trees are fitted on two thirds of a bounded sample of labelled rows, calibrated on the rest,
with weights that restore the labels' shares.

The sample is bounded by SAMPLE_PER_LABEL rows of each label, drawn by a hash of the id. Defined
cases: null or empty texts get the score of their (zero) features; labels that are null are not
learnt from; without both labels every score is the share of label 1 (0 if there is none), and if two thirds of the sample lack a label all of it is fitted; an id with several labels counts with
each; equal rows get equal scores; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dynreach.llm.common import cut, id_residue

#: About so many labelled rows of each label are learnt from.
SAMPLE_PER_LABEL = 5000
MOST_TERMS, LEAST_TEXTS, LEAST_LIFT, STEMS = 600, 8, 8.0, (3, 4, 5, 6, 7)
NEAR, MOST_WORDS = 5, 1_000_000
#: Second-person pronouns of English, French, German and Spanish.
SECOND_PERSON = frozenset("you your yours yourself u ur tu te toi ton ta tes vous votre vos du dich dir dein deine sie ihr euch usted ustedes ti vosotros".split())
FEATURES = ("log_words", "hits", "distinct_hits", "lift", "top_lift", "near_you", "you", "capitals", "shouted", "exclaims", "questions", "punctuation", "obfuscated", "stretched", "digits", "hit_count")
_STRIP = "".join(chr(i) for i in range(33, 127) if not chr(i).isalnum())
_HIT, _YOU, _SHOUT, _ODD, _LONG = 1, 2, 4, 8, 16
#: Characters written for letters.
_STANDS_FOR = str.maketrans("013457@$!", "oieastasi")


@dataclass
class Lexicon:
    """lift of whole words and of stems `word*`."""

    lift: dict[str, float]
    kept: dict[str, tuple[int, int]] = field(default_factory=dict, repr=False)

    def __post_init__(self):
        self.terms = sorted(self.lift)
        self.number = {t: i + 1 for i, t in enumerate(self.terms)}
        self.lifts = np.array([0.0, *(self.lift[t] for t in self.terms)])

    def __getstate__(self):
        return {"lift": self.lift}

    def __setstate__(self, state):
        self.lift, self.kept = state["lift"], {}
        self.__post_init__()

    def code(self, raw: str) -> int:
        """flags + 32 * number of the term, by white-space word."""
        word = raw.strip(_STRIP)
        low = word.lower()
        flags, term = 0, self.find(low)
        inner = any(not c.isalpha() for c in low) and any(c.isalpha() for c in low)
        if inner and "'" not in low and "-" not in low:
            flags |= _ODD
            term = term or self.find("".join(c for c in low.translate(_STANDS_FOR) if c.isalpha()))
        if any(a == b == c for a, b, c in zip(low, low[1:], low[2:])) and low.isalpha():
            flags |= _LONG
        if low in SECOND_PERSON:
            flags |= _YOU
        if len(word) > 2 and word.isupper():
            flags |= _SHOUT
        return flags | (_HIT if term else 0) | term * 32

    def find(self, low: str) -> int:
        best = self.number.get(low, 0)
        for n in STEMS:
            k = self.number.get(low[:n] + "*", 0) if len(low) >= n else 0
            if k and self.lifts[k] > self.lifts[best]:
                best = k
        return best

    def codes(self, words: list[str]) -> np.ndarray:
        kept = self.kept
        if len(kept) > MOST_WORDS:
            kept.clear()
        for w in set(words).difference(kept):
            kept[w] = self.code(w)
        return np.fromiter(map(kept.__getitem__, words), np.int64, len(words))


_PUNCTUATION = np.array([i < 128 and chr(i) in _STRIP for i in range(256)])


def features(text: str | None, lexicon: Lexicon) -> list[float]:
    text = text or ""
    words = text.split()
    n = max(1, len(words))
    codes = lexicon.codes(words)
    raw = np.bincount(np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8), minlength=256)
    chars = max(1, int(raw.sum()))
    hit, you = np.flatnonzero(codes & _HIT), np.flatnonzero(codes & _YOU)
    lifts = lexicon.lifts[codes[hit] >> 5]
    near = 0
    if len(hit) and len(you):
        at = np.searchsorted(you, hit)
        before = np.where(at > 0, hit - you[np.maximum(at - 1, 0)], NEAR + 1)
        after = np.where(at < len(you), you[np.minimum(at, len(you) - 1)] - hit, NEAR + 1)
        near = int((np.minimum(before, after) <= NEAR).sum())
    share = lambda flag: float(np.count_nonzero(codes & flag)) / n
    return [
        np.log1p(len(words)), len(hit) / n, len(set((codes[hit] >> 5).tolist())), float(lifts.sum()) / n, float(lifts.max(initial=0)), near / n, len(you) / n,
        float(raw[65:91].sum()) / chars, share(_SHOUT), float(raw[33]) / n, float(raw[63]) / n, float(raw[_PUNCTUATION].sum()) / chars, share(_ODD), share(_LONG), float(raw[48:58].sum()) / chars, len(hit),
    ]


@dataclass(frozen=True)
class Tree:
    """A complete binary tree: split features and bins by level order, then leaf values."""

    feature: np.ndarray
    bin: np.ndarray
    leaf: np.ndarray

    def predict(self, bins: np.ndarray) -> np.ndarray:
        node, rows = np.zeros(len(bins), int), np.arange(len(bins))
        for _ in range(int(np.log2(len(self.leaf)))):
            node = 2 * node + 1 + (bins[rows, self.feature[node]] > self.bin[node])
        return self.leaf[node - len(self.feature)]


class Boosted:
    """Logistic gradient boosting on histograms of quantile bins."""

    def __init__(self, trees: int = 60, depth: int = 3, rate: float = 0.2, bins: int = 32, ridge: float = 1.0):
        self.n, self.depth, self.rate, self.most_bins, self.ridge = trees, depth, rate, bins, ridge

    def binned(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(e, x[:, k], side="left") for k, e in enumerate(self.edges)], 1)

    def fit(self, x: np.ndarray, y: np.ndarray, w: np.ndarray) -> Boosted:
        quantiles = np.linspace(0, 1, self.most_bins + 1)[1:-1]
        self.edges = [np.unique(np.concatenate([np.quantile(c, quantiles), np.quantile(c[c > 0], quantiles) if (c > 0).any() else []])) for c in x.T]
        b, width = self.binned(x), max(len(e) for e in self.edges) + 1
        share = np.clip((w * y).sum() / w.sum(), 1e-6, 1 - 1e-6)
        self.base = float(np.log(share / (1 - share)))
        score, self.trees = np.full(len(y), self.base), []
        for _ in range(self.n):
            p = 1 / (1 + np.exp(-score))
            tree = self._grow(b, w * (y - p), w * np.maximum(p * (1 - p), 1e-6), width)
            self.trees.append(tree)
            score = score + tree.predict(b)
        return self

    def _grow(self, b: np.ndarray, g: np.ndarray, h: np.ndarray, width: int) -> Tree:
        inner = 2**self.depth - 1
        feature, split, node = np.zeros(inner, int), np.full(inner, width), np.zeros(len(b), int)
        for level in range(self.depth):
            first, many = 2**level - 1, 2**level
            at = node - first
            best = np.zeros(many)
            for k in range(b.shape[1]):
                cell = at * width + b[:, k]
                gs = np.bincount(cell, g, many * width).reshape(many, width).cumsum(1)
                hs = np.bincount(cell, h, many * width).reshape(many, width).cumsum(1)
                gt, ht = gs[:, -1:], hs[:, -1:]
                gain = gs**2 / (hs + self.ridge) + (gt - gs) ** 2 / (ht - hs + self.ridge) - gt**2 / (ht + self.ridge)
                top = gain.argmax(1)
                value = gain[np.arange(many), top]
                better = value > best + 1e-9
                best[better] = value[better]
                feature[first : first + many][better] = k
                split[first : first + many][better] = top[better]
            node = 2 * node + 1 + (b[np.arange(len(b)), feature[node]] > split[node])
        at = node - inner
        gs, hs = np.bincount(at, g, inner + 1), np.bincount(at, h, inner + 1)
        return Tree(feature, split, self.rate * gs / (hs + self.ridge))

    def raw(self, x: np.ndarray) -> np.ndarray:
        b = self.binned(x)
        return self.base + sum(t.predict(b) for t in self.trees)


def isotonic(raw: np.ndarray, y: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pool adjacent violators: knots (raw value, share) of the non-decreasing fit."""
    values, at = np.unique(raw, return_inverse=True)  # equal values are one to begin with
    weight, total = np.bincount(at, w), np.bincount(at, w * y)
    blocks: list[list[float]] = []  # weight, weighted sum, first and last raw value
    for r, m, v in zip(values, weight, total):
        blocks.append([m, v, r, r])
        while len(blocks) > 1 and blocks[-2][1] * blocks[-1][0] >= blocks[-1][1] * blocks[-2][0]:
            m2, s2, _, last = blocks.pop()
            blocks[-1] = [blocks[-1][0] + m2, blocks[-1][1] + s2, blocks[-1][2], last]
    knots = [(x, s / m) for m, s, a, b in blocks for x in ((a, b) if b > a else (a,))]
    return np.array([k[0] for k in knots]), np.array([k[1] for k in knots])


@dataclass(frozen=True)
class Model:
    share: float
    lexicon: Lexicon | None = None
    trees: Boosted | None = None
    knots: tuple[np.ndarray, np.ndarray] | None = None

    def scores(self, texts: list[str | None]) -> np.ndarray:
        if self.trees is None or not texts:
            return np.full(len(texts), self.share)
        raw = self.trees.raw(np.array([features(t, self.lexicon) for t in texts]))
        fitted = np.interp(raw, *self.knots)
        return np.clip(0.999 * fitted + 0.001 / (1 + np.exp(-raw)), 0, 1)  # the trees order what the steps tie


def learn_lexicon(sample: DataFrame) -> Lexicon:
    """Terms by smoothed lift of text shares; one aggregate over distinct terms of the sample's texts."""
    words = F.array_distinct(F.split(F.lower("text"), "[^\\p{L}]+"))
    stems = [F.transform(F.filter(words, lambda w, n=n: F.length(w) >= n), lambda w, n=n: F.concat(F.substring(w, 1, n), F.lit("*"))) for n in STEMS]
    terms = sample.select("toxic", F.explode(F.array_distinct(F.concat(F.filter(words, lambda w: F.length(w) > 1), *stems))).alias("term"))
    totals = {r[0]: r[1] for r in sample.groupBy("toxic").count().collect()}
    counted = terms.groupBy("term").agg(F.sum(F.col("toxic")).alias("bad"), F.sum(1 - F.col("toxic")).alias("good"))
    lift = ((F.col("bad") + 0.5) / (totals.get(1, 0) + 1)) / ((F.col("good") + 0.5) / (totals.get(0, 0) + 1))
    top = counted.where(F.col("bad") >= LEAST_TEXTS).withColumn("lift", F.log2(lift)).where(F.col("lift") >= np.log2(LEAST_LIFT))
    return Lexicon({r.term: float(r.lift) for r in top.orderBy(F.desc(F.col("lift") * F.log2("bad")), "term").limit(MOST_TERMS).collect()})


def learn(docs: DataFrame, labels: DataFrame, per_label: int = SAMPLE_PER_LABEL, seed: int = 5) -> Model:
    """Fits lexicon, trees and calibration on a bounded sample of the labelled rows."""
    labels = labels.where(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull()).select("doc_id", F.col("toxic").cast("int").alias("toxic"))
    totals = {r[0]: r[1] for r in labels.groupBy("toxic").count().collect()}
    share = totals.get(1, 0) / max(1, sum(totals.values()))
    if len(totals) < 2:
        return Model(share)
    chance = F.when(F.col("toxic") == 1, min(1.0, per_label / totals[1])).otherwise(min(1.0, per_label / totals[0]))
    drawn = labels.where(F.pmod(F.xxhash64(F.lit(seed), "doc_id"), F.lit(1_000_003)) / 1_000_003 < chance)
    sample = cut(docs.select("doc_id", "text").where(F.col("doc_id").isNotNull()).join(F.broadcast(drawn), "doc_id"))  # bounded by per_label
    part = F.pmod(F.xxhash64(F.lit(seed + 1), "doc_id"), F.lit(3))
    present = {tuple(r) for r in sample.select("toxic", part == 0).distinct().collect()}  # four rows at most
    if len({label for label, _ in present}) < 2:
        return Model(share)
    both = len({label for label, third in present if not third}) == 2  # else there is nothing to hold out
    lexicon = learn_lexicon(sample.where(part != 0) if both else sample)

    def extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [features(t, lexicon) for t in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(rows, pa.list_(pa.float64()))], ["toxic", "part", "x"])

    rows = sample.select("toxic", part.cast("int").alias("part"), "text").mapInArrow(extract, "toxic int, part int, x array<double>").collect()
    rows.sort(key=lambda r: (r.part, r.toxic, r.x))
    x, y, third = np.array([r.x for r in rows]), np.array([r.toxic for r in rows], float), np.array([r.part for r in rows]) == 0
    drawn_share = np.array([max(1, (y == v).sum()) for v in (0, 1)])
    w = np.where(y == 1, totals[1] / drawn_share[1], totals[0] / drawn_share[0])
    w /= w.mean()
    if len(set(y[~third])) < 2 or not third.any():
        third[:] = False
    trees = Boosted().fit(x[~third], y[~third], w[~third])
    held = third if len(set(y[third])) == 2 else ~third
    return Model(share, lexicon, trees, isotonic(trees.raw(x[held]), y[held], w[held]))


def score(docs: DataFrame, model: Model, threshold: float = 0.3) -> DataFrame:
    """doc_id, score, predicted of every row; one scan."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(model.scores(batch.column(1).to_pylist()), pa.float64())], ["doc_id", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, score double").withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def held_out():
    return id_residue("doc_id", 4) == 2


def assess(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted of every row, learnt from the labels that are not held out."""
    model = learn(docs, labels.where(~held_out()))
    return score(docs, model).select("doc_id", held_out().alias("held_out"), "score", "predicted")
