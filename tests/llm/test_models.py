import math
import random
import zlib
from collections import Counter

import numpy as np
import pytest

from dynreach.llm import language_id, mixing, toxicity

from tests.llm.test_tokens_secrets_shards import odd  # noqa: F401


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet("/root/testdata/sf0.01/documents.parquet")


def test_language_held_out(spark, docs):
    truth = {r.doc_id: r.lang for r in docs.select("doc_id", "lang").collect()}
    got = language_id.identify(docs).collect()
    assert len(got) == len(truth)
    held = [r for r in got if r.held_out]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in got)
    assert sum(r.lang_pred == truth[r.doc_id] for r in held) >= 0.95 * len(held)
    assert not any(r.rejected for r in got) and all(0 <= r.score <= 1 for r in got)


def test_language_odd_rows(spark, odd):  # noqa: F811
    got = {r.doc_id: r for r in language_id.identify(odd.unionByName(spark.createDataFrame([(20, "123 !!", "en", "a", 6, 1, 2)], odd.schema))).collect()}
    assert got[1].lang_pred == got[2].lang_pred == got[20].lang_pred == "und"
    assert got[20].rejected and got[20].score == 0 and got[5].lang_pred == "en"
    assert language_id.identify(odd.limit(0)).count() == 0
    nothing = language_id.classify(odd, language_id.learn(odd.where("lang is null")))
    assert {r.lang_pred for r in nothing.collect()} == {"und"} and set(odd.columns) < set(nothing.columns)


def test_language_rejects_what_is_unlike_all(spark, docs):
    model = language_id.learn(docs)
    langs, scores, rejected = model.predict(["漢字仮名交じり文" * 40, "the of and to in that is was for with " * 20])
    assert rejected[0] and scores[0] < scores[1] and langs[1] == "en" and not rejected[1]


def test_lone_letters_and_case():
    assert language_id.counts("123") is None and language_id.counts("") is None
    assert (language_id.counts("ABC d") == language_id.counts("abc, D")).all()


def test_toxicity_held_out(spark):
    d = "/root/testdata/sf0.1"
    labels = spark.read.parquet(f"{d}/labels.parquet")
    frame = spark.read.parquet(f"{d}/documents.parquet").join(labels.select("doc_id"), "doc_id", "left_semi")
    truth = {r.doc_id: r.toxic for r in labels.collect()}
    got = toxicity.assess(frame, labels).collect()
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in got)
    assert all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.3) for r in got)
    held = [r for r in got if r.held_out]
    bad, good = [r.score for r in held if truth[r.doc_id] == 1], [r.score for r in held if truth[r.doc_id] == 0]
    auc = np.mean([(b > g) + 0.5 * (b == g) for b in bad for g in good])
    assert auc > 0.9
    assert sum(s >= 0.3 for s in bad) >= 0.7 * len(bad) and sum(s >= 0.3 for s in good) <= 0.02 * len(good)


def test_toxicity_odd_rows(spark, odd):  # noqa: F811
    learnt = next(d for d in (3, 5, 6) if zlib.crc32(str(d).encode()) % 4 != 2)
    labels = spark.createDataFrame([(1, 0, None), (learnt, 1, 1)], "doc_id long, quality int, toxic int")
    got = toxicity.assess(odd, labels).collect()
    assert Counter(r.doc_id for r in got) == Counter([1, 2, 2, 3, None, 5, 6]) and {r.score for r in got} == {1.0}
    assert {r.score for r in toxicity.assess(odd, labels.limit(0)).collect()} == {0.0}
    assert toxicity.assess(odd.limit(0), labels).count() == 0


@pytest.mark.parametrize("bad", [{3}, {3, 5}, set(range(40))])
def test_few_labels(spark, bad):
    """Wherever the few toxic labels fall, in the third that calibrates or not."""
    texts = [(i, f"you {'vile' if i in bad else 'kind'} word{i} text") for i in range(40)]
    for shift in range(0, 30, 10):
        docs = spark.createDataFrame([(i + shift * 40, t) for i, t in texts], "doc_id long, text string")
        labels = spark.createDataFrame([(i + shift * 40, int(i in bad)) for i, _ in texts], "doc_id long, toxic int")
        got = toxicity.assess(docs, labels).collect()
        assert len(got) == 40 and all(0 <= r.score <= 1 for r in got)


def test_isotonic_is_the_best_monotone_fit():
    rng = np.random.default_rng(1)
    raw, w = rng.integers(0, 6, 40).astype(float), np.ones(40)
    y = (rng.random(40) < raw / 8).astype(float)
    x, p = toxicity.isotonic(raw, y, w)
    assert (np.diff(p) >= 0).all()
    fitted = np.interp(raw, x, p)
    assert abs(fitted.sum() - y.sum()) < 1e-9
    for _ in range(300):
        other = np.sort(rng.random(6))[raw.astype(int)]
        assert ((y - fitted) ** 2).sum() <= ((y - other) ** 2).sum() + 1e-9


def test_boosting_learns_an_interaction():
    rng = np.random.default_rng(2)
    x = rng.random((2000, 3))
    y = ((x[:, 0] > 0.5) & (x[:, 1] > 0.5)).astype(float)
    model = toxicity.Boosted(trees=30).fit(x, y, np.ones(2000))
    assert ((model.raw(x) > 0) == y).mean() > 0.97


def brute_exponent(shares, limit, cover):
    low, high = 0.0, 1.0
    for _ in range(60):
        a = (low + high) / 2
        power = [p ** (a - 1) for p in shares]
        z = sum(p**a for p in shares)
        worst = max(power) / min(power) if cover else max(power) / z
        low, high = (low, a) if worst <= limit else (a, high)
    return high


@pytest.mark.parametrize("cover", [False, True])
def test_mixing_matches_brute_force(spark, cover):
    rng = random.Random(4)
    rows = [(i, rng.choice("aaaaaaaabbbccd"), "x" * rng.randint(1, 400)) for i in range(3000)] + [(9000, None, "x" * 40), (9001, "e", None)]
    frame = spark.createDataFrame(rows, "doc_id long, source string, text string")
    old, mixing.BUCKET_ROWS = mixing.BUCKET_ROWS, 100
    try:
        got = mixing.draw(frame, repeat_limit=3.0, cover=cover).collect()
    finally:
        mixing.BUCKET_ROWS = old
    assert len(got) == len(rows)
    totals = Counter()
    for _, s, x in rows:
        totals[s] += max(1, math.ceil(len(x or "") / 4))
    whole = sum(totals.values())
    shares = {s: n / whole for s, n in totals.items()}
    a = brute_exponent(list(shares.values()), 3.0, cover)
    assert abs(got[0].mix_exponent - a) < 1e-5
    z = sum(p**a for p in shares.values())
    least = min(p ** (a - 1) for p in shares.values())
    for s, total in totals.items():
        mine = [r for r in got if r.source == s]
        assert abs(mine[0].mix_weight - shares[s] ** a / z) < 1e-5
        budget = total * shares[s] ** (a - 1) / least if cover else whole * shares[s] ** a / z
        drawn = sum(r.mix_copies * r.mix_tokens for r in mine)
        assert drawn <= budget + 2 and drawn >= budget - 2 - max(r.mix_tokens for r in mine)
        if cover:
            assert min(r.mix_copies for r in mine) >= 1
    if cover:
        assert Counter(r.doc_id for r in mixing.mixed(frame, repeat_limit=3.0).collect()).keys() == {r[0] for r in rows}


def test_permutations(spark, monkeypatch):
    rng = random.Random(6)
    rows = [(i, rng.choice("aaaaaaaabbbccd"), "x" * rng.randint(1, 400)) for i in range(1500)] + [(9000, None, "x" * 40), (9001, "e", None)] + [(None, "a", "same")] * 40
    frame = spark.createDataFrame(rows, "doc_id long, source string, text string")
    monkeypatch.setattr(mixing, "BUCKET_ROWS", 50)
    counts = Counter((r.doc_id, r.source, r.mix_copies) for r in mixing.draw(frame, repeat_limit=3.0).collect())
    got = mixing.permuted(frame, repeat_limit=3.0).collect()
    copies = Counter()
    for (d, s, n), times in counts.items():
        copies[(d, s)] += n * times
    assert Counter((r.doc_id, r.source) for r in got if r.mix_block is not None) == +copies
    assert sum(r.mix_block is None for r in got) == sum(times for (_, _, n), times in counts.items() if n == 0)
    blocks = {}
    for r in got:
        if r.mix_block is not None:
            blocks.setdefault((r.source, r.mix_block), []).append((r.mix_place, r.doc_id))
    sizes = Counter(s for _, s, _ in rows)
    for (source, block), members in blocks.items():
        assert sorted(p for p, _ in members) == list(range(len(members)))
        whole = {r.mix_blocks for r in got if r.source == source}.pop()
        assert block <= whole and (block == whole or len(members) == sizes[source])
    orders = [[d for _, d in sorted(blocks[(s, b)], key=lambda x: x[0])] for s, b in blocks if s == "c"]
    assert len(orders) >= 2 and all(x != y and x != sorted(x, key=str) for x in orders[:-1] for y in orders if x is not y)
    again = mixing.permuted(frame.repartition(1), repeat_limit=3.0).where("doc_id is not null").collect()
    assert Counter((r.doc_id, r.mix_block) for r in again) == Counter((r.doc_id, r.mix_block) for r in got if r.doc_id is not None)


def test_mixed_rows_come_in_order(spark):
    rows = [(i, "a" if i < 900 else "b", "x" * 40) for i in range(1000)]
    frame = spark.createDataFrame(rows, "doc_id long, source string, text string")
    got = [r.source for r in mixing.mixed(frame, repeat_limit=2.0).collect()]
    shares = [got[k : k + 100].count("b") for k in range(0, len(got) - 99, 100)]
    assert got.count("a") == 900 and max(shares) - min(shares) <= 12 and min(shares) > 5
    assert [r.doc_id for r in mixing.mixed(frame, chunk_tokens=500).collect()] != sorted(range(len(got)))


def test_mixing_clashing_names(spark):
    frame = spark.createDataFrame([(1, "a", "t", 7, "s", 2), (2, "b", "t", 8, "s", 3)], "doc_id long, source string, text string, mix_x int, __source string, mix_copies int")
    assert [tuple(r) for r in mixing.mixed(frame).orderBy("doc_id").collect()] == [tuple(r) for r in frame.collect()]
    assert mixing.draw(frame).columns == ["doc_id", "source", "text", "mix_x", "__source", *mixing.DRAWN]
    assert mixing.permuted(frame).select("mix_x", "mix_copies", "mix_place").count() == 2


def test_entropy_target(spark):
    rows = [(i, "a" if i < 900 else "b" if i < 990 else "c", "xxxx") for i in range(1000)]
    got = mixing.draw(spark.createDataFrame(rows, "doc_id long, source string, text string"), target_entropy=0.8, repeat_limit=None).collect()
    w = {r.source: r.mix_weight for r in got}
    entropy = -sum(x * math.log(x) for x in w.values()) / math.log(3)
    assert abs(entropy - 0.8) < 1e-3


def test_mixing_odd_rows(odd):  # noqa: F811
    got = mixing.draw(odd, repeat_limit=2.0).collect()
    assert Counter(r.doc_id for r in got) == Counter([1, 2, 2, 3, None, 5, 6])
    assert mixing.draw(odd.limit(0)).count() == 0 and mixing.mixed(odd.limit(0)).columns == odd.columns
