import random
import re
from collections import Counter

import numpy as np

from dynreach.llm import common, minmax_dedup as M

from tests.llm.test_tokens_secrets_shards import ODD, odd  # noqa: F401


def plain_set(text):
    words = re.findall("[^\\x20\\x09-\\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    if len(words) < 5:
        return {tuple(words)} if words else set()
    return {tuple(words[i : i + 5]) for i in range(len(words) - 4)}


def brute(rows, percent=85):
    sets = {d: plain_set(t) for d, t in rows if d is not None}
    ids, parent = sorted(sets), {d: d for d in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            both = len(sets[a] & sets[b])
            if both and 100 * both >= percent * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    return {d: (len(sets[d]), find(d)) for d in ids}


def made(seed=1):
    rng = random.Random(seed)
    words = [f"w{i}" for i in range(400)]
    rows = []
    for base in range(6):
        text = [rng.choice(words) for _ in range(rng.choice([4, 30, 150, 150, 400]))]
        for _ in range(40):
            copy = list(text)
            for _ in range(rng.randint(0, max(1, len(text) // 60))):
                copy[rng.randrange(len(copy))] = rng.choice(words)
            rows.append(" ".join(copy).upper() if rng.random() < 0.2 else "\t".join(copy))
    rng.shuffle(rows)
    return [*enumerate(rows), (1000, None), (1001, ""), (1002, " \n"), (1003, "one"), (1004, "ONE"), (1005, "é one")]


def answers(frame):
    return {r.doc_id: (r.n_shingles, r.component_id) for r in frame.collect()}


def test_all_ways_match_brute_force(spark):
    rows = made()
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    want = brute(rows)
    assert len({c for _, c in want.values()}) < len(want) - 100
    for block, part in ((512, 20_000), (7, 20_000), (7, 10)):
        got = M.dedup(docs, block=block, part=part).collect()
        assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == want
        assert all(r.kept == (r.doc_id == r.component_id) for r in got)


def families(large, small, seed=2):
    """One family of `large` near copies and many of three, with ids that floats can't hold."""
    rng = random.Random(seed)
    rows = []
    for n in [large] + [3] * small:
        text = [f"w{rng.randrange(10**6)}" for _ in range(300)]
        for _ in range(n):
            copy = list(text)
            copy[rng.randrange(300)] = f"w{rng.randrange(10**6)}"
            rows.append((2**62 + 2 * len(rows) + 1, " ".join(copy)))
    return rows


def test_a_vast_part_beside_small_ones(spark):
    rows = families(60, 60)
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    want = brute(rows)
    assert len({c for _, c in want.values()}) == 61
    for block, part in ((512, 20), (7, 20), (512, 20_000)):
        assert answers(M.dedup(docs, block=block, part=part)) == want


def test_hot_copies_and_hubs(spark, monkeypatch):
    monkeypatch.setattr(common, "HOT_SHARE", 5)
    monkeypatch.setattr(common, "LEAST_HOT", 3)
    rows = [(i, "the very same words in every one of these rows") for i in range(50)] + made()[:60]
    rows = [(2**61 + i, t) for i, (_, t) in enumerate(rows)]
    assert answers(M.dedup(spark.createDataFrame(rows, "doc_id long, text string"))) == brute(rows)


def test_given_documents(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    assert answers(M.dedup(docs)) == brute([(r.doc_id, r.text) for r in docs.collect()])


def test_odd_rows(spark, odd):  # noqa: F811
    got = Counter((r.doc_id, r.n_shingles, r.component_id, r.kept) for r in M.dedup(odd).collect())
    n = len(plain_set(ODD[3][1]))
    assert got == Counter({(1, 0, 1, True): 1, (2, 0, 2, True): 2, (3, n, 3, True): 1, (None, 1, None, True): 1, (5, 1, 5, True): 1, (6, 1, 5, False): 1})
    assert M.dedup(odd.limit(0)).count() == 0
    assert Counter(r.doc_id for r in M.keep_one(odd).collect()) == Counter([1, 2, 2, 3, None, 5])


def test_signature_estimates():
    a, b = np.arange(1, 2000, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15), np.arange(400, 2400, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    same = (M.signature(M._mixed(a)) == M.signature(M._mixed(b))).mean()
    assert abs(same - 1600 / 2399) < 0.12


def test_texts_not_asked_for_stay_where_they_are(spark):
    texts = spark.range(20_000).selectExpr("id - 5 as rep", "concat('text ', id) as text").union(spark.createDataFrame([(None, "x")], "rep long, text string"))
    ids = spark.range(0, 15_000, 15).selectExpr("id as rep").union(spark.createDataFrame([(-5,), (10**12,)], "rep long"))
    got = [r.rep for r in common.likely(texts, ids, "rep").collect() if r.rep is not None]
    assert len(got) == len(set(got)) and set(range(0, 15_000, 15)) | {-5} <= set(got)
    assert len(got) < 1001 + 20_000 / 8
    assert common.likely(texts, ids.limit(0), "rep").count() == 0
