import math
from collections import Counter

import numpy as np
import pytest

from dynreach.llm import cap_filters, one_bit_search

SCHEMA = "vec_id long, embedding array<float>, label int, n_links int, rank int"


@pytest.fixture(scope="module")
def odd(spark):
    x = [1.0, 2.0, 3.0]
    rows = [(1, x, 1), (2, x, 1), (2, x, 1), (3, x, None), (4, [0.0] * 3, 1), (5, None, 1), (6, [1.0, None, 2.0], 1), (7, [1.0, math.nan, 2.0], 1), (8, [1.0, math.inf, 2.0], 1), (9, [], 1), (None, x, 1), (10, [2.0, 4.0, 6.1], 1), (11, x, 2), (12, [1.0, 2.0], 1)]
    return spark.createDataFrame([(*r, 0, 0) for r in rows], SCHEMA)


def made(seed=1, n=400, d=64):
    rng = np.random.default_rng(seed)
    base = rng.standard_normal((n, d))
    near = base[rng.integers(0, 20, n)] + 0.25 * rng.standard_normal((n, d))
    x = np.concatenate([base, near, near[:5]]).astype(np.float32)
    return [(i, v.tolist(), int(i % 2)) for i, v in enumerate(x)]


def exact_links(rows, least=0.93):
    links = {r[0]: set() for r in rows}
    for a, x, p in rows:
        for b, y, q in rows:
            if a < b and p == q and len(x) == len(y):
                x64, y64 = np.array(x, float), np.array(y, float)
                if x64 @ y64 / np.linalg.norm(x64) / np.linalg.norm(y64) >= least:
                    links[a].add(b)
                    links[b].add(a)
    return links


def parts(links):
    comp = {}
    for a in sorted(links):
        if a not in comp:
            todo = [a]
            while todo:
                x = todo.pop()
                if x not in comp:
                    comp[x] = a
                    todo += links[x]
    return comp


def test_caps_match_brute_force(spark):
    rows = made()
    links = exact_links(rows)
    comp = parts(links)
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").repartition(5)
    for block in (512, 16):
        got = {r.vec_id: r for r in cap_filters.near_duplicates(frame, block=block).collect()}
        found, there = sum(r.n_links for r in got.values()), sum(map(len, links.values()))
        assert all(r.n_links <= len(links[v]) for v, r in got.items())
        assert found >= 0.99 * there > 1000
        assert sum(got[v].component_id == comp[v] for v in got) >= 0.99 * len(got)
        assert all(r.kept == (r.vec_id == r.component_id) for r in got.values())


def test_given_vectors(spark, sf_dir):
    frame = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    links = exact_links([(r.vec_id, r.embedding, r.label) for r in frame.collect()])
    got = {r.vec_id: r for r in cap_filters.near_duplicates(frame).collect()}
    assert sum(r.n_links for r in got.values()) >= 0.99 * sum(map(len, links.values()))
    assert all(r.n_links <= len(links[v]) for v, r in got.items())


def test_caps_odd_rows(odd):
    got = Counter((r.vec_id, r.n_links, r.component_id, r.kept) for r in cap_filters.near_duplicates(odd).collect())
    want = Counter([(1, 2, 1, True), (2, 2, 1, False), (2, 2, 1, False), (10, 2, 1, False), (None, 0, None, True)] + [(i, 0, i, True) for i in (3, 4, 5, 6, 7, 8, 9, 11, 12)])
    assert got == want
    assert cap_filters.near_duplicates(odd.limit(0)).count() == 0


def exact_search(rows, k=20, every=20):
    ids, x = np.array([r[0] for r in rows]), np.array([r[1] for r in rows], float)
    out = {}
    for q in ids[ids % every == 0]:
        scores = x @ x[ids == q][0]
        order = [i for i in np.lexsort((ids, -scores)) if ids[i] != q][:k]
        out[int(q)] = [(int(ids[i]), scores[i]) for i in order]
    return out


@pytest.mark.parametrize("blocks", [(16_384, 4_096), (100, 7)])
def test_search_recall(spark, blocks):
    rows = made(2)
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    want = exact_search(rows)
    got = one_bit_search.search(frame, frame.where("vec_id % 20 = 0"), row_block=blocks[0], query_block=blocks[1]).collect()
    by = {}
    for r in sorted(got, key=lambda r: (r.query_id, r.rank)):
        by.setdefault(r.query_id, []).append((r.vec_id, r.score))
    assert {q: len(v) for q, v in by.items()} == {q: len(v) for q, v in want.items()}
    same = sum(len({i for i, _ in by[q]} & {i for i, _ in want[q]}) for q in want)
    assert same >= 0.99 * sum(map(len, want.values()))
    for q, found in by.items():
        assert [s for _, s in found] == sorted((s for _, s in found), reverse=True)
        exact = {i: s for i, s in want[q]}
        assert all(abs(s - exact[i]) < 1e-9 for i, s in found if i in exact)


def test_search_odd_rows(odd):
    got = [(r.query_id, r.rank, r.vec_id) for r in one_bit_search.search(odd, odd.where("vec_id = 10")).collect()]
    assert sorted(got) == [(10, 1, 1), (10, 2, 2), (10, 3, 3), (10, 4, 11)]
    assert one_bit_search.search(odd.limit(0), odd).count() == 0


def test_search_sums_in_order_only_what_may_be_near(monkeypatch):
    rng = np.random.default_rng(5)
    x = rng.standard_normal((8_000, 64))
    x /= np.linalg.norm(x, axis=1)[:, None]
    ids, asked, summed = np.arange(8_000), np.arange(0, 8_000, 200), []
    cumsum = np.cumsum
    monkeypatch.setattr(one_bit_search.np, "cumsum", lambda a, axis: summed.append(len(a)) or cumsum(a, axis=axis))
    found = list(one_bit_search.best_of_block(x[asked], asked, x, ids, *one_bit_search.codes(x), 20, one_bit_search.TRUST))
    assert max(summed) <= 25
    for q, near, products in found:
        scores = np.where(ids == q, -9, x @ x[q])
        assert set(near.tolist()) == set(np.argsort(-scores)[:20].tolist()) and np.allclose(products, scores[near])


def test_search_counts_bits_over_several_words():
    bits = np.random.default_rng(3).integers(0, 256, (50, 20), dtype=np.uint8)
    columns = list(one_bit_search.words(bits).T)
    plane = one_bit_search.words(bits[:1])[0]
    assert one_bit_search.counted(columns, plane).tolist() == np.unpackbits(bits & bits[:1], axis=1).sum(1).tolist()
