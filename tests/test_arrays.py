"""The index of a bin of parts, worked out of arrays in one task."""

import random

import numpy as np
import pytest

from dynreach.conf import EngineConf
from dynreach.operators import arrays, index as I, kernel, labels as L, parts


def drawn(seed, n, m):
    rng = random.Random(seed)
    return np.array([(rng.randrange(n), rng.randrange(n)) for _ in range(m)], dtype="int64").reshape(-1, 2).T


@pytest.mark.parametrize("seed, n, m", [(1, 1, 0), (2, 1, 3), (3, 12, 14), (4, 60, 70), (5, 60, 200), (6, 400, 420), (7, 3000, 2900)])
def test_components_and_walks_as_the_kernel_has_them(seed, n, m):
    a, b = drawn(seed, n, m)
    out = kernel.index_of(zip(a.tolist(), b.tolist()))
    want = {x: min(p) for p in kernel.strongly_connected(range(n), lambda x: out.get(x, ())) for x in p}
    comp = arrays.components(n, a, b)
    assert comp.tolist() == [want[x] for x in range(n)]
    names, at, sizes = np.unique(comp, return_inverse=True, return_counts=True)
    s, t, times = arrays.condensed(len(names), at[a], at[b])
    assert times.sum() == (comp[a] != comp[b]).sum() and len({*zip(s.tolist(), t.tolist())}) == len(s)
    low, high = map(np.array, arrays.walked(len(names), s, t, sizes, 7, np.random.default_rng(seed)))
    assert (low[s] <= low[t]).all() and (high[t] < high[s]).all() and (high - low >= sizes).all() and low.min() == 7


def test_a_long_chain_and_sparse_ids():
    n = 50_000
    a = np.arange(n - 1) * 10**12
    ids, x, y = arrays.numbered(a, a + 10**12)
    assert len(ids) == n and (arrays.components(n, x, y) == np.arange(n)).all() and (arrays.united(n, x, y) == 0).all()
    assert (arrays.components(n, np.append(x, n - 1), np.append(y, 0)) == 0).all()
    low, high = arrays.walked(n, x, y, np.ones(n, dtype="int64"), 0, np.random.default_rng(0))
    assert low == [0] * n and high == list(range(n, 0, -1))


def test_bins_take_whole_parts_and_leave_those_that_are_too_large():
    edges = [(100 * p + i, 100 * p + i + 1) for p in range(9) for i in range(20 if p == 4 else 3)] + [(950, 950)]
    ids, a, b = arrays.numbered(*np.array(edges).T)
    part, bins, sizes = parts.shares(len(ids), a, b, EngineConf(local_rows=32))
    assert (bins[a] == bins[b]).all() and set(ids[bins < 0]) == {400 + i for i in range(21)}
    assert sizes.sum() == (bins >= 0).sum() and sizes.min() > 0 and len(set(part)) == 10


@pytest.mark.parametrize("conf", [EngineConf(local_rows=1000, driver_rows=0), EngineConf(local_rows=60, driver_rows=0, slack=3)], ids=["dealt by one task", "dealt by sets"])
def test_an_index_in_bins_is_the_one_made_step_by_step(spark, monkeypatch, conf):
    edges = [(100 * p + int(u), 100 * p + int(v)) for p in range(8) for u, v in zip(*drawn(p, 12, 22))]
    e = spark.createDataFrame(sorted(set(edges)), "src long, dst long")
    extra = spark.createDataFrame([(5,), (5000,), (5001,)], "node long")
    want = I.build(e, extra, k=2)
    monkeypatch.setattr(I, "assemble", lambda *a, **kw: pytest.fail("not in bins"))
    got = I.build(e, extra, k=2, conf=conf, as_is=True)
    for table in ("nodes", "edges", "components", "dag_edges", "containment", "membership"):
        a, b = getattr(want, table), getattr(got, table)
        assert a.columns == b.columns and [t for _, t in a.dtypes] == [t for _, t in b.dtypes]
        assert sorted(a.collect()) == sorted(b.collect()), table
    assert L.violations(got.labels, got.dag_edges).count() == 0 and got.labels.count() == got.components.count()
    roots = [r for r in got.labels.join(got.components, "comp").collect() if r.comp >= 5000]
    assert len({r.iv[0].b for r in roots}) == 2 and all(r.iv[0].e - r.iv[0].b == conf.slack for r in roots)
