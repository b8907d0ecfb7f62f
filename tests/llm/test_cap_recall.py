import tracemalloc

import numpy as np
import pytest

from dynreach.llm import cap_filters as C


def pairs(n, d=64, least=0.93):
    x, y = np.random.default_rng(9).standard_normal((2, n, d))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    y -= (x * y).sum(1, keepdims=True) * x
    return x, least * x + np.sqrt(1 - least**2) * y / np.linalg.norm(y, axis=1, keepdims=True)


@pytest.mark.parametrize("codewords", [256, 1024, 4096])
def test_pairs_at_the_threshold_meet_at_every_size(codewords):
    tables, apart = C.tables_for(64, codewords, 0.93), 0
    assert tables
    for x, y in zip(*(np.split(v, 10) for v in pairs(2000))):
        both = zip(C.passed(x, tables, codewords=codewords), C.passed(y, tables, codewords=codewords))
        apart += sum(not len(np.intersect1d(f, g)) for f, g in both)
    assert apart <= 1  # 0.2 expected; four codes of 4096 codewords miss 6


def test_thresholds_come_from_the_top_sums():
    a, b = np.random.default_rng(1).standard_normal((2, 16, 256))
    sums = a[:, :, None] + b[:, None, :]
    assert abs(C.top_sum(a, b, 16) - np.quantile(sums, 1 - 16 / 256**2)) < 1e-12
    tracemalloc.start()
    C.code.__wrapped__(64, 0, 16, 3, 4096)
    assert tracemalloc.get_traced_memory()[1] < 50e6
    tracemalloc.stop()


def test_codewords_follow_the_label_itself(spark):
    rng = np.random.default_rng(2)
    rows = [(i, rng.standard_normal(12).tolist(), int(i >= 5)) for i in range(1505)]
    reps = spark.createDataFrame(rows, "rep long, embedding array<double>, label int")
    assert {(r.label, r.codewords) for r in C.sized(reps).select("label", "codewords").distinct().collect()} == {(0, 256), (1, 512)}
    few = {r.rep: r.filters for r in C.listed_filters(reps.where("label = 0"), 0.93, 16, 3).collect()}
    assert few == {r.rep: r.filters for r in C.listed_filters(reps, 0.93, 16, 3).where("rep < 5").collect()}


def test_too_many_codes_means_all_pairs():
    assert C.tables_for(9, 256, 0.7) == 0
    assert [f.tolist() for f in C.passed(pairs(3, 9)[0], 0)] == [[0]] * 3
