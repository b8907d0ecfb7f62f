"""The closure needs no round for each step of a path, and keeps nothing of what it writes."""

from dynreach.conf import EngineConf
from dynreach.operators import baselines as B


def test_closure_of_a_long_path_and_of_cycles(spark):
    path = [(i, i + 1) for i in range(60)]
    edges = path + [(100 + i, 100 + (i + 1) % 70) for i in range(70)] + [(60, 100), (300, 300), (300, 0)]
    got = [tuple(r) for r in B.closure(spark.createDataFrame(edges + path, "src long, dst long"), EngineConf(max_rounds=5)).collect()]
    out = {}
    for a, b in edges:
        out.setdefault(a, []).append(b)
    want = set()
    for a in out:
        stack = list(out[a])
        while stack:
            x = stack.pop()
            if (a, x) not in want:
                want.add((a, x))
                stack += out.get(x, ())
    assert len(got) == len(set(got)) and set(got) == want
    assert B.closure(spark.createDataFrame([], "src long, dst long")).count() == 0
