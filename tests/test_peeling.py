"""Components that fall apart into single nodes are peeled, not searched and decomposed again."""

from dynreach.conf import EngineConf
from dynreach.operators import index as I, scc, splits
from dynreach.operators.kernel import DynamicIndex
from dynreach.plans import batch
from dynreach.model import OPS
from tests.test_engine import holds

SETS = EngineConf(rebuild_ratio=1e9, local_rows=0)


def test_a_ring_that_opens_is_peeled(spark, monkeypatch):
    ring, loop = [(i, (i + 1) % 7) for i in range(7)], [(3, 20), (20, 3)]
    edges = spark.createDataFrame(ring + loop, "src long, dst long")
    ix, kernel = I.build(edges, k=2), DynamicIndex((), ring + loop, k=2)

    def no_searches(*_, **__):
        raise AssertionError("decomposed again")

    ops = spark.createDataFrame([(0, None, "delete_edge", 4, 5, None, None), (1, None, "delete_edge", 20, 3, None, None)], OPS)
    with monkeypatch.context() as patch:
        patch.setattr(scc, "by_sets", no_searches)
        ix = batch.apply(ix, ops, conf=SETS)
    for e in ((4, 5), (20, 3)):
        kernel.delete_edge(*e)
    holds(ix, kernel)
    assert ix.facts["split"] == "extract" and ix.facts["left"] == 7


def test_heights_lead_down(spark):
    edges = [(0, 1), (1, 0), (1, 2), (2, 3), (5, 6), (6, 1), (5, 3)]  # (3, 5) was there
    members = spark.createDataFrame([(i, 0) for i in (0, 1, 2, 3, 5, 6)], "node long, comp long")
    lost = spark.createDataFrame([(3, 5, 0)], "src long, dst long, comp long")
    found, _, middle = splits.leavers(spark.createDataFrame(edges, "src long, dst long"), members, lost)
    height = {r.node: r.height for r in found.collect()}
    assert height.keys() == {2, 3, 5, 6} and None not in height.values()
    assert all(height.get(a, middle) > height.get(b, middle) for a, b in edges if {a, b} != {0, 1})
