"""Queries that need no index make none."""

import pytest

from dynreach import registry


@pytest.mark.parametrize("name", ["dag_view_order_citation", "base_search_order_citation", "base_search_goods_flow_light"])
def test_no_index_is_built(spark, sf_dir, monkeypatch, name):
    monkeypatch.setattr(registry.I, "build", lambda *a, **kw: pytest.fail("an index was built"))
    monkeypatch.setattr(registry, "_kept", {})
    assert registry.QUERIES[name](spark, sf_dir).count()
