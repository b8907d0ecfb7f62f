"""The index as SQL: views live_edges, membership, components, dag_edges, labels, and the function label_covers."""

from __future__ import annotations

from dynreach.functions import intervals
from dynreach.model import Index


def register(index: Index) -> None:
    for name, table in (("live_edges", index.edges), ("membership", index.membership), ("components", index.components), ("dag_edges", index.dag_edges), ("labels", index.labels), ("containment", index.containment)):
        table.createOrReplaceTempView(name)
    intervals.register(index.spark)
