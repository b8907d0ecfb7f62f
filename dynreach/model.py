"""Tables of the engine. Ids are long and not negative; negative ids are components made by the engine.

Where the text that this engine follows leaves a rule open or slips, these hold: an interval's end is the
larger of the counter and the largest child end plus one; a search drops a node whose label does not contain the
goal's; containment of different components is strict at the end, and equal ends are not nested; the new
components of a split are those the deleted edge's tail can reach, and their nodes join the component table; the
condensation holds every crossing edge; a piece that is not walked in a split is the one that holds the head.
Inserting a present edge or deleting an absent one is a counted no-op.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession

NODES = "node long"
EDGES = "src long, dst long"
MEMBERSHIP = "node long, comp long"
COMPONENTS = "comp long, size long, status string"
CONTAINMENT = "child long, parent long, epoch long"
DAG_EDGES = "s long, t long, mult long"
LABELS = "comp long, iv array<struct<b:long,e:long>>"
OPS = "op_id long, ts timestamp_ntz, kind string, u long, v long, outs array<long>, ins array<long>"
PAIRS = "qid long, u long, v long"
ANSWERS = "qid long, u long, v long, reachable boolean, decided_by string, expanded long"
OP_LOG = "op_id long, kind string, case string, comps_touched long, labels_changed long, rounds long, ms double"
KINDS = ("insert_edge", "delete_edge", "insert_node", "delete_node")


@dataclass(frozen=True)
class Index:
    """An immutable version: the live graph, its condensation, the containment forest and the labels.

    Components are named by their smallest node. Which component a node is in, the forest says: `containment` has rows for
    nodes and absorbed components only, at most `depth` steps below a current component. `membership` lists it for all
    nodes; it is made when asked for and kept.
    """

    nodes: DataFrame
    edges: DataFrame
    components: DataFrame
    dag_edges: DataFrame
    labels: DataFrame
    containment: DataFrame
    k: int
    version: int = 0
    depth: int = 1
    facts: dict = field(default_factory=dict)
    kept: dict = field(default_factory=dict, repr=False, compare=False)

    def lookup(self, nodes: DataFrame) -> DataFrame:
        """(node, comp) of the nodes given, through the forest."""
        from dynreach.operators.containment import find

        return find(self.containment, nodes, self.depth)

    @property
    def membership(self) -> DataFrame:
        if "membership" not in self.kept:
            from dynreach.plans.loops import cut

            self.kept["membership"] = cut(self.lookup(self.nodes))
        return self.kept["membership"]

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    def next(self, **changed) -> Index:
        return replace(self, **{"version": self.version + 1, "kept": {}} | changed)


def check_ids(edges: DataFrame) -> None:
    """Raises for a negative or null id."""
    if edges.where("src < 0 or dst < 0 or src is null or dst is null").limit(1).count():
        raise ValueError("node ids are not negative and not null")
