"""Planner thresholds."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class EngineConf:
    """local_rows: edges up to which a graph is handled by one task's kernel; every use counts rows first.
    driver_rows: edges up to which the driver gathers a graph and broadcasts it to the tasks that search it.
    k: intervals per component. slack: label width per input node. rebuild_ratio: a batch of more than
    this share of the edges rebuilds the index. max_rounds: loops raise beyond it, they never stop short.
    split: how components that lose inner edges are decomposed: naive reads them whole, extract only what leaves and its
    surroundings, auto is naive while they fit a task. forest_depth: steps beyond which the forest is compressed.
    broadcast_rows: counted rows up to which operations are broadcast. relabel_drift: largest end of labels over the number
    of nodes, beyond which a batch draws the labels anew.
    """

    k: int = 1
    slack: int = 1
    seed: int = 42
    local_rows: int = 2_000_000
    driver_rows: int = 200_000
    rebuild_ratio: float = 0.2
    checkpoint_every: int = 4
    split: str = "auto"
    forest_depth: int = 4
    broadcast_rows: int = 100_000
    max_rounds: int = 10_000
    relabel_drift: float = 8.0


DEFAULT = EngineConf()
