"""The live graph alone, in one task: what plain search keeps, and what random operations are drawn from."""

from __future__ import annotations

import random
from collections.abc import Iterable


class Bag:
    """A set that draws a member uniformly in constant time."""

    def __init__(self, items: Iterable = ()):
        self.items, self.at = [], {}
        for x in items:
            self.add(x)

    def __len__(self) -> int:
        return len(self.items)

    def __contains__(self, x) -> bool:
        return x in self.at

    def add(self, x) -> None:
        if x not in self.at:
            self.at[x] = len(self.items)
            self.items.append(x)

    def discard(self, x) -> None:
        place = self.at.pop(x, None)
        if place is not None:
            last = self.items.pop()
            if last != x:
                self.items[place], self.at[last] = last, place

    def draw(self, rng: random.Random):
        return self.items[rng.randrange(len(self.items))]


class PlainGraph:
    """Adjacency under all four kinds of operations, with the same rules as the index."""

    def __init__(self, edges: Iterable[tuple[int, int]], nodes: Iterable[int] = ()):
        self.nodes, self.edges = Bag(nodes), Bag()
        self.out: dict[int, set[int]] = {n: set() for n in self.nodes.items}
        self.inn: dict[int, set[int]] = {n: set() for n in self.nodes.items}
        for u, v in edges:
            self.insert_edge(u, v)

    def insert_node(self, n: int) -> None:
        self.nodes.add(n)
        self.out.setdefault(n, set())
        self.inn.setdefault(n, set())

    def insert_edge(self, u: int, v: int) -> None:
        self.insert_node(u)
        self.insert_node(v)
        self.out[u].add(v)
        self.inn[v].add(u)
        self.edges.add((u, v))

    def delete_edge(self, u: int, v: int) -> None:
        if (u, v) in self.edges:
            self.edges.discard((u, v))
            self.out[u].discard(v)
            self.inn[v].discard(u)

    def apply(self, kind: str, u: int, v: int | None, outs: Iterable[int], ins: Iterable[int]) -> None:
        if kind == "insert_edge":
            self.insert_edge(u, v)
        elif kind == "delete_edge":
            self.delete_edge(u, v)
        elif kind == "insert_node":
            self.insert_node(u)
            for x in outs:
                self.insert_edge(u, x)
            for x in ins:
                self.insert_edge(x, u)
        elif kind == "delete_node":
            if u in self.nodes:
                for x in list(self.out[u]):
                    self.delete_edge(u, x)
                for x in list(self.inn[u]):
                    self.delete_edge(x, u)
                self.nodes.discard(u)
                del self.out[u], self.inn[u]
        else:
            raise ValueError(kind)

    def search(self, u: int, v: int) -> tuple[bool, int]:
        """Plain depth-first search; nodes expanded."""
        if u not in self.out or v not in self.out:
            return False, 0
        seen, stack, expanded = {u}, [u], 0
        while stack:
            x = stack.pop()
            expanded += 1
            if x == v:
                return True, expanded
            for y in self.out[x]:
                if y not in seen:
                    seen.add(y)
                    stack.append(y)
        return False, expanded


def drawn_operations(graph: PlainGraph, n_ops: int, ratio: tuple[int, int, int, int], most_degree: int, seed: int) -> Iterable[tuple]:
    """(kind, u, v, outs, ins), applied to the graph as they are drawn. Kinds are random in the ratio given; heads are drawn in
    proportion to in-degree, as the heads of uniform edges; what goes is uniform over what is there then."""
    rng = random.Random(seed)
    kinds = ("insert_edge", "delete_edge", "insert_node", "delete_node")
    fresh = max(graph.nodes.items, default=-1) + 1
    for kind in rng.choices(kinds, ratio, k=n_ops):
        u, v, outs, ins = -1, -1, [], []
        head = lambda: graph.edges.draw(rng)[1] if len(graph.edges) else graph.nodes.draw(rng)
        if not len(graph.nodes) or (kind == "delete_edge" and not len(graph.edges)):
            kind = "insert_node"
        if kind == "insert_edge":
            u, v = graph.nodes.draw(rng), head()
        elif kind == "delete_edge":
            u, v = graph.edges.draw(rng)
        elif kind == "insert_node":
            u, fresh = fresh, fresh + 1
            if len(graph.nodes):
                outs, ins = (sorted({head() for _ in range(rng.randint(0, most_degree))}) for _ in range(2))
        else:
            u = graph.nodes.draw(rng)
        graph.apply(kind, u, v, outs, ins)
        yield kind, u, v, outs, ins
