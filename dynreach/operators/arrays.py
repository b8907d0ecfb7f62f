"""What one task works out of a graph held as two arrays of ends: weak parts, components, condensation and walked labels.

Nodes are numbered in the order of their ids, so the least number of a set stands for its least id.
"""

from __future__ import annotations

import numpy as np


def numbered(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ids, a, b): the sorted distinct ends, and the places of both ends among them."""
    top = int(max(src.max(), dst.max())) if len(src) else 0
    if len(src) and min(src.min(), dst.min()) >= 0 and top < 8 * len(src) + 1024:  # dense ids: a table in place of a sort
        there = np.zeros(top + 1, dtype=bool)
        there[src] = there[dst] = True
        place = np.cumsum(there) - 1
        return np.flatnonzero(there), place[src], place[dst]
    ids, at = np.unique(np.concatenate([src, dst]), return_inverse=True)
    return ids, at[: len(src)], at[len(src) :]


def starts(n: int, a: np.ndarray) -> np.ndarray:
    """Where the edges of each tail begin, once they are sorted by it; n + 1 numbers."""
    return np.concatenate([[0], np.cumsum(np.bincount(a, minlength=n))])


def united(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least node of each node's weakly connected part."""
    low = np.arange(n)
    while True:
        x, y = low[a], low[b]
        apart = x != y
        if not apart.any():
            return low
        a, b, x, y = a[apart], b[apart], x[apart], y[apart]
        np.minimum.at(low, np.maximum(x, y), np.minimum(x, y))
        while not np.array_equal(up := low[low], low):
            low = up


def components(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least node of each node's strongly connected component.

    Edges that no cycle takes go in rounds while a round takes a twentieth of them; a depth-first pass has the rest.
    """
    comp = np.arange(n)
    loose = a != b
    a, b = a[loose], b[loose]
    while len(a):
        heads, tails = np.zeros(n, dtype=bool), np.zeros(n, dtype=bool)
        heads[b] = tails[a] = True
        stay = heads[a] & tails[b]
        left = int(stay.sum())
        few = 20 * (len(a) - left) < len(a)
        a, b = a[stay], b[stay]
        if few:
            break
    if not len(a):
        return comp
    nodes, a, b = numbered(a, b)
    m = len(nodes)
    heads, first = b[np.argsort(a, kind="stable")].tolist(), starts(m, a).tolist()
    at, number, low, of = first[:-1], [0] * m, [0] * m, [0] * m
    count, open_ = 0, []
    for root in range(m):
        if number[root]:
            continue
        count += 1
        number[root] = low[root] = count
        open_.append(root)
        path = [root]
        while path:
            x = path[-1]
            i = at[x]
            if i < first[x + 1]:
                at[x] = i + 1
                y = heads[i]
                if not number[y]:
                    count += 1
                    number[y] = low[y] = count
                    open_.append(y)
                    path.append(y)
                elif number[y] < low[x]:
                    low[x] = number[y]
            else:
                path.pop()
                if path and low[x] < low[path[-1]]:
                    low[path[-1]] = low[x]
                if low[x] == number[x]:
                    while True:
                        y = open_.pop()
                        number[y], of[y] = m + 1, x  # beyond all that are open
                        if y == x:
                            break
    of = np.array(of)
    least = np.full(m, m)
    np.minimum.at(least, of, np.arange(m))
    comp[nodes] = nodes[least[of]]
    return comp


def condensed(n: int, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(s, t, times): distinct edges between different nodes, sorted, with their multiplicity."""
    apart = a != b
    pairs, times = np.unique(a[apart] * n + b[apart], return_counts=True)
    return pairs // max(n, 1), pairs % max(n, 1), times


def walked(n: int, s: np.ndarray, t: np.ndarray, widths: np.ndarray, start: int, rng: np.random.Generator) -> tuple[list[int], list[int]]:
    """Begins and ends as kernel.walk has them, on an acyclic graph with children and roots in random order."""
    mixed = rng.permutation(len(s))
    heads, first = t[mixed][np.argsort(s[mixed], kind="stable")].tolist(), starts(n, s).tolist()
    at, width, low, high = first[:-1], widths.tolist(), [-1] * n, [0] * n
    counter = start
    for root in rng.permutation(np.flatnonzero(np.bincount(t, minlength=n) == 0)).tolist():
        low[root] = counter
        path = [root]
        while path:
            x = path[-1]
            i, end = at[x], first[x + 1]
            while i < end:
                y = heads[i]
                i += 1
                if low[y] < 0:
                    low[y] = counter
                    if first[y] < first[y + 1]:
                        at[x] = i
                        path.append(y)
                        break
                    counter += width[y]
                    high[y] = counter
            else:
                path.pop()
                counter += width[x]
                b, e = low[x], counter
                for y in heads[first[x] : end]:
                    if low[y] < b:
                        b = low[y]
                    if high[y] >= e:
                        e = high[y] + 1
                low[x], high[x] = b, e
    return low, high
