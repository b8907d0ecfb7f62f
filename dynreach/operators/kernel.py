"""The index inside one task: exact rules, one operation at a time.

DataFrame operators hand a graph that fits a task to this class through Arrow; larger graphs
take the set-at-a-time operators beside it. It also is what these are tested against.
"""

from __future__ import annotations

import heapq
import random
import time
from collections import defaultdict, deque
from collections.abc import Callable, Iterable

Edge = tuple[int, int]


def strongly_connected(nodes: Iterable[int], out: Callable[[int], Iterable[int]]) -> list[list[int]]:
    """Components in reverse topological order, by one iterative depth-first pass."""
    number: dict[int, int] = {}
    low: dict[int, int] = {}
    open_nodes: list[int] = []
    is_open: set[int] = set()
    found = []
    for root in nodes:
        if root in number:
            continue
        number[root] = low[root] = len(number)
        open_nodes.append(root)
        is_open.add(root)
        path = [(root, iter(out(root)))]
        while path:
            x, rest = path[-1]
            for y in rest:
                if y not in number:
                    number[y] = low[y] = len(number)
                    open_nodes.append(y)
                    is_open.add(y)
                    path.append((y, iter(out(y))))
                    break
                if y in is_open and number[y] < low[x]:
                    low[x] = number[y]
            else:
                path.pop()
                if path and low[x] < low[path[-1][0]]:
                    low[path[-1][0]] = low[x]
                if low[x] == number[x]:
                    part = []
                    while True:
                        y = open_nodes.pop()
                        is_open.discard(y)
                        part.append(y)
                        if y == x:
                            break
                    found.append(part)
    return found


def walk(roots: Iterable[int], children: Callable[[int], list[int]], width: Callable[[int], int], start: int = 0, known: Callable[[int], tuple[int, int] | None] = lambda c: None) -> dict[int, tuple[int, int]]:
    """Post-order intervals. A node begins at the counter on entry or at its lowest child, the counter
    moves on by the node's width, and the end is the larger of the counter and one past its highest child.

    known gives labels of nodes outside the walk.
    """
    labels: dict[int, tuple[int, int]] = {}
    entered: set[int] = set()
    counter = start
    for root in roots:
        if root in entered:
            continue
        entered.add(root)
        path = [[root, iter(children(root)), counter, counter]]
        while path:
            top = path[-1]
            for c in top[1]:
                there = known(c) or labels.get(c)
                if there is None:
                    entered.add(c)
                    path.append([c, iter(children(c)), counter, counter])
                    break
                top[2], top[3] = min(top[2], there[0]), max(top[3], there[1] + 1)
            else:
                path.pop()
                counter += width(top[0])
                labels[top[0]] = b, e = top[2], max(top[3], counter)
                if path:
                    up = path[-1]
                    up[2], up[3] = min(up[2], b), max(up[3], e + 1)
    return labels


def repaired(dag: Iterable[Edge], labels: dict[int, list[tuple[int, int]]], inserted: Iterable[Edge], fresh: Iterable[int], k: int) -> tuple[dict[int, int], dict[int, list[tuple[int, int]]]]:
    """(component -> the one it becomes part of, labels that change) after edges were inserted between components.

    dag holds the inserted edges too. Cycles lie above the inserted tails and below the inserted heads, so a component that
    nothing is above costs nothing more. fresh components have no labels yet: each gets one around its children's.
    """
    ix = DynamicIndex(k=k)
    succ, pred = defaultdict(set), defaultdict(set)
    for s, t in dag:
        succ[s].add(t)
        pred[t].add(s)
    inserted, fresh = list(inserted), set(fresh)
    ix.top = max((e for ivs in labels.values() for _, e in ivs), default=0)

    def spread(start: Iterable[int], step: dict[int, set[int]], within: set[int] | None = None) -> set[int]:
        seen = {x for x in start if within is None or x in within}
        todo = list(seen)
        while todo:
            for y in step.get(todo.pop(), ()):
                if y not in seen and (within is None or y in within):
                    seen.add(y)
                    todo.append(y)
        return seen

    above = spread((s for s, _ in inserted), pred)
    around = spread((t for _, t in inserted), succ, above)
    merged: dict[int, int] = {}
    parts = strongly_connected(sorted(around), lambda x: [y for y in succ.get(x, ()) if y in around])
    changed: set[int] = set()

    def label(part: list[int]) -> list[tuple[int, int]]:
        """Around the labels that members and their children have; past all ends if there are none."""
        have = [labels[c] for c in part if c in labels]
        below = [labels[y] for c in part if c in fresh for y in succ.get(c, ()) if y in labels]
        if not have and not below:
            ix.top += 1
            return [(ix.top - 1, ix.top)] * k
        return [(min([*(iv[d][0] for iv in have), *(iv[d][0] for iv in below)]), max([*(iv[d][1] for iv in have), *(iv[d][1] + 1 for iv in below)])) for d in range(k)]

    # new components from the bottom up; those on cycles are labelled with their part
    for part in strongly_connected(sorted(fresh), lambda x: [y for y in succ.get(x, ()) if y in fresh]):
        for c in part:
            labels[c] = label([c])
            changed.add(c)
    for part in parts:
        if len(part) > 1:
            rep = min(part)
            labels[rep] = label(part)
            changed.add(rep)
            for c in part:
                merged[c] = rep
    for c, rep in merged.items():
        if c != rep:
            changed.discard(c)
            del labels[c]
            for step, back in ((succ, pred), (pred, succ)):
                for y in step.pop(c, ()):
                    back[y].discard(c)
                    if merged.get(y) != rep:
                        step[rep].add(y)
                        back[y].add(rep)
    for rep in set(merged.values()):
        succ[rep].discard(rep)
        pred[rep].discard(rep)
    ix.pred, ix.succ, ix.labels, ix.changed = pred, succ, labels, changed
    ix.propagate_up({merged.get(t, t) for _, t in inserted} | set(merged.values()) | fresh - merged.keys())
    return merged, {c: labels[c] for c in ix.changed}


class DynamicIndex:
    """Live graph, condensation with multiplicities, containment forest and k intervals per component."""

    def __init__(self, nodes: Iterable[int] = (), edges: Iterable[Edge] = (), k: int = 1, seed: int = 42, slack: int = 1, order: str = "random", propagate: str = "two_phase", split: str = "extract", shrink: bool = False, next_id: int = -1):
        self.k, self.slack, self.order = k, slack, order
        self.propagate_mode, self.split_mode, self.shrink = propagate, split, shrink
        self.random = random.Random(seed)
        self.out: dict[int, set[int]] = {}
        self.inn: dict[int, set[int]] = {}
        self.up: dict[int, int] = {}
        self.size: dict[int, int] = {}
        self.expired: set[int] = set()
        self.succ: dict[int, dict[int, int]] = {}
        self.pred: dict[int, dict[int, int]] = {}
        self.labels: dict[int, list[tuple[int, int]]] = {}
        self.next_id, self.top, self.raises, self.touched, self.changed = next_id, 0, 0, 0, set()
        for n in nodes:
            self._live(n)
        for a, b in edges:
            self._live(a)
            self._live(b)
            self.out[a].add(b)
            self.inn[b].add(a)
        self._build()

    # construction

    def _live(self, n: int) -> None:
        self.out.setdefault(n, set())
        self.inn.setdefault(n, set())

    def _build(self) -> None:
        for part in strongly_connected(sorted(self.out), lambda x: sorted(self.out[x])):
            if len(part) == 1:
                self.size[part[0]] = 1
            else:
                c = self._new_id()
                self.size[c] = len(part)
                for n in part:
                    self.up[n] = c
        for c in self.size:
            self.succ[c], self.pred[c] = {}, {}
        for a, bs in self.out.items():
            s = self.find(a)
            for b in bs:
                self._count(s, self.find(b), 1)
        self.labels = self.draw_labels(self.order)

    def _new_id(self) -> int:
        self.next_id -= 1
        return self.next_id + 1

    def width(self, c: int) -> int:
        return self.size[c] * self.slack

    def draw_labels(self, order: str = "random") -> dict[int, list[tuple[int, int]]]:
        """k walks over the whole condensation; asc and desc visit children and roots in order of ids."""
        drawn = {c: [] for c in self.size}
        for _ in range(self.k):
            arranged = self._arranger(order)
            roots = arranged([c for c in self.size if not self.pred[c]])
            for c, iv in walk(roots, lambda c: arranged(list(self.succ[c])), self.width).items():
                drawn[c].append(iv)
        self.top = max([self.top, *(iv[1] for ivs in drawn.values() for iv in ivs)])
        return drawn

    def _arranger(self, order: str) -> Callable[[list[int]], list[int]]:
        if order == "random":
            return lambda xs: self.random.sample(sorted(xs), len(xs))
        return lambda xs: sorted(xs, reverse=order == "desc")

    # containment forest

    def find(self, x: int) -> int:
        top = x
        while top in self.up:
            top = self.up[top]
        while x != top:
            self.up[x], x = top, self.up[x]
        return top

    def depth(self, x: int) -> int:
        n = 0
        while x in self.up:
            x, n = self.up[x], n + 1
        return n

    # condensation

    def _count(self, s: int, t: int, by: int) -> None:
        if s == t:
            return
        m = self.succ[s].get(t, 0) + by
        if m:
            self.succ[s][t] = self.pred[t][s] = m
        else:
            del self.succ[s][t], self.pred[t][s]

    # queries

    def covers(self, s: int, t: int) -> bool:
        return all(a[0] <= b[0] and b[1] < a[1] for a, b in zip(self.labels[s], self.labels[t]))

    def query(self, u: int, v: int, prune: bool = True) -> tuple[bool, str, int]:
        """(reachable, decided by, components expanded)."""
        if u not in self.out or v not in self.out:
            return False, "unknown_node", 0
        s, t = self.find(u), self.find(v)
        if s == t:
            return True, "same_comp", 0
        if prune and not self.covers(s, t):
            return False, "labels", 0
        return self._search(s, t, prune)

    def _search(self, s: int, t: int, prune: bool = True) -> tuple[bool, str, int]:
        seen, stack, expanded = {s}, [s], 0
        while stack:
            x = stack.pop()
            expanded += 1
            for y in self.succ[x]:
                if y == t:
                    return True, "search", expanded
                if y not in seen and (not prune or self.covers(y, t)):
                    seen.add(y)
                    stack.append(y)
        return False, "search", expanded

    def reaches(self, u: int, v: int) -> bool:
        return self.query(u, v)[0]

    def comp_reaches(self, s: int, t: int) -> bool:
        return s == t or (self.covers(s, t) and self._search(s, t)[0])

    def raw_search(self, u: int, v: int) -> tuple[bool, int]:
        """Plain depth-first search on the live graph; nodes expanded."""
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

    def between(self, t: int, s: int) -> list[int]:
        """Components on paths from t to s; labels keep the forward walk small."""
        seen, queue = {t}, deque([t])
        while queue:
            x = queue.popleft()
            for y in self.succ[x]:
                if y not in seen and (y == s or self.covers(y, s)):
                    seen.add(y)
                    queue.append(y)
        if s not in seen:
            return []
        back, queue = {s}, deque([s])
        while queue:
            for y in self.pred[queue.popleft()]:
                if y in seen and y not in back:
                    back.add(y)
                    queue.append(y)
        return list(back)

    # label repair

    def propagate_up(self, seeds: Iterable[int], mode: str | None = None) -> int:
        """Raises ancestors until every parent contains its children; how many raises of ends it took.

        All modes end in the same labels: the least ones above the present labels that satisfy the rules.
        """
        mode, raises = mode or self.propagate_mode, 0
        seeds = list(seeds)
        for d in range(self.k):
            if mode == "unordered":
                stack = list(seeds)
                while stack:
                    x = stack.pop()
                    b, e = self.labels[x][d]
                    for p in self.pred[x]:
                        pb, pe = self.labels[p][d]
                        if pb > b or pe <= e:
                            raises += pe <= e
                            self._set(p, d, min(pb, b), max(pe, e + 1))
                            stack.append(p)
                continue
            if mode == "fixpoint":
                layer = set(seeds)
                while layer:
                    new = {}
                    for x in layer:
                        b, e = self.labels[x][d]
                        for p in self.pred[x]:
                            pb, pe = new.get(p, self.labels[p][d])
                            if pb > b or pe <= e:
                                new[p] = min(pb, b), max(pe, e + 1)
                    for p, (b, e) in new.items():
                        raises += e > self.labels[p][d][1]
                        self._set(p, d, b, e)
                    layer = set(new)
                continue
            stack = list(seeds)
            while stack:  # begins
                x = stack.pop()
                b = self.labels[x][d][0]
                for p in self.pred[x]:
                    if self.labels[p][d][0] > b:
                        self._set(p, d, b, self.labels[p][d][1])
                        stack.append(p)
            due = {x: 0 for x in seeds}
            heap = [(self.labels[x][d][1], x) for x in due]
            heapq.heapify(heap)
            while heap:  # ends, lowest old end first: what a node is due is known when its turn comes
                _, x = heapq.heappop(heap)
                b, e = self.labels[x][d]
                if (more := due.pop(x)) > e:
                    raises += 1
                    self._set(x, d, b, more)
                    e = more
                for p in self.pred[x]:
                    pe = self.labels[p][d][1]
                    if pe <= e:
                        if p not in due:
                            heapq.heappush(heap, (pe, p))
                        due[p] = max(due.get(p, 0), e + 1)
        self.raises += raises
        return raises

    def _set(self, c: int, d: int, b: int, e: int) -> None:
        self.labels[c][d] = (b, e)
        self.top = max(self.top, e)
        self.changed.add(c)

    # insertions

    def insert_edge(self, u: int, v: int) -> str:
        for n in (u, v):
            if n not in self.out:
                self.insert_node(n)
        if v in self.out[u]:
            return "I0"
        self.out[u].add(v)
        self.inn[v].add(u)
        s, t = self.find(u), self.find(v)
        if s == t:
            return "I1"
        if t in self.succ[s]:
            self._count(s, t, 1)
            return "I2"
        if self.comp_reaches(t, s):
            self._count(s, t, 1)
            self.merge(self.between(t, s), t)
            return "I5"
        self._count(s, t, 1)
        if self.covers(s, t):
            return "I3"
        for d, (b, e) in enumerate(self.labels[t]):
            sb, se = self.labels[s][d]
            self._set(s, d, min(sb, b), max(se, e + 1))
        self.propagate_up([s])
        return "I4"

    def representative(self, comps: list[int]) -> int:
        """The largest absorbs the others; a new id only if all are single nodes."""
        best = max(comps, key=lambda c: (self.size[c], -c if c >= 0 else c))
        return best if best < 0 else self._new_id()

    def merge(self, comps: list[int], head: int) -> int:
        rep = self.representative(comps)
        label, inside = list(self.labels[head]), set(comps)
        if rep not in inside:
            self.size[rep], self.succ[rep], self.pred[rep] = 0, {}, {}
        self.labels[rep] = label
        self.changed.add(rep)
        for c in comps:
            outs, ins = list(self.succ[c].items()), list(self.pred[c].items())
            if c != rep:
                for x, m in outs:
                    self._count(c, x, -m)
                    if x not in inside:
                        self._count(rep, x, m)
                for x, m in ins:
                    if x in self.succ and c in self.succ[x]:
                        self._count(x, c, -m)
                        if x not in inside:
                            self._count(x, rep, m)
                self.size[rep] += self.size.pop(c)
                self.up[c] = rep
                if c < 0:
                    self.expired.add(c)
                del self.succ[c], self.pred[c], self.labels[c]
        for c in inside:
            self.succ[rep].pop(c, None)
            self.pred[rep].pop(c, None)
        self.touched += len(comps)
        self.propagate_up([rep])
        return rep

    def insert_node(self, n: int, outs: Iterable[int] = (), ins: Iterable[int] = ()) -> str:
        outs, ins = [x for x in dict.fromkeys(outs)], list(dict.fromkeys(ins))
        if n in self.out:
            for x in outs:
                self.insert_edge(n, x)
            for x in ins:
                self.insert_edge(x, n)
            return "N1"
        for x in (*outs, *ins):
            if x != n and x not in self.out:
                self.insert_node(x)
        self._live(n)
        self.size[n], self.succ[n], self.pred[n] = 1, {}, {}
        for x in outs:
            self.out[n].add(x)
            self.inn[x].add(n)
            self._count(n, self.find(x), 1)
        below = [self.labels[c] for c in self.succ[n]]
        if below:
            self.labels[n] = [(min(iv[d][0] for iv in below), max(iv[d][1] for iv in below) + 1) for d in range(self.k)]
        else:
            self.labels[n] = [(self.top, self.top + 1)] * self.k
        self.top = max([self.top, *(e for _, e in self.labels[n])])
        self.changed.add(n)
        for x in ins:
            self.insert_edge(x, n)
        return "N0"

    # deletions

    def delete_edge(self, u: int, v: int) -> str:
        if v not in self.out.get(u, ()):
            return "D0"
        self.out[u].discard(v)
        self.inn[v].discard(u)
        s, t = self.find(u), self.find(v)
        if s != t:
            last = self.succ[s][t] == 1
            self._count(s, t, -1)
            if last and self.shrink:
                self._shrink(s, t)
            return "D2" if last else "D1"
        if u == v:
            return "D3"
        leavers = self.leavers(s, u, v) if self.split_mode == "extract" else self.naive_leavers(s, v)
        if not leavers:
            return "D3"
        self.split(s, leavers, v)
        return "D4"

    def _shrink(self, s: int, t: int) -> None:
        """Tightens labels upward while an interval's end or begin is owed to what has gone."""
        for d in range(self.k):
            todo = [(s, self.labels[t][d])]
            while todo:
                x, gone = todo.pop()
                b, e = self.labels[x][d]
                if gone[0] != b and gone[1] + 1 != e:
                    continue
                below = [self.labels[c][d] for c in self.succ[x]]
                least = e - self.width(x) if not below else min(c[0] for c in below)
                new = (max(b, least) if below else b, max([c[1] + 1 for c in below]) if below else min(e, b + self.width(x)))
                if new != (b, e) and new[0] < new[1]:
                    self._set(x, d, *new)
                    todo += [(p, (b, e)) for p in self.pred[x]]

    def leavers(self, comp: int, u: int, v: int) -> set[int]:
        """Members that no longer reach v. Members never met by the search stay and cost nothing."""
        inside = lambda x: self.find(x) == comp
        gone, queue = {u}, deque([u])
        while queue:
            x = queue.popleft()
            for y in self.out[x]:
                if y == v:
                    self.touched += len(gone)
                    return set()
                if y not in gone and inside(y):
                    gone.add(y)
                    queue.append(y)
        stays, todo = {v}, deque(p for x in gone for p in self.inn[x])
        while todo:
            c = todo.popleft()
            if c in gone or c in stays or not inside(c):
                continue
            seen, queue, stay = {c}, [c], False
            while queue and not stay:
                for y in self.out[queue.pop()]:
                    if y in stays:
                        stay = True
                        break
                    if y not in seen and y not in gone and inside(y):
                        seen.add(y)
                        queue.append(y)
            if stay:
                stays.add(c)
            else:
                gone |= seen
                todo.extend(p for x in seen for p in self.inn[x])
        self.touched += len(gone) + len(stays)
        return gone

    def naive_leavers(self, comp: int, v: int) -> set[int]:
        """The same from a decomposition of the whole component."""
        members, queue = {v}, [v]
        while queue:
            for y in self.out[queue.pop()]:
                if y not in members and self.find(y) == comp:
                    members.add(y)
                    queue.append(y)
        self.touched += len(members)
        for part in strongly_connected(members, lambda x: [y for y in self.out[x] if y in members]):
            if v in part:
                return members - set(part)
        return set()

    def split(self, comp: int, leavers: set[int], v: int) -> list[int]:
        """Parts of the leavers become components; the rest keeps the id, or its node's if one is left."""
        parts = strongly_connected(sorted(leavers), lambda x: sorted(y for y in self.out[x] if y in leavers))
        old_label = self.labels[comp]
        alone = self.size[comp] - len(leavers) == 1
        moving = leavers | ({v} if alone else set())
        touching = {(x, y) for x in moving for y in self.out[x]} | {(y, x) for x in moving for y in self.inn[x]}
        for a, b in touching:
            self._count(self.find(a), self.find(b), -1)
        made = []
        for part in parts:
            c = part[0] if len(part) == 1 else self._new_id()
            for n in part:
                self.up.pop(n, None)
                if len(part) > 1:
                    self.up[n] = c
            self.size[c], self.succ[c], self.pred[c] = len(part), {}, {}
            made.append(c)
        self.size[comp] -= len(leavers)
        rest = comp
        if alone:
            self.up.pop(v)
            rest = v
            self.size[v], self.succ[v], self.pred[v] = 1, {}, {}
            del self.size[comp], self.succ[comp], self.pred[comp], self.labels[comp]
            self.expired.add(comp)
        for a, b in touching:
            self._count(self.find(a), self.find(b), 1)
        made.append(rest)
        self.relabel_split(made, old_label)
        self.touched += len(made)
        return made

    def relabel_split(self, pieces: list[int], old: list[tuple[int, int]]) -> None:
        """Local walks from the old begin; ends respect children outside. Parents are raised if that went past them."""
        inside, new = set(pieces), {c: [] for c in pieces}
        for d in range(self.k):
            arranged = self._arranger("random" if self.order == "random" else self.order)
            known = lambda c, d=d: None if c in inside else self.labels[c][d]
            roots = arranged([c for c in pieces if not inside & self.pred[c].keys()])
            for c, iv in walk(roots, lambda c: arranged(list(self.succ[c])), self.width, old[d][0], known).items():
                new[c].append(iv)
        for c in pieces:
            self.labels[c] = new[c]
            self.changed.add(c)
            self.top = max([self.top, *(e for _, e in new[c])])
        self.propagate_up(pieces)

    def delete_node(self, n: int) -> str:
        if n not in self.out:
            return "D0"
        for x in list(self.out[n]):
            self.delete_edge(n, x)
        for x in list(self.inn[n]):  # no edges leave n, so these cross components and need no search
            self.out[x].discard(n)
            self._count(self.find(x), n, -1)
        del self.out[n], self.inn[n], self.size[n], self.succ[n], self.pred[n], self.labels[n]
        return "N2"

    # operations and what they leave

    def apply(self, kind: str, u: int, v: int | None = None, outs: Iterable[int] = (), ins: Iterable[int] = ()) -> dict:
        before, touched, self.changed = time.perf_counter(), self.touched, set()
        raises = self.raises
        if kind == "insert_edge":
            case = self.insert_edge(u, v)
        elif kind == "delete_edge":
            case = self.delete_edge(u, v)
        elif kind == "insert_node":
            case = self.insert_node(u, outs, ins)
        elif kind == "delete_node":
            case = self.delete_node(u)
        else:
            raise ValueError(kind)
        ms = (time.perf_counter() - before) * 1000
        return {"kind": kind, "case": case, "comps_touched": self.touched - touched, "labels_changed": len(self.changed), "rounds": self.raises - raises, "ms": ms}

    def names(self) -> dict[int, int]:
        """Smallest node of each component."""
        low: dict[int, int] = {}
        for n in self.out:
            c = self.find(n)
            low[c] = min(n, low.get(c, n))
        return low

    def membership(self) -> dict[int, int]:
        low = self.names()
        return {n: low[self.find(n)] for n in self.out}

    def dag(self) -> dict[Edge, int]:
        low = self.names()
        return {(low[s], low[t]): m for s, ts in self.succ.items() for t, m in ts.items()}

    def violations(self) -> list[tuple[int, int]]:
        """Condensation edges whose labels break the rule; there are none after any operation."""
        return [(s, t) for s, ts in self.succ.items() for t in ts if not self.covers(s, t)]

    def edges(self) -> set[Edge]:
        return {(a, b) for a, bs in self.out.items() for b in bs}


def index_of(edges: Iterable[Edge]) -> dict[int, list[int]]:
    out = defaultdict(list)
    for a, b in edges:
        out[a].append(b)
    return out
