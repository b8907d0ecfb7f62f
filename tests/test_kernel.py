import random

import pytest

from dynreach.operators.kernel import DynamicIndex
from dynreach.sources.example import EXAMPLE_EDGES, letter, name


def example(**more):
    return DynamicIndex((), [(letter(a), letter(b)) for a, b in EXAMPLE_EDGES], **more)


def comps(ix):
    parts = {}
    for n, c in ix.membership().items():
        parts.setdefault(c, set()).add(name(n))
    return {frozenset(p) for p in parts.values() if len(p) > 1}


def of(ix, x):
    return ix.find(letter(x))


def show(ix):
    """Labels by a letter of each component."""
    return {min(name(n) for n in ix.out if ix.find(n) == c): iv[0] for c, iv in ix.labels.items()}


def dag(ix):
    return {name(s) + name(t) for s, t in ix.dag()}


# components are named by their first letter here: A = {A,B,C}, D = {D,E,F,G}, N = {N,O,P,S,T}
def test_components_and_condensation():
    ix = example()
    assert comps(ix) == {frozenset("ABC"), frozenset("DEFG"), frozenset("NOPST")}
    assert dag(ix) == set("RA RD AH AI DH DJ HL IN JK KN LN LM".split())


class Ordered(DynamicIndex):
    """Visits children and roots by letter, in one direction; components stand at the place of their drawn order."""

    PLACE = {"A": 0, "D": 1, "N": 2}

    def _arranger(self, order):
        place = lambda c: self.PLACE.get(min(name(n) for n in self.out if self.find(n) == c), 10 + min(n for n in self.out if self.find(n) == c))
        return lambda xs: sorted(xs, key=place, reverse=order == "desc")


def ordered(order):
    return Ordered((), [(letter(a), letter(b)) for a, b in EXAMPLE_EDGES], order=order)


WALK_1 = {"N": (0, 5), "M": (5, 6), "L": (0, 7), "H": (0, 8), "I": (0, 9), "A": (0, 12), "K": (0, 13), "J": (0, 14), "D": (0, 18), "R": (0, 19)}
WALK_2 = {"N": (0, 5), "M": (7, 8), "L": (0, 9), "H": (0, 10), "I": (0, 15), "A": (0, 18), "K": (0, 6), "J": (0, 7), "D": (0, 14), "R": (0, 19)}


def test_labels_of_both_walks():
    assert show(ordered("asc")) == WALK_1
    assert show(ordered("desc")) == WALK_2


def test_merge_then_splits():
    ix = ordered("desc")
    assert {min(name(n) for n in ix.out if ix.find(n) == c) for c in ix.between(of(ix, "B"), of(ix, "N"))} == set("NLHIA")
    assert ix.insert_edge(letter("N"), letter("B")) == "I5"
    assert comps(ix) == {frozenset("ABCHILNOPST"), frozenset("DEFG")}
    assert show(ix) == {"A": (0, 18), "K": (0, 19), "J": (0, 20), "D": (0, 21), "R": (0, 22), "M": (7, 8)}
    assert dag(ix) == set("RA DA KA AM RD DJ JK".split())
    assert len(ix.expired) == 1 and ix.size[of(ix, "A")] == 11
    assert ix.delete_edge(letter("L"), letter("P")) == "D4"
    labels = show(ix)
    assert (labels["L"], labels["H"], labels["A"], labels["R"]) == ((0, 9), (0, 10), (0, 11), (0, 22))
    assert dag(ix) == set("RA RD AH DJ HL JK LM DH KA".split())
    assert ix.delete_edge(letter("N"), letter("B")) == "D4"
    labels = show(ix)
    assert (labels["N"], labels["I"], labels["A"]) == ((0, 5), (0, 6), (0, 11))
    assert dag(ix) == set("RA RD AH AI DJ HL JK LM DH KN IN".split())


def test_touched_in_a_split_leaves_out_the_rest():
    ix = ordered("desc")
    ix.insert_edge(letter("N"), letter("B"))
    ix.out[letter("L")].discard(letter("P"))
    ix.inn[letter("P")].discard(letter("L"))
    seen = set()
    find = ix.find
    ix.find = lambda x: seen.add(name(x)) or find(x) if x >= 0 else find(x)
    assert {name(x) for x in ix.leavers(of(ix, "B"), letter("L"), letter("P"))} == {"L", "H"}


def test_what_ifs_from_the_start():
    ix = example()
    ix.insert_edge(letter("C"), letter("J"))
    assert ix.reaches(letter("A"), letter("K")) and ix.reaches(letter("B"), letter("J"))
    ix = example()
    ix.delete_edge(letter("H"), letter("L"))
    assert not ix.reaches(letter("H"), letter("M")) and not ix.reaches(letter("R"), letter("M"))
    ix = example()
    assert ix.delete_edge(letter("D"), letter("G")) == "D4"
    assert frozenset("DEF") in comps(ix) and not ix.reaches(letter("D"), letter("J")) and ix.reaches(letter("G"), letter("J"))


def agrees(ix):
    fresh = DynamicIndex(ix.out, ix.edges(), k=0)
    assert ix.membership() == fresh.membership()
    assert ix.dag() == fresh.dag()
    assert not ix.violations()
    assert sum(ix.size.values()) == len(ix.out)
    assert not ix.expired & set(ix.size)
    for c in ix.size:
        assert c not in ix.up


@pytest.mark.parametrize("seed", range(12))
def test_random_sequences(seed):
    rng = random.Random(seed)
    modes = [dict(propagate=m, split=s, shrink=sh) for m, s, sh in (("two_phase", "extract", False), ("fixpoint", "naive", False), ("unordered", "extract", False), ("two_phase", "extract", True))]
    for _ in range(6):
        n = rng.randint(3, 12)
        edges = {(rng.randrange(n), rng.randrange(n)) for _ in range(rng.randint(0, 2 * n))}
        many = [DynamicIndex(range(n), edges, k=k, seed=seed, **modes[i % 4]) for i, k in enumerate((0, 1, 2, 4))]
        for step in range(40):
            kind = rng.choices(("insert_edge", "delete_edge", "insert_node", "delete_node"), (6, 6, 2, 1))[0]
            u, v = rng.randrange(n + step // 4), rng.randrange(n + step // 4)
            outs, ins = [rng.randrange(n) for _ in range(rng.randint(0, 2))], [rng.randrange(n) for _ in range(rng.randint(0, 2))]
            cases = [ix.apply(kind, u, v, outs, ins)["case"][:1] for ix in many]
            assert len(set(cases)) == 1
            for ix in many:
                agrees(ix)
            a, b = rng.randrange(n + 3), rng.randrange(n + 3)
            answers = {ix.query(a, b)[0] for ix in many} | {many[0].raw_search(a, b)[0], many[1].query(a, b, prune=False)[0]}
            assert len(answers) == 1


def test_modes_of_propagation_agree():
    rng = random.Random(8)
    totals = {"two_phase": 0, "unordered": 0}
    for _ in range(120):
        n = 14
        edges = {(a, b) for a in range(n) for b in range(n) if a < b and rng.random() < 0.25}
        ends = {}
        for mode in ("two_phase", "fixpoint", "unordered"):
            ix = DynamicIndex(range(n), edges, k=1, seed=3)
            ix._set(n - 1, 0, 0, 60)
            ix.propagate_up([n - 1], mode)
            ends[mode] = ix.labels
            if mode in totals:
                totals[mode] += ix.raises
        assert ends["two_phase"] == ends["fixpoint"] == ends["unordered"]
    assert totals["two_phase"] <= totals["unordered"]


def test_edge_cases():
    empty = DynamicIndex()
    assert empty.query(1, 2) == (False, "unknown_node", 0)
    chain = DynamicIndex((), [(i, i + 1) for i in range(300)], k=2)
    assert chain.reaches(0, 300) and not chain.reaches(300, 0)
    chain.insert_edge(300, 0)
    assert len(chain.size) == 1
    assert chain.delete_edge(150, 151) == "D4" and len(chain.size) == 301
    loop = DynamicIndex((), [(1, 1)])
    assert loop.reaches(1, 1) and loop.delete_edge(1, 1) == "D3"
    full = DynamicIndex((), [(a, b) for a in range(8) for b in range(8) if a != b])
    assert full.delete_edge(0, 1) == "D3" and full.delete_node(3) == "N2" and full.insert_node(3, [0], [1]) == "N0" and full.reaches(3, 1)
    two = DynamicIndex((), [(0, 1), (1, 0), (2, 3), (3, 2), (0, 2), (0, 3), (1, 2)])
    assert list(two.dag().values()) == [3] and two.delete_edge(0, 2) == "D1"
