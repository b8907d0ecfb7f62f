"""The worked example: 19 lettered nodes, 28 edges."""

from __future__ import annotations

#: The example's edges in order.
EXAMPLE_EDGES = tuple("RA RD RE AB BC CA DE FD DG EF GF BH CI GJ DH HL JK LM KN IO LP NT OT PT TS SN SO SP".split())


def letter(x: str) -> int:
    return ord(x) - ord("A")


def name(n: int) -> str:
    return chr(n + ord("A"))
