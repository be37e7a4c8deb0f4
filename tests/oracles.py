"""Brute-force references."""

from __future__ import annotations

from itertools import product


def grammar_facts(edges, nf, vertices):
    """Facts of a binary normal form by saturation."""
    facts = {(u, a, v) for u, s, v in edges for a, t in nf.units if s == t} | {(u, a, u) for a in nf.nullable for u in vertices}
    while True:
        new = {(u, a, w) for a, b, c in nf.pairs for u, x, v in facts if x == b for y, z, w in facts if y == v and z == c} - facts
        if not new:
            return facts
        facts |= new


def walks(edges, length):
    """All walks of up to ``length`` edges: (start, end, tuple of edges)."""
    vertices = {e[0] for e in edges} | {e[2] for e in edges}
    level = [(u, u, ()) for u in vertices]
    out = list(level)
    for _ in range(length):
        level = [(u, e[2], (*path, e)) for u, v, path in level for e in edges if e[0] == v]
        out += level
    return out


def words(alphabet, length):
    for n in range(length + 1):
        yield from product(alphabet, repeat=n)
