"""Discovery orders: which permutations are valid, and one for each class of
equivalent ones.

Three searches: all permutations filtered by validity; connected prefixes only; and
connected prefixes that follow one label of each orbit of the prefix's stabiliser.
The last gives one order for each automorphism class.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import permutations

from .pattern import Pattern
from .symmetry import Perm, automorphisms, orbits, stabiliser


def is_valid(p: Pattern, order: Perm) -> bool:
    """Every label after the first touches an earlier one."""
    seen = 0
    for i, v in enumerate(order):
        if i and not p.neighbours[v] & seen:
            return False
        seen |= 1 << v
    return True


def by_permutation(p: Pattern) -> Iterator[Perm]:
    return (o for o in permutations(range(p.k)) if is_valid(p, o))


def _grow(p: Pattern, follow) -> Iterator[Perm]:
    """Depth-first over prefixes; ``follow(candidates, state)`` picks the labels to
    try next with the state that goes with each."""
    everything = (1 << p.k) - 1
    stack = [((), 0, everything, None)]
    while stack:
        prefix, used, open_, state = stack.pop()
        if len(prefix) == p.k:
            yield prefix
            continue
        for v, after in reversed(list(follow(open_ & ~used, state))):
            reach = p.neighbours[v] if not prefix else open_ | p.neighbours[v]
            stack.append(((*prefix, v), used | 1 << v, reach, after))


def _labels(mask: int) -> list[int]:
    return [v for v in range(mask.bit_length()) if mask >> v & 1]


def by_prefix(p: Pattern) -> Iterator[Perm]:
    return _grow(p, lambda mask, _: ((v, None) for v in _labels(mask)))


def distinct(p: Pattern) -> list[Perm]:
    """One order of every automorphism class: the lexicographically least label of
    each orbit is followed, with the stabiliser that fixes it."""
    whole = automorphisms(p)

    def follow(mask: int, group):
        group = whole if group is None else group
        moved = orbits(group, p.k)
        for v in _labels(mask):
            if not moved[v] & mask & ((1 << v) - 1):
                yield v, stabiliser(group, v)

    return list(_grow(p, follow))


def equivalent(p: Pattern, a: Perm, b: Perm) -> bool:
    return any(tuple(g[x] for x in a) == tuple(b) for g in automorphisms(p))


def census(p: Pattern) -> dict:
    """Search-space sizes: permutations, valid and distinct orders."""
    kinds = distinct(p)
    g = len(automorphisms(p))
    tested = 1
    for i in range(2, p.k + 1):
        tested *= i
    return {"k": p.k, "autos": g, "tested": tested, "valid": sum(1 for _ in by_prefix(p)), "distinct": len(kinds)}
