"""Automorphisms and the ID bounds that leave one mapping per instance.

Discovering labels in an order walks down a chain of stabilisers: the group that
fixes the labels discovered so far. A label whose orbit in that group has other
members takes the largest ID of its orbit; the next group fixes it. Read as
inequalities these are the bounds; because an orbit's bounds chain, one bound a
label (from the latest label that bounds it) implies the rest.
"""

from __future__ import annotations

from functools import lru_cache

from .pattern import Pattern

Perm = tuple[int, ...]


@lru_cache(maxsize=20_000)
def automorphisms(p: Pattern) -> tuple[Perm, ...]:
    """Every label permutation that keeps present pairs present and absent ones
    absent; images are tried among labels of equal degree only."""
    degree = [n.bit_count() for n in p.neighbours]
    out: list[Perm] = []
    partial: list[tuple[int, ...]] = [()]
    while partial:
        images = partial.pop()
        i = len(images)
        if i == p.k:
            out.append(images)
            continue
        for x in range(p.k):
            if x not in images and degree[x] == degree[i] and all(p.has(i, j) == p.has(x, images[j]) for j in range(i)):
                partial.append((*images, x))
    return tuple(sorted(out))


def multiplicity(p: Pattern) -> int:
    """How many mappings each instance has without bounds."""
    return len(automorphisms(p))


def is_valid_mapping(p: Pattern, order: Perm) -> bool:
    """Does this label ordering describe a mapping of the same instance?"""
    return tuple(order) in set(automorphisms(p))


def orbits(group, labels: int) -> list[int]:
    """For each label a bit mask of where the group can move it."""
    return [sum(1 << x for x in {g[v] for g in group}) for v in range(labels)]


def stabiliser(group, v: int):
    return tuple(g for g in group if g[v] == v)


def bounds_full(p: Pattern, order: Perm) -> list[tuple[int, int]]:
    """All bounds (upper, lower) of the stabiliser chain, in discovery order."""
    out, group = [], automorphisms(p)
    for v in order:
        out += [(v, w) for w in sorted({g[v] for g in group} - {v}, key=order.index)]
        group = stabiliser(group, v)
    return out


def bounds_min(p: Pattern, order: Perm) -> dict[int, int]:
    """Lower label -> the latest discovered label above it."""
    latest: dict[int, int] = {}
    for upper, lower in bounds_full(p, order):
        latest[lower] = upper  # bounds come in discovery order, so the last one stays
    return latest


def closure(pairs) -> set[tuple[int, int]]:
    """Transitive closure of (upper, lower) pairs."""
    out = set(pairs)
    while True:
        more = {(a, d) for a, b in out for c, d in out if b == c} - out
        if not more:
            return out
        out |= more


def root_exchangeable(p: Pattern, order: Perm) -> bool:
    """Whether some automorphism swaps the first two labels of the order."""
    a, b = order[:2]
    return any(g[a] == b and g[b] == a for g in automorphisms(p))


def bounds(p: Pattern, order: Perm, form: str = "min") -> list[tuple[int, int]]:
    """(upper, lower) pairs of a form: ``min``, ``full``, ``root`` or ``none``."""
    if form == "min":
        return [(u, w) for w, u in bounds_min(p, order).items()]
    if form == "full":
        return bounds_full(p, order)
    if form == "root":
        return [(order[0], order[1])] if root_exchangeable(p, order) else []
    if form == "none":
        return []
    raise ValueError(f"unknown form of bounds: {form!r}")


def mappings_per_instance(p: Pattern, order: Perm, form: str) -> int:
    """How often a program with these bounds meets each instance."""
    g = multiplicity(p)
    return {"min": 1, "full": 1, "none": g, "root": g // 2 if root_exchangeable(p, order) else g}[form]
