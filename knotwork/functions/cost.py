"""Expected work of an order on a random graph.

Model: n vertices, every pair an edge with probability p, IDs exchangeable. A loop
over the common neighbours of a labels and non-neighbours of b labels has
n p^a (1-p)^b iterations; it runs as often as the loops around it, times the
probability that the bounds met so far hold jointly. One-bound sets are forests
whose parents come first, so for exchangeable IDs that probability is the product
over labels of 1 / (size of the label's subtree within the prefix).
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

from .orders import distinct
from .pattern import Pattern
from .symmetry import Perm, automorphisms, bounds_min, orbits, stabiliser


@dataclass(frozen=True)
class ModelGraph:
    """The random graph that orders are priced on. The default has 1000 vertices of
    average degree 5."""

    n: int = 1000
    p: float = 0.005
    closing: float | None = None  # probability of a further anchor's edge; p if None

    @classmethod
    def from_stats(cls, n: int, m: int, triangles: int | None = None, wedges: int | None = None) -> ModelGraph:
        """Fitted to a graph; with triangle and two-edge-path counts an edge that
        closes a path has the graph's clustering coefficient."""
        p = min(1.0, 2 * m / (n * (n - 1))) if n > 1 else 0.0
        closing = 3 * triangles / wedges if triangles is not None and wedges else None
        return cls(max(n, 1), p, closing)


def loop_length(g: ModelGraph, anchors: int, excluded: int) -> float:
    if not anchors:
        return float(g.n)
    more = g.p if g.closing is None else max(g.closing, g.p)
    return g.n * g.p * more ** (anchors - 1) * (1 - g.p) ** excluded


def prefix_probability(order: Perm, bound_of: dict[int, int], i: int) -> float:
    """The chance that all bounds among the first i labels hold."""
    prefix = order[:i]
    size = dict.fromkeys(prefix, 1)
    for v in reversed(prefix):
        if v in bound_of and bound_of[v] in size:
            size[bound_of[v]] += size[v]
    out = 1.0
    for s in size.values():
        out /= s
    return out


def loop_costs(p: Pattern, order: Perm, g: ModelGraph = ModelGraph(), bound_of: dict[int, int] | None = None, early_exit: bool = False) -> list[dict]:
    """Length, probability and cost of every loop. ``bound_of`` defaults to the
    pattern's one-bound set; pass {} for a program without bounds. ``early_exit``
    charges a loop only for candidates within its own bound."""
    bound_of = bounds_min(p, order) if bound_of is None else bound_of
    out, entries, seen = [], 1.0, 0
    for i, v in enumerate(order):
        a = (p.neighbours[v] & seen).bit_count()
        length = loop_length(g, a, i - a)
        entries *= length
        chance = prefix_probability(order, bound_of, i + 1 if early_exit else i)
        out.append({"loop": i, "label": v, "anchors": a, "excluded": i - a, "length": length, "chance": chance, "cost": entries * chance})
        seen |= 1 << v
    return out


def order_cost(p: Pattern, order: Perm, g: ModelGraph = ModelGraph(), **how) -> float:
    return sum(x["cost"] for x in loop_costs(p, order, g, **how))


def ranked(p: Pattern, g: ModelGraph = ModelGraph(), **how) -> list[tuple[float, Perm]]:
    """Distinct orders, cheapest first; ties by the order itself. Costs that agree
    to 12 digits count as tied."""
    return sorted(((order_cost(p, o, g, **how), o) for o in distinct(p)), key=lambda x: (float(f"{x[0]:.12e}"), x[1]))


@lru_cache(maxsize=4096)
def choose(p: Pattern, g: ModelGraph = ModelGraph(), early_exit: bool = False) -> Perm:
    """The first order of ``ranked``, without pricing all of them. Loop costs are
    known from the prefix alone and only add up, so a prefix that already costs more
    than the best whole order is left; cheap branches are followed first."""
    lengths = [[loop_length(g, a, i - a) for a in range(i + 1)] for i in range(p.k)]
    best: list = [float("inf"), ()]

    def follow(prefix: Perm, used: int, reach: int, group, entries: float, total: float, bound_of: dict[int, int]) -> None:
        i = len(prefix)
        if i == p.k:
            best[:] = min(best, [float(f"{total:.12e}"), prefix])
            return
        ready = reach & ~used
        moved = orbits(group, p.k) if len(group) > 1 else None
        chance = prefix_probability(prefix, bound_of, i)
        steps = []
        for v in range(p.k):
            if not ready >> v & 1 or moved and moved[v] & ready & ((1 << v) - 1):
                continue
            n = entries * lengths[i][(p.neighbours[v] & used).bit_count()]
            c = prefix_probability((*prefix, v), bound_of, i + 1) if early_exit else chance
            steps.append((total + n * c, v, n))
        for t, v, n in sorted(steps):
            if t > best[0] * (1 + 1e-9):
                break
            below = {w: v for w in {x[v] for x in group} - {v}}
            next_reach = p.neighbours[v] if not prefix else reach | p.neighbours[v]
            follow((*prefix, v), used | 1 << v, next_reach, stabiliser(group, v) if len(group) > 1 else group, n, t, bound_of | below if below else bound_of)

    follow((), 0, (1 << p.k) - 1, automorphisms(p), 1.0, 0.0, {})
    return best[1]


def worst(p: Pattern, g: ModelGraph = ModelGraph()) -> Perm:
    return ranked(p, g)[-1][1]
