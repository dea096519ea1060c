"""Loop programs: what each level of a pattern's nested search does.

A level discovers one label: it intersects the neighbour sets of its anchors,
subtracts those of its excluded labels, and keeps candidates within the ID bounds.
Positions count along the order, so a program is independent of label names.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field
from functools import lru_cache

from ..functions import cost
from ..functions.pattern import Pattern, canonical
from ..functions.symmetry import Perm, bounds, closure, mappings_per_instance


@dataclass(frozen=True)
class Level:
    anchors: tuple[int, ...]  # earlier positions joined to this one by an edge
    excluded: tuple[int, ...]  # earlier positions that must not be adjacent
    below: tuple[int, ...]  # earlier positions whose id bounds this one
    distinct: tuple[int, ...]  # earlier positions this one could land on otherwise
    implied: tuple[int, ...]  # earlier positions known to lie above, by closure

    @property
    def oriented(self) -> tuple[int, ...]:
        """Anchors whose oriented half of the edges suffices."""
        return tuple(a for a in self.anchors if a in self.implied)


@dataclass(frozen=True)
class LoopProgram:
    pattern: Pattern
    order: Perm
    form: str
    levels: tuple[Level, ...]
    multiplicity: int  # mappings met per instance
    direction: str = "down"
    induced: bool = True
    key: str = field(default="", compare=False)

    @property
    def k(self) -> int:
        return len(self.levels)

    def live_after(self, i: int) -> list[int]:
        """Positions up to i that a later level still reads."""
        later = self.levels[i + 1 :]
        return [j for j in range(i + 1) if any(j in (*x.anchors, *x.excluded, *x.below, *x.distinct) for x in later)]

    def checks(self) -> int:
        return sum(len(x.below) for x in self.levels)

    def explain(self) -> str:
        name = [chr(65 + i) for i in range(self.k)]
        lines = ["A in all vertices"]
        for i, x in enumerate(self.levels[1:], 1):
            text = f"{name[i]} in " + " & ".join(f"N({name[a]})" for a in x.anchors) + "".join(f" - N({name[e]})" for e in x.excluded)
            sign = "<" if self.direction == "down" else ">"
            text += "".join(f", {name[i]} {sign} {name[b]}" + ("" if b in x.anchors else " (no edge)") for b in x.below)
            text += "".join(f", {name[i]} <> {name[d]}" for d in x.distinct)
            lines.append(text)
        return "\n".join(lines)


def _look_alike(p: Pattern, order: Perm, i: int, j: int, induced: bool) -> bool:
    """Could label i be put on label j's vertex? With non-edges enforced, only where
    every other earlier label is adjacent to both or to neither."""
    if p.has(order[i], order[j]):
        return False
    if not induced:
        return True
    return all(p.has(order[i], order[x]) == p.has(order[j], order[x]) for x in range(i) if x != j)


def compile_program(p: Pattern, order: Perm | None = None, form: str = "min", direction: str = "down", induced: bool = True, model: cost.ModelGraph | None = None) -> LoopProgram:
    """The program of an order (the cheapest distinct one by default)."""
    order = tuple(order) if order is not None else cost.choose(p, model or cost.ModelGraph())
    place = {v: i for i, v in enumerate(order)}
    pairs = [(place[u], place[w]) for u, w in bounds(p, order, form)]
    known = closure(pairs)
    levels = []
    for i, v in enumerate(order):
        anchors = tuple(j for j in range(i) if p.has(v, order[j]))
        if i and not anchors:
            raise ValueError("every label after the first must touch an earlier one")
        apart = tuple(j for j in range(i) if j not in anchors)
        implied = tuple(j for j in range(i) if (j, i) in known)
        guards = tuple(j for j in apart if j not in implied and _look_alike(p, order, i, j, induced))
        levels.append(Level(anchors, apart if induced else (), tuple(sorted(u for u, w in pairs if w == i)), guards, implied))
    return LoopProgram(p, order, form, tuple(levels), mappings_per_instance(p, order, form), direction, induced)


_cache: dict[tuple, tuple[LoopProgram, float]] = {}


def compile_cached(p: Pattern, form: str = "min", model: cost.ModelGraph | None = None, direction: str = "down", induced: bool = True) -> tuple[LoopProgram, float]:
    """Just-in-time compilation: the program and the seconds it took (0 when an
    isomorphic pattern was compiled before)."""
    c = canonical(Pattern(p.k, p.edge_mask))
    key = (c.k, c.edge_mask, form, model, direction, induced)
    if key in _cache:
        return _cache[key][0], 0.0
    start = time.perf_counter()
    program = compile_program(c, None, form, direction, induced, model)
    _cache[key] = (program, time.perf_counter() - start)
    return _cache[key]


@lru_cache(maxsize=1024)
def near_best(p: Pattern, slack: float = 0.1) -> tuple[LoopProgram, ...]:
    """Programs of the orders within ``slack`` of the cheapest."""
    rows = cost.ranked(p)
    return tuple(compile_program(p, o) for c, o in rows if c <= rows[0][0] * (1 + slack))


@dataclass
class TrieNode:
    """A shared leading part of several programs."""

    level: Level | None
    depth: int
    children: list[TrieNode] = field(default_factory=list)
    done: list[int] = field(default_factory=list)  # programs that end here

    def size(self) -> int:
        return 1 + sum(c.size() for c in self.children)


def merge(choices: list[tuple[LoopProgram, ...]]) -> tuple[TrieNode, list[LoopProgram]]:
    """One trie for many patterns: of each pattern's near-best programs the one that
    shares the longest prefix with what is already there. Levels are shared only
    when anchors, exclusions, bounds and guards are all equal."""
    root, picked = TrieNode(None, -1), []

    def shared(program: LoopProgram) -> int:
        node, n = root, 0
        for level in program.levels:
            node = next((c for c in node.children if c.level == level), None)
            if node is None:
                return n
            n += 1
        return n

    for i, some in enumerate(choices):
        best = max(some, key=shared)
        picked.append(best)
        node = root
        for d, level in enumerate(best.levels):
            child = next((c for c in node.children if c.level == level), None)
            if child is None:
                child = TrieNode(level, d)
                node.children.append(child)
            node = child
        node.done.append(i)
    return root, picked
