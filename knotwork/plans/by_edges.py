"""Triangles and stars of three leaves by the edges of their roots, for graphs with hubs.

The nested loops of these programs read, for every edge (a, b) of a root, the neighbours that
both ends have, and the rest follows from degrees, places in sorted lists and sums over their
beginnings. So an edge costs the shorter of its two lists, not the longer, and the pairs and
triples of a hub's leaves are counted and not visited. Mappings and elements read are those
of the loops.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from .program import LoopProgram

#: List elements, or pairs of common neighbours, that are looked up at a time.
SLICE = 2_000_000


def shape(program: LoopProgram) -> str | None:
    """``triangle`` or ``star`` where the program is one with its labels in descending order."""
    if program.direction != "down" or not program.induced:
        return None
    levels = [(x.anchors, x.excluded, x.below[-1:], x.distinct) for x in program.levels[1:]]
    if levels == [((0,), (), (0,), ()), ((0, 1), (), (1,), ())]:
        return "triangle"
    if levels == [((0,), (), (), ()), ((0,), (1,), (1,), ()), ((0,), (1, 2), (2,), ())]:
        return "star"
    return None


def counts(program: LoopProgram) -> str | None:
    """The shape whose instances a program meets once each, also where a star's first label is
    a leaf and its second the centre: in sum over all roots it counts the same stars."""
    levels = [(x.anchors, x.excluded, x.below[-1:], x.distinct) for x in program.levels[1:]]
    if program.direction == "down" and levels == [((0,), (), (), ()), ((1,), (0,), (0,), ()), ((1,), (0, 2), (2,), ())]:
        return "star"
    return shape(program)


class EdgeSearch:
    """One program over a CSR, many roots at once; a star's roots are the centres."""

    def __init__(self, starts: np.ndarray, nbrs: np.ndarray, program: LoopProgram, early_exit: bool = True):
        self.starts, self.nbrs, self.shape, self.early_exit = starts, nbrs, counts(program), early_exit
        self.n, self.degree = len(starts) - 1, np.diff(starts)
        src = np.repeat(np.arange(self.n), self.degree)
        self.keys = src * self.n + nbrs  # ascending, as the lists are
        self.down = np.bincount(src[nbrs < src], minlength=self.n)
        self.read = self.down if early_exit else self.degree  # of a list that is cut at its own vertex
        self.sums = np.concatenate([[0], np.cumsum(self.read[nbrs])])
        self.touched = 0

    def count(self, roots: np.ndarray) -> int:
        """Mappings from these roots; adds to ``touched``."""
        d = (self.down if self.shape == "triangle" else self.degree)[roots]
        first = np.concatenate([[0], np.cumsum(d)])
        a = np.repeat(roots, d)
        j = np.arange(len(a)) - np.repeat(first[:-1], d)
        b = self.nbrs[self.starts[a] + j]
        if self.shape == "triangle":
            own = j if self.early_exit else self.degree[a]
            self.touched += int(self.read[roots].sum()) + int((own + self.read[b]).sum())
            return sum(int(np.count_nonzero(hit)) for _, _, hit, _, _ in self.slices(a, b, j))
        return self.stars(d, first, a, b, j)

    def slices(self, a: np.ndarray, b: np.ndarray, j: np.ndarray) -> Iterator[tuple]:
        """(edges, of, hit, in_a, in_b): for a slice of edges the elements below b of the shorter
        list, the edge that each is of, whether the other list has it too, and its place in both."""
        mine = j <= self.down[b]
        size = np.where(mine, j, self.down[b])
        lo, other = self.starts[np.where(mine, a, b)], np.where(mine, b, a)
        ends, at = np.cumsum(size), 0
        while at < len(a):
            past = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + SLICE, "right")))
            s = size[at:past]
            of = np.repeat(np.arange(at, past), s)
            place = np.arange(len(of)) - np.repeat(np.cumsum(s) - s, s)
            key = other[of] * self.n + self.nbrs[lo[of] + place]
            found = np.searchsorted(self.keys, key)
            hit = self.keys[np.minimum(found, len(self.keys) - 1)] == key
            found -= self.starts[other[of]]
            yield slice(at, past), of, hit, np.where(mine[of], place, found), np.where(mine[of], found, place)
            at = past

    def stars(self, d: np.ndarray, first: np.ndarray, a: np.ndarray, b: np.ndarray, j: np.ndarray) -> int:
        """Leaves b > c > e of a that are pairwise apart: all triples, less those with a joined
        pair, and for each leaf the pairs joined to it back, and less those all joined."""
        both, closed = np.zeros(len(a), np.int64), 0  # neighbours shared with the root
        base = np.repeat(first[:-1], d)
        lead = self.nbrs[self.starts[a]]
        at_lead = np.searchsorted(self.keys, b * self.n + lead)
        apart = (j > 0) & (self.keys[np.minimum(at_lead, len(self.keys) - 1)] != b * self.n + lead)
        da, db = self.degree[a], self.degree[b]
        self.touched += int(d.sum()) + int(((j if self.early_exit else da) + (j > 0) * self.read[b]).sum())
        for edges, of, hit, in_a, in_b in self.slices(a, b, j):
            here = of[hit] - edges.start
            e, c = of[hit], in_a[hit]
            joined = np.bincount(here, minlength=edges.stop - edges.start)
            both[edges] += joined
            both += np.bincount(base[e] + c, minlength=len(a)) if len(e) else 0
            closed += self.closed(a[e], c, joined)
            x, lo = j[edges], self.starts[a[edges]]
            # Third leaves: the root's list, then the first leaf's, then the second's, as long as any remain.
            left = x - joined
            rank = np.arange(len(e)) - np.repeat(np.cumsum(joined) - joined, joined)
            led = np.bincount(here[c == rank], minlength=len(x))  # leaves before the least one apart from b
            w = self.read[self.nbrs[self.starts[a[e]] + c]]
            own = self.sums[lo + x] - self.sums[np.minimum(lo + led + 1, lo + x)] - _added(here[c != rank], w[c != rank], len(x))
            self.touched += int(own.sum())
            if self.early_exit:
                longer = np.where(j[of] <= self.down[b[of]], in_b, j[of] - in_a - hit)
                self.touched += int((x * (x - 1) // 2).sum()) - int(c.sum()) + int(longer.sum()) - int(in_b[hit].sum())
                self.touched -= int((at_lead[edges] - self.starts[b[edges]])[apart[edges]].sum())
            else:
                self.touched += int((da[edges] * left).sum()) + int((db[edges] * (left - apart[edges])).sum())
        pairs = np.add.reduceat(np.append(both, 0), first[:-1]) * (d > 0) // 2 if len(d) else d
        triples = d * (d - 1) // 2 * (d - 2) // 3
        return int(triples.sum()) - int((pairs * (d - 2)).sum()) + int((both * (both - 1) // 2).sum()) - closed

    def closed(self, a: np.ndarray, c: np.ndarray, joined: np.ndarray) -> int:
        """The joined pairs among the neighbours that the ends of each edge share."""
        x = self.nbrs[self.starts[a] + c]
        rank = np.arange(len(x)) - np.repeat(np.cumsum(joined) - joined, joined)
        ends, at, total = np.cumsum(rank), 0, 0
        while at < len(x):
            past = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + SLICE, "right")))
            s = rank[at:past]
            of = np.repeat(np.arange(at, past), s)
            before = of - rank[of] + np.arange(len(of)) - np.repeat(np.cumsum(s) - s, s)
            key = x[of] * self.n + x[before]
            total += int(np.count_nonzero(self.keys[np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)] == key))
            at = past
        return total


def _added(at: np.ndarray, w: np.ndarray, n: int) -> np.ndarray:
    out = np.zeros(n, np.int64)
    np.add.at(out, at, w)
    return out
