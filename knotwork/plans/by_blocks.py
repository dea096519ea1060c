"""Programs over blocks of neighbour lists, for graphs too large to broadcast.

Vertices are dealt to blocks. A task takes one pair of blocks, with the lists of both, and
runs the first three labels of a program for the roots of one block and the second labels
of the other: prefixes are counted where they are met and never shuffled. A program of
more labels whose first label touches all others goes on inside the neighbourhoods of its
roots, which are written once, in proportion to the triangles. Only the half of the lists
that the program's bounds can reach is sent.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.pattern import CATALOG
from ..operators.graph import GraphStore
from .by_kernel import Search
from .program import LoopProgram, compile_program

#: Longest neighbour list that a row carries.
DEGREE = 2_000_000
#: List elements that a task holds at a time, and most prefixes that it expands at a time.
TASK = 24_000_000
PREFIXES = 4_000_000
SLICE = 2_000_000
#: Vertices up to which a task keeps one flag each.
FLAGS = 100_000_000
#: Least list elements of a slice that is kept short for the sake of its flags.
FLAGGED = 100_000


def fits(store: GraphStore, program: LoopProgram) -> bool:
    """Whether the blocks can run a program on a graph."""
    rooted = all(0 in x.anchors for x in program.levels[1:])
    return program.direction == "down" and (program.k == 3 or program.k > 3 and rooted) and store.max_degree <= DEGREE


def halves(program: LoopProgram) -> tuple[bool, bool]:
    """Whether the roots' lists, and those of all other labels, are read only below their
    own vertex."""
    deeper = [(i, x) for i, x in enumerate(program.levels) if i]
    return all(0 in x.implied for _, x in deeper), all(j in x.implied for i, x in deeper for j in range(1, i))


class PairSearch(Search):
    """The kernel's search over the lists of two blocks: roots, and second labels."""

    def __init__(self, roots: tuple, others: tuple, n: int, program: LoopProgram, early_exit: bool = True):
        ids, starts, nbrs = others
        super().__init__(starts, nbrs, program, early_exit)
        self.padded = np.append(ids, -1)
        self.ids, (self.root_ids, self.root_starts, self.root_nbrs) = ids, roots
        self.flags = np.zeros(n if n <= FLAGS else 0, bool)

    def whole(self, u: int) -> np.ndarray:
        if u != self.root:
            raise KeyError(f"the list of {u} is read for many labels at once only")
        return self.own

    def spans(self, xs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at = np.searchsorted(self.ids, xs)
        ok = self.padded[at] == xs  # a vertex without elements in its half has no list
        return np.where(ok, self.starts[at], 0), np.where(ok, self.starts[np.minimum(at + 1, len(self.starts) - 1)], 0)

    def inside(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        if not len(self.flags) or len(a) < 4 * len(b):
            return super().inside(a, b)
        self.flags[b] = True
        out = self.flags[a]
        self.flags[b] = False
        return out

    def enter(self, at: int) -> int:
        """Go to the root at a place; returns its id."""
        self.root, self.own = int(self.root_ids[at]), self.root_nbrs[self.root_starts[at] : self.root_starts[at + 1]]
        return self.root


class Meeting:
    """The roots of one block and the second labels of another, met in slices of a bounded
    number of list elements."""

    def __init__(self, t: pa.Table, blocks: int, n: int):
        role, task = t.column("role").to_numpy(), t.column("task")[0].as_py()
        (self.ids, self.root_starts, self.root_nbrs), (others, self.starts, self.nbrs) = [_csr(t.filter(pa.array(role == r)).select(["id", "nbrs"])) for r in (0, 1)]
        self.root_of = np.repeat(np.arange(len(self.ids)), np.diff(self.root_starts))
        mine = self.root_nbrs % blocks == task % blocks
        self.x, self.c = self.root_nbrs[mine].astype(np.int64), self.root_of[mine]
        at = np.searchsorted(others, self.x)
        ok = np.append(others, -1)[at] == self.x  # a vertex without elements in its half has no list
        self.lo = np.where(ok, self.starts[at], 0)
        self.size = np.where(ok, self.starts[np.minimum(at + 1, len(others))], 0) - self.lo
        self.n, self.rows = n, max(1, SLICE * 8 // max(1, n))
        self.flags = np.zeros(self.rows * n if n <= FLAGS else 0, bool)

    def slices(self) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """(x, c, near, of): second labels with their roots' places, the elements of their
        lists, and the place in x that each is of."""
        ends, at = np.cumsum(self.size), 0
        while at < len(self.x):
            done = ends[at - 1] if at else 0
            past = max(at + 1, min(int(np.searchsorted(ends, done + SLICE, "right")), at + SLICE))
            flagged = int(np.searchsorted(self.c, self.c[at] + self.rows))
            # A flag for each root and vertex pays only where the lists of these roots are long.
            past = flagged if flagged < past and ends[flagged - 1] - done >= FLAGGED else past
            size = self.size[at:past]
            of = np.repeat(np.arange(past - at), size)
            flat = np.arange(int(size.sum())) + np.repeat(self.lo[at:past] - (np.cumsum(size) - size), size)
            yield self.x[at:past], self.c[at:past], self.nbrs[flat], of
            at = past

    def weight(self, w: np.ndarray) -> int:
        """The triples of vertices joined pairwise in oriented lists, each by the product of its weights."""
        total = 0
        for x, c, near, of in self.slices():
            keep = self.shared(c, near, of)
            inner = np.bincount(of[keep], w[near[keep]], len(x)).astype(np.int64)  # whole below 2^53
            total += int((w[self.ids[c]] * w[x] * inner).sum())
        return total

    def shared(self, c: np.ndarray, near: np.ndarray, of: np.ndarray) -> np.ndarray:
        """Which elements the root of their second label has in its list too."""
        a, b = self.root_starts[c[0]], self.root_starts[c[-1] + 1]
        own = (self.root_of[a:b] - c[0]) * self.n + self.root_nbrs[a:b]
        asked = ((c - c[0]) * self.n)[of] + near
        if (c[-1] - c[0] + 1) * self.n > len(self.flags):
            return own[np.minimum(np.searchsorted(own, asked), len(own) - 1)] == asked
        self.flags[own] = True
        out = self.flags[asked]
        self.flags[own] = False
        return out

    def count(self, program: LoopProgram) -> int:
        """Mappings of a program of three labels that all touch each other."""
        first, level = program.levels[1:]
        total = 0
        for x, c, near, of in self.slices():
            u = self.ids[c]
            keep = (x < u if 0 in first.below else np.ones(len(x), bool))[of]
            for b in level.below:
                keep &= near < (x if b else u)[of]
            total += int(np.count_nonzero(self.shared(c, near[keep], of[keep])))
        return total


def _csr(t: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ids, starts, neighbours), sorted by id and by neighbour."""
    t = t.sort_by("id").combine_chunks()
    lists = t.column("nbrs").combine_chunks()
    starts = np.concatenate([[0], np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))]).astype(np.int64)
    return t.column("id").to_numpy().astype(np.int64), starts, lists.flatten().to_numpy(zero_copy_only=False).astype(np.int32 if lists.type.value_type == pa.int32() else np.int64)


def _lists(store: GraphStore, half: bool) -> DataFrame:
    kind = "int" if store.n < 1 << 31 else "long"
    edges = (store.down if half else store.pairs).select(F.col("src").alias("id"), F.col("dst").cast(kind))
    return edges.groupBy("id").agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))


def pairs_of_blocks(store: GraphStore, half_root: bool, half_other: bool) -> tuple[DataFrame, int]:
    """(task, role, id, nbrs): the lists of every pair of blocks, and the number of blocks."""
    held = store.m * ((1 if half_root else 2) + (1 if half_other else 2))
    p = max(1, -(-held // TASK), min(6, held // 100_000))
    block, other = F.pmod(F.col("id"), F.lit(p)), F.explode(F.sequence(F.lit(0), F.lit(p - 1)))

    def dealt(half: bool, role: int, task: Column) -> DataFrame:
        return _lists(store, half).select("id", "nbrs", other.alias("o")).select(task.cast("int").alias("task"), F.lit(role).alias("role"), "id", "nbrs")

    return dealt(half_root, 0, block * p + F.col("o")).unionByName(dealt(half_other, 1, F.col("o") * p + block)), p


def counted_many(store: GraphStore, programs: list[LoopProgram], early_exit: bool = True, touch: bool = False) -> DataFrame:
    """(slot, mappings), and with ``touch`` the list elements that the nested loops read, of
    programs of three labels in one pass."""
    if not touch and any(len(x.pattern.edges) == 2 for x in programs):
        return _with_paths(store, programs)
    # Whole scans read whole lists, whatever the bounds say.
    needed = [halves(p) if early_exit else (False, False) for p in programs]
    dealt, p = pairs_of_blocks(store, all(r for r, _ in needed), all(o for _, o in needed))
    n = store.n

    def run(t: pa.Table) -> pa.Table:
        if not touch:
            met = Meeting(t, p, n)
            return pa.table({"slot": pa.array(range(len(programs)), pa.int32()), "mappings": pa.array([met.count(x) for x in programs], pa.int64()), "touched": pa.array([0] * len(programs), pa.int64())})
        role, task = t.column("role").to_numpy(), t.column("task")[0].as_py()
        roots, others = [_csr(t.filter(pa.array(role == r)).select(["id", "nbrs"])) for r in (0, 1)]
        searches = [PairSearch(roots, others, n, x, early_exit) for x in programs]
        total = [0] * len(programs)
        for at in range(len(roots[0])):
            for i, s in enumerate(searches):
                u, before = s.enter(at), s.touched
                found = s.at(s.program.levels[1], [u])
                if task % p:  # the first level's list is read once, not once a block
                    s.touched = before
                xs = found[found % p == task % p]
                if len(xs):
                    total[i] += s.last(s.program.levels[2], [u], xs, touch)
        return pa.table({"slot": pa.array(range(len(programs)), pa.int32()), "mappings": pa.array(total, pa.int64()), "touched": pa.array([s.touched for s in searches], pa.int64())})

    each = dealt.repartition(p * p, "task").groupBy("task").applyInArrow(run, "slot int, mappings long, touched long")
    return each.groupBy("slot").agg(*[F.sum(c).alias(c) for c in (("mappings", "touched") if touch else ("mappings",))])


def triangles_of(store: GraphStore, weights: np.ndarray) -> DataFrame:
    """One row: mappings, the triangles weighted by the product of their vertices' weights."""
    dealt, p = pairs_of_blocks(store, True, True)
    n, held = store.n, store.spark.sparkContext.broadcast(weights)

    def run(t: pa.Table) -> pa.Table:
        return pa.table({"mappings": pa.array([Meeting(t, p, n).weight(held.value)], pa.int64())})

    each = dealt.repartition(p * p, "task").groupBy("task").applyInArrow(run, "mappings long")
    return each.agg(F.coalesce(F.sum("mappings"), F.lit(0)).alias("mappings"))


def _with_paths(store: GraphStore, programs: list[LoopProgram]) -> DataFrame:
    """(slot, mappings) of programs of three labels: a path is a pair of neighbours, and of
    the pairs those that are joined are in a triangle, three to each. So a hub's pairs are
    counted by its degree, and only triangles meet."""
    closed = [x for x in programs if len(x.pattern.edges) == 3]
    found = counted_many(store, [*closed, compile_program(CATALOG["triangle"])])
    paths = store.vertices.agg(F.expr("coalesce(sum(degree * (degree - 1) div 2), 0L)")).first()[0]
    rows, at = [], iter(range(len(closed)))
    for i, x in enumerate(programs):
        if len(x.pattern.edges) == 3:
            rows.append((next(at), i, 1, 0))
        else:
            rows.append((len(closed), i, -3 * x.multiplicity if any(level.excluded for level in x.levels) else 0, paths * x.multiplicity))
    to = store.spark.createDataFrame(rows, "slot int, to int, each long, more long")
    return F.broadcast(to).join(found, "slot").select(F.col("to").alias("slot"), (F.col("more") + F.col("each") * F.col("mappings")).alias("mappings"))


def neighbourhoods(store: GraphStore, program: LoopProgram) -> DataFrame:
    """(root, v, sizes, nbrs): for each root, in as many rows as there are blocks, its
    neighbours and the part of each one's list that the root has too."""
    half_root, half_other = halves(program)
    dealt, p = pairs_of_blocks(store, half_root, half_other)
    n = store.n
    kind = pa.int32() if n < 1 << 31 else pa.int64()

    def run(t: pa.Table) -> pa.Table:
        met = Meeting(t, p, n)
        out: list[list] = [[], [], [], []]
        for x, c, near, of in met.slices():
            keep = met.shared(c, near, of)
            size = np.bincount(of[keep], minlength=len(x))
            ends = np.flatnonzero(np.append(np.diff(c), 1)) + 1  # a row a root and slice
            cut = np.cumsum(size)[ends - 1]
            many = lambda xs, e, k: pa.ListArray.from_arrays(np.append(0, e).astype(np.int32), pa.array(xs, k))
            for column, y in zip(out, (pa.array(met.ids[c[ends - 1]], pa.int64()), many(x, ends, kind), many(size, ends, pa.int32()), many(near[keep], cut, kind)), strict=True):
                column.append(y)
        types = (pa.int64(), pa.list_(kind), pa.list_(pa.int32()), pa.list_(kind))
        return pa.table({name: pa.chunked_array(column, k) for name, column, k in zip(("root", "v", "sizes", "nbrs"), out, types, strict=True)})

    word = "int" if kind == pa.int32() else "long"
    return dealt.groupBy("task").applyInArrow(run, f"root long, v array<{word}>, sizes array<int>, nbrs array<{word}>")


class Frontier:
    """All prefixes of a program inside the neighbourhoods of many roots at once."""

    def __init__(self, roots: np.ndarray, v: list[np.ndarray], sizes: list[np.ndarray], nbrs: list[np.ndarray], program: LoopProgram):
        self.program = program
        root_at = np.repeat(np.arange(len(roots)), [len(x) for x in v])
        ids, size = np.concatenate(v).astype(np.int64), np.concatenate(sizes)
        owner, of = np.unique(roots, return_inverse=True)
        self.roots, group = owner, of[root_at]
        order = np.lexsort((ids, group))
        self.group, self.ids = group[order], ids[order]  # a vertex of a neighbourhood each
        self.first = np.searchsorted(self.group, np.arange(len(owner) + 1))
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        src = np.repeat(place, size)
        # A neighbour's place: (group, id) pairs are coded as one number in the same order.
        names, code = np.unique(self.ids, return_inverse=True)
        self.width = len(names) + 1
        flat = np.concatenate(nbrs).astype(np.int64)
        dst = np.searchsorted(self.group * self.width + code, self.group[src] * self.width + np.searchsorted(names, flat))
        keys = np.sort(src * (len(order) + 1) + dst)
        self.keys, self.dst = keys, keys % (len(order) + 1)
        self.starts = np.searchsorted(keys, np.arange(len(order) + 1) * (len(order) + 1))

    def joined(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        if not len(self.keys):
            return np.zeros(len(a), bool)
        k = a * (len(self.ids) + 1) + b
        return self.keys[np.minimum(np.searchsorted(self.keys, k), len(self.keys) - 1)] == k

    def count(self) -> int:
        level = self.program.levels[1]
        v1 = np.arange(len(self.ids))
        if 0 in level.below:
            v1 = v1[self.ids < self.roots[self.group]]
        return self._count([v1], 2)

    def _count(self, chosen: list[np.ndarray], i: int) -> int:
        if i == self.program.k:
            return len(chosen[0])
        level = self.program.levels[i]
        near = [a for a in level.anchors if a]
        if near:
            lo, hi = self.starts[chosen[near[0] - 1]], self.starts[chosen[near[0] - 1] + 1]
        else:
            lo, hi = self.first[self.group[chosen[0]]], self.first[self.group[chosen[0]] + 1]
        ends = np.cumsum(hi - lo)
        total, at = 0, 0
        while at < len(ends):  # a bounded number of prefixes at a time
            past = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + PREFIXES, "right")))
            size = (hi - lo)[at:past]
            row = np.repeat(np.arange(at, past), size)
            x = np.repeat(lo[at:past] - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))
            x = self.dst[x] if near else x
            ok = np.ones(len(x), bool)
            for b in level.below:
                ok &= x < chosen[b - 1][row] if b else self.ids[x] < self.roots[self.group[x]]
            for g in level.distinct:
                ok &= x != chosen[g - 1][row]
            row, x = row[ok], x[ok]
            for a in near[1:]:
                ok = self.joined(chosen[a - 1][row], x)
                row, x = row[ok], x[ok]
            for e in level.excluded:
                ok = ~self.joined(chosen[e - 1][row], x)
                row, x = row[ok], x[ok]
            total += len(x) if i == self.program.k - 1 else self._count([*[c[row] for c in chosen], x], i + 1)
            at = past
        return total


def counted_inside(store: GraphStore, program: LoopProgram) -> DataFrame:
    """One row: mappings of a program whose first label touches all others."""
    rows = neighbourhoods(store, program)
    parts = max(1, min(4096, store.m // 250_000))
    rows = rows.repartition(parts, "root").sortWithinPartitions("root")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, held, size = 0, [], 0

        def flush(upto: int | None) -> int:
            """Counts the collected roots, all but the last one unless ``upto`` is None."""
            nonlocal held
            now = [h for h in held if h[0] != upto]
            held = [h for h in held if h[0] == upto]
            return Frontier(np.array([h[0] for h in now]), *[[h[c] for h in now] for c in (1, 2, 3)], program).count() if now else 0

        for b in batches:
            columns = []
            for c in ("v", "sizes", "nbrs"):
                x = b.column(b.schema.get_field_index(c))
                columns.append((x.offsets.to_numpy(), x.values.to_numpy()))
            for i, u in enumerate(b.column(0).to_pylist()):
                held.append((u, *[flat[o[i] : o[i + 1]] for o, flat in columns]))
                size += len(held[-1][1]) + len(held[-1][3])
                if size > 1_000_000 and held[0][0] != u:
                    total += flush(u)
                    size = sum(len(h[1]) + len(h[3]) for h in held)
        total += flush(None)
        yield pa.RecordBatch.from_pydict({"mappings": pa.array([total], pa.int64())})

    return rows.mapInArrow(run, "mappings long").agg(F.coalesce(F.sum("mappings"), F.lit(0)).alias("mappings"))


def counted(store: GraphStore, program: LoopProgram) -> DataFrame:
    """One row: mappings."""
    if not fits(store, program):
        raise ValueError("the blocks run programs of three labels, or whose first label touches all others")
    if program.k == 3:
        return counted_many(store, [program]).agg(F.coalesce(F.sum("mappings"), F.lit(0)).alias("mappings"))
    return counted_inside(store, program)
