"""Programs as nested loops over a broadcast compressed adjacency.

For graphs that fit one executor: the driver reads the edges only after a check of
their number and broadcasts two arrays, once a stored graph; the arrays of the graphs
used longest ago are freed on driver and executors. Tasks take ranges of roots. Sorted
lists are cut at the bound by binary search before they are intersected.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.graph import GraphStore
from .by_edges import EdgeSearch, counts, shape
from .by_join import v
from .program import Level, LoopProgram

#: Most directed edges that are broadcast: 8 bytes each, so 160 MB.
LIMIT = 20_000_000
#: Longest neighbour list whose pairs are visited where a program can go by edges.
HUB = 5_000


def csr(store: GraphStore, limit: int = LIMIT) -> tuple[np.ndarray, np.ndarray]:
    """(starts, neighbours) with ids 0..n-1; refuses graphs beyond the limit."""
    if 2 * store.m > limit:
        raise ValueError(f"{2 * store.m} directed edges exceed the kernel's limit of {limit}")
    t = store.pairs.select(F.col("src").cast("int"), F.col("dst").cast("int")).toArrow()
    src, dst = t.column("src").to_numpy(), t.column("dst").to_numpy()
    order = np.lexsort((dst, src))
    starts = np.searchsorted(src[order], np.arange(store.n + 1))
    return starts, dst[order].astype(np.int64)


#: Broadcast graphs of this process, the latest last, and how many may stay.
_shared: dict[tuple[str, str], Broadcast] = {}
KEPT = 4


def shared(store: GraphStore, limit: int = LIMIT) -> Broadcast:
    """The graph's broadcast arrays, made once; beyond ``KEPT`` graphs the one used longest
    ago leaves the executors. A plan that still needs it fetches it from the driver
    again, and the driver's copy goes with the last such plan."""
    sc = store.spark.sparkContext
    key = (sc.applicationId, store.path)
    if 2 * store.m > limit or key not in _shared:
        made = sc.broadcast(csr(store, limit))
        for old in [k for k in _shared if k[0] != sc.applicationId] + list(_shared)[: max(0, len(_shared) + 1 - KEPT)]:
            if (gone := _shared.pop(old, None)) is not None and old[0] == sc.applicationId:
                gone.unpersist()  # executors forget it; a plan that still needs it fetches it again
        _shared[key] = made
    _shared[key] = _shared.pop(key)
    return _shared[key]


def _inside(sorted_a: np.ndarray, sorted_b: np.ndarray) -> np.ndarray:
    """Which of a's ids occur in b."""
    if not len(sorted_b):
        return np.zeros(len(sorted_a), bool)
    at = np.minimum(np.searchsorted(sorted_b, sorted_a), len(sorted_b) - 1)
    return sorted_b[at] == sorted_a


class Search:
    """Depth-first search of one program over a CSR; counts list elements touched."""

    def __init__(self, starts: np.ndarray, nbrs: np.ndarray, program: LoopProgram, early_exit: bool = True):
        self.starts, self.nbrs, self.program, self.early_exit = starts, nbrs, program, early_exit
        self.touched = 0

    def whole(self, u: int) -> np.ndarray:
        return self.nbrs[self.starts[u] : self.starts[u + 1]]

    def spans(self, xs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where the lists of ``xs`` start and end."""
        return self.starts[xs], self.starts[xs + 1]

    def gather(self, xs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The elements of all lists of ``xs``, and the place in ``xs`` that each is of."""
        lo, hi = self.spans(xs)
        lengths = hi - lo
        ends = np.cumsum(lengths)
        flat = np.repeat(lo - (ends - lengths), lengths) + np.arange(int(ends[-1]) if len(ends) else 0)
        return self.nbrs[flat], np.repeat(np.arange(len(xs)), lengths)

    def inside(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return _inside(a, b)

    def list_of(self, u: int, cap: int | None) -> np.ndarray:
        out = self.whole(u)
        if cap is not None and self.early_exit:
            out = out[: np.searchsorted(out, cap)] if self.program.direction == "down" else out[np.searchsorted(out, cap, "right") :]
        self.touched += len(out)
        return out

    def candidates(self, chosen: list[int], i: int) -> np.ndarray:
        return self.at(self.program.levels[i], chosen)

    def at(self, level: Level, chosen: list[int]) -> np.ndarray:
        down = self.program.direction == "down"
        limits = [chosen[b] for b in level.below]
        cap = (min(limits) if down else max(limits)) if limits else None
        sets = sorted((self.list_of(chosen[a], cap) for a in level.anchors), key=len)
        out = sets[0]
        for other in sets[1:]:
            out = out[_inside(out, other)]
        if cap is not None and not self.early_exit:
            out = out[out < cap] if down else out[out > cap]
        for x in level.excluded:
            if len(out):
                out = out[~_inside(out, self.list_of(chosen[x], cap))]
        for g in level.distinct:
            out = out[out != chosen[g]]
        return out

    def count(self, root: int) -> int:
        """Mappings from one root, by the plain nested loops (keeps ``touched``)."""
        return self._count([root], 1)

    def _count(self, chosen: list[int], i: int) -> int:
        found = self.candidates(chosen, i)
        if i == self.program.k - 1:
            return len(found)
        return sum(self._count([*chosen, x], i + 1) for x in found.tolist())

    def touch_count(self, root: int) -> int:
        """The same, with the elements that the innermost loop touches added up at once."""
        return self._touch([root], 1)

    def _touch(self, chosen: list[int], i: int) -> int:
        found = self.candidates(chosen, i)
        if i == self.program.k - 1 or not len(found):
            return len(found)
        if i == self.program.k - 2:
            return self.last(self.program.levels[i + 1], chosen, found, touch=True)
        return sum(self._touch([*chosen, x], i + 1) for x in found.tolist())

    def fast_count(self, root: int) -> int:
        """The same with the two innermost loops done at once."""
        return self._fast([root], 1)

    def _fast(self, chosen: list[int], i: int) -> int:
        found = self.candidates(chosen, i)
        if i == self.program.k - 1 or not len(found):
            return len(found) if i == self.program.k - 1 else 0
        if i == self.program.k - 2:
            return self.last(self.program.levels[i + 1], chosen, found)
        return sum(self._fast([*chosen, x], i + 1) for x in found.tolist())

    def last(self, level: Level, chosen: list[int], xs: np.ndarray, touch: bool = False) -> int:
        """How many candidates ``level`` has in total when the label before it takes
        each id of ``xs`` in turn: one gather of all their lists, filtered at once.
        With ``touch`` the list elements that the loops would read are added up."""
        p, down, before = len(chosen), self.program.direction == "down", self.touched
        fixed = [chosen[b] for b in level.below if b != p]
        cap = (min(fixed) if down else max(fixed)) if fixed else None
        bound = xs if p in level.below else None
        if cap is not None and bound is not None:
            bound = np.minimum(xs, cap) if down else np.maximum(xs, cap)
        elif cap is not None:
            bound = np.full(len(xs), cap)
        read = 0

        def reach(sorted_ids: np.ndarray) -> np.ndarray:  # elements within the bound, for each of xs
            if bound is None:
                return np.full(len(xs), len(sorted_ids))
            return np.searchsorted(sorted_ids, bound) if down else len(sorted_ids) - np.searchsorted(sorted_ids, bound, "right")

        def cost(u: int, alive: np.ndarray | slice = slice(None)) -> int:
            out = self.whole(u)
            return int((reach(out) if self.early_exit else np.full(len(xs), len(out)))[alive].sum())

        near, owner = self.gather(xs) if p in level.anchors or p in level.excluded else (xs[:0], xs[:0])
        own_read = np.bincount(owner, minlength=len(xs)) if touch else None
        if bound is not None:
            keep = near < bound[owner] if down else near > bound[owner]
            near, owner = near[keep], owner[keep]
            if touch and self.early_exit:
                own_read = np.bincount(owner, minlength=len(xs))
        if p in level.anchors:
            if touch:
                read += int(own_read.sum()) + sum(cost(chosen[a]) for a in level.anchors if a != p)
            for a in level.anchors:
                if a != p and len(near):
                    keep = self.inside(near, self.list_of(chosen[a], cap))
                    near, owner = near[keep], owner[keep]
            for x in level.excluded:
                if len(near):
                    if touch:
                        read += cost(chosen[x], np.bincount(owner, minlength=len(xs)) > 0)
                    keep = ~self.inside(near, self.list_of(chosen[x], cap))
                    near, owner = near[keep], owner[keep]
            for g in level.distinct:
                near = near[near != chosen[g]]
            total = len(near)
        else:
            # The label before is no anchor: the candidates are one set, and each x only
            # takes away its own neighbours (if excluded), itself, and what its bound cuts.
            own = self.at(Level(level.anchors, (), tuple(b for b in level.below if b != p), (), ()), chosen)
            if touch:
                read += sum(cost(chosen[a]) for a in level.anchors)
            for x in level.excluded:
                if touch:
                    alive = reach(own) > 0
                    read += cost(chosen[x], alive) if x != p else int(own_read[alive].sum())
                if x != p and len(own):
                    own = own[~self.inside(own, self.list_of(chosen[x], cap))]
            for g in level.distinct:
                if g != p:
                    own = own[own != chosen[g]]
            total = int(reach(own).sum())
            if p in level.distinct and p not in level.below:
                total -= int(np.count_nonzero(_inside(xs, own)))
            if p in level.excluded:
                total -= int(np.count_nonzero(self.inside(near, own)))
        self.touched = before + read
        return total

    def listing(self, chosen: list[int]) -> Iterator[np.ndarray]:
        i = len(chosen)
        found = self.candidates(chosen, i)
        if i == self.program.k - 1:
            if len(found):
                yield np.concatenate([np.tile(np.array(chosen, np.int64), (len(found), 1)), found[:, None]], axis=1)
            return
        for x in found.tolist():
            yield from self.listing([*chosen, x])


def counted(store: GraphStore, program: LoopProgram, limit: int = LIMIT) -> DataFrame:
    """One row: mappings."""
    lists, hub = shared(store, limit), store.max_degree > HUB and counts(program) is not None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if hub:
            by_edge = EdgeSearch(*lists.value, program)
            yield pa.RecordBatch.from_pydict({"mappings": [sum(by_edge.count(b.column(0).to_numpy()) for b in batches)]})
            return
        search = Search(*lists.value, program)
        total = sum(search.fast_count(u) for b in batches for u in b.column(0).to_pylist())
        yield pa.RecordBatch.from_pydict({"mappings": [total]})

    return _roots(store).mapInArrow(run, "mappings long").agg(F.coalesce(F.sum("mappings"), F.lit(0)).alias("mappings"))


def counted_many(store: GraphStore, programs: list[LoopProgram], early_exit: bool = True, limit: int = LIMIT, at_once: bool = False) -> DataFrame:
    """(slot, mappings, touched, seconds) of several programs in one pass over the roots;
    ``seconds`` is the tasks' processor time on each. ``at_once`` adds up the innermost
    loop, with the same numbers but its time; in a graph with hubs it adds up more of them."""
    lists = shared(store, limit)
    hub = [at_once and store.max_degree > HUB and shape(p) is not None for p in programs]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        searches = [(EdgeSearch if h else Search)(*lists.value, p, early_exit) for p, h in zip(programs, hub, strict=True)]
        total, seconds = [0] * len(programs), [0.0] * len(programs)
        for b in batches:
            ids, roots = b.column(0).to_numpy(), b.column(0).to_pylist()
            for i, search in enumerate(searches):
                start = time.process_time()
                total[i] += search.count(ids) if hub[i] else sum(map(search.touch_count if at_once else search.count, roots))
                seconds[i] += time.process_time() - start
        yield pa.RecordBatch.from_pydict({"slot": pa.array(range(len(programs)), pa.int32()), "mappings": total, "touched": [s.touched for s in searches], "seconds": seconds})

    every = _roots(store).mapInArrow(run, "slot int, mappings long, touched long, seconds double")
    return every.groupBy("slot").agg(*[F.sum(c).alias(c) for c in ("mappings", "touched", "seconds")])


def mappings(store: GraphStore, program: LoopProgram, limit: int = LIMIT) -> DataFrame:
    names = [v(i) for i in range(program.k)]
    lists = shared(store, limit)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        search = Search(*lists.value, program)
        for b in batches:
            for u in b.column(0).to_pylist():
                for rows in search.listing([u]):
                    yield pa.RecordBatch.from_arrays([pa.array(rows[:, i]) for i in range(program.k)], names)

    return _roots(store).mapInArrow(run, ", ".join(f"{n} long" for n in names))


def _roots(store: GraphStore) -> DataFrame:
    """Roots spread by hash, since neighbouring ids of a ranked graph are all hubs."""
    tasks = max(1, min(8 * store.spark.sparkContext.defaultParallelism, store.n // 64 + 1))
    return store.spark.range(store.n).repartition(tasks, F.xxhash64("id"))
