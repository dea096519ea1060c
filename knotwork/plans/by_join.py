"""Programs as joins over the edge table (the default executor).

A level is one equi-join on an anchor; further anchors are semi joins and non-edges
anti joins on both endpoints, so hub lists never gather in one task. A bound on a
pattern edge reads only the oriented half of the edges (a pruned partition); a bound
across a non-edge stays a residual predicate of the join. Everything spills, and
adaptive execution splits what hubs skew.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.graph import GraphStore
from .program import Level, LoopProgram


def v(i: int) -> str:
    return f"v{i}"


def _half(store: GraphStore, oriented: bool, direction: str, s: str, d: str) -> DataFrame:
    """Edges as (s, d); ``oriented``: only those with d below s (above, for the
    mirrored direction)."""
    if oriented and direction == "down":
        return store.down.select(F.col("src").alias(s), F.col("dst").alias(d))
    if oriented:
        return store.down.select(F.col("dst").alias(s), F.col("src").alias(d))
    return store.pairs.select(F.col("src").alias(s), F.col("dst").alias(d))


def _below(direction: str, low: Column, high: Column) -> Column:
    return low < high if direction == "down" else low > high


def root(store: GraphStore) -> DataFrame:
    return store.vertices.select(F.col("id").alias(v(0)))


def extend(prefix: DataFrame, store: GraphStore, level: Level, i: int, direction: str = "down", scan_half: bool = True) -> DataFrame:
    """The prefix with one more label. ``scan_half=False`` keeps the bounds but reads
    whole neighbour lists (the ablation of the bounded scan)."""
    new, d = F.col(v(i)), direction
    # Start from an oriented anchor if there is one: its lists are the short ones.
    first = next((a for a in level.anchors if a in level.implied), level.anchors[0])
    edges = _half(store, scan_half and first in level.implied, d, v(first), v(i))
    out = prefix.join(edges, v(first))
    for b in level.below:
        if not (b == first and scan_half):
            out = out.where(_below(d, new, F.col(v(b))))
    for g in level.distinct:
        out = out.where(new != F.col(v(g)))
    for a in level.anchors:
        if a != first:
            out = out.join(_half(store, scan_half and a in level.implied, d, v(a), v(i)), [v(a), v(i)], "left_semi")
    for x in level.excluded:
        out = out.join(_half(store, scan_half and x in level.implied, d, v(x), v(i)), [v(x), v(i)], "left_anti")
    return out


def mappings(store: GraphStore, program: LoopProgram, scan_half: bool = True) -> DataFrame:
    """All mappings v0..v(k-1) that the program meets, in stored ids."""
    out = root(store)
    for i in range(1, program.k):
        if i == 1:  # the first edge needs no look at the vertex table
            level = program.levels[1]
            out = _half(store, 0 in level.implied and scan_half, program.direction, v(0), v(1))
            if 0 in level.below and not scan_half:
                out = out.where(_below(program.direction, F.col(v(1)), F.col(v(0))))
            continue
        out = extend(out, store, program.levels[i], i, program.direction, scan_half)
    return out.select(*[v(i) for i in range(program.k)])


def counted(store: GraphStore, program: LoopProgram, scan_half: bool = True) -> DataFrame:
    """One row: mappings."""
    return mappings(store, program, scan_half).agg(F.count("*").alias("mappings"))
