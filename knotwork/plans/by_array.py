"""Programs over adjacency arrays.

A prefix carries the sorted neighbour arrays its later levels read. Bounds cut the
arrays by binary search before anything is intersected, so ids beyond a bound are never
touched, and the last level is counted by array size without being listed. For graphs
whose largest list fits a row comfortably: longer lists are refused, and the planner
sends hub graphs to the joins.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators import setops
from ..operators.graph import GraphStore, adjacency
from .by_join import v
from .program import Level, LoopProgram


#: Longest neighbour list that a row carries.
DEGREE = 20_000


def lists(store: GraphStore) -> DataFrame:
    """(id, nbrs): one sorted array a vertex; refuses graphs with longer lists."""
    if store.max_degree > DEGREE:
        raise ValueError(f"a list of {store.max_degree} neighbours exceeds the arrays' limit of {DEGREE}; use the joins")
    return adjacency(store.pairs, block=1 << 62).select(F.col("src").alias("id"), "nbrs")


def _bounded(array: Column, level: Level, direction: str) -> Column:
    for b in level.below:
        array = setops.bounded(array, F.col(v(b)), direction)
    return array


def candidates(level: Level, direction: str = "down") -> Column:
    """The level's candidate array from the arrays n0, n1, ... of the prefix."""
    out = _bounded(F.col(f"n{level.anchors[0]}"), level, direction)
    for a in level.anchors[1:]:
        out = F.array_intersect(out, _bounded(F.col(f"n{a}"), level, direction))
    for x in level.excluded:
        out = F.array_except(out, _bounded(F.col(f"n{x}"), level, direction))
    if level.distinct:
        out = F.array_except(out, F.array(*[F.col(v(g)) for g in level.distinct]))
    return out


def _prefix(store: GraphStore, program: LoopProgram, upto: int) -> DataFrame:
    """Prefixes of ``upto`` labels with the arrays that levels from ``upto`` on, or
    levels in between, read."""
    base = lists(store)
    out = base.select(F.col("id").alias(v(0)), F.col("nbrs").alias("n0"))
    for i in range(1, upto):
        out = out.withColumn(v(i), F.explode(candidates(program.levels[i], program.direction)))
        needed = {j for x in program.levels[i + 1 :] for j in (*x.anchors, *x.excluded)}
        if i in needed:
            out = out.join(base.select(F.col("id").alias(v(i)), F.col("nbrs").alias(f"n{i}")), v(i))
        keep = [v(j) for j in range(i + 1)] + [f"n{j}" for j in sorted(needed) if j <= i]
        out = out.select(*keep)
    return out


def mappings(store: GraphStore, program: LoopProgram) -> DataFrame:
    last = program.k - 1
    out = _prefix(store, program, last).withColumn(v(last), F.explode(candidates(program.levels[last], program.direction)))
    return out.select(*[v(i) for i in range(program.k)])


def counted(store: GraphStore, program: LoopProgram) -> DataFrame:
    last = program.k - 1
    sizes = _prefix(store, program, last).select(F.size(candidates(program.levels[last], program.direction)).alias("s"))
    return sizes.agg(F.coalesce(F.sum("s"), F.lit(0)).cast("long").alias("mappings"))
