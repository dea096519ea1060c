"""Which executor runs a program, and how a huge one is cut into waves."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.graph import GraphStore
from . import by_array, by_blocks, by_edges, by_join, by_kernel, by_sql
from .program import LoopProgram

#: Most directed edges for the kernel by number of labels: its two innermost loops run
#: at once, so three labels cost one gather a vertex and four one a pair.
KERNEL_EDGES = {3: 8_000_000, 4: 1_000_000}
KERNEL_EDGES_MORE = 300_000
KERNEL_DEGREE = 5_000


def choose_executor(store: GraphStore, program: LoopProgram, mode: str = "count") -> str:
    """``kernel`` for a graph that one executor holds many times over, ``blocks`` for
    counts whose prefixes meet in pairs of lists, ``array`` for short lists and few levels,
    else ``join``."""
    if 2 * store.m <= KERNEL_EDGES.get(program.k, KERNEL_EDGES_MORE) and store.max_degree <= KERNEL_DEGREE:
        return "kernel"
    if mode == "count" and program.k > 3 and by_edges.counts(program) and store.max_degree > KERNEL_DEGREE and 2 * store.m <= by_kernel.LIMIT:
        return "kernel"  # a hub's leaves are counted and not visited
    if mode == "count" and by_blocks.fits(store, program):
        # A hub's neighbourhood has too many prefixes to expand, and the kernel counts the last two labels at once.
        hub = program.k > 3 and store.max_degree > KERNEL_DEGREE
        return "blocks" if not hub else "kernel" if 2 * store.m <= by_kernel.LIMIT else "join"
    if store.max_degree <= by_array.DEGREE and program.k <= 4 and mode == "count":
        return "array"
    return "join"


def mappings(store: GraphStore, program: LoopProgram, executor: str) -> DataFrame:
    run = {"join": by_join.mappings, "array": by_array.mappings, "kernel": by_kernel.mappings, "sql": lambda s, p: by_sql.run(s, p, count=False)}
    return run[executor](store, program)


def counted(store: GraphStore, program: LoopProgram, executor: str) -> DataFrame:
    """One row: mappings."""
    run = {"join": by_join.counted, "array": by_array.counted, "kernel": by_kernel.counted, "blocks": by_blocks.counted, "sql": by_sql.run}
    return run[executor](store, program).select("mappings")


def waves(store: GraphStore, program: LoopProgram, n_waves: int) -> list[DataFrame]:
    """The count as ``n_waves`` independent one-row jobs over disjoint roots, each of
    which can be run, stored and repeated on its own; their sum is the count."""
    out = []
    for r in range(n_waves):
        prefix = by_join.root(store).where(F.pmod(F.xxhash64("v0"), F.lit(n_waves)) == r)
        for i in range(1, program.k):
            prefix = by_join.extend(prefix, store, program.levels[i], i, program.direction)
        out.append(prefix.agg(F.count("*").alias("mappings")))
    return out
