"""The front door: a pattern and a stored graph to a count, a listing or
per-vertex participation.

Counts are of vertex-induced instances: absent pairs of the pattern must be absent
in the graph (``induced=False`` drops that, an extension).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.cost import ModelGraph
from ..functions.pattern import Pattern, parse
from ..functions.symmetry import Perm
from ..plans import planner
from ..plans.by_join import v
from ..plans.program import LoopProgram, compile_cached, compile_program
from .graph import GraphStore


def quotient(mappings: Column | str, multiplicity: int | str) -> Column:
    """Whole instances from whole mappings: a division of longs, never of doubles."""
    by = F.lit(multiplicity).cast("long") if isinstance(multiplicity, int) else F.col(multiplicity).cast("long")
    return F.call_function("div", F.col(mappings).cast("long") if isinstance(mappings, str) else mappings, by)


def program_for(store: GraphStore, pattern: str | Pattern, order: Perm | None = None, bounds: str = "min", direction: str = "down", induced: bool = True, fitted: bool = False) -> LoopProgram:
    """The program that ``mine`` would run, compiled just in time: an isomorphic pattern
    that was compiled before costs nothing. ``fitted`` prices orders on the graph's own
    size, density and clustering instead of the reference model."""
    p = parse(pattern) if isinstance(pattern, str) else pattern
    model = ModelGraph.from_stats(store.n, store.m, *store.clustering()) if fitted else None
    if order is None:
        return compile_cached(p, bounds, model, direction, induced)[0]
    return compile_program(p, order, bounds, direction, induced, model)


def mappings(store: GraphStore, program: LoopProgram, executor: str | None = None) -> DataFrame:
    return planner.mappings(store, program, executor or planner.choose_executor(store, program, "list"))


def count(store: GraphStore, pattern: str | Pattern, executor: str | None = None, **how) -> DataFrame:
    """One row: mappings met, multiplicity, cnt (their quotient)."""
    program = program_for(store, pattern, **how)
    met = planner.counted(store, program, executor or planner.choose_executor(store, program))
    return met.select("mappings", F.lit(program.multiplicity).cast("long").alias("multiplicity"), quotient("mappings", program.multiplicity).alias("cnt"))


def instances(store: GraphStore, pattern: str | Pattern, executor: str | None = None, **how) -> DataFrame:
    """v0..v(k-1) per instance: original ids, ascending within a row. Forms with
    several mappings an instance are reduced to one."""
    program = program_for(store, pattern, **how)
    met = mappings(store, program, executor)
    names = store.vertices.select("id", "orig")
    for i in range(program.k):
        met = met.join(names.withColumnsRenamed({"id": v(i), "orig": f"o{i}"}), v(i)).drop(v(i))
    ids = met.select(F.sort_array(F.array(*[F.col(f"o{i}") for i in range(program.k)])).alias("ids"))
    if program.multiplicity > 1:
        ids = ids.distinct()
    return ids.select(*[F.col("ids")[i].alias(v(i)) for i in range(program.k)])


def per_vertex(store: GraphStore, pattern: str | Pattern, executor: str | None = None, **how) -> DataFrame:
    """(vertex, cnt): instances that each vertex takes part in (an extension)."""
    program = program_for(store, pattern, **how)
    each = mappings(store, program, executor).select(F.explode(F.array(*[v(i) for i in range(program.k)])).alias("id"))
    n = each.groupBy("id").agg(quotient(F.count("*"), program.multiplicity).alias("cnt"))
    return n.join(store.vertices.select("id", F.col("orig").alias("vertex")), "id").select("vertex", "cnt")


def top_vertices(store: GraphStore, pattern: str | Pattern, n: int = 10, **how) -> DataFrame:
    """The vertices in most instances, ties by id (an extension)."""
    return per_vertex(store, pattern, **how).orderBy(F.desc("cnt"), "vertex").limit(n)


def mine(store: GraphStore, pattern: str | Pattern, mode: str = "count", **how) -> DataFrame:
    run = {"count": count, "list": instances, "per_vertex": per_vertex}
    return run[mode](store, pattern, **how)
