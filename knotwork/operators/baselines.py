"""The compared methods.

* ``topological``: set operations only; its best order by unbounded cost; at most
  the first edge taken in one direction; the count divided by what is left of the
  multiplicity.
* ``clique_pruned``: edges kept from lower to higher rank only, cliques mined on the
  directed rest without further bounds.
* ``worst_order``: full symmetry breaking on the dearest valid order.
"""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import cost
from ..functions.orders import by_prefix
from ..functions.pattern import Pattern, clique, parse
from ..functions.symmetry import Perm
from ..plans import by_blocks, by_join, planner
from ..plans.program import LoopProgram, compile_program
from .graph import GraphStore
from .mine import count, quotient


def topological_order(p: Pattern, model: cost.ModelGraph = cost.ModelGraph()) -> Perm:
    """The cheapest of all valid orders when no bound is known."""
    return min(by_prefix(p), key=lambda o: (float(f"{cost.order_cost(p, o, model, bound_of={}):.12e}"), o))


def topological_program(pattern: str | Pattern) -> LoopProgram:
    p = parse(pattern) if isinstance(pattern, str) else pattern
    return compile_program(p, topological_order(p), form="root")


def topological(store: GraphStore, pattern: str | Pattern, executor: str | None = None) -> DataFrame:
    """One row: mappings, multiplicity, cnt."""
    program = topological_program(pattern)
    met = planner.counted(store, program, executor or planner.choose_executor(store, program))
    return met.select("mappings", F.lit(program.multiplicity).cast("long").alias("multiplicity"), quotient("mappings", program.multiplicity).alias("cnt"))


def clique_pruned(store: GraphStore, k: int) -> DataFrame:
    """One row: cnt, cliques of k vertices by hand-pruned edges."""
    program = compile_program(clique(k), form="full")
    # The kept half of each list takes the place of the bounds, so none is compared.
    levels = tuple(replace(x, below=()) for x in program.levels)
    half = replace(program, levels=levels)
    run = by_blocks if by_blocks.fits(store, half) else by_join
    return run.counted(store, half).select(F.col("mappings").alias("cnt"))


def clique_default(store: GraphStore, k: int) -> DataFrame:
    return topological(store, clique(k))


def worst_order(store: GraphStore, pattern: str | Pattern, executor: str | None = None) -> DataFrame:
    p = parse(pattern) if isinstance(pattern, str) else pattern
    return count(store, p, executor=executor, order=cost.worst(p))


def ablation(oriented: GraphStore, plain: GraphStore, pattern: str | Pattern) -> DataFrame:
    """(bounds, oriented, bounded_scan, mappings, cnt) for every combination of the
    bound forms, degree renumbering and the bounded scan."""
    from ..plans.by_join import counted

    p = parse(pattern) if isinstance(pattern, str) else pattern
    rows = []
    for form in ("none", "root", "full", "min"):
        for store in (plain, oriented):
            for scan in (False, True):
                program = compile_program(p, form=form)
                rows.append(
                    counted(store, program, scan_half=scan).select(
                        F.lit(form).alias("bounds"), F.lit(store.oriented).alias("oriented"), F.lit(scan).alias("bounded_scan"),
                        "mappings", quotient("mappings", program.multiplicity).alias("cnt"),
                    )
                )
    return reduce(DataFrame.unionByName, rows)
