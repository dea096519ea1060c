"""Programs printed as SQL over a view of symmetric edges (src, dst, down)."""

from __future__ import annotations

import zlib

from pyspark.sql import DataFrame

from ..operators.graph import GraphStore
from .by_join import v
from .program import LoopProgram


def to_sql(program: LoopProgram, edges: str = "edges", count: bool = True) -> str:
    """One SELECT: a join for each pattern edge, NOT EXISTS for each absent one."""
    sign = "<" if program.direction == "down" else ">"
    near, far = ("dst", "src") if program.direction == "down" else ("src", "dst")
    where_from: dict[int, str] = {}
    tables, where = [], []
    for i, level in enumerate(program.levels):
        for n, a in enumerate(level.anchors):
            t, half = f"e{a}_{i}", a in level.implied
            s, d = (far, near) if half else ("src", "dst")
            on = [f"{t}.{s} = {where_from[a]}"] if a in where_from else []
            if n:
                on.append(f"{t}.{d} = {where_from[i]}")
            else:
                where_from[i] = f"{t}.{d}"
            if a not in where_from:
                where_from[a] = f"{t}.{s}"
            if half:
                on.append(f"{t}.down = 1")
            if tables:
                tables.append(f"JOIN {edges} {t} ON " + " AND ".join(on))
            else:
                tables.append(f"FROM {edges} {t}")
                where += on
        me = where_from.get(i)
        where += [f"{me} {sign} {where_from[b]}" for b in level.below if b not in level.anchors]
        where += [f"{me} <> {where_from[g]}" for g in level.distinct]
        where += [f"NOT EXISTS (SELECT 1 FROM {edges} x WHERE x.src = {where_from[x]} AND x.dst = {me})" for x in level.excluded]
    head = "SELECT count(*) AS mappings" if count else "SELECT " + ", ".join(f"{where_from[i]} AS {v(i)}" for i in range(program.k))
    return "\n".join([head, *tables, *(["WHERE " + "\n  AND ".join(where)] if where else [])])


def run(store: GraphStore, program: LoopProgram, count: bool = True) -> DataFrame:
    view = f"edges_{zlib.crc32(store.path.encode()):08x}"
    store.edges.createOrReplaceTempView(view)
    return store.spark.sql(to_sql(program, view, count))
