"""Driver-side results as DataFrames: groups, bounds, orders, costs, patterns."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import cost, orders
from ..functions.pattern import CATALOG, Pattern, connected_patterns, known_name, parse
from ..functions.symmetry import automorphisms, bounds
from ..plans import by_join
from ..plans.program import compile_program
from .graph import GraphStore
from .measures import explosion, order_text


def _p(pattern: str | Pattern) -> Pattern:
    return parse(pattern) if isinstance(pattern, str) else pattern


def automorphism_report(spark: SparkSession, pattern: str | Pattern) -> DataFrame:
    """(perm): each automorphism as the images of a, b, c, ..."""
    return spark.createDataFrame([(order_text(g),) for g in automorphisms(_p(pattern))], "perm string")


def bounds_report(spark: SparkSession, pattern: str | Pattern, order: str, form: str) -> DataFrame:
    """(upper, lower) label pairs."""
    o = tuple(ord(c) - 97 for c in order)
    return spark.createDataFrame([(chr(97 + u), chr(97 + w)) for u, w in bounds(_p(pattern), o, form)], "upper string, lower string")


def automorphisms_in(store: GraphStore, pattern: str | Pattern) -> DataFrame:
    """(v0..v(k-1)) in original ids: each instance of a graph under each automorphism."""
    p = _p(pattern)
    met = by_join.mappings(store, compile_program(p, tuple(range(p.k))))
    names = store.vertices.select("id", "orig")
    for i in range(p.k):
        met = met.join(names.withColumnsRenamed({"id": by_join.v(i), "orig": f"o{i}"}), by_join.v(i)).drop(by_join.v(i))
    moved = F.array(*[F.struct(*[F.col(f"o{g[i]}").alias(by_join.v(i)) for i in range(p.k)]) for g in automorphisms(p)])
    return met.select(F.explode(moved).alias("m")).select("m.*")


def bounds_in(store: GraphStore, pattern: str | Pattern, order: str, form: str) -> DataFrame:
    """(upper, lower, high, low): each bound of an order, with the stored ids that it
    compares in each mapping met in a graph."""
    p, o = _p(pattern), tuple(ord(c) - 97 for c in order)
    met = by_join.mappings(store, compile_program(p, o, form))
    at = {x: by_join.v(i) for i, x in enumerate(o)}
    held = F.array(*[F.struct(F.lit(chr(97 + u)).alias("upper"), F.lit(chr(97 + w)).alias("lower"), F.col(at[u]).alias("high"), F.col(at[w]).alias("low")) for u, w in bounds(p, o, form)])
    return met.select(F.explode(held).alias("b")).select("b.*")


def orders_report(spark: SparkSession, pattern: str | Pattern, model: cost.ModelGraph | None = None) -> DataFrame:
    """(rnk, ord, cost, bounds) of the distinct orders, cheapest first."""
    p = _p(pattern)
    rows = [
        (i + 1, order_text(o), float(round(c, 2)), ",".join(f"{chr(97 + u)}>{chr(97 + w)}" for u, w in sorted(bounds(p, o, "min"), key=lambda x: o.index(x[1]))))
        for i, (c, o) in enumerate(cost.ranked(p, model or cost.ModelGraph()))
    ]
    return spark.createDataFrame(rows, "rnk int, ord string, cost double, bounds string")


def census(spark: SparkSession, patterns: list[Pattern] | None = None) -> DataFrame:
    """(pattern, k, autos, valid, distinct_orders, best, worst)."""
    rows = []
    for p in patterns or list(CATALOG.values()):
        c, r = orders.census(p), cost.ranked(p)
        rows.append((p.name or str(p), c["k"], c["autos"], c["valid"], c["distinct"], float(round(r[0][0], 2)), float(round(r[-1][0], 2))))
    return spark.createDataFrame(rows, "pattern string, k int, autos long, valid long, distinct_orders long, best double, worst double")


def census_many(spark: SparkSession, k: int) -> DataFrame:
    """(edge_mask, autos, valid, distinct_orders) of all connected patterns of k
    labels, searched on the executors (853 patterns for k = 7)."""
    rows = spark.createDataFrame([(p.edge_mask,) for p in connected_patterns(k)], "edge_mask long")

    def run(frames):
        for f in frames:
            found = [orders.census(Pattern(k, int(m))) for m in f["edge_mask"]]
            f["autos"], f["valid"], f["distinct_orders"] = [[c[x] for c in found] for x in ("autos", "valid", "distinct")]
            yield f

    tasks = spark.sparkContext.defaultParallelism
    return rows.repartition(tasks).mapInPandas(run, "edge_mask long, autos long, valid long, distinct_orders long")


def pattern_totals(spark: SparkSession, most: int = 7) -> DataFrame:
    """(k, patterns): connected patterns up to isomorphism."""
    return spark.createDataFrame([(k, len(connected_patterns(k))) for k in range(3, most + 1)], "k int, patterns long")


def order_totals(spark: SparkSession, most: int = 5) -> DataFrame:
    """(k, valid, distinct_orders) summed over all patterns of k labels."""
    every = {k: [orders.census(p) for p in connected_patterns(k)] for k in range(3, most + 1)}
    rows = [(k, sum(c["valid"] for c in cs), sum(c["distinct"] for c in cs)) for k, cs in every.items()]
    return spark.createDataFrame(rows, "k int, valid long, distinct_orders long")


def cost_report(spark: SparkSession, pattern: str | Pattern, order: str | None = None, early_exit: bool = False) -> DataFrame:
    """(loop, label, anchors, excluded, length, chance, cost) of an order."""
    p = _p(pattern)
    o = tuple(ord(c) - 97 for c in order) if order else cost.choose(p)
    rows = [(x["loop"], chr(97 + x["label"]), x["anchors"], x["excluded"], round(x["length"], 6), round(x["chance"], 9), round(x["cost"], 4)) for x in cost.loop_costs(p, o, early_exit=early_exit)]
    return spark.createDataFrame(rows, "loop int, label string, anchors int, excluded int, length double, chance double, cost double")


def program_report(spark: SparkSession, pattern: str | Pattern, form: str = "min") -> DataFrame:
    """(loop, text): the compiled program, one line a loop."""
    program = compile_program(_p(pattern), form=form)
    return spark.createDataFrame(list(enumerate(program.explain().split("\n"))), "loop int, text string")


def explosion_report(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(explosion(), "family string, k int, multiplicity long")


def named(k: int) -> list[str]:
    return [known_name(p) for p in connected_patterns(k)]
