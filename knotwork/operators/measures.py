"""Cost and accuracy measures: time, redundancy, work, compile time, model fit.

Counts are exact, so accuracy is equality; the statistical measure is the fit of the
cost model. Work counters (candidates, kept, bound checks, list elements) are the
portable stand-ins for time.
"""

from __future__ import annotations

import statistics
import threading
import time
import uuid
from collections.abc import Callable
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import cost, orders
from ..functions.pattern import Pattern, clique, connected_patterns, known_name, parse
from ..functions.symmetry import Perm, multiplicity
from ..plans import by_blocks, by_join, by_kernel, planner
from ..plans.by_join import v
from ..plans.program import LoopProgram, compile_program
from ..scratch import drop_shuffles, stored
from .baselines import clique_pruned, topological, topological_order
from .graph import GraphStore, normalise, stats
from .mine import count, quotient


class TimedOut(Exception):
    """A run was stopped at its limit."""


def within(spark: SparkSession, run: Callable[[], object], timeout_s: float | None) -> object:
    """The result of ``run``; its Spark jobs are cancelled at the limit."""
    if timeout_s is None:
        return run()
    sc, group, late = spark.sparkContext, f"measure-{uuid.uuid4().hex}", threading.Event()

    def stop() -> None:
        while not over.is_set():  # a job that starts after the limit is stopped as well
            late.set()
            sc.cancelJobGroup(group)
            over.wait(0.5)

    over = threading.Event()
    timer = threading.Timer(timeout_s, stop)
    sc.setJobGroup(group, "measured run", interruptOnCancel=True)
    timer.start()
    try:
        return run()
    except Exception as e:
        if late.is_set():
            raise TimedOut(f"stopped after {timeout_s} s") from e
        raise
    finally:
        over.set()
        timer.cancel()
        for key in ("spark.jobGroup.id", "spark.job.description", "spark.job.interruptOnCancel"):
            sc.setLocalProperty(key, None)


def timed(make: Callable[[], DataFrame]) -> tuple[float, int | None]:
    """Seconds to plan and compute a one-row result, and its ``cnt`` or ``mappings``."""
    start = time.perf_counter()
    row = make().first()
    return time.perf_counter() - start, next((row[c] for c in ("cnt", "mappings") if c in row), None)


def repeated(spark: SparkSession, make: Callable[[], DataFrame], repeats: int = 3, timeout_s: float | None = 259_200.0) -> dict:
    """Median and spread of repeated runs, and their count. A run beyond the limit is
    stopped and marked ``timed_out``; it has no count and no later repeats."""
    seconds, found = [], None
    for _ in range(repeats):
        try:
            took, found = within(spark, lambda: timed(make), timeout_s)
        except TimedOut:
            return {"seconds": float(timeout_s), "spread": 0.0, "timed_out": True, "count": None}
        finally:
            drop_shuffles(spark)  # outside of the time
        seconds.append(took)
    mid = statistics.median(seconds)
    return {"seconds": mid, "spread": (max(seconds) - min(seconds)) / mid if mid else 0.0, "timed_out": False, "count": found}


RUNS = "pattern string, method string, seconds double, spread double, timed_out boolean, cnt long, gain double"


def compared(spark: SparkSession, runs: dict[str, dict[str, Callable[[], DataFrame]]], repeats: int = 3, timeout_s: float | None = 259_200.0) -> DataFrame:
    """(pattern, method, seconds, spread, timed_out, cnt, gain) of named runs; ``gain``
    is the first method's time over the method's own, null after a timeout."""
    rows = []
    for pattern, methods in runs.items():
        base = None
        for method, make in methods.items():
            r = repeated(spark, make, repeats, timeout_s)
            base = r if base is None else base
            gain = base["seconds"] / r["seconds"] if r["seconds"] and not (base["timed_out"] or r["timed_out"]) else None
            rows.append((pattern, method, float(r["seconds"]), float(r["spread"]), r["timed_out"], r["count"], gain))
    return spark.createDataFrame(rows, RUNS)


def speedups(oriented: GraphStore, plain: GraphStore, patterns: list[str], executor: str | None = None, **how) -> DataFrame:
    """The topological baseline against the engine, pattern by pattern."""
    return compared(oriented.spark, {
        x: {"baseline": lambda x=x: topological(plain, x, executor), "engine": lambda x=x: count(oriented, x, executor=executor)} for x in patterns
    }, **how)


def clique_ways(oriented: GraphStore, plain: GraphStore, k: int, executor: str | None = None, **how) -> DataFrame:
    """Cliques of k labels by the default baseline, by hand-pruned edges, and by the
    engine without and with orientation."""
    p = clique(k)
    return compared(oriented.spark, {p.name: {
        "baseline": lambda: topological(plain, p, executor), "pruned": lambda: clique_pruned(oriented, k),
        "engine_plain": lambda: count(plain, p, executor=executor), "engine": lambda: count(oriented, p, executor=executor),
    }}, **how)


def orientation_times(oriented: GraphStore, plain: GraphStore, patterns: list[str], executor: str | None = None, **how) -> DataFrame:
    """The engine without and with degree renumbering, pattern by pattern."""
    return compared(oriented.spark, {
        x: {"plain": lambda x=x: count(plain, x, executor=executor), "oriented": lambda x=x: count(oriented, x, executor=executor)} for x in patterns
    }, **how)


def redundancy(store: GraphStore, pattern: str | Pattern, executor: str | None = None) -> DataFrame:
    """(bounds, mappings, cnt, factor): mappings met per instance of each form."""
    p = parse(pattern) if isinstance(pattern, str) else pattern
    rows = []
    for form in ("none", "root", "full", "min"):
        program = compile_program(p, order=topological_order(p) if form == "root" else None, form=form)
        met = planner.counted(store, program, executor or planner.choose_executor(store, program))
        rows.append(met.select(F.lit(form).alias("bounds"), "mappings", quotient("mappings", program.multiplicity).alias("cnt"), F.lit(program.multiplicity).cast("long").alias("factor")))
    return reduce(DataFrame.unionByName, rows)


def work(store: GraphStore, program: LoopProgram, scan_half: bool = True) -> DataFrame:
    """(level, candidates, kept, checks): per level the rows its first anchor gives,
    the rows that pass everything, and the bound comparisons made."""
    prefix = by_join.root(store)

    def row(i: int, df: DataFrame, column: str, checks: int = 0) -> DataFrame:
        n = F.count("*")
        return df.agg(
            F.lit(i).alias("level"), (n if column == "candidates" else F.lit(0).cast("long")).alias("candidates"),
            (n if column == "kept" else F.lit(0).cast("long")).alias("kept"), (n * checks if column == "candidates" else F.lit(0).cast("long")).alias("checks"),
        )

    rows = [row(0, prefix, "candidates"), row(0, prefix, "kept")]
    for i in range(1, program.k):
        level = program.levels[i]
        first = next((a for a in level.anchors if a in level.implied), level.anchors[0])
        edges = by_join._half(store, scan_half and first in level.implied, program.direction, v(first), v(i))
        rows.append(row(i, prefix.join(edges, v(first)), "candidates", len(level.below)))
        prefix = stored(by_join.extend(prefix, store, level, i, program.direction, scan_half), "work")
        rows.append(row(i, prefix, "kept"))
    every = reduce(DataFrame.unionByName, rows)
    return every.groupBy("level").agg(*[F.sum(c).alias(c) for c in ("candidates", "kept", "checks")])


def touched(store: GraphStore, program: LoopProgram, early_exit: bool = True) -> DataFrame:
    """One row: mappings, touched: neighbour-list elements the nested loops read."""
    return counters(store, [program], early_exit).select("mappings", "touched")


def counters(store: GraphStore, programs: list[LoopProgram], early_exit: bool = True) -> DataFrame:
    """(slot, mappings, touched) of several programs; beyond the kernel's limit those of
    three labels run in blocks."""
    if 2 * store.m > by_kernel.LIMIT and all(p.k == 3 and by_blocks.fits(store, p) for p in programs):
        return by_blocks.counted_many(store, programs, early_exit, touch=True)
    return by_kernel.counted_many(store, programs, early_exit, at_once=True).drop("seconds")


def order_work(store: GraphStore, pattern: str | Pattern, model: cost.ModelGraph | None = None) -> DataFrame:
    """(ord, predicted, touched, mappings) for every distinct order of a pattern."""
    p = parse(pattern) if isinstance(pattern, str) else pattern
    g = model or cost.ModelGraph()
    kinds = orders.distinct(p)
    found = counters(store, [compile_program(p, o) for o in kinds])
    meta = store.spark.createDataFrame([(i, order_text(o), float(cost.order_cost(p, o, g))) for i, o in enumerate(kinds)], "slot int, ord string, predicted double")
    return F.broadcast(meta).join(found, "slot").select("ord", "predicted", "touched", "mappings")


def order_times(store: GraphStore, pattern: str | Pattern, model: cost.ModelGraph | None = None) -> DataFrame:
    """(ord, predicted, seconds, mappings) for every distinct order of a pattern: the
    kernel's nested loops run every order on its own, in one pass over the roots, and
    ``seconds`` is the processor time that all tasks spent on it."""
    p = parse(pattern) if isinstance(pattern, str) else pattern
    g = model or cost.ModelGraph()
    kinds = orders.distinct(p)
    found = by_kernel.counted_many(store, [compile_program(p, o) for o in kinds])
    meta = store.spark.createDataFrame([(i, order_text(o), float(cost.order_cost(p, o, g))) for i, o in enumerate(kinds)], "slot int, ord string, predicted double")
    return F.broadcast(meta).join(found, "slot").select("ord", "predicted", "seconds", "mappings")


def model_fit(store: GraphStore, patterns: list[str], model: cost.ModelGraph | None = None) -> DataFrame:
    """(pattern, n, r2, r2_log, low, high): predicted cost against time over all orders
    of each pattern, with the 95 % interval of r2_log."""
    rows = reduce(DataFrame.unionByName, [order_times(store, x, model).withColumn("pattern", F.lit(x)) for x in patterns])
    rows = stored(rows, "orders")
    interval = F.pandas_udf(r2_interval, "array<double>")
    spread = rows.groupBy("pattern").agg(interval(F.log("predicted"), F.log(F.greatest("seconds", F.lit(1e-9)))).alias("i"))
    return r_squared(rows, y="seconds", by="pattern").join(spread, "pattern").select("pattern", "n", "r2", "r2_log", F.col("i")[0].alias("low"), F.col("i")[1].alias("high"))


def r2_interval(x: pd.Series, y: pd.Series) -> list:
    """The 95 % interval of the squared correlation of two columns (an extension), by
    the usual normal approximation of its inverse hyperbolic tangent."""
    n = len(x)
    if n < 4 or x.std() == 0 or y.std() == 0:
        return [None, None]
    z, half = np.arctanh(min(abs(np.corrcoef(x, y)[0, 1]), 1 - 1e-12)), 1.959964 / np.sqrt(n - 3)
    return [float(np.tanh(max(0.0, z - half)) ** 2), float(np.tanh(z + half) ** 2)]


def bound_checks(store: GraphStore, pattern: str | Pattern) -> DataFrame:
    """(bounds, checks, kept): comparisons made with all bounds and with one a label,
    over the joins' levels, and the instances that remain."""
    p = parse(pattern) if isinstance(pattern, str) else pattern
    rows = []
    for form in ("full", "min"):
        program = compile_program(p, form=form)
        w = work(store, program, scan_half=False)
        rows.append(w.agg(F.lit(form).alias("bounds"), F.sum("checks").alias("checks"), F.max_by("kept", "level").alias("kept")))
    return reduce(DataFrame.unionByName, rows)


def orientation_gain(oriented: GraphStore, plain: GraphStore, patterns: list[str]) -> DataFrame:
    """(pattern, oriented, bounded_scan, mappings, touched): list elements that the
    nested loops read with and without degree renumbering and the bounded scan."""
    rows = []
    for store in (plain, oriented):
        for scan in (False, True):
            found = counters(store, [compile_program(parse(x)) for x in patterns], scan)
            meta = store.spark.createDataFrame(list(enumerate(patterns)), "slot int, pattern string")
            rows.append(F.broadcast(meta).join(found, "slot").select("pattern", F.lit(store.oriented).alias("oriented"), F.lit(scan).alias("bounded_scan"), "mappings", "touched"))
    return reduce(DataFrame.unionByName, rows)


def r_squared(df: DataFrame, x: str = "predicted", y: str = "touched", by: str | None = None) -> DataFrame:
    """n, r2 of the values and r2_log of their logarithms: one row, or one a group."""
    def corr(a: Column, b: Column) -> Column:  # null where one of them never varies
        return F.try_divide(F.covar_pop(a, b), F.stddev_pop(a) * F.stddev_pop(b))

    a, b = F.col(x).cast("double"), F.col(y).cast("double")
    r, s = corr(a, b), corr(F.log(a), F.log(F.greatest(b, F.lit(1e-9))))
    return df.groupBy(*([by] if by else [])).agg(F.count("*").alias("n"), F.round(r * r, 6).alias("r2"), F.round(s * s, 6).alias("r2_log"))


def dearest(k: int, n: int = 4) -> list[Pattern]:
    """The n connected patterns of k labels with the most valid orders."""
    return sorted(connected_patterns(k), key=lambda p: (-sum(1 for _ in orders.by_prefix(p)), p.edge_mask))[:n]


ALGORITHMS = ("permutation", "prefix", "distinct", "pruned")


def fitted_model(raw: DataFrame) -> cost.ModelGraph:
    """The model of a raw (u, v) table: its size, density and clustering."""
    edges = stored(normalise(raw), "pairs")
    whole, up = stats(edges).first(), edges.where("src < dst")
    paths = up.join(up.select(F.col("src").alias("dst"), F.col("dst").alias("third")), "dst")
    triangles = paths.join(up.withColumnRenamed("dst", "third"), ["src", "third"], "left_semi").count()
    return cost.ModelGraph.from_stats(whole["n"], whole["m"], triangles, whole["wedges"])


def compiled_by(p: Pattern, name: str, model: cost.ModelGraph = cost.ModelGraph()) -> tuple[int, float, float]:
    """(orders priced, best cost, ms) of one pattern by one algorithm: all valid
    permutations, connected prefixes, one order of each class, or the same cut off at
    the best cost so far. The first two price without bounds."""
    start = time.perf_counter()
    if name == "pruned":
        found, best = [cost.choose.__wrapped__(p, model)], cost.order_cost(p, cost.choose.__wrapped__(p, model), model)
    elif name == "distinct":
        found = orders.distinct(p)
        best = min(cost.order_cost(p, o, model) for o in found)
    else:
        found = list(orders.by_permutation(p) if name == "permutation" else orders.by_prefix(p))
        best = min(cost.order_cost(p, o, model, bound_of={}) for o in found)
    return len(found), float(best), 1000 * (time.perf_counter() - start)


def compile_times(spark: SparkSession, patterns: list[Pattern], algorithms: tuple[str, ...] = ALGORITHMS, model: cost.ModelGraph = cost.ModelGraph()) -> DataFrame:
    """(pattern, k, algorithm, orders, best_cost, ms): order search and pricing by
    algorithm, on the driver."""
    rows = [(known_name(p), p.k, name, *compiled_by(p, name, model)) for p in patterns for name in algorithms]
    return spark.createDataFrame(rows, "pattern string, k int, algorithm string, orders long, best_cost double, ms double")


def reindex_time(raw: DataFrame, name: str = "") -> DataFrame:
    """(graph, form, numbered_by, seconds, n, m): seconds to renumber a graph by degree
    and by id, offline into a store and on demand within the query. A later
    ``GraphStore.open`` costs none of it."""
    rows = []
    for form, make in (("offline", GraphStore.build), ("on demand", GraphStore.on_demand)):
        for by in ("degree", "id"):
            st = make(raw, by == "degree", name=name)
            rows.append((name, form, by, st.seconds, st.n, st.m))
            st.drop()
    return raw.sparkSession.createDataFrame(rows, "graph string, form string, numbered_by string, seconds double, n long, m long")


def explosion(ks: range = range(3, 8)) -> list[tuple[str, int, int]]:
    """(family, k, multiplicity): how over-counting grows with the pattern."""
    from ..functions.pattern import clique, cycle, near_clique

    return [(f, k, multiplicity(make(k))) for k in ks for f, make in (("cycle", cycle), ("clique", clique), ("near_clique", near_clique))]


def compile_sets(spark: SparkSession, most: int = 6, algorithms: tuple[str, ...] = ALGORITHMS, model: cost.ModelGraph = cost.ModelGraph()) -> DataFrame:
    """(k, algorithm, patterns, orders, ms): whole motif sets by algorithm. Patterns are
    compiled on the executors, one at a time; ``ms`` is their time in sum."""
    rows = [(k, i, p.edge_mask, a) for k in range(3, most + 1) for i, p in enumerate(connected_patterns(k)) for a in algorithms]
    todo = spark.createDataFrame(rows, "k int, i int, edge_mask long, algorithm string")

    def run(frames):
        for f in frames:
            found = [compiled_by(Pattern(int(k), int(m)), a, model) for k, m, a in zip(f["k"], f["edge_mask"], f["algorithm"], strict=True)]
            yield pd.DataFrame({"k": f["k"], "algorithm": f["algorithm"], "orders": [x[0] for x in found], "ms": [x[2] for x in found]})

    tasks = 4 * spark.sparkContext.defaultParallelism
    each = todo.repartition(tasks, F.xxhash64("k", "i")).mapInPandas(run, "k int, algorithm string, orders long, ms double")
    return each.groupBy("k", "algorithm").agg(F.count("*").alias("patterns"), F.sum("orders").alias("orders"), F.sum("ms").alias("ms"))


def order_text(order: Perm) -> str:
    return "".join(chr(97 + x) for x in order)
