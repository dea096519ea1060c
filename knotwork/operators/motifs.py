"""Counting every connected pattern of k labels.

``count`` compiles all patterns, merges programs that share leading levels into a
trie, and runs the trie: a prefix with several continuations is written once to the
shared folder and read by each. ``count_by_classification`` is the generic
alternative: enumerate connected vertex sets, then look up each one's shape.
"""

from __future__ import annotations

from functools import reduce
from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.pattern import Pattern, canonical, connected_patterns, known_name, pair_bit
from ..plans import by_blocks, by_join, by_kernel, planner
from ..plans.by_join import v
from ..plans.program import LoopProgram, TrieNode, compile_program, merge, near_best
from ..scratch import stored
from ..sources import groups
from .graph import GraphStore, stats_of
from .mine import quotient

COUNTS = "k int, pattern string, edges int, autos long, cnt long"


def _table(spark: SparkSession, programs: list[LoopProgram], rows: DataFrame) -> DataFrame:
    """(slot, mappings) rows to the motif table, zeros included."""
    names = [(i, p.k, known_name(p.pattern), len(p.pattern.edges), _autos(p.pattern), p.multiplicity) for i, p in enumerate(programs)]
    meta = spark.createDataFrame(names, "slot int, k int, pattern string, edges int, autos long, multiplicity long")
    total = rows.groupBy("slot").agg(F.sum("mappings").alias("mappings"))
    out = F.broadcast(meta).join(total, "slot", "left")  # one row a pattern
    return out.select("k", "pattern", "edges", "autos", quotient(F.coalesce("mappings", F.lit(0).cast("long")), "multiplicity").alias("cnt"))


def _autos(p: Pattern) -> int:
    from ..functions.symmetry import multiplicity

    return multiplicity(p)


def count(store: GraphStore, k: int, executor: str | None = None, form: str = "min") -> DataFrame:
    """One row per connected pattern of k labels: k, pattern, edges, autos, cnt."""
    patterns = connected_patterns(k)
    if form != "min":
        programs = [compile_program(p, form=form) for p in patterns]
        return separately(store, programs, executor)
    root, programs = merge([near_best(p) for p in patterns])
    executor = executor or planner.choose_executor(store, programs[0])
    if executor == "kernel":
        return by_kernel_trie(store, root, programs)
    if executor == "join":
        return _table(store.spark, programs, by_join_trie(store, root))
    if executor == "blocks":
        return _table(store.spark, programs, by_blocks.counted_many(store, programs)) if k == 3 else separately(store, programs)
    return separately(store, programs, executor)


def count_merged(classes: DataFrame) -> DataFrame:
    """The motif table of three labels of a graph given by classes of members with equal
    groups. Members of the same heavy groups form few classes, which meet by the product of
    their sizes; the links that only small groups give are few, and triangles with one,
    two or three of them are counted around these. Pairs of neighbours come from the
    degrees. The members' edges are never made."""
    spark = classes.sparkSession
    own, sets, near = groups.split(classes)
    degree = stored(groups.degrees(sets), "degrees")
    triangles = _heavy_triangles(sets, degree) + _light_triangles(own, sets, near)
    both = _both_ways(near)
    far = both.groupBy("c").agg(F.sum("w").alias("far"))
    inner = F.when(F.col("h").isNull(), F.col("w") - 1).otherwise(F.col("degree"))
    each = own.join(degree.select(F.col("c").alias("h"), "degree"), "h", "left").join(far, "c", "left").select(F.col("w").alias("vertices"), (inner + F.coalesce("far", F.lit(0))).alias("degree"))
    paths = stats_of(each).first()["wedges"]
    programs = [compile_program(p) for p in connected_patterns(3)]
    found = [(i, (triangles if len(p.pattern.edges) == 3 else paths - 3 * triangles) * p.multiplicity) for i, p in enumerate(programs)]
    return _table(spark, programs, spark.createDataFrame(found, "slot int, mappings long"))


def _total(df: DataFrame, expression: str) -> int:
    return df.agg(F.expr(f"coalesce(sum({expression}), 0L)")).first()[0]


def _both_ways(near: DataFrame) -> DataFrame:
    """(c, n, h, w): each class beside each other that it is linked to by small groups only."""
    return near.selectExpr("u c", "wu n", "hv h", "wv w").unionByName(near.selectExpr("v c", "wv n", "hu h", "wu w"))


def _weighted(links: DataFrame, sizes: DataFrame, name: str) -> tuple[GraphStore, int]:
    """A stored graph of classes, and its triangles by the product of the classes' sizes."""
    store = GraphStore.build(links, name=name)
    t = store.vertices.join(sizes, "orig").select("id", "w").toArrow()  # one number a class
    weights = np.ones(store.n, np.int64)
    weights[t.column("id").to_numpy()] = t.column("w").to_numpy()
    return store, by_blocks.triangles_of(store, weights).first()["mappings"]


def _heavy_triangles(sets: DataFrame, degree: DataFrame) -> int:
    """Triangles of links by heavy groups. Where most pairs of classes are linked, the pairs
    that are not give them: of three members, those neither all linked nor all apart
    have two that see one link and one gap."""
    sizes = sets.select(F.col("c").alias("orig"), "w")
    n, many, linked = degree.agg(F.expr("coalesce(sum(vertices), 0L)"), F.count("*"), F.expr("coalesce(sum(linked), 0L)")).first()
    dense = 2 * linked > many * (many - 1)
    store, apart = _weighted(groups.links(sets, apart=dense), sizes, "classes")
    if dense:
        return n * (n - 1) * (n - 2) // 6 - _total(degree, f"vertices * degree * ({n}L - 1 - degree)") // 2 - apart
    named = store.vertices.join(sizes, "orig").select("id", "w")
    a, b = named.withColumnsRenamed({"id": "src", "w": "a"}), named.withColumnsRenamed({"id": "dst", "w": "b"})
    two = _total(store.down.join(a, "src").join(b, "dst"), "a * b * (a + b - 2) div 2")
    return apart + two + _total(sizes, "w * (w - 1) div 2 * (w - 2) div 3")


def _light_triangles(own: DataFrame, sets: DataFrame, near: DataFrame) -> int:
    """Triangles with a link that only small groups give: with one, by what both of its ends are linked
    to; with two, by the linked pairs around the end that they share; with three, among these links."""
    alone = _total(own.where("h is null"), "w * (w - 1) div 2 * (w - 2) div 3")
    if near.isEmpty():
        return alone
    _, three = _weighted(near.select("u", "v"), own.select(F.col("c").alias("orig"), "w"), "near")
    pair = _total(near, "if(hu is null, wu * (wu - 1) div 2 * wv, 0L) + if(hv is null, wv * (wv - 1) div 2 * wu, 0L)")
    held = near.where("hu is not null and hv is not null").select(F.least("hu", "hv").alias("u"), F.greatest("hu", "hv").alias("v"), (F.col("wu") * F.col("wv")).alias("n"))
    one = groups.common(sets, stored(held.groupBy("u", "v").agg(F.sum("n").alias("n")), "held")).first()["mappings"]
    around = _both_ways(near).where("h is not null").groupBy("c", F.col("h").alias("u")).agg(F.first("n").alias("n"), F.sum("w").alias("w"))
    two = groups.linked_around(sets, stored(around, "around")).first()["mappings"]
    return alone + three + pair + one + two


def separately(store: GraphStore, programs: list[LoopProgram], executor: str | None = None) -> DataFrame:
    """Every program on its own, without sharing."""
    parts = [planner.counted(store, p, executor or planner.choose_executor(store, p)).withColumn("slot", F.lit(i)) for i, p in enumerate(programs)]
    return _table(store.spark, programs, reduce(DataFrame.unionByName, parts))


def by_join_trie(store: GraphStore, root: TrieNode) -> DataFrame:
    """(slot, mappings) of a merged program with joins."""
    parts: list[DataFrame] = []

    def walk(node: TrieNode, prefix: DataFrame | None) -> None:
        if node.level is not None:
            prefix = by_join.root(store) if node.depth == 0 else by_join.extend(prefix, store, node.level, node.depth)
        for slot in node.done:
            parts.append(prefix.agg(F.count("*").alias("mappings")).withColumn("slot", F.lit(slot)))
        if len(node.children) > 1 and node.depth >= 1:
            prefix = stored(prefix, "prefix")
        for child in node.children:
            walk(child, prefix)

    walk(root, None)
    return reduce(DataFrame.unionByName, parts)


def by_kernel_trie(store: GraphStore, root: TrieNode, programs: list[LoopProgram]) -> DataFrame:
    """The merged program inside one kernel: a task walks the trie from its roots,
    so shared levels are searched once and leaf levels only counted."""
    import pyarrow as pa

    lists = by_kernel.shared(store)
    n = len(programs)

    def run(batches):
        search = by_kernel.Search(*lists.value, programs[0])
        total = np.zeros(n, np.int64)

        def deeper(nodes: list[TrieNode], chosen: list[int]) -> None:
            for node in nodes:  # their own counts are in; go on below them
                found = search.at(node.level, chosen)
                inner = [g for g in node.children if g.children]
                for leaf in node.children:
                    if len(found) and leaf.done:
                        n = search.last(leaf.level, chosen, found)
                        for slot in leaf.done:
                            total[slot] += n
                for x in found.tolist() if inner else ():
                    deeper(inner, [*chosen, x])

        for b in batches:
            for u in b.column(0).to_pylist():
                for top in root.children:
                    deeper(top.children, [u])
        yield pa.RecordBatch.from_pydict({"slot": pa.array(range(n), pa.int32()), "mappings": total})

    return _table(store.spark, programs, by_kernel._roots(store).mapInArrow(run, "slot int, mappings long"))


def shape_lookup(spark: SparkSession, k: int) -> DataFrame:
    """(mask, pattern) of every connected labelled graph of k labels: at most 2^10
    rows for k = 5, the largest this is meant for."""
    if k > 5:
        raise ValueError("classification is for patterns of at most five labels")
    names = {p.edge_mask: known_name(p) for p in connected_patterns(k)}
    rows = []
    for mask in range(1 << (k * (k - 1) // 2)):
        p = Pattern(k, mask)
        if p.connected:
            rows.append((mask, names[canonical(p).edge_mask]))
    return spark.createDataFrame(rows, "mask long, pattern string")


def count_by_classification(store: GraphStore, k: int) -> DataFrame:
    """(pattern, cnt) by enumerating each connected k-set once and looking its shape
    up: the generic method, here as a baseline and an independent check."""
    pairs = store.pairs
    sets = store.vertices.select(F.col("id").alias("v0"))
    for i in range(1, k):
        # Grow each connected set by a neighbour of any member; sort to meet it once.
        member = F.explode(F.array(*[v(j) for j in range(i)])).alias("src")
        grown = sets.select("*", member).join(pairs, "src").where(~F.array_contains(F.array(*[v(j) for j in range(i)]), F.col("dst")))
        ids = F.sort_array(F.array(*[v(j) for j in range(i)], "dst")).alias("ids")
        sets = grown.select(ids).distinct().select(*[F.col("ids")[j].alias(v(j)) for j in range(i + 1)])
    mask = F.lit(0).cast("long")
    for i, j in combinations(range(k), 2):
        flag = pairs.select(F.col("src").alias(v(i)), F.col("dst").alias(v(j)), F.lit(1 << pair_bit(i, j)).cast("long").alias(f"b{i}{j}"))
        sets = sets.join(flag, [v(i), v(j)], "left")
        mask = mask + F.coalesce(f"b{i}{j}", F.lit(0))
    shapes = sets.select(mask.alias("mask")).groupBy("mask").agg(F.count("*").alias("cnt"))
    lookup = shape_lookup(store.spark, k)
    found = shapes.join(F.broadcast(lookup), "mask").groupBy("pattern").agg(F.sum("cnt").alias("cnt"))
    return lookup.select("pattern").distinct().join(found, "pattern", "left").select("pattern", F.coalesce("cnt", F.lit(0)).alias("cnt"))


def rollup(store: GraphStore, ks: tuple[int, ...] = (3, 4)) -> DataFrame:
    """(k, pattern, cnt) with totals: pattern ``all`` a size, k 0 over all sizes (an
    extension)."""
    each = reduce(DataFrame.unionByName, [count(store, k).select("k", "pattern", "cnt") for k in ks])
    out = each.rollup("k", "pattern").agg(F.sum("cnt").alias("cnt"))
    return out.select(F.coalesce("k", F.lit(0)).alias("k"), F.coalesce("pattern", F.lit("all")).alias("pattern"), "cnt")
