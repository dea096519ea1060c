"""Connected components of a link table by alternating star contraction.

Links are (a, b) pairs of long ids. A round hangs every vertex's larger neighbours
on its smallest neighbour, then every vertex and its smaller neighbours on the
smallest of them; the number of rounds grows with the logarithm of a component's
size. Each round is written to the shared folder; the driver sees two sums a round.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored


def _state(links: DataFrame) -> tuple:
    return tuple(links.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, component): the smallest id each linked vertex can reach. Vertices
    without links are not listed."""
    pairs = links.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    pairs = stored(pairs.distinct(), "links")
    before = _state(pairs)
    for _ in range(most_rounds):
        if not before[0]:
            break
        # Large star: every larger neighbour v of u hangs on the smallest in u's star.
        both = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
        # Stored, so that adaptive execution can split the centre of a large star.
        low = stored(both.groupBy("a").agg(F.min("b").alias("m")).withColumn("m", F.least("m", "a")), "lowest")
        large = both.where("b > a").join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        # Small star: u and its smaller neighbours hang on the smallest of them.
        small = large.groupBy("a").agg(F.min("b").alias("m"))
        hung = large.join(small, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b")
        pairs = stored(hung.unionByName(small.select("a", F.col("m").alias("b"))).distinct(), "links")
        after = _state(pairs)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError("star contraction did not settle")
    roots = pairs.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct()
    return pairs.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(roots)


def lowest(groups: DataFrame, names: DataFrame) -> DataFrame:
    """(rep, component_id): the smallest ``low`` of each component, from (rep,
    component) and the representatives' (rep, low)."""
    groups = stored(groups.join(names.select("rep", "low"), "rep"), "groups")
    low = groups.groupBy("component").agg(F.min("low").alias("component_id"))
    return groups.join(low, "component").select("rep", "component_id")
