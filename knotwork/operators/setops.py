"""Set operations on sorted neighbour arrays and common neighbours of pairs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def intersect(a: Column | str, b: Column | str) -> Column:
    return F.array_intersect(a, b)


def subtract(a: Column | str, b: Column | str) -> Column:
    return F.array_except(a, b)


def reached(a: Column, limit: Column, inclusive: bool = False) -> Column:
    """How many ids of a sorted array lie below ``limit`` (or at it), by binary search:
    as many steps as the array's length has bits, whatever lies beyond the bound."""
    turns = F.sequence(F.lit(1), F.greatest(F.ceil(F.log2(F.size(a) + 1)).cast("int"), F.lit(1)))
    pair = lambda low, high: F.struct(low.alias("low"), high.alias("high"))

    def halve(s: Column, _: Column) -> Column:
        mid = F.call_function("div", s["low"] + s["high"], F.lit(2)).cast("int")
        at = F.get(a, mid)
        return F.when(s["low"] >= s["high"], s).when((at <= limit) if inclusive else (at < limit), pair(mid + 1, s["high"])).otherwise(pair(s["low"], mid))

    return F.aggregate(turns, pair(F.lit(0), F.size(a)), halve, lambda s: s["low"])


def bounded(a: Column | str, limit: Column, direction: str = "down") -> Column:
    """The part of a sorted array within a bound: a slice found by binary search, so ids
    beyond the bound are neither tested nor copied."""
    a = F.col(a) if isinstance(a, str) else a
    if direction == "down":
        return F.slice(a, F.lit(1), reached(a, limit))
    return F.slice(a, reached(a, limit, True) + 1, F.size(a))


def common_neighbours(edges: DataFrame, pairs: DataFrame) -> DataFrame:
    """(u, v, common) for pairs of vertices, zero included, over symmetric edges
    (src, dst): a join on one end and a semi join on the other, never two arrays."""
    via = pairs.join(edges.select(F.col("src").alias("u"), F.col("dst").alias("w")), "u")
    met = via.join(edges.select(F.col("src").alias("v"), F.col("dst").alias("w")), ["v", "w"], "left_semi")
    n = met.groupBy("u", "v").agg(F.count("*").alias("common"))
    return pairs.join(n, ["u", "v"], "left").select("u", "v", F.coalesce("common", F.lit(0)).alias("common"))
