"""SQL table functions over the compiler (an extension).

``register(spark)`` makes ``pattern_orders('a-b,b-c,c-a')`` and
``connected_patterns(4)`` callable from SQL.
"""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


class _PatternOrders:
    def eval(self, text: str):
        from knotwork.functions import cost
        from knotwork.functions.pattern import parse
        from knotwork.functions.symmetry import bounds

        p = parse(text)
        name = lambda o: "".join(chr(97 + x) for x in o)
        for c, o in cost.ranked(p):
            yield name(o), ",".join(f"{chr(97 + u)}>{chr(97 + w)}" for u, w in bounds(p, o, "min")), float(c)


class _ConnectedPatterns:
    def eval(self, k: int):
        from knotwork.functions.pattern import connected_patterns, known_name
        from knotwork.functions.symmetry import multiplicity

        for p in connected_patterns(k):
            yield known_name(p), p.edge_mask, len(p.edges), multiplicity(p)


def register(spark: SparkSession) -> None:
    spark.udtf.register("pattern_orders", udtf(_PatternOrders, returnType="ord: string, bounds: string, cost: double"))
    spark.udtf.register("connected_patterns", udtf(_ConnectedPatterns, returnType="pattern: string, edge_mask: long, edges: int, autos: long"))
