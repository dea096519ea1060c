"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Workloads: renumbering, motif counting with engine and baseline, single patterns
with engine and baseline, cliques by hand-pruned edges and by the engine with and
without orientation, order search. Counts of compared methods must agree.
"""

from __future__ import annotations

import json
import os
import sys
import time

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = ROOT + os.pathsep + os.environ.get("PYTHONPATH", "")

from pyspark.sql import SparkSession  # noqa: E402


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench")
        .config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "8g"))
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")

    from knotwork import queries as q
    from knotwork.functions import cost, orders
    from knotwork.functions.pattern import CATALOG, connected_patterns
    from knotwork.operators import baselines, mine, motifs
    from knotwork.operators.graph import GraphStore
    from knotwork.scratch import release
    from knotwork.sources import graphs

    took: dict[str, float] = {}
    counts: dict[str, int] = {}

    def timed(name: str, f, check: str | None = None):
        start = time.perf_counter()
        out = f()
        took[name] = round(time.perf_counter() - start, 4)
        if check is not None:
            if counts.setdefault(check, out) != out:
                raise AssertionError(f"{name}: {out}, expected {counts[check]}")
        return out

    cnt = lambda df: df.first()["cnt"]
    total = lambda df: sum(r["cnt"] for r in df.collect())
    spark.range(1000).selectExpr("sum(id)").collect()
    mine.count(GraphStore.build(graphs.tiny(spark, "tiny_k5")), "triangle", executor="kernel").collect()  # warm-up

    stores = {}
    for g in ("copart_q45", "copart_s2", "doc_lines", "copart_all", "cust_supp"):
        stores[g] = timed(f"renumber_{g}", lambda g=g: GraphStore.build(graphs.from_tables(spark, sf, g), name=g))
    plain = {g: GraphStore.build(graphs.from_tables(spark, sf, g), False, name=g) for g in ("copart_q45", "doc_lines", "copart_all", "cust_supp")}

    for g in ("copart_q45", "copart_s2", "doc_lines", "copart_all"):
        timed(f"motif3_{g}", lambda g=g: total(motifs.count(stores[g], 3)), f"motif3_{g}")
    for g in ("copart_q45", "copart_s2", "doc_lines"):
        timed(f"motif4_{g}", lambda g=g: total(motifs.count(stores[g], 4)), f"motif4_{g}")
    timed("motif5_copart_q45", lambda: total(motifs.count(stores["copart_q45"], 5)), "motif5")
    for k, g in ((3, "copart_q45"), (4, "copart_q45"), (4, "doc_lines")):
        base = [baselines.topological_program(p) for p in connected_patterns(k)]
        timed(f"motif{k}_baseline_{g}", lambda g=g, base=base: total(motifs.separately(plain[g], base, "kernel")), f"motif{k}_{g}")

    for p, g in (("rectangle", "doc_lines"), ("pentagon", "doc_lines"), ("house", "copart_q45"), ("bow_tie", "copart_q45"), ("near_clique_7", "copart_q45")):
        timed(f"{p}_{g}", lambda p=p, g=g: cnt(mine.count(stores[g], p)), f"{p}_{g}")
        timed(f"{p}_baseline_{g}", lambda p=p, g=g: cnt(baselines.topological(plain[g], p)), f"{p}_{g}")
    for k, name in ((3, "triangle"), (4, "clique_4")):
        for g in ("doc_lines", "copart_all"):
            timed(f"{name}_join_{g}", lambda name=name, g=g: cnt(mine.count(stores[g], name, executor="join")), f"{name}_{g}")
            timed(f"{name}_pruned_{g}", lambda k=k, g=g: cnt(baselines.clique_pruned(stores[g], k)), f"{name}_{g}")
    timed("triangle_join_unoriented_copart_all", lambda: cnt(mine.count(plain["copart_all"], "triangle", executor="join")), "triangle_copart_all")
    timed("triangle_join_cust_supp", lambda: cnt(mine.count(stores["cust_supp"], "triangle", executor="join")), "triangle_cust_supp")
    timed("triangle_join_unoriented_cust_supp", lambda: cnt(mine.count(plain["cust_supp"], "triangle", executor="join")), "triangle_cust_supp")

    p = CATALOG["near_clique_7"]
    timed("orders_permutation_near_clique_7", lambda: min(cost.order_cost(p, o, bound_of={}) for o in orders.by_permutation(p)))
    timed("orders_distinct_near_clique_7", lambda: min(cost.order_cost(p, o) for o in orders.distinct(p)))
    timed("compile_motif6", lambda: [cost.choose(x) for x in connected_patterns(6)])
    timed("compile_motif7", lambda: [cost.choose(x) for x in connected_patterns(7)])

    for name in ("graph_emb_knn_edges", "graph_user_chain_edges"):
        timed(name, lambda name=name: q.QUERIES[name](spark, sf).count())
    release(spark)
    print(json.dumps({"metric": "total_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(sf.rstrip("/"))}))


if __name__ == "__main__":
    main()
