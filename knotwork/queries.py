"""The registered graph queries and their oracles.

Each query builds (or reuses, within a session) the stored form of a stand-in graph
and runs one method, variant, baseline, measure or operator on it.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracle
from .functions.pattern import CATALOG, connected_patterns, parse
from .operators import baselines, graph, measures, mine, motifs, reports, setops
from .operators.graph import GraphStore
from .plans import by_sql, planner
from .plans.program import compile_program
from .scratch import new_path
from .sources import graphs, groups
from .streaming import incremental

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
_stores: dict[tuple, GraphStore] = {}


def store(spark: SparkSession, sf_dir: str, name: str, orient: bool = True) -> GraphStore:
    """The stored graph of this session: renumbered once, then opened."""
    key = (spark.sparkContext.applicationId, sf_dir, name, orient)
    if key not in _stores:
        _stores[key] = GraphStore.build(graphs.from_tables(spark, sf_dir, name), orient, name=name)
    return _stores[key]


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql is not None:
        ORACLES[name] = sql


def on(g: str, f: Callable[[GraphStore], DataFrame], orient: bool = True) -> Query:
    return lambda spark, sf: f(store(spark, sf, g, orient))


GRAPHS = ("copart_q45", "copart_s2", "copart_all", "doc_lines", "cust_supp", "cust_nation", "user_chain", "emb_knn")

# The line graph is defined over lines of 2 to 50 documents, so links by more frequent lines
# are no part of it; ``doc_lines_all`` has every line, ``graph_doc_lines_all_members`` the
# same links without their squares.

# Graph building, degrees, renumbering, adjacency.
def _line_classes(s: SparkSession, sf: str) -> DataFrame:
    return groups.merged(graphs.line_groups(s.read.parquet(f"{sf}/documents.parquet")))


def _stats(s: SparkSession, sf: str, g: str) -> DataFrame:
    if g == "doc_lines_all":  # by degrees alone: its edges need not be made
        return graph.stats_of(groups.degrees(_line_classes(s, sf)))
    return graph.stats(graph.normalise(graphs.from_tables(s, sf, g)))


for _g in (*GRAPHS, "doc_lines_all"):
    add(
        f"graph_{_g}_edges",
        lambda s, sf, g=_g: graphs.from_tables(s, sf, g).select(F.least("u", "v").cast("long").alias("u"), F.greatest("u", "v").cast("long").alias("v")),
        f"WITH {oracle.GRAPHS[_g]} SELECT u, v FROM e0",
    )
    add(
        f"graph_{_g}_stats", lambda s, sf, g=_g: _stats(s, sf, g).drop("avg_degree"),
        f"{oracle.graph(_g)} SELECT count(*) AS n, CAST(sum(degree) // 2 AS BIGINT) AS m, max(degree) AS max_degree, CAST(sum(degree * (degree - 1) // 2) AS BIGINT) AS wedges FROM d",
    )
add(
    "graph_doc_lines_all_members", lambda s, sf: graphs.line_members(s.read.parquet(f"{sf}/documents.parquet")),
    "WITH p AS (SELECT DISTINCT doc_id, md5(line) AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 20 AND doc_id IS NOT NULL) SELECT doc_id, line FROM p WHERE line IN (SELECT line FROM p GROUP BY line HAVING count(*) >= 2)",
)
for _g in ("copart_q45", "doc_lines", "cust_supp", "user_chain"):
    add(
        f"graph_{_g}_renumbered", on(_g, lambda st: st.vertices),
        f"{oracle.graph(_g)} SELECT row_number() OVER (ORDER BY degree DESC, x) - 1 AS id, x AS orig, degree FROM d",
    )
    add(f"graph_{_g}_degrees", lambda s, sf, g=_g: graph.degree_histogram(graph.normalise(graphs.from_tables(s, sf, g))), f"{oracle.graph(_g)} SELECT degree, count(*) AS vertices FROM d GROUP BY degree")
add(
    "graph_doc_lines_adjacency",
    on("doc_lines", lambda st: graph.adjacency(st.pairs).select("src", "block", "lo", "hi", F.size("nbrs").cast("long").alias("n"), F.array_join(F.transform("nbrs", lambda x: x.cast("string")), ",").alias("nbrs"))),
    f"{oracle.graph('doc_lines')}, r AS (SELECT x, row_number() OVER (ORDER BY degree DESC, x) - 1 AS id FROM d), q AS (SELECT a.id AS src, b.id AS dst FROM e JOIN r a ON a.x = e.u JOIN r b ON b.x = e.v) SELECT src, CAST(0 AS INTEGER) AS block, min(dst) AS lo, max(dst) AS hi, count(*) AS n, string_agg(CAST(dst AS VARCHAR), ',' ORDER BY dst) AS nbrs FROM q GROUP BY src",
)
_ranked = "r AS (SELECT x, row_number() OVER (ORDER BY degree DESC, x) - 1 AS id FROM d), q AS (SELECT a.id AS src, b.id AS dst FROM e JOIN r a ON a.x = e.u JOIN r b ON b.x = e.v)"
for _g in ("cust_supp", "cust_nation", "doc_lines"):
    add(
        f"degree_report_{_g}", on(_g, graph.degree_report),
        f"{oracle.graph(_g)}, {_ranked}, c AS (SELECT count(*) AS n, count(*) FILTER (dst < src) AS m FROM q GROUP BY src) SELECT max(n) AS max_degree, max(m) AS max_down_degree, CAST(sum(n * n) AS BIGINT) AS sum_degree2, CAST(sum(m * m) AS BIGINT) AS sum_down_degree2 FROM c",
    )

# Single patterns: the default engine, by the planner's executor, and the baseline. The
# prism and the near-clique of seven labels are left out on the clique-rich line graph.
_single = {
    "copart_q45": ("triangle", "rectangle", "tailed_triangle", "diamond", "clique_4", "pentagon", "house", "bow_tie", "hexagon", "prism", "near_clique_7"),
    "copart_s2": ("rectangle", "pentagon", "house", "bow_tie", "prism", "near_clique_7"),
    "doc_lines": ("triangle", "rectangle", "pentagon", "house", "bow_tie"),
    "emb_knn": ("rectangle", "pentagon", "house", "bow_tie", "prism", "near_clique_7", "joined_triangles"),
}
for _g, _names in _single.items():
    for _p in _names:
        add(f"count_{_p}_{_g}", on(_g, lambda st, p=_p: mine.count(st, p).select("cnt")), oracle.count(_g, _p))
for _p, _g in (("triangle", "cust_supp"), ("triangle", "user_chain"), ("star_3", "copart_q45"), ("path_4", "copart_s2")):
    add(f"count_{_p}_{_g}", on(_g, lambda st, p=_p: mine.count(st, p, executor="join").select("cnt")), oracle.count(_g, _p))
# Here the joins would shuffle every two-edge path of a dense graph, or every star of a hub.
for _p, _g in (("triangle", "copart_all"), ("wedge", "cust_nation")):
    add(f"count_{_p}_{_g}", on(_g, lambda st, p=_p: mine.count(st, p).select("cnt")), oracle.count(_g, _p))

# Listings in original ids.
for _p, _g in (("triangle", "copart_q45"), ("rectangle", "doc_lines"), ("tailed_triangle", "copart_q45"), ("clique_4", "copart_q45"), ("pentagon", "doc_lines"), ("bow_tie", "copart_q45"), ("rectangle", "emb_knn")):
    add(f"match_{_p}_{_g}", on(_g, lambda st, p=_p: mine.instances(st, p, executor="join")), oracle.listing(_g, _p))

# The four executors, bound forms, directions, orientation.
for _e in ("join", "array", "kernel", "sql"):
    add(f"executor_{_e}_rectangle_doc_lines", on("doc_lines", lambda st, e=_e: mine.count(st, "rectangle", executor=e).select("cnt")), oracle.count("doc_lines", "rectangle"))
    add(f"executor_{_e}_list_house_copart_q45", on("copart_q45", lambda st, e=_e: mine.instances(st, "house", executor=e)), oracle.listing("copart_q45", "house"))
for _f in ("none", "root", "full", "min"):
    add(f"bounds_{_f}_rectangle_copart_s2", on("copart_s2", lambda st, f=_f: mine.count(st, "rectangle", executor="join", bounds=f).select("cnt")), oracle.count("copart_s2", "rectangle"))
add("bounds_upward_rectangle_copart_s2", on("copart_s2", lambda st: mine.count(st, "rectangle", executor="join", direction="up").select("cnt"), orient=False), oracle.count("copart_s2", "rectangle"))
add("unoriented_pentagon_doc_lines", on("doc_lines", lambda st: mine.count(st, "pentagon").select("cnt"), orient=False), oracle.count("doc_lines", "pentagon"))
add("fitted_order_bow_tie_copart_s2", on("copart_s2", lambda st: mine.count(st, "bow_tie", fitted=True).select("cnt")), oracle.count("copart_s2", "bow_tie"))
for _p in ("wedge", "rectangle", "pentagon"):
    add(f"edge_induced_{_p}_copart_q45", on("copart_q45", lambda st, p=_p: mine.count(st, p, executor="join", induced=False).select("cnt")), oracle.count("copart_q45", _p, induced=False))


def _waves(st: GraphStore, pattern: str, n: int) -> DataFrame:
    program = compile_program(parse(pattern))
    return reduce(DataFrame.unionByName, planner.waves(st, program, n)).agg(F.sum("mappings").alias("cnt"))


add("waves_tailed_triangle_copart_s2", on("copart_s2", lambda st: _waves(st, "tailed_triangle", 3)), oracle.count("copart_s2", "tailed_triangle"))

# Participation and set operations.
add("per_vertex_triangle_doc_lines", on("doc_lines", lambda st: mine.per_vertex(st, "triangle")), oracle.per_vertex("doc_lines", "triangle"))
add("per_vertex_rectangle_copart_s2", on("copart_s2", lambda st: mine.per_vertex(st, "rectangle", executor="join")), oracle.per_vertex("copart_s2", "rectangle"))
add("top_vertices_triangle_doc_lines", on("doc_lines", lambda st: mine.top_vertices(st, "triangle", 10)), f"{oracle.per_vertex('doc_lines', 'triangle')} ORDER BY cnt DESC, vertex LIMIT 10")
add(
    "common_neighbours_copart_q45",
    lambda s, sf: (lambda e: setops.common_neighbours(e, e.where("src < dst").select(F.col("src").alias("u"), F.col("dst").alias("v"))))(graph.normalise(graphs.from_tables(s, sf, "copart_q45"))),
    f"{oracle.graph('copart_q45')} SELECT p.u, p.v, (SELECT count(*) FROM e a JOIN e b ON a.v = b.v WHERE a.u = p.u AND b.u = p.v) AS common FROM e0 p",
)


def _set_operations(st: GraphStore) -> DataFrame:
    lists = graph.adjacency(st.pairs, 1 << 62).select("src", "nbrs")
    pairs = st.down.join(lists.withColumnsRenamed({"nbrs": "a"}), "src").join(lists.withColumnsRenamed({"src": "dst", "nbrs": "b"}), "dst")
    return pairs.select("src", "dst", F.size(setops.intersect("a", "b")).alias("both"), F.size(setops.subtract("a", "b")).alias("only_first"), F.size(setops.bounded("a", F.col("dst"))).alias("below"))


add(
    "set_operations_copart_q45", on("copart_q45", _set_operations),
    f"{oracle.graph('copart_q45')}, {_ranked}, n AS (SELECT src, list(dst) AS l FROM q GROUP BY src) SELECT q.src, q.dst, CAST(len(list_intersect(a.l, b.l)) AS INTEGER) AS both, CAST(len(a.l) - len(list_intersect(a.l, b.l)) AS INTEGER) AS only_first, CAST(len(list_filter(a.l, lambda x: x < q.dst)) AS INTEGER) AS below FROM q JOIN n a ON a.src = q.src JOIN n b ON b.src = q.dst WHERE q.dst < q.src",
)

# Motif counting.
for _g in GRAPHS:
    add(f"motif3_{_g}", on(_g, lambda st: motifs.count(st, 3)), oracle.motif3(_g))
add("motif3_doc_lines_all", lambda s, sf: motifs.count_merged(_line_classes(s, sf)), oracle.motif3("doc_lines_all"))
for _g in ("copart_q45", "copart_s2", "doc_lines", "emb_knn"):
    add(f"motif4_{_g}", on(_g, lambda st: motifs.count(st, 4)), oracle.motifs(_g, 4))
for _g in ("copart_q45", "copart_s2"):
    add(f"motif5_{_g}", on(_g, lambda st: motifs.count(st, 5)), oracle.motifs(_g, 5))
add("motif4_by_joins_copart_q45", on("copart_q45", lambda st: motifs.count(st, 4, executor="join")), oracle.motifs("copart_q45", 4))
add("motif4_by_arrays_copart_q45", on("copart_q45", lambda st: motifs.count(st, 4, executor="array")), oracle.motifs("copart_q45", 4))
add("motif4_topological_copart_q45", on("copart_q45", lambda st: motifs.separately(st, [baselines.topological_program(p) for p in connected_patterns(4)], "kernel")), oracle.motifs("copart_q45", 4))
for _k, _g in ((3, "doc_lines"), (4, "copart_q45"), (4, "emb_knn")):
    add(f"classified_motif{_k}_{_g}", on(_g, lambda st, k=_k: motifs.count_by_classification(st, k)), f"SELECT pattern, cnt FROM ({oracle.motifs(_g, _k)})")
add("motif_rollup_copart_q45", on("copart_q45", motifs.rollup), f"SELECT CAST(coalesce(k, 0) AS INTEGER) AS k, coalesce(pattern, 'all') AS pattern, cnt FROM (SELECT k, pattern, CAST(sum(cnt) AS BIGINT) AS cnt FROM (({oracle.motifs('copart_q45', 3)}) UNION ALL ({oracle.motifs('copart_q45', 4)})) GROUP BY ROLLUP (k, pattern))")

# Baselines, ablations, redundancy.
SIX = ("rectangle", "pentagon", "near_clique_7", "house", "bow_tie", "prism")
CELLS = {_g: tuple(p for p in SIX if p in _names) for _g, _names in _single.items()}
for _g, _names in CELLS.items():
    for _p in _names:
        add(f"topological_{_p}_{_g}", on(_g, lambda st, p=_p: baselines.topological(st, p).select("cnt"), orient=False), oracle.count(_g, _p))
for _k in (3, 4, 5):
    add(f"clique_pruned_{_k}_copart_q45", on("copart_q45", lambda st, k=_k: baselines.clique_pruned(st, k)), oracle.count("copart_q45", f"clique_{_k}" if _k > 3 else "triangle"))
CLIQUE_GRAPHS = ("copart_all", "doc_lines", "user_chain", "emb_knn")
for _g in CLIQUE_GRAPHS:
    for _k, _p in ((3, "triangle"), (4, "clique_4")):
        add(f"clique_default_{_k}_{_g}", on(_g, lambda st, k=_k: baselines.clique_default(st, k).select("cnt"), orient=False), oracle.cliques(_g, _k))
        add(f"clique_pruned_{_k}_{_g}", on(_g, lambda st, k=_k: baselines.clique_pruned(st, k)), oracle.cliques(_g, _k))
        add(f"clique_unoriented_{_k}_{_g}", on(_g, lambda st, p=_p: mine.count(st, p).select("cnt"), orient=False), oracle.cliques(_g, _k))
        if f"count_{_p}_{_g}" not in QUERIES:
            add(f"count_{_p}_{_g}", on(_g, lambda st, p=_p: mine.count(st, p).select("cnt")), oracle.cliques(_g, _k))
add("worst_order_tailed_triangle_copart_s2", on("copart_s2", lambda st: baselines.worst_order(st, "tailed_triangle", "join").select("cnt")), oracle.count("copart_s2", "tailed_triangle"))
for _p, _g in (("rectangle", "copart_s2"), ("pentagon", "emb_knn"), ("clique_4", "copart_q45")):
    add(f"ablation_{_p}_{_g}", lambda s, sf, p=_p, g=_g: baselines.ablation(store(s, sf, g), store(s, sf, g, False), p), oracle.grid(_g, _p, root=True))
for _p, _g in (("rectangle", "copart_s2"), ("pentagon", "copart_s2"), ("triangle", "doc_lines")):
    add(f"redundancy_{_p}_{_g}", on(_g, lambda st, p=_p: measures.redundancy(st, p)), oracle.redundancy(_g, _p, root=True))

# Work. The oracles give the orders as letters and derive bounds and counts themselves.
_orders = {"triangle_first": (0, 1, 2, 3), "wedge_first": (3, 2, 0, 1)}
for _n, _o in _orders.items():
    add(
        f"work_tailed_triangle_{_n}_doc_lines", on("doc_lines", lambda st, o=_o: measures.work(st, compile_program(CATALOG["tailed_triangle"], o))),
        f"{oracle.ranked('doc_lines')} {oracle.work_rows(oracle.levels(CATALOG['tailed_triangle'], _o))}",
    )


def _touched(g: str, pattern: str, order: tuple[int, ...], oriented: bool = True, bounded: bool = True) -> tuple[Query, str]:
    plan = oracle.levels(CATALOG[pattern], order)
    query = on(g, lambda st: measures.touched(st, compile_program(CATALOG[pattern], order), bounded), oriented)
    return query, f"{oracle.ranked(g, oriented)} SELECT (SELECT count(*) FROM {oracle.prefixes(plan, len(plan))}) AS mappings, {oracle.touched_sum(plan, bounded)} AS touched"


add("touched_rectangle_bounded_doc_lines", *_touched("doc_lines", "rectangle", (0, 1, 2, 3)))
add("touched_rectangle_whole_doc_lines", *_touched("doc_lines", "rectangle", (0, 1, 2, 3), bounded=False))
# The star argument: a pattern that starts at the centre of a star, and one that no star holds.
for _n, _oriented in (("oriented", True), ("plain", False)):
    add(f"touched_star_3_star_{_n}", *_touched("cust_nation", "star_3", (0, 1, 2, 3), _oriented))
    add(f"touched_triangle_star_{_n}", *_touched("cust_nation", "triangle", (0, 1, 2), _oriented))
add("count_star_3_cust_nation", on("cust_nation", lambda st: mine.count(st, "star_3").select("cnt")), oracle.count("cust_nation", "star_3"))
for _p in ("tailed_triangle", "diamond", "pentagon", "bow_tie", "house"):
    _sql = oracle.order_work("copart_q45", _p) if _p != "house" else None  # thirty orders: minutes in SQL, so a test compares them
    add(f"order_work_{_p}_copart_q45", on("copart_q45", lambda st, p=_p: measures.order_work(st, p).withColumn("predicted", F.round("predicted", 2))), _sql)
for _p, _g in (("rectangle", "copart_s2"), ("clique_4", "doc_lines"), ("clique_5", "copart_q45")):
    _each = " UNION ALL ".join(
        f"SELECT '{f}' AS bounds, CAST(sum(checks) AS BIGINT) AS checks, max_by(kept, level) AS kept FROM ({oracle.work_rows(oracle.levels(CATALOG[_p], tuple(range(CATALOG[_p].k)), f), half=False)})" for f in ("full", "min")
    )
    add(f"bound_checks_{_p}_{_g}", on(_g, lambda st, p=_p: measures.bound_checks(st, p)), f"{oracle.ranked(_g)} {_each}")
# Orders that the engine chooses, as letters.
GAIN = {"triangle": "abc", "clique_4": "abcd", "rectangle": "abcd", "pentagon": "abecd", "bow_tie": "abcde", "star_3": "abcd"}
_gains = {"copart_s2": tuple(GAIN)[:5], "doc_lines": tuple(GAIN)[:5], "cust_supp": ("triangle",), "cust_nation": ("triangle", "star_3")}
for _g, _names in _gains.items():
    add(
        f"orientation_gain_{_g}", lambda s, sf, g=_g, names=_names: measures.orientation_gain(store(s, sf, g), store(s, sf, g, False), list(names)),
        oracle.gain_rows(_g, {x: GAIN[x] for x in _names}),
    )

# The cost model and the order searches.
for _p in ("bow_tie", "tailed_triangle", "house"):
    add(
        f"model_fit_{_p}_copart_q45", on("copart_q45", lambda st, p=_p: measures.r_squared(measures.order_work(st, p).withColumn("predicted", F.round("predicted", 2)))),
        oracle.order_fit("copart_q45", _p) if _p != "house" else None,
    )
add("model_fit_house_uniform", lambda s, sf: measures.r_squared(measures.order_work(_uniform(s), "house")))
FITTED = [p.name for p in CATALOG.values() if p.k in (4, 5) and p.name not in ("clique_4", "clique_5")]  # cliques have one order
add("model_time_fit_copart_q45", on("copart_q45", lambda st: measures.model_fit(st, FITTED)))
add("model_time_fit_uniform", lambda s, sf: measures.model_fit(_uniform(s), FITTED))
# Orders are priced on the part graph of the given table.
_model = lambda s, sf: measures.fitted_model(graphs.from_tables(s, sf, "copart_q45"))
add("compile_times_catalog", lambda s, sf: measures.compile_times(s, [p for p in CATALOG.values() if p.k <= 6], model=_model(s, sf)))
add("compile_times_motif_sets", lambda s, sf: measures.compile_sets(s, 6, model=_model(s, sf)))
add("compile_times_motif_sets_7", lambda s, sf: measures.compile_sets(s, 7, model=_model(s, sf)).where("k = 7"))
add("compile_times_dearest_7", lambda s, sf: measures.compile_times(s, measures.dearest(7), model=_model(s, sf)))
add("compile_times_near_clique_7", lambda s, sf: measures.compile_times(s, [CATALOG["near_clique_7"]], model=_model(s, sf)))
_searched = [(k, a, n, {"permutation": valid, "prefix": valid, "distinct": kinds, "pruned": n}[a]) for (k, n), (_, valid, kinds) in zip(oracle.TOTALS, oracle.ORDER_TOTALS + oracle.MORE_TOTALS) for a in measures.ALGORITHMS]
add(
    "compile_orders_motif_sets", lambda s, sf: measures.compile_sets(s, 6, model=_model(s, sf)).drop("ms"),
    oracle.values(_searched, {"k": "INTEGER", "algorithm": "VARCHAR", "patterns": "BIGINT", "orders": "BIGINT"}),
)
add(
    "compile_orders_catalog", lambda s, sf: measures.compile_times(s, [CATALOG[r[0]] for r in oracle.CENSUS], model=_model(s, sf)).select("pattern", "algorithm", "orders"),
    oracle.values([(r[0], a, {"permutation": r[3], "prefix": r[3], "distinct": r[4], "pruned": 1}[a]) for r in oracle.CENSUS for a in measures.ALGORITHMS], {"pattern": "VARCHAR", "algorithm": "VARCHAR", "orders": "BIGINT"}),
)

# Experiments in time. The counts beside them are checked by the queries above.
for _g, _names in CELLS.items():
    add(f"speedup_{_g}", lambda s, sf, g=_g, names=_names: measures.speedups(store(s, sf, g), store(s, sf, g, False), list(names), repeats=1, timeout_s=60.0))
for _g in CLIQUE_GRAPHS:
    add(f"clique_ways_{_g}", lambda s, sf, g=_g: measures.clique_ways(store(s, sf, g), store(s, sf, g, False), 3, repeats=1, timeout_s=60.0).unionByName(measures.clique_ways(store(s, sf, g), store(s, sf, g, False), 4, repeats=1, timeout_s=60.0)))
for _g, _names in (("copart_s2", ("rectangle", "pentagon", "bow_tie")), ("doc_lines", ("rectangle", "pentagon", "bow_tie")), ("cust_supp", ("triangle",))):
    add(f"orientation_time_{_g}", lambda s, sf, g=_g, names=_names: measures.orientation_times(store(s, sf, g), store(s, sf, g, False), list(names), repeats=1, timeout_s=60.0))
for _g in GRAPHS:
    add(f"reindex_time_{_g}", lambda s, sf, g=_g: measures.reindex_time(graphs.from_tables(s, sf, g), g))
for _g in ("copart_q45", "doc_lines", "cust_supp"):
    add(
        f"reindex_sizes_{_g}", lambda s, sf, g=_g: measures.reindex_time(graphs.from_tables(s, sf, g), g).drop("seconds"),
        f"{oracle.graph(_g)} SELECT '{_g}' AS graph, f.form, b.numbered_by, (SELECT count(*) FROM d) AS n, (SELECT count(*) FROM e0) AS m FROM (VALUES ('offline'), ('on demand')) f(form), (VALUES ('degree'), ('id')) b(numbered_by)",
    )


def _uniform(spark: SparkSession) -> GraphStore:
    key = (spark.sparkContext.applicationId, "", "uniform", True)
    if key not in _stores:
        _stores[key] = GraphStore.build(graphs.uniform(spark, 1000, 0.005), name="uniform")
    return _stores[key]


# Automorphisms and bounds of the rectangles of the line graph and the near-cliques of the part graph;
# bounds read the table itself, also where the session has stored its graph before.
add("automorphisms_rectangle", on("doc_lines", lambda st: reports.automorphisms_in(st, "rectangle")), oracle.automorphisms_in("doc_lines", "rectangle"))
for _f, _p, _g, _held in (("full", "rectangle", "doc_lines", "ab ac ad bc"), ("min", "rectangle", "doc_lines", "ab bc ad"), ("root", "rectangle", "doc_lines", "ab"), ("min", "near_clique_7", "copart_q45", "ab bc cd de fg")):
    add(
        f"bounds_{_f}_{_p}", lambda s, sf, g=_g, f=_f, p=_p: reports.bounds_in(GraphStore.build(graphs.from_tables(s, sf, g), name=g), p, "abcdefg"[: CATALOG[p].k], f),
        oracle.bounds_in(_g, _p, [tuple(x) for x in _held.split()]),
    )

# Driver-side results.
add("orders_census", lambda s, sf: reports.census(s, [CATALOG[r[0]] for r in oracle.CENSUS]), oracle.values(oracle.CENSUS, oracle.CENSUS_COLUMNS))
add("orders_census_motif6", lambda s, sf: reports.census_many(s, 6).agg(F.count("*").alias("patterns"), F.sum(F.col("valid") - F.col("autos") * F.col("distinct_orders")).alias("unexplained")), oracle.values([(112, 0)], {"patterns": "BIGINT", "unexplained": "BIGINT"}))
add("pattern_totals", lambda s, sf: reports.pattern_totals(s), oracle.values(oracle.TOTALS, {"k": "INTEGER", "patterns": "BIGINT"}))
add("order_totals", lambda s, sf: reports.order_totals(s), oracle.values(oracle.ORDER_TOTALS, {"k": "INTEGER", "valid": "BIGINT", "distinct_orders": "BIGINT"}))
add("orders_tailed_triangle", lambda s, sf: reports.orders_report(s, "tailed_triangle"), oracle.orders_table("tailed_triangle"))
add("cost_report_rectangle", lambda s, sf: reports.cost_report(s, "rectangle", "abcd").select("loop", F.round("cost", 2).alias("cost")), oracle.values([(0, 1000.0), (1, 5000.0), (2, 12437.5), (3, 103.13)], {"loop": "INTEGER", "cost": "DOUBLE"}))
add("program_rectangle", lambda s, sf: reports.program_report(s, "rectangle"), oracle.values([(0, "A in all vertices"), (1, "B in N(A), B < A"), (2, "C in N(A) - N(B), C < B (no edge)"), (3, "D in N(B) & N(C) - N(A), D < A (no edge)")], {"loop": "BIGINT", "text": "VARCHAR"}))
add("redundancy_explosion", lambda s, sf: reports.explosion_report(s), oracle.values([(f, k, n) for k in range(3, 8) for f, n in (("cycle", 2 * k), ("clique", {3: 6, 4: 24, 5: 120, 6: 720, 7: 5040}[k]), ("near_clique", 2 * {1: 1, 2: 2, 3: 6, 4: 24, 5: 120}[k - 2]))], {"family": "VARCHAR", "k": "INTEGER", "multiplicity": "BIGINT"}))

# Worked examples on literal graphs.
_tiny = [
    ("tiny_rect", "rectangle", 1), ("tiny_tailed", "tailed_triangle", 1), ("tiny_k7m", "near_clique_7", 1), ("tiny_k5", "clique_4", 5), ("tiny_k6", "clique_5", 6),
    ("tiny_k5", "diamond", 0), ("tiny_star", "star_3", 120), ("tiny_bowtie", "bow_tie", 1), ("twin_guard", "rectangle", 0), ("tiny_empty", "triangle", 0),
]
add(
    "worked_examples",
    lambda s, sf: reduce(DataFrame.unionByName, [mine.count(store(s, sf, g), p, executor="join").select(F.lit(g).alias("graph"), F.lit(p).alias("pattern"), "cnt") for g, p, _ in _tiny]),
    oracle.values(_tiny, {"graph": "VARCHAR", "pattern": "VARCHAR", "cnt": "BIGINT"}),
)

# Executors agree row by row; SQL text of a program; co-occurrence in time windows.
add(
    "executor_difference_copart_q45",
    on("copart_q45", lambda st: mine.instances(st, "bow_tie", executor="join").exceptAll(mine.instances(st, "bow_tie", executor="kernel")).agg(F.count("*").alias("cnt"))),
    oracle.values([(0,)], {"cnt": "BIGINT"}),
)
add("sql_text_rectangle", lambda s, sf: s.createDataFrame([(by_sql.to_sql(compile_program(CATALOG["rectangle"])),)], "text string"))
add(
    "graph_user_window_edges", lambda s, sf: graphs.user_window(s.read.parquet(f"{sf}/events.parquet"), "1 hour"),
    "WITH p AS (SELECT DISTINCT date_trunc('hour', ts) AS o, user_id AS x FROM events) SELECT DISTINCT a.x AS u, b.x AS v FROM p a JOIN p b ON a.o = b.o AND a.x < b.x",
)


def _motif_cube(s: SparkSession, sf: str) -> DataFrame:
    each = [motifs.count(store(s, sf, g), 3).select(F.lit(g).alias("graph"), "pattern", "cnt") for g in ("copart_q45", "doc_lines", "emb_knn")]
    out = reduce(DataFrame.unionByName, each).cube("graph", "pattern").agg(F.sum("cnt").alias("cnt"))
    return out.select(F.coalesce("graph", F.lit("all")).alias("graph"), F.coalesce("pattern", F.lit("all")).alias("pattern"), "cnt")


_cube = " UNION ALL ".join(f"SELECT '{g}' AS graph, pattern, cnt FROM ({oracle.motif3(g)})" for g in ("copart_q45", "doc_lines", "emb_knn"))
add("motif_cube", _motif_cube, f"SELECT coalesce(graph, 'all') AS graph, coalesce(pattern, 'all') AS pattern, CAST(n AS BIGINT) AS cnt FROM (SELECT graph, pattern, sum(cnt) AS n FROM ({_cube}) GROUP BY CUBE (graph, pattern))")

# Streaming.
add(
    "streaming_triangles_user_day",
    lambda s, sf: incremental.run_events(s, f"{sf}/events.parquet", new_path(s, "stream"), "triangle"),
    oracle.count("user_day", "triangle"),
)


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Motif-3 and motif-4 counts of the part graph, with its own merged program."""
    st = store(spark, sf_dir, "copart_q45")
    return motifs.count(st, 3).unionByName(motifs.count(st, 4))


assert QUERIES.keys() >= ORACLES.keys()
