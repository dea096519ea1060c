"""Graphs, executors, motifs, baselines, measures and streams on small inputs."""

import os

import duckdb
import pytest
from pyspark.sql import functions as F

from knotwork import oracle, queries
from knotwork.functions.pattern import CATALOG, connected_patterns
from knotwork.functions import orders
from knotwork.operators import baselines, graph, measures, mine, motifs, setops
from knotwork.operators.graph import GraphStore
from knotwork.plans import by_join, planner
from knotwork.plans.program import compile_program
from knotwork.sources import graphs
from knotwork.streaming.incremental import Counter

# Induced counts on the part graph of sf0.001.
GOLDEN = {"triangle": 26, "wedge": 283, "rectangle": 3, "tailed_triangle": 115, "diamond": 0, "clique_4": 1, "pentagon": 1, "house": 4, "bow_tie": 6, "hexagon": 2, "prism": 0}


def one(df, column="cnt"):
    return df.first()[column]


@pytest.fixture(scope="module")
def part(spark, sf):
    return queries.store(spark, sf, "copart_q45")


@pytest.fixture(scope="module")
def db(sf):
    c = duckdb.connect()
    for t in "customer orders lineitem events documents embeddings".split():
        c.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


def test_golden_counts(part):
    assert {p: one(mine.count(part, p, executor="kernel")) for p in GOLDEN} == GOLDEN


@pytest.mark.parametrize("executor", ["join", "array", "kernel", "sql"])
def test_executors_agree(part, executor):
    for p in ("triangle", "rectangle", "house"):
        assert one(mine.count(part, p, executor=executor)) == GOLDEN[p]
    rows = {tuple(r) for r in mine.instances(part, "bow_tie", executor=executor).collect()}
    assert len(rows) == GOLDEN["bow_tie"] and all(len(set(r)) == 5 and list(r) == sorted(r) for r in rows)


@pytest.mark.parametrize("form", ["none", "root", "full", "min"])
def test_bound_forms_and_directions(spark, sf, part, form):
    plain = queries.store(spark, sf, "copart_q45", False)
    for p in ("wedge", "rectangle", "diamond"):
        for store in (part, plain):
            for direction in ("down", "up"):
                for executor in ("join", "kernel"):
                    assert one(mine.count(store, p, executor=executor, bounds=form, direction=direction)) == GOLDEN[p]


def test_every_distinct_order_counts_the_same(part):
    for p in ("tailed_triangle", "bow_tie"):
        assert {one(mine.count(part, p, executor="kernel", order=o)) for o in orders.distinct(CATALOG[p])} == {GOLDEN[p]}


def test_unbounded_mappings_are_multiples(part):
    rows = {r["bounds"]: (r["mappings"], r["factor"]) for r in measures.redundancy(part, "rectangle").collect()}
    assert rows == {"none": (24, 8), "root": (12, 4), "full": (3, 1), "min": (3, 1)}


def test_worked_rectangle(spark):
    st = GraphStore.build(graphs.tiny(spark, "tiny_rect"), orient=False)
    program = compile_program(CATALOG["rectangle"], (0, 1, 2, 3))
    names = {r["id"]: r["orig"] for r in st.vertices.collect()}
    assert [[names[x] for x in r] for r in by_join.mappings(st, program).collect()] == [[8, 7, 2, 3]] or [[names[x] for x in r] for r in by_join.mappings(st, program).collect()] == [[8, 2, 7, 3]]
    assert by_join.mappings(st, compile_program(CATALOG["rectangle"], form="none")).count() == 8


def test_near_clique_planted(spark):
    st = GraphStore.build(graphs.tiny(spark, "tiny_k7m"))
    assert one(mine.count(st, "near_clique_7", executor="kernel")) == 1
    assert one(mine.count(st, "near_clique_7", executor="kernel", bounds="none"), "mappings") == 240
    assert one(baselines.topological(st, "near_clique_7", "kernel"), "mappings") == 120


def test_dirty_and_empty_input(spark):
    raw = spark.createDataFrame([(1, 1), (1, 2), (2, 1), (1, 2), (None, 3), (4, None), (2, 3), (3, 1)], "u long, v long")
    st = GraphStore.build(raw)
    assert (st.n, st.m) == (3, 3) and one(mine.count(st, "triangle", executor="join")) == 1
    empty = GraphStore.build(graphs.tiny(spark, "tiny_empty"))
    for e in ("join", "array", "kernel", "sql"):
        assert one(mine.count(empty, "triangle", executor=e)) == 0
    assert {r["cnt"] for r in motifs.count(empty, 3).collect()} == {0}
    assert graph.stats(empty.pairs).first()["m"] == 0


def test_renumbering(spark, sf, db, part):
    want = db.sql(queries.ORACLES["graph_copart_q45_renumbered"]).fetchall()
    assert sorted(map(tuple, part.vertices.collect())) == sorted(want)
    assert part.edges.where("down = 1").count() == part.m == part.edges.where("down = 0").count()
    star = GraphStore.build(graphs.tiny(spark, "tiny_star"))
    assert graph.degree_report(star).first()["max_down_degree"] == 1


def test_adjacency_blocks_cover_lists(part):
    small = graph.adjacency(part.pairs, block=3)
    whole = {r["src"]: r["nbrs"] for r in graph.adjacency(part.pairs).collect()}
    joined = {}
    for r in small.orderBy("src", "block").collect():
        assert r["lo"] == r["nbrs"][0] and r["hi"] == r["nbrs"][-1]
        joined.setdefault(r["src"], []).extend(r["nbrs"])
    assert joined == whole and all(v == sorted(v) for v in whole.values())


def test_bounded_scan_touches_less_and_hubs_shrink(spark, sf):
    oriented, plain = queries.store(spark, sf, "cust_nation"), queries.store(spark, sf, "cust_nation", False)
    p = compile_program(CATALOG["triangle"])
    with_, without = one(measures.touched(oriented, p), "touched"), one(measures.touched(oriented, p, False), "touched")
    assert with_ < without and with_ <= one(measures.touched(plain, p), "touched")


@pytest.mark.parametrize("k", [3, 4])
def test_motifs_by_all_ways(spark, sf, part, k):
    want = {r["pattern"]: r["cnt"] for r in motifs.count(part, k).collect()}
    assert len(want) == len(connected_patterns(k))
    assert want == {r["pattern"]: r["cnt"] for r in motifs.count(part, k, executor="join").collect()}
    assert want == {r["pattern"]: r["cnt"] for r in motifs.count_by_classification(part, k).collect()}
    assert want == {r["pattern"]: r["cnt"] for r in motifs.count(part, k, form="root").collect()}
    assert all(want[p] == GOLDEN[p] for p in want if p in GOLDEN)


def test_wedge_identity(part):
    w = graph.stats(part.pairs).first()["wedges"]
    assert w == GOLDEN["wedge"] + 3 * GOLDEN["triangle"]


def test_cliques_by_pruned_edges(spark):
    st = GraphStore.build(graphs.tiny(spark, "tiny_k6"))
    assert [one(baselines.clique_pruned(st, k)) for k in (3, 4, 5)] == [20, 15, 6]


def test_waves_sum_to_the_count(part):
    program = compile_program(CATALOG["tailed_triangle"])
    assert sum(one(w, "mappings") for w in planner.waves(part, program, 3)) == GOLDEN["tailed_triangle"]


def test_kernel_and_arrays_refuse_large_graphs(part, monkeypatch):
    with pytest.raises(ValueError):
        mine.planner.by_kernel.csr(part, limit=10)
    monkeypatch.setattr(mine.planner.by_array, "DEGREE", 2)
    with pytest.raises(ValueError):
        mine.count(part, "triangle", executor="array")


def test_counts_are_whole_above_the_doubles(spark):
    n = 27_021_597_764_222_979
    df = spark.createDataFrame([(n,)], "mappings long").select(mine.quotient("mappings", 3).alias("a"), mine.quotient(F.col("mappings"), "mappings").alias("b"))
    assert tuple(df.first()) == (9_007_199_254_740_993, 1) and int(n / 3) != n // 3


def test_bounded_arrays_by_binary_search(spark):
    rows = [(sorted(set(a)), x) for a in ([], [3], [1, 4, 9], list(range(0, 70, 3)), list(range(128))) for x in (-1, 0, 3, 4, 5, 64, 127, 500)]
    df = spark.createDataFrame(rows, "a array<long>, x long")
    got = df.select("a", "x", setops.bounded("a", F.col("x")).alias("down"), setops.bounded("a", F.col("x"), "up").alias("up")).collect()
    assert all(r["down"] == [i for i in r["a"] if i < r["x"]] and r["up"] == [i for i in r["a"] if i > r["x"]] for r in got)


def test_a_run_is_stopped_at_its_limit(spark):
    slow = lambda: spark.range(0, 10**12, 1, 8).select(F.max(F.xxhash64("id")).alias("cnt"))
    r = measures.repeated(spark, slow, 3, timeout_s=1.5)
    assert r["timed_out"] and r["count"] is None
    r = measures.repeated(spark, lambda: spark.range(5).select(F.count("*").alias("cnt")), 3, timeout_s=60)
    assert not r["timed_out"] and r["count"] == 5 and r["spread"] >= 0


def test_methods_agree_when_timed(spark, sf, part):
    plain = queries.store(spark, sf, "copart_q45", False)
    rows = measures.speedups(part, plain, ["rectangle", "house"], repeats=1).collect()
    rows += measures.clique_ways(part, plain, 3, repeats=1).collect() + measures.orientation_times(part, plain, ["rectangle"], repeats=1).collect()
    want = {**GOLDEN, "clique_3": GOLDEN["triangle"]}
    assert all(r["cnt"] == want[r["pattern"]] and r["gain"] > 0 and not r["timed_out"] for r in rows) and len(rows) == 10


def test_model_fit_in_time_and_its_interval(part):
    rows = {r["pattern"]: r for r in measures.model_fit(part, ["tailed_triangle", "rectangle"]).collect()}
    t = rows["tailed_triangle"]
    assert t["n"] == 7 and 0 <= t["low"] <= t["r2_log"] <= t["high"] <= 1 and rows["rectangle"]["low"] is None


def test_work_of_every_order_equals_sql(part, db):
    for p in ("house", "bow_tie"):
        want = {r[0]: r[1:] for r in db.sql(oracle.order_work("copart_q45", p)).fetchall()} if p == "bow_tie" else None
        got = {r["ord"]: (round(r["predicted"], 2), r["touched"], r["mappings"]) for r in measures.order_work(part, p).collect()}
        assert want is None or got == want
        assert set(got) == {oracle.letters(o) for o in oracle.classes(CATALOG[p])} and {x[2] for x in got.values()} == {GOLDEN[p]}
        assert all(c == round(oracle.expected_cost(CATALOG[p], tuple(ord(x) - 97 for x in o)), 2) for o, (c, *_) in got.items())


def test_graphs_on_demand_equal_stored_ones(spark, sf, part):
    made = GraphStore.on_demand(graphs.from_tables(spark, sf, "copart_q45"))
    assert (made.n, made.m) == (part.n, part.m) and sorted(made.edges.collect()) == sorted(part.edges.collect())
    assert one(mine.count(made, "rectangle", executor="join")) == one(mine.count(made, "rectangle", executor="kernel")) == GOLDEN["rectangle"]
    assert made.clustering() == (GOLDEN["triangle"], GOLDEN["wedge"] + 3 * GOLDEN["triangle"])
    made.drop()


def test_compilation_is_cached_and_sets_agree(spark, part):
    from knotwork.plans.program import compile_cached

    compile_cached(CATALOG["hexagon"])
    assert compile_cached(CATALOG["hexagon"])[1] == 0.0 and mine.program_for(part, "a-b,b-c,c-d,d-e,e-f,f-a") is compile_cached(CATALOG["hexagon"])[0]
    rows = {(r["k"], r["algorithm"]): (r["patterns"], r["orders"]) for r in measures.compile_sets(spark, 4).collect()}
    assert rows[4, "permutation"] == rows[4, "prefix"] == (6, 94) and rows[4, "distinct"] == (6, 21) and rows[3, "pruned"] == (2, 2)


def test_the_order_with_the_rarer_prefix_meets_fewer_candidates(spark, sf, part):
    """Triangle first where paths outnumber triangles; the other way round on the line
    graph, whose documents form cliques."""
    for st, fewer in ((part, 0), (queries.store(spark, sf, "doc_lines"), 1)):
        rows = [measures.work(st, compile_program(CATALOG["tailed_triangle"], o)).collect() for o in ((0, 1, 2, 3), (3, 2, 0, 1))]
        kept = [next(r["kept"] for r in x if r["level"] == 2) for x in rows]
        met = [sum(r["candidates"] for r in x) for x in rows]
        final = [max(x, key=lambda r: r["level"])["kept"] for x in rows]
        assert final[0] == final[1] and kept[fewer] < kept[1 - fewer] and met[fewer] < met[1 - fewer]


def test_plans_have_no_nested_loop_and_prune_the_oriented_half(part):
    plan = by_join.mappings(part, compile_program(CATALOG["rectangle"]))._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan
    assert "PartitionFilters: [isnotnull(down" in plan and "LeftAnti" in plan


def test_sources_equal_sql(spark, sf, db):
    for g in queries.GRAPHS:
        got = {tuple(r) for r in queries.QUERIES[f"graph_{g}_edges"](spark, sf).collect()}
        assert got == set(db.sql(queries.ORACLES[f"graph_{g}_edges"]).fetchall()), g


def test_uniform_graph(spark):
    e = graphs.uniform(spark, 300, 0.05, seed=4)
    rows = e.collect()
    assert all(0 <= r["u"] < r["v"] < 300 for r in rows) and len(set(rows)) == len(rows)
    assert abs(len(rows) - 0.05 * 300 * 299 / 2) < 300
    assert rows == graphs.uniform(spark, 300, 0.05, seed=4).collect()


def test_edge_list_readers(spark, tmp_path):
    (tmp_path / "a.txt").write_text("# comment\n1 2\n\n 2\t3 \n")
    assert {tuple(r) for r in graphs.read_edge_list(spark, str(tmp_path / "a.txt")).collect()} == {(1, 2), (2, 3)}
    for fmt in ("csv", "json", "parquet"):
        df = spark.createDataFrame([(1, 2), (2, 3)], "u long, v long")
        writer = df.write.option("header", True)
        getattr(writer, fmt)(str(tmp_path / fmt))
        assert {tuple(r) for r in graphs.read_edge_list(spark, str(tmp_path / fmt), fmt).collect()} == {(1, 2), (2, 3)}


def test_store_written_once_opens_again(spark, tmp_path):
    GraphStore.build(graphs.tiny(spark, "tiny_k5"), path=str(tmp_path / "g"))
    st = GraphStore.open(spark, str(tmp_path / "g"))
    assert (st.n, st.m, st.max_degree) == (5, 10, 4) and one(mine.count(st, "clique_4")) == 5


def test_incremental_counts_follow_the_batch(spark, tmp_path):
    edges = [(i, j) for i in range(8) for j in range(i) if (i * 7 + j * 3) % 4 != 0]
    for pattern in ("triangle", "wedge"):
        c = Counter(spark, str(tmp_path / pattern), pattern)
        for batch, at in enumerate(range(0, len(edges), 7)):
            some = spark.createDataFrame(edges[at : at + 7] + edges[:1], "u long, v long")
            c.apply(some, batch)
            if batch == 1:
                c.apply(some, batch)  # a retried batch changes nothing
            now = spark.createDataFrame(edges[: at + 7], "u long, v long")
            assert one(c.count()) == one(mine.count(GraphStore.build(now), pattern, executor="kernel"))


def test_table_functions(spark):
    from knotwork.functions.tables import register

    register(spark)
    assert spark.sql("select count(*) n from connected_patterns(4)").first()["n"] == 6
    assert spark.sql("select * from pattern_orders('a-b,b-c,c-a')").first()["bounds"] == "a>b,b>c"


def test_order_model_fits_work(spark):
    st = GraphStore.build(graphs.uniform(spark, 300, 0.03, seed=2))
    assert one(measures.r_squared(measures.order_work(st, "tailed_triangle")), "r2_log") > 0.5


def test_registry(sf):
    assert set(queries.ORACLES) <= set(queries.QUERIES)
    assert os.path.exists(f"{sf}/lineitem.parquet") and oracle.autos(CATALOG["rectangle"]) == 8


def test_per_vertex_sums(part):
    total = mine.per_vertex(part, "triangle", executor="join").agg(F.sum("cnt")).first()[0]
    assert total == 3 * GOLDEN["triangle"]


def test_lines_of_any_frequency_link_documents(spark):
    line = "a line that very many documents share"
    table = spark.createDataFrame([(i, f"{line}\n{line}\nown line of the document {i}") for i in range(60)] + [(99, "short")], "doc_id long, text string")
    assert graphs.doc_lines(table).count() == 0
    edges = {tuple(r) for r in graphs.doc_lines(table, max_docs=None).collect()}
    assert edges == {(i, j) for j in range(60) for i in range(j)}
    members = graphs.line_members(table).collect()
    assert sorted(r["doc_id"] for r in members) == list(range(60)) and len({r["line"] for r in members}) == 1


def test_blocks_count_as_the_kernel(spark, sf, monkeypatch):
    """Beyond the kernel, prefixes meet in pairs of blocks of lists."""
    from knotwork.plans import by_blocks

    monkeypatch.setattr(by_blocks, "TASK", 2_000), monkeypatch.setattr(by_blocks, "SLICE", 300), monkeypatch.setattr(by_blocks, "PREFIXES", 500)
    for oriented in (True, False):
        st = queries.store(spark, sf, "doc_lines", oriented)
        programs = [compile_program(CATALOG[p], form=f) for p in ("triangle", "wedge", "clique_4", "diamond") for f in ("root", "min")]
        for p in programs:
            assert one(planner.counted(st, p, "blocks"), "mappings") == one(planner.counted(st, p, "kernel"), "mappings")
    want = {r["pattern"]: r["cnt"] for r in motifs.count(st, 3, executor="kernel").collect()}
    assert want == {r["pattern"]: r["cnt"] for r in motifs.count(st, 3, executor="blocks").collect()}
    monkeypatch.setattr(planner, "KERNEL_EDGES", {3: 0, 4: 0})
    for p in ("triangle", "wedge", "clique_4", "star_3"):
        assert planner.choose_executor(st, compile_program(CATALOG[p])) == "blocks"
    assert planner.choose_executor(st, compile_program(CATALOG["rectangle"])) != "blocks"


def test_pruned_cliques_write_no_paths(spark, sf):
    """the hand-pruned cliques meet in blocks, not in a shuffle of all paths."""
    st = queries.store(spark, sf, "doc_lines")
    for k, p in ((3, "triangle"), (4, "clique_4")):
        found = baselines.clique_pruned(st, k)
        assert one(found) == one(mine.count(st, p)) and "SortMergeJoin" not in found._jdf.queryExecution().toString()


@pytest.mark.parametrize("name", ["count_triangle_copart_all", "count_wedge_cust_nation", "count_star_3_cust_nation"])
def test_dense_and_hub_counts_do_not_list(spark, sf, db, name):
    """the last labels are counted, not joined row by row."""
    found = queries.QUERIES[name](spark, sf)
    assert "Join" not in found._jdf.queryExecution().toString() and [tuple(r) for r in found.collect()] == db.sql(queries.ORACLES[name]).fetchall()


def test_touched_at_once_and_in_blocks(spark, sf, monkeypatch):
    """the innermost loop's elements are added up, with equal numbers."""
    from knotwork.plans import by_blocks, by_kernel

    for oriented in (True, False):
        st = queries.store(spark, sf, "doc_lines", oriented)
        three = [compile_program(CATALOG["triangle"]), compile_program(CATALOG["wedge"]), compile_program(CATALOG["triangle"], form="none")]
        four = [compile_program(CATALOG[p], o, form=f) for p in ("star_3", "tailed_triangle", "rectangle") for o in orders.distinct(CATALOG[p])[:3] for f in ("none", "min")]
        for scan in (True, False):
            plain = [tuple(r) for r in by_kernel.counted_many(st, three + four, scan).drop("seconds").orderBy("slot").collect()]
            assert plain == [tuple(r) for r in measures.counters(st, three + four, scan).orderBy("slot").collect()]
            with monkeypatch.context() as m:
                m.setattr(by_kernel, "LIMIT", 0), m.setattr(by_blocks, "TASK", 800)
                assert plain[:3] == [tuple(r) for r in measures.counters(st, three, scan).orderBy("slot").collect()]


def test_window_pairs_meet_without_a_shuffle_of_pairs(spark, sf, db):
    """blocks of members meet; each pair comes once."""
    found = queries.QUERIES["graph_user_window_edges"](spark, sf)
    assert "Join" not in found._jdf.queryExecution().toString()
    assert sorted(map(tuple, found.collect())) == sorted(db.sql(queries.ORACLES["graph_user_window_edges"]).fetchall())
    rows = [(o, x) for x in range(60) for o in range(x % 7, 40, 7 + x % 3)]
    want = sorted({(a, b) for o, a in rows for q, b in rows if o == q and a < b})
    assert sorted(map(tuple, graphs.meeting_pairs(spark.createDataFrame(rows, "o long, x long"), held=40).collect())) == want


@pytest.mark.parametrize("name", ["automorphisms_rectangle", "bounds_full_rectangle", "bounds_min_rectangle", "bounds_root_rectangle", "bounds_min_near_clique_7"])
def test_automorphisms_and_bounds_come_from_a_table(spark, sf, db, name):
    """The instances of a graph of the given tables carry them."""
    found = queries.QUERIES[name](spark, sf)
    assert found.inputFiles()
    assert sorted(map(tuple, found.collect())) == sorted(db.sql(queries.ORACLES[name]).fetchall())


def test_bounds_of_a_planted_near_clique(spark):
    from knotwork.operators import reports

    st = GraphStore.build(graphs.tiny(spark, "tiny_k7m"))
    rows = reports.bounds_in(st, "near_clique_7", "abcdefg", "min").collect()
    assert [r["upper"] + r["lower"] for r in rows] == ["ab", "bc", "cd", "de", "fg"] and all(r["high"] > r["low"] for r in rows)
    assert len({tuple(r) for r in reports.automorphisms_in(st, "near_clique_7").collect()}) == 240


def test_compile_runs_are_priced_on_a_table(spark, sf, part):
    """The model is that of the part graph, read from the given table."""
    from knotwork.functions import cost

    model = measures.fitted_model(graphs.from_tables(spark, sf, "copart_q45"))
    assert model == cost.ModelGraph.from_stats(part.n, part.m, *part.clustering()) and model.closing > 0
    rows = {r["algorithm"]: r for r in measures.compile_times(spark, [CATALOG["house"]], model=model).collect()}
    assert rows["distinct"]["best_cost"] == pytest.approx(min(cost.order_cost(CATALOG["house"], o, model) for o in orders.distinct(CATALOG["house"])))
    assert rows["pruned"]["best_cost"] == pytest.approx(rows["distinct"]["best_cost"]) and rows["prefix"]["orders"] == 60


def _linked_groups(spark):
    """Members with copies (equal groups), a group of all multiples, members alone, and nulls."""
    rows = [(f"g{o}", x) for x in range(90) for o in {x % 5, 5 + x % 3, 10 + x // 30}] + [("all", x) for x in range(0, 90, 4)]
    rows += [("one", 500), ("two", 501), ("two", 502), (None, 7), (None, 8), ("g0", None)]
    plain = [(o, x) for o, x in rows if o is not None and x is not None]
    want = sorted({(a, b) for o, a in plain for q, b in plain if o == q and a < b})
    return spark.createDataFrame(rows + rows[:20], "o string, x long"), want


def test_groups_make_every_pair_once(spark, monkeypatch):
    """classes of equal groups meet in blocks; no pair is shuffled."""
    from knotwork.sources import groups

    members, want = _linked_groups(spark)
    for sizes in ((500_000, 2_000_000, 500_000), (40, 50, 30)):
        for name, value in zip(("HELD", "PAIRS", "BATCH"), sizes):
            monkeypatch.setattr(groups, name, value)
        found = groups.pairs(members)
        assert "Join" not in found._jdf.queryExecution().toString()
        assert sorted(map(tuple, found.collect())) == want
    assert groups.pairs(members.where("false")).count() == 0
    monkeypatch.setattr(groups, "merged", lambda m, most=None, make=groups.merged: make(m, 2))  # parts of classes
    assert sorted(map(tuple, groups.pairs(members).collect())) == want


def test_stats_of_groups_make_no_edge(spark, sf, db, monkeypatch):
    """n, m, largest degree and wedges come from degrees of merged classes."""
    from knotwork.sources import groups

    members, want = _linked_groups(spark)
    edges = spark.createDataFrame(want, "u long, v long")
    for pairs in (2_000_000, 50):
        monkeypatch.setattr(groups, "PAIRS", pairs)
        assert graph.stats_of(groups.degrees(groups.merged(members))).first() == graph.stats(graph.normalise(edges)).first()
    monkeypatch.setattr(graphs, "doc_lines", None)  # the query needs no edge table
    found = queries.QUERIES["graph_doc_lines_all_stats"](spark, sf)
    assert [tuple(r) for r in found.collect()] == db.sql(queries.ORACLES["graph_doc_lines_all_stats"]).fetchall()


def test_paths_of_hubs_are_counted_by_degree(spark, monkeypatch):
    """only the oriented halves of the lists meet, though a hub has most of the edges."""
    from knotwork.plans import by_blocks

    edges = [(0, i) for i in range(1, 400)] + [(i, i + 1) for i in range(1, 60)] + [(1000, i) for i in range(30, 90)]
    sent, deal = [], by_blocks.pairs_of_blocks
    monkeypatch.setattr(by_blocks, "pairs_of_blocks", lambda st, *half: sent.append(half) or deal(st, *half))
    for oriented in (True, False):
        st = GraphStore.build(spark.createDataFrame(edges, "u long, v long"), oriented)
        want = {r["pattern"]: r["cnt"] for r in motifs.count(st, 3, executor="kernel").collect()}
        assert want["triangle"] > 0 and want == {r["pattern"]: r["cnt"] for r in motifs.count(st, 3, executor="blocks").collect()}
        for p in [compile_program(CATALOG["wedge"], o, form=f) for o in orders.distinct(CATALOG["wedge"]) for f in ("none", "root", "full", "min")] + [compile_program(CATALOG["wedge"], induced=False)]:
            assert one(planner.counted(st, p, "blocks"), "mappings") == one(planner.counted(st, p, "kernel"), "mappings")
    assert set(sent) == {(True, True)}
    with monkeypatch.context() as m:  # slices of many roots with short lists look their neighbours up
        m.setattr(by_blocks, "SLICE", 100), m.setattr(by_blocks, "FLAGGED", 10**9)
        assert one(planner.counted(st, compile_program(CATALOG["triangle"]), "blocks"), "mappings") == want["triangle"]


def test_motifs_of_merged_members(spark, sf, db, monkeypatch):
    """classes of members meet, weighted by their sizes; no edge of members is stored."""
    from knotwork.sources import groups

    members, want = _linked_groups(spark)
    st = GraphStore.build(spark.createDataFrame(want, "u long, v long"))
    assert sorted(motifs.count_merged(groups.merged(members)).collect()) == sorted(motifs.count(st, 3, executor="kernel").collect())
    assert {r["cnt"] for r in motifs.count_merged(groups.merged(members.where("false"))).collect()} == {0}
    alone = spark.createDataFrame([("a", x) for x in range(5)], "o string, x long")  # one class, linked inside only
    assert {r["pattern"]: r["cnt"] for r in motifs.count_merged(groups.merged(alone)).collect()} == {"triangle": 10, "wedge": 0}
    built, build = [], GraphStore.build
    monkeypatch.setattr(GraphStore, "build", lambda raw, *a, **k: built.append(raw.count()) or build(raw, *a, **k))
    found = queries.QUERIES["motif3_doc_lines_all"](spark, sf)
    assert sorted(map(tuple, found.collect())) == sorted(db.sql(queries.ORACLES["motif3_doc_lines_all"]).fetchall())
    assert built and built[0] < db.sql(f"select count(*) from ({queries.ORACLES['graph_doc_lines_all_edges']})").fetchall()[0][0]


def test_stream_counts_without_listing(spark, sf, db, monkeypatch):
    """F16: the change of a batch is the difference of two counts; no instance is listed."""
    def listed(*_, **__):
        raise AssertionError("instances are listed")

    monkeypatch.setattr(by_join, "mappings", listed)
    found = queries.QUERIES["streaming_triangles_user_day"](spark, sf)
    assert [tuple(r) for r in found.collect()] == db.sql(queries.ORACLES["streaming_triangles_user_day"]).fetchall()


@pytest.mark.parametrize("name", ["bounds_full_rectangle", "bounds_min_rectangle", "bounds_min_near_clique_7", "compile_orders_motif_sets", "compile_times_catalog", "compile_times_motif_sets", "compile_times_dearest_7"])
def test_each_run_reads_its_table(spark, sf, monkeypatch, name):
    """Also in a session that has stored the graph."""
    queries.store(spark, sf, "doc_lines"), queries.store(spark, sf, "copart_q45")
    read, make = [], graphs.from_tables
    monkeypatch.setattr(graphs, "from_tables", lambda s, at, g: read.append(make(s, at, g)) or read[-1])
    monkeypatch.setattr(measures, "compile_times", lambda s, *_, **__: s.range(1)), monkeypatch.setattr(measures, "compile_sets", lambda s, *_, **__: s.range(1).withColumn("ms", F.lit(0)))
    queries.QUERIES[name](spark, sf).count()
    assert read and any(f.endswith(("documents.parquet", "lineitem.parquet")) for f in read[0].inputFiles())


def test_stream_of_meetings_makes_no_edge(spark, sf, db, monkeypatch, tmp_path):
    """users who meet are counted through their windows, in any number of batches."""
    from knotwork.streaming import incremental

    def paired(*_, **__):
        raise AssertionError("edges are made")

    monkeypatch.setattr(graphs, "meeting_pairs", paired)
    events = spark.read.parquet(f"{sf}/events.parquet").where("user_id % 3 > 0 or ts < '2024-01-04'")
    events.repartition(3, "user_id").write.parquet(str(tmp_path / "events.parquet"))
    want = db.sql(f"with p as (select distinct date_trunc('day', ts) o, user_id x from read_parquet('{tmp_path}/events.parquet/*.parquet')), e as (select distinct a.x u, b.x v from p a join p b on a.o = b.o and a.x < b.x) select count(*) from e a join e b on a.v = b.u join e c on a.u = c.u and b.v = c.v").fetchall()
    found = incremental.run_events(spark, str(tmp_path / "events.parquet"), str(tmp_path / "stream"), "triangle")
    assert [tuple(r) for r in found.collect()] == want and not (tmp_path / "stream" / "edges").exists()

    # A batch that reaches a part of the members only, repeated rows, and a batch that is retried.
    rows = [(o, x) for o in range(12) for x in range(40) if (o * 7 + x * 5) % 11 < 2 and (x < 20) == (o < 6)]
    for pattern in ("triangle", "wedge"):
        c, known = Counter(spark, str(tmp_path / pattern), pattern), []
        for batch, now in enumerate((rows[:20], rows[15:30], rows[30:])):
            for _ in range(2 if batch == 1 else 1):
                c.apply_meeting(spark.createDataFrame(known, "o long, x long"), spark.createDataFrame(now + now[:2], "o long, x long"), batch)
            known = sorted({*known, *now})
            edges = {(a, b) for o, a in known for p, b in known if o == p and a < b}
            assert one(c.count()) == one(mine.count(GraphStore.build(spark.createDataFrame(sorted(edges), "u long, v long")), pattern, executor="kernel"))


@pytest.mark.parametrize("held", [0.02, 0.8])
def test_motifs_by_heavy_and_light_groups(spark, monkeypatch, held):
    """classes of heavy groups meet, and links by other groups only are added to them."""
    import numpy as np

    from knotwork.sources import groups

    rng = np.random.default_rng(5)
    rows = [(int(o), x) for x in range(120) for o in np.flatnonzero(rng.random(6) < held)] + [(100 + int(o), x) for x in range(120) for o in rng.integers(0, 50, 2)]
    rows += [(o, x) for o, xs in ((200, range(200, 205)), (201, range(203, 209)), (0, (203, 210, 211))) for x in xs]  # whole classes
    edges = sorted({(a, b) for o, a in rows for p, b in rows if o == p and a < b})
    st = GraphStore.build(spark.createDataFrame(edges, "u long, v long"))
    want, classes, apart = sorted(motifs.count(st, 3, executor="kernel").collect()), groups.merged(spark.createDataFrame(rows, "o long, x long")), set()
    monkeypatch.setattr(groups, "ASKED", 50), monkeypatch.setattr(groups, "TOLD", 8), monkeypatch.setattr(groups, "FLAGGED", 100)
    links = groups.links
    monkeypatch.setattr(groups, "links", lambda c, apart=False, seen=apart: seen.add(apart) or links(c, apart))
    for heavy in (1, 8, 1000):
        monkeypatch.setattr(groups, "HEAVY", heavy)
        assert sorted(motifs.count_merged(classes).collect()) == want
    assert apart == ({False, True} if held > 0.5 else apart)


def test_members_of_a_common_group_are_not_linked_in_pairs(spark, monkeypatch):
    """one line in all documents, and another shared by two, leave few links to store."""
    from knotwork.sources import groups

    built, build = [], GraphStore.build
    monkeypatch.setattr(GraphStore, "build", lambda raw, *a, **k: built.append(raw.count()) or build(raw, *a, **k))
    rows = [(0, x) for x in range(400)] + [(1 + x // 2, x) for x in range(500)]
    found = {r["pattern"]: r["cnt"] for r in motifs.count_merged(groups.merged(spark.createDataFrame(rows, "o long, x long"))).collect()}
    assert found == {"triangle": 400 * 399 * 398 // 6, "wedge": 0} and sum(built) < 400


def test_edges_add_up_what_the_loops_read(monkeypatch):
    """mappings and list elements by the edges of hubs, as the nested loops find them."""
    import numpy as np

    from knotwork.plans import by_edges, by_kernel

    rng = np.random.default_rng(3)
    for trial in range(60):
        n = int(rng.integers(2, 25))
        joined = np.triu(rng.random((n, n)) < rng.random(), 1)
        joined[:, n - 1 :] |= trial % 3 == 0
        joined[:1] |= trial % 4 == 0
        joined = np.triu(joined, 1) | np.triu(joined, 1).T
        starts, nbrs = np.concatenate([[0], np.cumsum(joined.sum(1))]), np.nonzero(joined)[1].astype(np.int64)
        if not len(nbrs):
            continue
        monkeypatch.setattr(by_edges, "SLICE", (1, 7, 10**6)[trial % 3])
        for program in [compile_program(CATALOG[p], form=f) for p in ("triangle", "star_3") for f in ("min", "full")]:
            assert by_edges.shape(program)
            for early in (True, False):
                loops, edges = by_kernel.Search(starts, nbrs, program, early), by_edges.EdgeSearch(starts, nbrs, program, early)
                assert sum(loops.count(x) for x in range(n)) == sum(edges.count(x) for x in np.array_split(rng.permutation(n), 2)) and loops.touched == edges.touched
    assert by_edges.shape(compile_program(CATALOG["star_3"], form="none")) is None


def test_gain_of_hubs_goes_by_edges(spark, sf, db, monkeypatch):
    """no list element of a hub's pairs is visited."""
    from knotwork.plans import by_kernel

    monkeypatch.setattr(by_kernel, "HUB", 5), monkeypatch.setattr(by_kernel.Search, "touch_count", None)
    found = queries.QUERIES["orientation_gain_cust_nation"](spark, sf)
    assert sorted(map(tuple, found.collect())) == sorted(db.sql(queries.ORACLES["orientation_gain_cust_nation"]).fetchall())


def test_hubs_count_stars_by_their_edges(spark, monkeypatch):
    """a star is counted by edges where its centre is a hub, from a leaf as from the centre."""
    from knotwork.plans import by_kernel

    edges = [(0, i) for i in range(1, 120)] + [(i, i + 1) for i in range(1, 60)] + [(200, i) for i in range(30, 90)] + [(0, 200), (1, 3)]
    st = GraphStore.build(spark.createDataFrame(edges, "u long, v long"))
    near = {x: {b for a, b in edges + [(b, a) for a, b in edges] if a == x} for x in range(201)}
    want = sum(all(b not in near[a] for a, b in ((x, y), (x, z), (y, z))) for c in near for x in near[c] for y in near[c] if x < y for z in near[c] if y < z)
    monkeypatch.setattr(planner, "KERNEL_DEGREE", 50), monkeypatch.setattr(by_kernel, "HUB", 50)
    monkeypatch.setattr(by_kernel.Search, "fast_count", None)
    for order in (None, (0, 1, 2, 3)):
        assert planner.choose_executor(st, mine.program_for(st, "star_3", order)) == "kernel"
        assert one(mine.count(st, "star_3", order=order)) == want > 0


def test_a_stored_graph_leaves_no_passing_tables(spark, monkeypatch):
    """pairs and ranks are deleted once the graph is written, and shuffles after each measured run."""
    from knotwork import scratch

    before = set(scratch._made)
    st = GraphStore.build(spark.createDataFrame([(1, 2), (2, 3), (1, 3), (3, 9)], "u long, v long"))
    assert set(scratch._made) - before == {st.path} and one(mine.count(st, "triangle")) == 1
    assert sorted(map(tuple, st.edges.collect())) == [(0, 1, 0), (0, 2, 0), (0, 3, 0), (1, 0, 1), (1, 2, 0), (2, 0, 1), (2, 1, 1), (3, 0, 1)]
    dropped = []
    monkeypatch.setattr(measures, "drop_shuffles", dropped.append)
    measures.clique_ways(st, st, 3, repeats=1)
    assert len(dropped) == 4
