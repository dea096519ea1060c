"""Vectors, packing, shards, near duplicates, token files, pipeline: against brute
force, exact round trips and bounds."""

import zlib
from itertools import combinations

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from knotwork.llm import components, minhash_join, packing, sharding, token_blocks, vector_dedup
from knotwork.llm.common import runs
from knotwork.llm.shingles import MinHash, WordHashes, shingle_set

from .helpers import AWKWARD, LONG, docs


def connect(nodes, links):
    root = {n: n for n in nodes}
    change = True
    while change:
        change = False
        for a, b in links:
            m = min(root[a], root[b])
            if root[a] != m or root[b] != m:
                root[a] = root[b] = m
                change = True
    return root


def test_components(spark):
    rng = np.random.default_rng(1)
    links = [(int(a), int(b)) for a, b in rng.integers(0, 300, (220, 2))] + [(1000 + i, 1001 + i) for i in range(70)] + [(2000, 2001 + i) for i in range(80)] + [(5, 5)]
    got = {r["node"]: r["component"] for r in components.components(spark.createDataFrame(links, "a long, b long")).collect()}
    want = connect({x for p in links for x in p}, links)
    assert got == {n: c for n, c in want.items() if n in got} and {x for a, b in links if a != b for x in (a, b)} == set(got)
    assert components.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_runs_join_groups_across_batches():
    table = pa.table({"cell": [1, 1, 2, 3, 3, 3, 3, 4], "x": list(range(8))})
    for size in range(1, 9):
        out = list(runs(iter(table.to_batches(size)), "cell"))
        assert pa.concat_tables(out).to_pylist() == table.to_pylist()
        seen = [set(t.column("cell").to_pylist()) for t in out]
        assert all(not a & b for a, b in combinations(seen, 2))


# vectors ----------------------------------------------------------------------


def brute_vectors(rows):
    unit = {}
    for i, v, label in rows:
        if i is not None and label is not None and v and None not in v and np.isfinite(v).all() and np.any(v):
            unit[i] = (np.array(v, float) / np.linalg.norm(v), label)
    links = [(a, b) for a, b in combinations(unit, 2) if unit[a][1] == unit[b][1] and len(unit[a][0]) == len(unit[b][0]) and unit[a][0] @ unit[b][0] >= 0.98]
    return connect([r[0] for r in rows], links), {i: sum(i in p for p in links) for i, *_ in rows}


@pytest.mark.parametrize("block,guests", [(4096, 1 << 16), (16, 40)])
def test_vectors_equal_brute_force(spark, block, guests):
    rng = np.random.default_rng(7)
    rows, base = [], rng.normal(size=(40, 16))
    for i in range(400):
        v = base[rng.integers(40)] + rng.normal(size=16) * rng.choice([0.02, 0.15, 0.19, 0.3])
        rows.append((i, [float(x) for x in v * rng.uniform(0.1, 9)], int(rng.choice([0, 0, 0, 1]))))
    rows += [(500 + i, rows[0][1], rows[0][2]) for i in range(30)]
    rows += [(600, None, 0), (601, [0.0] * 16, 0), (602, [float("nan")] * 16, 0), (603, [None, 1.0], 0), (604, rows[0][1], None), (605, [1.0, 2.0], 0), (606, [2.0, 4.0], 0), (607, [], 0), (608, [1e200, 1e200], 0), (609, [float("inf"), 1.0], 0)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").withColumn("key", F.lit(1)).withColumn("list", F.lit(2))
    want, links = brute_vectors(rows)
    index_rows = {r["vec_id"]: r for r in vector_dedup.near_vectors(df, block=block, guests=guests, sample=200).collect()}
    assert len(index_rows) == len(rows)
    assert {i: r["n_links"] for i, r in index_rows.items()} == links
    assert {i: r["component_id"] for i, r in index_rows.items()} == want
    assert all(r["kept"] == (i == r["component_id"]) for i, r in index_rows.items())


def test_vector_edges(spark):
    empty = spark.createDataFrame([], "vec_id long, embedding array<float>, label int")
    assert vector_dedup.near_vectors(empty).count() == 0
    bad = spark.createDataFrame([(1, None, 1), (2, [0.0], 1)], "vec_id long, embedding array<float>, label int")
    assert [(r["vec_id"], r["n_links"], r["kept"]) for r in vector_dedup.near_vectors(bad).orderBy("vec_id").collect()] == [(1, 0, True), (2, 0, True)]


def test_probes_are_sufficient_and_codes_bounded():
    rng = np.random.default_rng(3)
    x = rng.normal(size=(600, 24))
    x[300:] = x[:300] + rng.normal(size=(300, 24)) * 0.03
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    index = vector_dedup.Index(x, lists=20, parts=6, words=16)
    home = vector_dedup.nearest(x, index.coarse)
    probes = index.probes(x, home, 0.2)
    for i, j in zip(range(300), range(300, 600), strict=True):
        if x[i] @ x[j] >= 0.98:
            assert home[i] == home[j] or probes[i, home[j]] or probes[j, home[i]]
    codes, err = index.encode(x, home)
    for c in range(3):
        own = np.flatnonzero(home == c)
        exact = np.linalg.norm(x[:50, None] - x[own][None], axis=2)
        assert (np.abs(index.table_distances(x[:50], c, codes[own]) - exact) <= err[own] + 1e-9).all()


# packing ----------------------------------------------------------------------


@settings(max_examples=100, deadline=None)
@given(st.lists(st.integers(1, 60), min_size=1, max_size=14))
def test_best_fit_and_bounds(sizes):
    lengths = np.array(sizes)
    bins, offsets, fills = packing.best_fit(lengths, 60)
    assert fills.max() <= 60 and fills.sum() == lengths.sum()
    for b in range(len(fills)):
        at = 0
        for o, n in sorted((offsets[i], lengths[i]) for i in np.flatnonzero(bins == b)):
            assert o == at
            at += n
    assert packing.lower_bound(lengths, 60) <= optimum(sorted(sizes, reverse=True), 60) <= len(fills)


def optimum(sizes, most):
    best = [len(sizes)]

    def put(i, free):
        if len(free) >= best[0]:
            return
        if i == len(sizes):
            best[0] = len(free)
            return
        for j in range(len(free)):
            if free[j] >= sizes[i] and free[j] not in free[:j]:
                put(i + 1, free[:j] + [free[j] - sizes[i]] + free[j + 1 :])
        put(i + 1, [*free, most - sizes[i]])

    put(0, [])
    return best[0]


def test_bounds_see_large_items():
    assert packing.lower_bound(np.array([31] * 10), 60) == 10 and packing.lower_bound(np.array([21] * 9), 60) == 5
    assert packing.lower_bound(np.zeros(0, np.int64), 60) == 0


def test_cut_lengths():
    assert packing.cut_lengths(2048, 2048) == [(0, 2048)] and packing.cut_lengths(1, 2048) == [(0, 1)]
    assert packing.cut_lengths(5000, 2048) == [(0, 904), (904, 2048), (2952, 2048)] and packing.cut_lengths(4096, 2048) == [(0, 2048), (2048, 2048)]


def test_packing_documents(spark):
    from tokenizers import Tokenizer

    from knotwork.llm.tokenization import tokenizer_path

    t = Tokenizer.from_file(tokenizer_path("byte_bpe_50k.json"))
    table = docs(spark, AWKWARD + [(100 + i, f"text {i} " * (i % 90)) for i in range(300)])
    rows = packing.pack_documents(table, per_task=150).collect()
    by_seq, by_doc = {}, {}
    for r in rows:
        by_seq.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
        by_doc.setdefault(r["doc_id"], []).append(r)
    for parts in by_seq.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= 2048
    for i, text, *_ in AWKWARD:
        if i == 8:
            continue
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 0]
        parts = sorted(by_doc[i], key=lambda r: r["piece"])
        assert [r["start"] for r in parts] == [s for s, _ in packing.cut_lengths(len(ids), 2048)] and sum(r["length"] for r in parts) == len(ids)
        for r in parts:
            assert r["ids_crc32"] == zlib.crc32(np.array(ids[r["start"] : r["start"] + r["length"]], "<u4").tobytes())
    total = sum(r["length"] for r in rows)
    assert len(by_seq) <= 1.02 * packing.lower_bound(np.array([r["length"] for r in rows]), 2048) + 1 and total / 2048 <= len(by_seq)
    assert packing.pack_documents(docs(spark, [])).count() == 0


def test_sequences_hold_the_pieces(spark):
    table = docs(spark, [(i, f"some words {i} " * (i % 40 + 1)) for i in range(80)])
    packed = packing.pack_documents(table).cache()
    found = {r["sequence_id"]: r["ids"] for r in packing.sequences(table, packed).collect()}
    for r in packed.collect():
        ids = found[r["sequence_id"]][r["offset"] : r["offset"] + r["length"]]
        assert zlib.crc32(np.array(ids, "<u4").tobytes()) == r["ids_crc32"]
    c = packing.certificate(packed).first()
    lengths = [r["length"] for r in packed.collect()]
    assert c["fullest"] <= 2048 and c["sequences"] == len(found) and c["bound"] == packing.lower_bound(np.array(lengths), 2048) <= c["sequences"]
    assert c["gap"] == c["sequences"] - c["bound"] and c["tokens"] == sum(lengths) and c["mean_fill"] == pytest.approx(sum(lengths) / len(found))
    assert packing.certificate(packed.limit(0)).first()["sequences"] == 0


def test_rounds_go_on_while_they_help(spark):
    rng = np.random.default_rng(5)
    rows = [(i, 0, 0, int(n), i) for i, n in enumerate(rng.integers(300, 1200, 4000))]
    table = spark.createDataFrame(rows, packing.PIECES)
    first = packing._pack_round(table, 0, 40, 2048, 1).select("sequence_id").distinct().count()
    out = packing.pack(table, per_task=100)
    c = packing.certificate(out).first()
    assert out.count() == 4000 and c["fullest"] <= 2048 and c["bound"] <= c["sequences"] < first


# sharding ---------------------------------------------------------------------


def test_shards_are_even_and_keep_groups(spark):
    rows = [(i, f"t{i % 60}" if i < 240 else f"u{i}") for i in range(1003)]
    out = sharding.shard_rows(docs(spark, rows)).collect()
    sizes = [sum(r["shard"] == s for r in out) for s in range(8)]
    assert sum(sizes) == 1003 and max(sizes) - min(sizes) <= 1
    for s in range(8):
        assert sorted(r["slot"] for r in out if r["shard"] == s) == list(range(sizes[s]))
    text = dict(rows)
    groups = {}
    for r in out:
        assert r["size"] == len(text[r["doc_id"]].encode()) + 1 and r["text_crc32"] == zlib.crc32(text[r["doc_id"]].encode()) and r["law"] == "rows" and r["grown_shard"] is None
        groups.setdefault(text[r["doc_id"]], set()).add(r["shard"])
    rows_ = spark.createDataFrame([(text[r["doc_id"]], r["shard"]) for r in out], "grp string, shard int")
    c = sharding.cut_groups(rows_, 125).first()
    assert (c["groups"], c["cut"], c["least"]) == (60, 0, 0) and sum(len(g) > 1 for g in groups.values()) == 0


def test_a_hot_group_spreads_only_as_far_as_it_must(spark):
    rows = [(i, "copy" if i % 3 == 0 else f"u{i}") for i in range(600)]
    out = sharding.shard_rows(docs(spark, rows)).collect()
    sizes = [sum(r["shard"] == s for r in out) for s in range(8)]
    assert max(sizes) - min(sizes) <= 1 and sum(sizes) == 600
    assert len({r["shard"] for r in out if r["doc_id"] % 3 == 0}) <= 4  # 200 rows, at least three shards of 75


def test_shard_edges_cases(spark):
    out = sharding.shard_rows(docs(spark, AWKWARD)).collect()
    assert len(out) == len(AWKWARD) and {r["size"] for r in out if r["doc_id"] in (5, 6)} == {1}
    assert sharding.shard_rows(docs(spark, [])).count() == 0
    few = sharding.shard_rows(docs(spark, [(1, "a"), (2, "a"), (3, "b")])).collect()
    assert sorted(r["shard"] for r in few) == [0, 1, 2]


def test_propagation_cuts_fewer_edges_than_hashing(spark):
    rng = np.random.default_rng(2)
    edges = [(int(b * 40 + a), int(b * 40 + c)) for b in range(16) for a, c in rng.integers(0, 40, (160, 2)) if a != c]
    v = spark.createDataFrame([(i,) for i in range(640)], "doc_id long")
    e = spark.createDataFrame(edges, "src long, dst long").distinct()
    out = sharding.shard_edges(v, e, shards=4).cache()
    sizes = [r["count"] for r in out.groupBy("shard").count().collect()]
    assert sizes == [160] * 4
    n = sharding.cut(out, e).first()
    assert n["n_cut"] < 0.6 * n["n_edges"]  # hashing cuts three quarters


def test_quotas_never_overfill():
    flows = {(0, 0): 50, (0, 1): 30, (1, 0): 10, (1, 1): 60, (2, 1): 40, (2, 2): 10}
    q = sharding.quotas(flows, [90, 75, 60])
    into = sum(n * q[k] for k, n in flows.items() if k[1] == 1 and k[0] != 1)
    away = sum(n * q[k] for k, n in flows.items() if k[0] == 1 and k[1] != 1)
    assert 70 + into - away <= 75 + 1e-9 and all(0 <= x <= 1 for x in q.values())


# near duplicates --------------------------------------------------------------


def shingles(text):
    w = [x for x in __import__("re").split(r"[\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")) if x]
    return set() if not w else {tuple(w)} if len(w) < 5 else {tuple(w[i : i + 5]) for i in range(len(w) - 4)}


def brute_near(rows):
    sets = {i: shingles(t) for i, t in rows}
    links = [(a, b) for a, b in combinations(sets, 2) if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])]
    return connect(sets, links), {i: len(s) for i, s in sets.items()}


def near_rows(seed=4, n=120):
    rng = np.random.default_rng(seed)
    vocabulary = [f"v{i}" for i in range(500)]
    passage = [vocabulary[i] for i in rng.integers(0, 500, 60)]
    rows, doc = [], 0
    for _ in range(n):
        words = [vocabulary[i] for i in rng.integers(0, 500, int(rng.integers(1, 200)))]
        if rng.random() < 0.5:
            words += passage
        for _ in range(int(rng.choice([1, 1, 2, 6]))):
            copy = list(words)
            for _ in range(int(rng.integers(0, 4))):
                copy[int(rng.integers(len(copy)))] = "edit"
            rows.append((doc, (" " if doc % 2 else "\n").join(copy).upper() if doc % 5 == 0 else " ".join(copy)))
            doc += 1
    return rows


@pytest.mark.parametrize("limit,depth", [(1024, 5), (8, 3)])
def test_near_duplicates_equal_brute_force(spark, limit, depth):
    rows = near_rows()
    want, sizes = brute_near(rows)
    out = {r["doc_id"]: r for r in minhash_join.near_duplicates(docs(spark, rows), limit=limit, depth=depth).collect()}
    assert {i: r["n_shingles"] for i, r in out.items()} == sizes
    assert {i: r["component_id"] for i, r in out.items()} == want
    assert all(r["kept"] == (i == r["component_id"]) for i, r in out.items())


def grouped(spark, table, block_shingles, per_group=1):
    """All texts as one tentative cluster, ready to be confirmed."""
    signed = minhash_join.signatures(table).where("key is not null")
    one = signed.select(F.col("doc_id").alias("rep"), F.col("doc_id").alias("low"), "mark", "n_shingles", "sketch", F.lit(1).cast("long").alias("component"))
    return minhash_join.confirm(one, table, minhash_join.LEAST, block_shingles=block_shingles)


@pytest.mark.parametrize("block", [1 << 20, 700])
def test_confirmation_in_blocks(spark, block):
    rows = near_rows(seed=9, n=40)
    want, _ = brute_near(rows)
    links = [(r["a"], r["b"]) for r in grouped(spark, docs(spark, rows), block).collect()]
    assert connect([i for i, _ in rows], links) == want
    texts = {i: shingles(t) for i, t in rows}
    assert all(100 * len(texts[a] & texts[b]) >= 75 * len(texts[a] | texts[b]) for a, b in links if a != b)


def test_chains_of_links_are_found_across_blocks(spark):
    """Every text is linked with its neighbours only, so no pivot reaches far."""
    words = [f"w{i}" for i in range(1400)]
    rows = [(i, " ".join(words[5 * i : 5 * i + 60])) for i in range(250)] + [(300 + i, " ".join(words[-60:]) + f" x{i}") for i in range(20)]
    want, _ = brute_near(rows)
    links = [(r["a"], r["b"]) for r in grouped(spark, docs(spark, rows), 900).collect()]
    assert connect([i for i, _ in rows], links) == want and len(set(want.values())) < 10


def test_rows_of_a_large_group_grow_in_proportion(spark):
    rng = np.random.default_rng(3)
    base = [f"b{i}" for i in range(60)]

    def dealt(n):
        rows = [(i, " ".join([*base[: (at := int(rng.integers(60)))], f"e{i}", *base[at + 1 :]])) for i in range(n)]
        signed = minhash_join.signatures(docs(spark, rows)).select(F.lit(1).cast("long").alias("group"), F.col("doc_id").alias("rep"), F.lit(n).cast("long").alias("n"), F.lit(n // 128).cast("long").alias("blocks"), "sketch").cache()
        cells = minhash_join.pivot_cells(signed)
        met = minhash_join._meet(cells, minhash_join.Sketches, (minhash_join.LEAST,)).where("kind = 1")
        main = met.groupBy("b").count().orderBy(F.desc("count")).first()["b"]
        lone = met.where(F.col("b") != main).select("group", F.col("a").alias("rep"))
        cross = minhash_join.cross_cells(signed, lone).count() if lone.count() else 0
        most = cells.groupBy("cell").count().agg(F.max("count")).first()[0]
        links = [(r["a"], r["b"]) for r in minhash_join.spanning(signed, minhash_join.Sketches, (minhash_join.LEAST,)).collect()]
        assert set(connect(range(n), links).values()) == {0} if n <= 2000 else len(links) >= n - 1
        return cells.count() + cross, most

    (a, most), (b, _), (c, more) = dealt(2000), dealt(4000), dealt(8000)
    assert b < 2.2 * a and c < 2.2 * b and c < 2.5 * 8000 and more < 1.5 * most


def test_near_duplicate_edges(spark):
    rows = [r for r in AWKWARD if r[0] != 8] + [(20, "one two three"), (21, "ONE two\tthree"), (22, "one two four")]
    out = {r["doc_id"]: r for r in minhash_join.near_duplicates(docs(spark, rows)).collect()}
    assert [out[i]["n_shingles"] for i in (5, 6, 7, 20)] == [0, 0, 0, 1] and out[21]["component_id"] == 20 and out[22]["component_id"] == 22
    assert out[14]["component_id"] == 13 and out[10]["component_id"] == 9 and out[None]["component_id"] is None and not out[None]["kept"]
    assert minhash_join.near_duplicates(docs(spark, [])).count() == 0
    repeated = minhash_join.keep_one(docs(spark, [(1, LONG), (1, LONG), (2, LONG)]))
    assert [r["doc_id"] for r in repeated.collect()] == [1] and repeated.columns == docs(spark, []).columns


def test_near_texts_under_one_id_or_none_stay_apart(spark):
    long = " ".join(f"w{i}" for i in range(100))
    rows = [(3, long), (7, "a text of its own that nobody else has at all"), (7, long + " tail"), (None, long + " more"), (None, "without an id"), (8, long + " x"), (5, "q r s t u v"), (5, "Q r s t u v"), (1, "alpha one"), (1, "beta two")]
    kept = sorted(((r["doc_id"], r["text"]) for r in minhash_join.keep_one(docs(spark, rows)).collect()), key=str)
    five = [x for x in kept if x[0] == 5]
    assert len(five) == 1 and five[0] in rows
    assert [x for x in kept if x[0] != 5] == sorted(((i, t) for i, t in rows if (i, t) not in {(7, long + " tail"), (8, long + " x")} and i != 5), key=str)
    out = sorted((r["doc_id"], r["component_id"]) for r in minhash_join.near_duplicates(docs(spark, rows)).where("doc_id is not null").collect())
    assert out == [(1, 1), (1, 1), (3, 3), (5, 5), (5, 5), (7, 3), (7, 7), (8, 3)]


def test_miss_rate_and_minhash():
    assert 1e-6 < minhash_join.miss_rate(0.75) < 2.3e-6 and minhash_join.miss_rate(0.8) < 1e-7 and minhash_join.miss_rate(0.75, trees=6, least=76) > 5e-5
    words, m = WordHashes(limit=50), MinHash(128)
    a = shingle_set(LONG.encode(), words)
    b = shingle_set((LONG + " x y z").encode(), words)
    exact = len(np.intersect1d(a, b)) / len(np.union1d(a, b))
    assert abs((m(a) == m(b)).mean() - exact) < 0.12


# token files ------------------------------------------------------------------


@settings(max_examples=150, deadline=None)
@given(st.lists(st.integers(0, 5000), max_size=700))
def test_elias_fano(steps):
    values = np.cumsum(np.array(steps, np.int64)) if steps else np.zeros(0, np.int64)
    ef = token_blocks.EliasFano.encode(values)
    assert ef.all().tolist() == values.tolist()
    for i in list(range(0, len(values), 37)) + [len(values) - 1] * bool(len(values)):
        assert ef.select(i) == values[i]
    if len(values) > 300:
        bits = 8 * (len(ef.low) + len(ef.high) + ef.samples.nbytes)
        assert bits <= len(values) * (3 + np.log2(max(1, values[-1] / len(values)))) + 128
    with pytest.raises(IndexError):
        ef.select(len(values))


def test_token_files_round_trip(spark, tmp_path):
    from tokenizers import Tokenizer

    from knotwork.llm.tokenization import tokenizer_path

    t = Tokenizer.from_file(tokenizer_path("word_bpe_49k.json"))
    rows = AWKWARD + [(200 - i, f"Text number {i}. " * (i % 7)) for i in range(60)]
    table = docs(spark, rows)
    path = str(tmp_path / "blocks")
    token_blocks.write_blocks(table, path, block_tokens=300)
    got = sorted(((r["doc_id"] if r["doc_id"] is not None else -1), r["start"], r["n_tokens"], r["ids_crc32"]) for r in token_blocks.read_blocks(spark, path).collect())
    at, want, whole = 0, [], []
    for i, text in sorted(((-1 if r[0] is None else r[0]), r[1] or "") for r in rows):
        ids = [*t.encode(text, add_special_tokens=False).ids, 2]
        want.append((i, at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        at, whole = at + len(ids), whole + ids
    assert got == want
    data = b"".join(open(f, "rb").read() for f in token_blocks.export_files(spark, path, str(tmp_path / "files"), per_file=2))
    pos, back = 0, []
    while pos < len(data):
        block, pos = token_blocks.Block.from_bytes(data, pos)
        back += block.ids.tolist()
        assert block.document(block.ends.n - 1)[-1] == 2
    assert back == whole
    with pytest.raises(ValueError):
        token_blocks.Block.from_bytes(b"x" * 80)
    wide = np.array([70_000, 2], "<u4").tobytes()
    with pytest.raises(ValueError):
        token_blocks.Block.build([wide], 2)
    assert token_blocks.Block.build([wide, wide[4:]], 4).document(0).tolist() == [70_000, 2] and token_blocks.width_of("word_bpe_49k.json", 2) == 2
    assert token_blocks.width_of("word_bpe_49k.json", 70_000) == 4
    assert token_blocks.round_trip(docs(spark, [])).count() == 0


# pipeline ---------------------------------------------------------------------


def test_pipeline_stages(spark, sf):
    import corpus_pipeline

    table = spark.read.parquet(f"{sf}/documents.parquet")
    docs_, counts = table, [table.count()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs_ = stage(spark, docs_, sf).cache()
        assert docs_.columns == table.columns, name
        counts.append(docs_.count())
    assert all(a >= b for a, b in zip(counts, counts[1:], strict=False)) and counts[-1] > 0
    texts = {r["doc_id"]: r["text"] for r in docs_.collect()}
    want, _ = brute_near([(i, t) for i, t in texts.items()])
    assert all(want[i] == i for i in texts)
    packed = corpus_pipeline.STAGES[-1][1](spark, docs_, sf).collect()
    assert {r["doc_id"] for r in packed} == set(texts)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality classifier", "language ID", "exact dedup", "MinHash near-dedup", "best-fit packing"]


def brute_pipeline(rows, labels):
    """The ids that stay after each of the first four stages, from the definitions."""
    import xxhash

    from knotwork.llm import exact_dedup, language_id

    from .test_text_operators import brute_weights

    scored = brute_weights(rows, labels)
    good = {i for i, q in labels if q == 1 and i is not None}
    held = {i for i in good if xxhash.xxh3_64_intdigest(f"17:{i}".encode()) % 5 == 0}
    held = held if len(held) >= 20 else good
    level = np.quantile([w for i, w, _ in scored if i in held and w is not None], 0.001) - 1.0
    k = sum(w is not None and w >= level for _, w, _ in scored)
    cut = sorted((key for _, _, key in scored if key is not None), reverse=True)[k - 1]
    stages = [[r for r, (_, _, key) in zip(rows, scored, strict=True) if key is not None and key >= cut]]
    stages.append([(i, t) for i, t in stages[-1] if t is not None and language_id.has_letter(t.encode())])
    first = {}
    for i, t in sorted(stages[-1]):
        first.setdefault(exact_dedup.normalise(t.encode()), (i, t))
    stages.append(sorted(first.values()))
    component, _ = brute_near(stages[-1])
    stages.append([(i, t) for i, t in stages[-1] if component[i] == i])
    return [[i for i, _ in x] for x in stages]


def test_pipeline_equals_brute_force(spark, sf):
    import corpus_pipeline
    from tokenizers import Tokenizer

    from knotwork.llm.tokenization import tokenizer_path

    table = spark.read.parquet(f"{sf}/documents.parquet")
    rows = [(r["doc_id"], r["text"]) for r in table.select("doc_id", "text").collect()]
    labels = [tuple(r) for r in spark.read.parquet(f"{sf}/labels.parquet").select("doc_id", "quality").collect()]
    want = brute_pipeline(rows, labels)
    docs_ = table
    for (name, stage), ids in zip(corpus_pipeline.STAGES[:-1], want, strict=True):
        docs_ = corpus_pipeline.stored(stage(spark, docs_, sf), "tested")
        assert docs_.columns == table.columns and sorted(r["doc_id"] for r in docs_.select("doc_id").collect()) == sorted(ids), name
    packed = corpus_pipeline.pack(spark, docs_, sf).collect()
    t, text = Tokenizer.from_file(tokenizer_path("byte_bpe_50k.json")), dict(rows)
    whole = {i: len(t.encode(text[i], add_special_tokens=False).ids) + 1 for i in want[-1]}
    found, ends = {}, {}
    for r in packed:
        found[r["doc_id"]] = found.get(r["doc_id"], 0) + r["length"]
        ends.setdefault(r["sequence_id"], []).append((r["offset"], r["offset"] + r["length"]))
    assert found == whole
    assert all(sorted(x)[0][0] == 0 and max(b for _, b in x) == sum(b - a for a, b in x) <= 2048 for x in ends.values())


def test_pipeline_of_awkward_and_empty_tables(spark, tmp_path):
    import corpus_pipeline

    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    for name, rows in (("awkward", AWKWARD + [(8, "another text of eight"), (None, "no id at all here")]), ("empty", [])):
        folder = str(tmp_path / name)
        docs(spark, rows).coalesce(1).write.parquet(f"{folder}/documents.parquet")
        labels.write.parquet(f"{folder}/labels.parquet")
        got = {r["doc_id"] for r in corpus_pipeline.run(spark, folder).collect()}
        # No letter: 5, 6, 7 (and 11); copies: 10 of 9, 16 of 15; near copy: 14 of 13.
        assert got == ({8, 9, 12, 13, 15, None} if rows else set())


def test_pipeline_drops_texts_of_no_clear_language(spark, monkeypatch):
    """the prediction itself decides, not only whether a text has a letter."""
    import corpus_pipeline
    from knotwork.llm import language_id

    class Net:
        labels = ["a", "b"]

        def predict(self, texts):
            return [("a", 0.9) if b"clear" in (t or b"") else ("b", 0.4) for t in texts]

    monkeypatch.setattr(language_id, "train", lambda docs: Net())
    some = docs(spark, [(1, "a clear text"), (2, "xq zv"), (3, None)])
    assert [r["doc_id"] for r in corpus_pipeline.keep_language(spark, some, "").collect()] == [1]
