"""Near-duplicate documents by a chosen-path set-similarity join.

Documents are sets of five-word shingles; two are linked when 100 * intersection
>= 75 * union. Equal sets are one representative from the start.

* A tree branches its representatives by minwise tokens: a node names ``branches``
  minhash places by a keyed hash, and its members go on with the others that agree
  with them there. A pair of similarity s survives a branching with ``branches * s``
  children on average, so with two branches and s >= 0.75 a tree keeps it with
  probability 0.88 at least at any depth (the extinction probability q solves
  q = (1 - s + s q)**2).
* A node of at most ``limit`` members is compared exhaustively on its sketches; a
  larger one branches on. A large node that kept more than ``dense`` of the node
  above it holds texts that are alike on average: branching no longer separates
  them. Such a node, and what is still large at ``depth``, meets by pivots (see
  ``spanning``), so a group of copies costs rows in proportion to its size.
* Sketch matches (below the threshold by more than five standard deviations) only
  bundle representatives into tentative clusters. A cluster's whole texts then meet,
  a large cluster's by pivots again, and links are confirmed on full shingle sets.

What is missed: all trees read the same 128 minhashes, so the trees' misses depend on
how many of these a pair shares. ``miss_rate`` sums over that number the chance that
eight trees lose the pair at unbounded depth, plus the chance that fewer than ``least``
sketch bytes agree: 2.3 in a million at the threshold, less above it and in nodes that
need fewer branchings. Nothing else is left out.

Defined cases: null and empty texts and texts without words have empty sets and
link with nothing; a null doc_id keeps its row, links with nothing and is its own
(null) component; repeated rows are equal sets; rows of one doc_id with different
texts are compared by their texts; a similarity of exactly 75 % is a link; very long
texts are read whole; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import documents, keep_rows, pick, runs, stored, tidy, utf8
from .components import components, lowest
from .shingles import U64, MinHash, WordHashes, mix, shingle_set

SIZE = 128
LEAST = 70  # sketch bytes that must agree
SIGNED = "doc_id long, mark long, n_shingles long, key binary, mins binary, sketch binary"


def miss_rate(similarity: float, branches: int = 2, trees: int = 8, least: int = LEAST) -> float:
    """The chance that a pair is lost: by all trees at unbounded depth, given the share
    of the minhashes that agree, or by its sketch."""
    out = 0.0
    for agree in range(SIZE + 1):
        s, q = agree / SIZE, 0.0
        for _ in range(2000):
            q = (1 - s + s * q) ** branches
        out += _binomial(agree, similarity) * q**trees
    return out + sum(_binomial(k, similarity + (1 - similarity) / 256) for k in range(least))


def _binomial(k: int, p: float) -> float:
    return math.comb(SIZE, k) * p**k * (1 - p) ** (SIZE - k)


def signatures(docs: DataFrame, width: int = 5) -> DataFrame:
    """A hash of the text, the set's size, a 128-bit key of the whole set, minhashes and
    a byte sketch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        words, signer = WordHashes(), MinHash(SIZE)
        for b in batches:
            n, keys, mins, sketches = [], [], [], []
            for text in utf8(b):
                s = shingle_set(text, words, width)
                n.append(len(s))
                if len(s):
                    m = signer(s)
                    keys.append(xxhash.xxh3_128_digest(s.tobytes()))
                    mins.append(m.tobytes())
                    sketches.append(m.astype(np.uint8).tobytes())
                else:
                    keys.append(None), mins.append(None), sketches.append(None)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(n, pa.int64()), pa.array(keys, pa.binary()), pa.array(mins, pa.binary()), pa.array(sketches, pa.binary())], ["doc_id", "mark", "n_shingles", "key", "mins", "sketch"])

    return documents(docs).withColumn("mark", F.xxhash64("text")).mapInArrow(tidy(run), SIGNED)


def _matrix(column: pa.Array, dtype: str, size: int) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), dtype).reshape(-1, size)


def _branch(rows: DataFrame, seeds: list[int], keep: str) -> DataFrame:
    """Rows (rep, mins[, node, members]) to their children (node, rep, above).
    Without a node, the trees' roots are the seeds; else every node branches by
    places it names, and ``above`` is the size of the node that branched."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            mins = _matrix(b.column(1), "<u4", SIZE).astype(np.uint64)
            reps = b.column(0)
            parent = b.column(2).to_numpy().view(np.uint64) if keep else None
            for seed in seeds:
                here = mix((parent if keep else np.zeros(len(mins), np.uint64)) + U64(seed))
                place = (here % U64(SIZE)).astype(np.int64)
                node = mix(here ^ mix(mins[np.arange(len(mins)), place] + U64(0x9E3779B97F4A7C15)))
                above = b.column(3) if keep else pa.nulls(len(mins), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(node.view(np.int64)), reps, above], ["node", "rep", "above"])

    return rows.mapInArrow(tidy(run), "node long, rep long, above long")


def candidates(reps: DataFrame, trees: int = 8, branches: int = 2, limit: int = 1024, depth: int = 5, least: int = LEAST, dense: float = 0.4) -> DataFrame:
    """Tentative links between representatives (rep, mins, sketch)."""
    roots = [1 + 1000 * t + k for t in range(trees) for k in range(branches)]
    level = _branch(reps.select("rep", "mins"), roots, "")
    out: DataFrame | None = None
    for d in range(1, depth + 1):
        # Both sides are stored, so that adaptive execution can split a hot node's rows.
        level = stored(level, "branches")
        sizes = stored(level.groupBy("node").agg(F.count("*").alias("members")).where("members > 1"), "sizes")
        level = stored(level.join(sizes, "node"), "nodes")
        done = F.col("members") <= limit
        if d > 1:
            done = done | (F.col("members") > dense * F.col("above")) | F.lit(d == depth)
        nodes = level.where(done).select(F.col("node").alias("group"), "rep", F.col("members").alias("n"), F.ceil(F.col("members") / limit).alias("blocks"))
        found = spanning(nodes.join(reps.select("rep", "sketch"), "rep"), Sketches, (least,))
        out = stored(found if out is None else out.unionByName(found).distinct(), "tentative")
        big = level.where(~done)
        if d == depth or big.isEmpty():
            return out
        grown = big.join(reps.select("rep", "mins"), "rep").select("rep", "mins", "node", "members")
        level = _branch(grown, [31 + k for k in range(branches)], "node")
    return out


# Links that connect what all links of a group connect -------------------------------


class Sketches:
    """Which rows of a cell agree in at least ``least`` sketch bytes. Made for a table of
    several cells; ``at`` names the cell whose rows are meant next."""

    def __init__(self, table: pa.Table, least: int):
        self.sketch, self.least, self.low, self.high = _matrix(table.column("sketch"), np.uint8, SIZE), least, 0, table.num_rows

    def at(self, low: int, high: int) -> None:
        self.low, self.high = low, high

    def agree(self, i: int, others: np.ndarray) -> np.ndarray:
        own = self.sketch[self.low : self.high]
        return np.count_nonzero(own[others] == own[i], axis=1)

    def near(self, i: int, others: np.ndarray, label: np.ndarray) -> np.ndarray:
        return others[self.agree(i, others) >= self.least]

    def pairs(self, lows: np.ndarray) -> np.ndarray:
        """Of cells of two rows, given by their first, which are links."""
        return np.count_nonzero(self.sketch[lows] == self.sketch[lows + 1], axis=1) >= self.least


class Texts(Sketches):
    """Which rows of a cell are linked by their full shingle sets; of rows that share
    a label one link is enough. The most similar sketches are tried first."""

    words = WordHashes()

    def __init__(self, table: pa.Table, least: int, width: int, percent: int):
        super().__init__(table, least)
        self.texts, self.width, self.percent = table.column("text").cast(pa.large_binary()), width, percent
        self.sets: dict[int, np.ndarray] = {}

    def at(self, low: int, high: int) -> None:
        super().at(low, high)
        self.sets = {}

    def of(self, i: int) -> np.ndarray:
        if i not in self.sets:
            self.sets[i] = shingle_set(self.texts[self.low + i].as_py(), self.words, self.width)
        return self.sets[i]

    def near(self, i: int, others: np.ndarray, label: np.ndarray) -> np.ndarray:
        agree = self.agree(i, others)
        hit = np.flatnonzero(agree >= self.least)
        out, known = [], set()
        for j in others[hit[np.argsort(-agree[hit], kind="stable")]].tolist():
            if label[j] not in known and similar(self.of(i), self.of(j), self.percent):
                known.add(label[j])
                out.append(j)
        return np.array(out, np.int64)

    def pairs(self, lows: np.ndarray) -> np.ndarray:
        out = super().pairs(lows)
        for k in np.flatnonzero(out).tolist():
            self.at(int(lows[k]), int(lows[k]) + 2)
            out[k] = similar(self.of(0), self.of(1), self.percent)
        return out


def similar(s: np.ndarray, z: np.ndarray, percent: int) -> bool:
    """100 * intersection >= percent * union, of sorted distinct hashes."""
    small, large = (s, z) if len(s) <= len(z) else (z, s)
    if 100 * len(small) < percent * len(large):
        return False
    at = np.searchsorted(large, small)
    shared = int(np.count_nonzero(large[np.minimum(at, len(large) - 1)] == small))
    return 100 * shared >= percent * (len(s) + len(z) - shared)


def forest(near, asking: np.ndarray, label: np.ndarray) -> list[tuple[int, int]]:
    """Links (i, j) that connect the rows as all links of asking rows do. Rows of equal
    label are connected already, so only rows of other labels are compared; ``label``
    ends as the connected sets."""
    out, done = [], np.zeros(len(label), bool)
    for i in np.flatnonzero(asking).tolist():
        done[i] = True
        others = np.flatnonzero((label != label[i]) & ~done)
        hit = near(i, others, label) if len(others) else others
        if len(hit):
            sets, first = np.unique(label[hit], return_index=True)
            out += [(i, int(hit[k])) for k in first]
            label[np.isin(label, sets)] = label[i]
    return out


def pivot_cells(rows: DataFrame, pivots: int = 32) -> DataFrame:
    """Rows (group, rep, n, blocks, ...) dealt to cells: a group of one block is a cell;
    of a larger group every block is one, and meets the group's pivots (side 1), about
    ``pivots`` rows by keyed hash."""
    one = rows.withColumn("block", F.pmod(F.xxhash64("rep"), F.col("blocks"))).withColumn("side", F.lit(0))
    some = rows.where((F.col("blocks") > 1) & (F.pmod(F.xxhash64(F.lit(77), "rep"), F.col("n")) < pivots))
    some = some.withColumn("block", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1))).withColumn("side", F.lit(1))
    return one.unionByName(some).withColumn("cell", F.xxhash64("group", "block")).drop("block")


def cross_cells(rows: DataFrame, lone: DataFrame) -> DataFrame:
    """Lone rows (group, rep) of large groups dealt to meet all rows of their group:
    side 1 the lone ones, side 0 all; ``main`` marks rows of the main set."""
    counts = lone.groupBy("group").agg(F.count("*").alias("few"))
    wide = rows.join(counts, "group").withColumn("some", F.greatest(F.lit(1).cast("long"), F.ceil(F.col("few") * F.col("blocks") / F.col("n"))))
    mine, every = F.pmod(F.xxhash64("rep"), F.col("some")), F.pmod(F.xxhash64("rep"), F.col("blocks"))
    upto = lambda c: F.explode(F.sequence(F.lit(0).cast("long"), F.col(c) - 1))
    flag = lone.withColumn("lone", F.lit(True))
    told = wide.join(flag, ["group", "rep"], "left").withColumn("main", F.col("lone").isNull()).drop("lone")
    told = told.withColumn("j", every).withColumn("i", upto("some")).withColumn("side", F.lit(0))
    asked = wide.join(lone, ["group", "rep"]).withColumn("main", F.lit(False)).withColumn("i", mine).withColumn("j", upto("blocks")).withColumn("side", F.lit(1))
    return told.unionByName(asked).withColumn("cell", F.xxhash64("group", F.lit(1), "i", "j")).drop("i", "j", "few", "some")


def _meet(dealt: DataFrame, matcher: type, how: tuple) -> DataFrame:
    """Cells to (kind, group, a, b): links (kind 0) and, of large groups, every member a
    with the pivot b that names its set in the cell, if it has one (kind 1)."""
    wide, cross = int(dealt.sparkSession.conf.get("spark.sql.shuffle.partitions")), "main" in dealt.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in runs(batches, "cell"):
            cells, reps, sides, groups, blocks = (t.column(c).to_numpy() for c in ("cell", "rep", "side", "group", "blocks"))
            main = t.column("main").to_numpy() if cross else None
            edges = np.concatenate([[0], np.flatnonzero(np.diff(cells)) + 1, [len(cells)]])
            out: list[list[np.ndarray]] = [[], [], [], []]

            def add(kind: int, group: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
                for column, x in zip(out, (np.full(len(a), kind), group, a, b), strict=True):
                    column.append(x)

            match, sizes = matcher(t, *how), np.diff(edges)
            small = (blocks[edges[:-1]] == 1) & (sizes == 2) & (not cross)
            two = edges[:-1][small]
            two = two[match.pairs(two)]
            add(0, groups[two], reps[two], reps[two + 1])
            for lo, hi in zip(edges[:-1][~small].tolist(), edges[1:][~small].tolist(), strict=True):
                rep, side, large = reps[lo:hi], sides[lo:hi], blocks[lo] > 1
                label = np.unique(rep, return_inverse=True)[1].astype(np.int64)  # a pivot is in its block twice
                if cross:
                    label[main[lo:hi]] = -1
                match.at(lo, hi)
                links = forest(match.near, side == 1 if large else np.ones(hi - lo, bool), label)
                if links:
                    i, j = np.array(links).T
                    add(0, groups[lo : lo + 1].repeat(len(i)), rep[i], rep[j])
                if large and not cross:
                    name = dict(sorted(zip(label[side == 1].tolist(), rep[side == 1].tolist(), strict=True), reverse=True))  # the smallest pivot of a set
                    member = np.flatnonzero(side == 0)
                    add(1, groups[lo : lo + 1].repeat(len(member)), rep[member], np.array([name.get(x, -1) for x in label[member].tolist()], np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c).astype(np.int64)) for c in out], ["kind", "group", "a", "b"])

    return dealt.repartition(wide, "cell").sortWithinPartitions("cell", "side", "rep").mapInArrow(tidy(run), "kind long, group long, a long, b long")


def spanning(rows: DataFrame, matcher: type, how: tuple, pivots: int = 32) -> DataFrame:
    """Links (a, b) that connect what all the links within each group connect, for rows
    (group, rep, n, blocks and what the matcher reads), n rows in ``blocks`` blocks a
    group. Small groups are compared exhaustively. In a large one every row meets the
    pivots; rows that these connect into the group's main set need not meet each
    other, and only the lone rest meets all rows. So a group of copies costs rows in
    proportion to its size, and no pair of different sets is left out."""
    met = stored(_meet(pivot_cells(rows, pivots), matcher, how), "met")
    links = met.where("kind = 0").select("a", "b")
    placed = met.where("kind = 1")
    if placed.isEmpty():
        return links.distinct()
    sets = placed.where("b >= 0").groupBy("group", "b").agg(F.count("*").alias("size"))
    main = stored(sets.groupBy("group").agg(F.max_by("b", F.struct("size", "b")).alias("main")), "main")
    lone = placed.join(main, "group", "left").where("main is null or b <> main").select("group", F.col("a").alias("rep"))
    lone = stored(lone, "lone")
    if lone.isEmpty():
        return links.distinct()
    return links.unionByName(_meet(cross_cells(rows, lone), matcher, how).select("a", "b")).distinct()


def confirm(clusters: DataFrame, docs: DataFrame, least: int, width: int = 5, percent: int = 75, block_shingles: int = 1 << 17) -> DataFrame:
    """Confirmed links (a, b) that connect exactly what the clusters' full-set links
    connect. ``clusters``: rep, n_shingles, sketch, component, low, mark (the id and the
    hash of the text of a representative)."""
    mass = stored(clusters.groupBy("component").agg(F.count("*").alias("n"), F.least(F.count("*"), F.ceil(F.sum("n_shingles") / block_shingles)).alias("blocks")), "mass")
    placed = clusters.join(mass, "component").select(F.col("component").alias("group"), "rep", "n", "blocks", "sketch", "low", "mark")
    texts = documents(docs).where("doc_id is not null").select(F.col("doc_id").alias("low"), F.xxhash64("text").alias("mark"), "text")
    met = stored(placed.join(texts, ["low", "mark"]).dropDuplicates(["rep"]).drop("low", "mark"), "texts")
    return spanning(met, Texts, (least, width, percent))


def _grouped(docs: DataFrame, least: int, **how) -> DataFrame:
    """doc_id, mark (hash of the text), n_shingles, group (number of the component; null
    without links), component_id of every document."""
    signed = stored(signatures(docs), "signatures")
    # Numbered, since rows of one doc_id may hold different texts.
    reps = stored(
        signed.where("key is not null and doc_id is not null").groupBy("key")
        .agg(F.min(F.struct("doc_id", "mark")).alias("one"), F.count("*").alias("copies"), F.first("n_shingles").alias("n_shingles"), F.first("mins").alias("mins"), F.first("sketch").alias("sketch"))
        .select("key", F.col("one.doc_id").alias("low"), F.col("one.mark").alias("mark"), "copies", "n_shingles", "mins", "sketch", F.monotonically_increasing_id().alias("rep")),
        "reps",
    )
    tentative = candidates(reps.select("rep", "mins", "sketch"), least=least, **how)
    bundles = components(tentative).withColumnRenamed("node", "rep")
    clusters = bundles.join(reps.select("rep", "n_shingles", "sketch", "low", "mark"), "rep")
    groups = components(confirm(clusters, docs, least)).withColumnRenamed("node", "rep")
    names = reps.select("key", "rep", "low", "copies")
    found = stored(groups, "components")
    lows = lowest(found, names)
    named = names.join(found, "rep", "left").join(lows, "rep", "left").select(
        "key", F.coalesce("component", F.when(F.col("copies") > 1, F.col("rep"))).alias("group"), F.coalesce("component_id", "low").alias("component_id")
    )
    rows = pick(signed, doc_id="long", mark="long", n_shingles="long", key="binary")
    own = F.when(F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id"))
    return rows.join(named, "key", "left").select("doc_id", "mark", "n_shingles", F.when(F.col("doc_id").isNotNull(), F.col("group")).alias("group"), own.alias("component_id"))


def near_duplicates(docs: DataFrame, least: int = LEAST, **how) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every document."""
    kept = F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(False))
    return _grouped(docs, least, **how).select("doc_id", "n_shingles", "component_id", kept.alias("kept"))


def keep_one(docs: DataFrame, least: int = LEAST, **how) -> DataFrame:
    """One document of each near-duplicate group (the smallest id; of several texts of
    that id the one with the smallest hash, of repeated rows any), with all its
    columns. Rows without an id link with nothing and stay."""
    grouped = stored(_grouped(docs, least, **how).where("group is not null"), "grouped")
    return keep_rows(docs, grouped.withColumn("kept", F.col("doc_id") == F.col("component_id")), "group")
