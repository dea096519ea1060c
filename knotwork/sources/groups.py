"""Graphs given by groups: two members are linked when they share a group.

Members of exactly the same groups have the same links, so they are merged into one class
first. Blocks of classes then meet pairwise in a task, which finds each linked pair of
classes once however many groups hold it; what is asked for (pairs of members, degrees, or
the links of the classes) is made from that inside the task, and no pair is shuffled.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..scratch import stored

#: Rows (class, group) of a block, pairs of members that a task is to make, most blocks, and
#: rows of a batch.
HELD = 500_000
PAIRS = 2_000_000
BLOCKS = 16
BATCH = 500_000
#: Members from which a group is heavy, elements of a matrix of flags, and flags made at a time.
HEAVY = 200
FLAGS = 50_000_000
FLAGGED = 4_000_000
#: Pairs and classes that a task of ``common`` holds.
ASKED = 20_000
TOLD = 2_048


def shared_groups(members: DataFrame) -> DataFrame:
    """(o, x): distinct members x of the groups o that have two or more; groups become numbers."""
    rows = stored(members.where("o is not null and x is not null").select("o", "x").distinct(), "members")
    names = stored(rows.groupBy("o").agg(F.count("*").alias("n")).where("n >= 2").select("o", F.monotonically_increasing_id().alias("g")), "groups")
    return rows.join(names, "o").select(F.col("g").alias("o"), F.col("x").cast("long").alias("x"))


def merged(members: DataFrame, most: int | None = None) -> DataFrame:
    """(c, xs, os): the classes of members of equal groups, named by their smallest member;
    with ``most`` in parts of so many members, which are linked like two classes."""
    own = shared_groups(members).groupBy("x").agg(F.sort_array(F.collect_list("o")).alias("os"))
    classes = own.groupBy("os").agg(F.sort_array(F.collect_list("x")).alias("xs"))
    if most is not None:
        part = F.transform(F.sequence(F.lit(0), F.expr(f"cast((size(xs) - 1) div {most} as int)")), lambda i: F.slice("xs", i * most + 1, most))
        classes = classes.select("os", F.explode(part).alias("xs"))
    return stored(classes.select(F.col("xs")[0].alias("c"), "xs", "os"), "classes")


class Block:
    """The classes of one block: their sizes, members (where asked for) and groups as flat arrays."""

    def __init__(self, c: np.ndarray, size: np.ndarray, xs: tuple, os: tuple):
        self.c, self.size = c, size
        (self.x_at, self.xs), (self.o_at, self.os) = xs, os

    @classmethod
    def bare(cls, c: np.ndarray, size: np.ndarray, os: list[np.ndarray]) -> Block:
        return cls(c, size, (None, None), _flat(os))

    def members(self, at: np.ndarray) -> np.ndarray:
        size = self.size[at]
        return self.xs[np.repeat(self.x_at[at] - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))]


def _flat(lists: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    return np.concatenate([[0], np.cumsum([len(x) for x in lists])]).astype(np.int64), np.concatenate([*lists, np.zeros(0, np.int64)]).astype(np.int64)


def _flags(low: Block, high: Block) -> Iterator[np.ndarray]:
    """For each class of one block, which classes of the other it is linked to. Few groups
    that many classes hold meet as matrices, others by the holders of each group."""
    groups, of = np.unique(high.os, return_inverse=True)
    at = np.searchsorted(groups, low.os)
    ok = np.append(groups, -1)[at] == low.os
    held = np.bincount(of, minlength=len(groups))
    owner = np.repeat(np.arange(len(high.c)), np.diff(high.o_at))
    marks, pairs = int(held[at[ok]].sum()), len(low.c) * len(high.c)
    if (len(low.c) + len(high.c)) * len(groups) <= FLAGS and pairs * (1 + len(groups) // 16) <= marks:
        a, b = [np.zeros((len(x.c), len(groups)), np.float32) for x in (low, high)]
        a[np.repeat(np.arange(len(low.c)), np.diff(low.o_at))[ok], at[ok]] = 1
        b[owner, of] = 1
        step = max(1, FLAGGED // max(1, len(high.c)))
        for i in range(0, len(low.c), step):
            yield from a[i : i + step] @ b.T > 0
        return
    holder, starts = owner[np.argsort(of, kind="stable")], np.concatenate([[0], np.cumsum(held)])
    flags = np.zeros(len(high.c), bool)
    for i in range(len(low.c)):
        here = slice(low.o_at[i], low.o_at[i + 1])
        for k in at[here][ok[here]].tolist():
            flags[holder[starts[k] : starts[k + 1]]] = True
        yield flags
        flags[:] = False


def _meet(low: Block, high: Block, same: bool, apart: bool = False) -> Iterator[tuple[int, np.ndarray]]:
    """(i, js): each class of one block with the classes of the other that it is linked to, or
    is not linked to (``apart``); with itself a block gives each pair once."""
    for i, flags in enumerate(_flags(low, high)):
        js = np.flatnonzero(~flags if apart else flags)
        yield i, js[js > i] if same else js


def weighed(classes: DataFrame) -> DataFrame:
    """Classes with their number of members, ``w``."""
    return classes if "w" in classes.columns else classes.withColumn("w", F.size("xs").cast("long"))


def _each_meeting(classes: DataFrame, make: Callable[[Block, Block, bool], Iterator[pa.RecordBatch]], schema: str, members: bool = False) -> DataFrame:
    classes = weighed(classes)
    if not members:  # sizes are enough
        classes = classes.withColumn("xs", F.array().cast("array<bigint>"))
    rows, pairs = classes.select(F.explode("os").alias("o"), F.col("w").alias("n")).groupBy("o").agg(F.count("*").alias("r"), F.sum("n").alias("n")).agg(F.sum("r"), F.sum(F.expr("n * (n - 1) div 2"))).first()
    p = max(1, -(-(rows or 0) // HELD), min(BLOCKS, int((2 * (pairs or 0) / PAIRS) ** 0.5)))
    block, other = F.pmod(F.xxhash64("c"), F.lit(p)), F.explode(F.sequence(F.lit(0), F.lit(p - 1)))
    dealt = classes.select("c", "w", "xs", "os", block.alias("b"), other.alias("q"))
    dealt = dealt.select((F.least("b", "q") * p + F.greatest("b", "q")).cast("int").alias("task"), F.col("b").cast("int").alias("b"), "c", "w", "xs", "os")
    dealt = dealt.repartition(p * (p + 1) // 2, "task").sortWithinPartitions("task")

    def block_of(parts: list[tuple], b: int) -> Block:
        mine = [x for x in parts if x[0] == b]
        c, w = (np.array([x[i] for x in mine], np.int64) for i in (1, 2))
        return Block(c, w, *[_flat([x[i] for x in mine]) for i in (3, 4)])

    def met(task: int, parts: list[tuple]) -> Iterator[pa.RecordBatch]:
        low, high = block_of(parts, task // p), block_of(parts, task % p)
        yield from make(low, high, task // p == task % p)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, parts = None, []
        for t in batches:
            task, b, c, w = [t.column(i).to_pylist() for i in range(4)]
            (x_at, xs), (o_at, os) = [(t.column(i).offsets.to_numpy(), t.column(i).values.to_numpy()) for i in (4, 5)]
            for i in range(t.num_rows):
                if task[i] != now and parts:
                    yield from met(now, parts)
                    parts = []
                now = task[i]
                parts.append((b[i], c[i], w[i], xs[x_at[i] : x_at[i + 1]], os[o_at[i] : o_at[i + 1]]))
        if parts:
            yield from met(now, parts)

    return dealt.mapInArrow(run, schema)


def _batches(found: Iterator[tuple[np.ndarray, ...]], names: list[str]) -> Iterator[pa.RecordBatch]:
    """Arrow batches of about ``BATCH`` rows."""
    held, size = [], 0
    for columns in found:
        held.append(columns)
        size += len(columns[0])
        if size >= BATCH:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x), pa.int64()) for x in zip(*held, strict=True)], names)
            held, size = [], 0
    if held:
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x), pa.int64()) for x in zip(*held, strict=True)], names)


def pairs(members: DataFrame) -> DataFrame:
    """(u, v), u < v: each linked pair of members once."""

    def made(low: Block, high: Block, same: bool) -> Iterator[tuple[np.ndarray, ...]]:
        for i, js in _meet(low, high, same):
            own, near = low.xs[low.x_at[i] : low.x_at[i + 1]], high.members(js)
            if same and len(own) > 1:
                a, b = np.triu_indices(len(own), 1)
                yield own[a], own[b]
            step = max(1, BATCH // max(1, len(near)))
            for at in range(0, len(own) if len(near) else 0, step):
                some = own[at : at + step]
                u, v = np.repeat(some, len(near)), np.tile(near, len(some))
                yield np.minimum(u, v), np.maximum(u, v)

    return _each_meeting(merged(members, 1000), lambda *x: _batches(made(*x), ["u", "v"]), "u long, v long", members=True)


def links(classes: DataFrame, apart: bool = False) -> DataFrame:
    """(u, v): each linked pair of classes once, or each pair that is not linked (``apart``)."""

    def made(low: Block, high: Block, same: bool) -> Iterator[tuple[np.ndarray, ...]]:
        for i, js in _meet(low, high, same, apart):
            yield np.full(len(js), low.c[i]), high.c[js]

    return _each_meeting(classes, lambda *x: _batches(made(*x), ["u", "v"]), "u long, v long")


def degrees(classes: DataFrame) -> DataFrame:
    """(c, vertices, degree, linked): the members of each class, the links that each of them
    has, and the classes that it is linked to."""

    def made(low: Block, high: Block, same: bool) -> Iterator[tuple[np.ndarray, ...]]:
        mine, theirs = low.size - 1 if same else np.zeros(len(low.c), np.int64), np.zeros(len(high.c), np.int64)
        near, far = np.zeros(len(low.c), np.int64), np.zeros(len(high.c), np.int64)
        for i, js in _meet(low, high, same):
            mine[i] += int(high.size[js].sum())
            theirs[js] += low.size[i]
            near[i] += len(js)
            far[js] += 1
        yield low.c, low.size, mine, near
        yield high.c, high.size, theirs, far

    names = ["c", "vertices", "degree", "linked"]
    each = _each_meeting(classes, lambda *x: _batches(made(*x), names), ", ".join(f"{n} long" for n in names))
    return each.groupBy("c").agg(F.first("vertices").alias("vertices"), F.sum("degree").alias("degree"), F.sum("linked").alias("linked"))


def split(classes: DataFrame, heavy: int | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Links by the size of their groups. Heavy groups link classes through what they hold of
    them: (c, w, os) of all members of the same heavy groups. The others link in proportion to
    their members: (u, v, wu, wv, hu, hv) of the classes that share one and no heavy group.
    The first table, (c, w, h), gives each class and the heavy class it is in, if any."""
    each = weighed(classes).select("c", "w", F.explode("os").alias("o"))
    held = each.groupBy("o").agg((F.sum("w") >= (heavy or HEAVY)).alias("heavy"))
    each = each.join(held, "o")
    parts = each.groupBy("c").agg(F.first("w").alias("w"), *[F.sort_array(F.collect_list(F.when(some, F.col("o")))).alias(n) for n, some in (("hs", F.col("heavy")), ("ls", ~F.col("heavy")))])
    parts = stored(parts, "parts")
    sets = stored(parts.where("size(hs) > 0").groupBy("hs").agg(F.min("c").alias("c"), F.sum("w").alias("w")).select("c", "w", F.col("hs").alias("os")), "heavy")
    own = stored(parts.join(sets.select(F.col("c").alias("h"), F.col("os").alias("hs")), "hs", "left").select("c", "w", "h", "hs"), "classes")
    few = parts.select("c", F.explode("ls").alias("o"))
    pairs = few.withColumnRenamed("c", "u").join(few.withColumnRenamed("c", "v"), "o").where("u < v").select("u", "v").distinct()
    for x in ("u", "v"):
        pairs = pairs.join(own.toDF(x, f"w{x}", f"h{x}", f"hs{x}"), x)
    near = pairs.where(~F.arrays_overlap("hsu", "hsv")).select("u", "v", "wu", "wv", "hu", "hv")
    return own.drop("hs"), sets, stored(near, "near")


def _blocks_of(t: pa.Table, c: str, os: str) -> tuple[np.ndarray, list[np.ndarray]]:
    """The different classes of a column, and their groups."""
    names, first = np.unique(t.column(c).to_numpy(), return_index=True)
    return names, [np.array(x, np.int64) for x in t.column(os).take(pa.array(first)).to_pylist()]


def common(sets: DataFrame, pairs: DataFrame) -> DataFrame:
    """One row: mappings, the members linked to both classes of a pair, over the pairs (u, v, n) of
    classes that are not linked, each n times."""
    p, r = max(1, -(-sets.count() // TOLD)), max(1, -(-pairs.count() // ASKED))
    every = lambda k: F.explode(F.sequence(F.lit(0), F.lit(k - 1)))
    for x in ("u", "v"):
        pairs = pairs.join(sets.select(F.col("c").alias(x), F.col("os").alias(f"o{x}")), x)
    asked = pairs.select(F.lit(1).alias("role"), "u", "v", "n", "ou", "ov", F.pmod(F.xxhash64("u", "v"), F.lit(r)).alias("i"), every(p).alias("j"))
    told = sets.select(F.lit(0).alias("role"), F.col("c").alias("u"), F.col("c").alias("v"), F.col("w").alias("n"), F.col("os").alias("ou"), F.col("os").alias("ov"), every(r).alias("i"), F.pmod(F.xxhash64("c"), F.lit(p)).alias("j"))
    dealt = told.unionByName(asked).withColumn("task", (F.col("i") * p + F.col("j")).cast("int")).drop("i", "j")

    def run(t: pa.Table) -> pa.Table:
        role = t.column("role").to_numpy()
        told, asked = [t.filter(pa.array(role == x)) for x in (0, 1)]
        total = 0
        if told.num_rows and asked.num_rows:
            high = Block.bare(told.column("u").to_numpy(), told.column("n").to_numpy(), [np.array(x, np.int64) for x in told.column("ou").to_pylist()])
            both = pa.concat_tables([asked.select(["u", "ou"]), asked.select(["v", "ov"]).rename_columns(["u", "ou"])])
            names, os = _blocks_of(both, "u", "ou")
            flags = np.array([x.copy() for x in _flags(Block.bare(names, names, os), high)])
            a, b = [np.searchsorted(names, asked.column(x).to_numpy()) for x in ("u", "v")]
            n, step = asked.column("n").to_numpy(), max(1, FLAGGED // len(high.c))
            for at in range(0, len(a), step):
                some = slice(at, at + step)
                total += int(((flags[a[some]] & flags[b[some]]) @ high.size * n[some]).sum())
        return pa.table({"mappings": pa.array([total], pa.int64())})

    return dealt.repartition(p * r, "task").groupBy("task").applyInArrow(run, "mappings long").agg(F.coalesce(F.sum("mappings"), F.lit(0)).alias("mappings"))


def linked_around(sets: DataFrame, near: DataFrame) -> DataFrame:
    """One row: mappings, the linked pairs among the members (class u, w of them) that stand
    around each centre c, over (c, n, u, w), each n times. Members of one class are linked."""
    rows = near.join(sets.select(F.col("c").alias("u"), "os"), "u")
    tasks = max(1, min(4096, near.count() // 100_000))

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by("c").combine_chunks()
        c, n, u, w = [t.column(x).to_numpy() for x in ("c", "n", "u", "w")]
        os, total = t.column("os").to_pylist(), 0
        ends = np.flatnonzero(np.append(np.diff(c), 1)) + 1
        for a, z in zip([0, *ends[:-1].tolist()], ends.tolist(), strict=True):
            found = int((w[a:z] * (w[a:z] - 1) // 2).sum())
            if z - a > 1:
                block = Block.bare(u[a:z], w[a:z], [np.array(x, np.int64) for x in os[a:z]])
                found += sum(int(w[a + i] * w[a:z][js].sum()) for i, js in _meet(block, block, True))
            total += int(n[a]) * found
        return pa.table({"mappings": pa.array([total], pa.int64())})

    dealt = rows.select(F.pmod(F.xxhash64("c"), F.lit(tasks)).cast("int").alias("task"), "c", "n", "u", "w", "os")
    return dealt.groupBy("task").applyInArrow(run, "mappings long").agg(F.coalesce(F.sum("mappings"), F.lit(0)).alias("mappings"))
