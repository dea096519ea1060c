"""Raw edge tables (u, v) from relational tables, files and generators."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..scratch import stored
from . import groups

RAW = "u long, v long"


def copart(lineitem: DataFrame, min_qty: float | None = None, min_support: int = 1) -> DataFrame:
    """Parts that share at least ``min_support`` orders, over lines of a quantity of
    at least ``min_qty``."""
    lines = lineitem if min_qty is None else lineitem.where(F.col("l_quantity") >= min_qty)
    parts = lines.select("l_orderkey", "l_partkey").distinct()
    a = parts.select("l_orderkey", F.col("l_partkey").alias("u"))
    b = parts.select("l_orderkey", F.col("l_partkey").alias("v"))
    pairs = a.join(b, "l_orderkey").where("u < v").select("u", "v")
    if min_support > 1:
        return pairs.groupBy("u", "v").agg(F.count("*").alias("n")).where(F.col("n") >= min_support).select("u", "v")
    return pairs.distinct()


def doc_lines(documents: DataFrame, min_chars: int = 20, max_docs: int | None = 50) -> DataFrame:
    """Documents that share a line of at least ``min_chars`` characters found in 2 to
    ``max_docs`` documents; with None, in any number of them. An edge table grows with
    the square of a line's documents, so ``line_members`` holds the same links in one
    row a document and line."""
    if max_docs is None:
        return groups.pairs(line_groups(documents, min_chars))
    shared = line_groups(documents, min_chars).select(F.col("x").alias("doc_id"), F.col("o").alias("line")).distinct()
    fit = shared.groupBy("line").agg(F.count("*").alias("n")).where((F.col("n") >= 2) & (F.col("n") <= max_docs)).select("line")
    shared = shared.join(fit, "line")
    a = shared.select("line", F.col("doc_id").alias("u"))
    b = shared.select("line", F.col("doc_id").alias("v"))
    return a.join(b, "line").where("u < v").select("u", "v").distinct()


def line_groups(documents: DataFrame, min_chars: int = 20) -> DataFrame:
    """(o, x): the lines of at least ``min_chars`` characters, by md5, and their documents."""
    lines = documents.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where(F.length("line") >= min_chars)
    return lines.select(F.md5("line").alias("o"), F.col("doc_id").alias("x"))


def line_members(documents: DataFrame, min_chars: int = 20) -> DataFrame:
    """(doc_id, line) of every line of at least ``min_chars`` characters found in two
    or more documents, by its md5: two documents are linked when they share one."""
    lines = documents.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where(F.length("line") >= min_chars)
    lines = lines.select("doc_id", F.md5("line").alias("line")).where("doc_id is not null").distinct()
    shared = lines.groupBy("line").agg(F.count("*").alias("n")).where("n >= 2").select("line")
    return lines.join(shared, "line").select("doc_id", "line")


def bipartite(left: DataFrame, right: DataFrame, key: str, l_id: str, r_id: str) -> DataFrame:
    """An edge for every matching row of two tables; ids 2 l and 2 r + 1."""
    return left.join(right, key).select((2 * F.col(l_id)).cast("long").alias("u"), (2 * F.col(r_id) + 1).cast("long").alias("v")).distinct()


def customer_supplier(orders: DataFrame, lineitem: DataFrame) -> DataFrame:
    left = orders.select(F.col("o_orderkey").alias("k"), "o_custkey")
    right = lineitem.select(F.col("l_orderkey").alias("k"), "l_suppkey").distinct()
    return bipartite(left, right, "k", "o_custkey", "l_suppkey")


def customer_nation(customer: DataFrame) -> DataFrame:
    return customer.select((2 * F.col("c_custkey")).cast("long").alias("u"), (2 * F.col("c_nationkey") + 1).cast("long").alias("v")).distinct()


def user_chain(events: DataFrame, bucket: str = "hour") -> DataFrame:
    """Users of consecutive events by (ts, user_id). Inside a time bucket a window
    finds the predecessor; a bucket's first event follows the last of the bucket
    before it, found among one row a bucket."""
    e = events.select("ts", F.col("user_id").cast("long").alias("user_id"), F.date_trunc(bucket, "ts").alias("b"))
    own = Window.partitionBy("b").orderBy("ts", "user_id")
    inside = e.withColumn("p", F.lag("user_id").over(own)).where("p is not null").select(F.col("p").alias("u"), F.col("user_id").alias("v"))
    at = F.struct("ts", "user_id")
    ends = e.groupBy("b").agg(F.min(at).alias("first"), F.max(at).alias("last"))
    over = Window.orderBy("b")  # one row a bucket, not a row an event
    across = ends.withColumn("p", F.lag("last").over(over)).where("p is not null").select(F.col("p.user_id").alias("u"), F.col("first.user_id").alias("v"))
    both = inside.unionByName(across).where("u <> v")
    return both.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct()


def user_window(events: DataFrame, width: str = "1 hour") -> DataFrame:
    """Users seen in the same time window (an extension)."""
    seen = events.select(F.window("ts", width).alias("w"), F.col("user_id").cast("long").alias("x")).distinct()
    # A time without a zone is read by its fields: a cast would fold the hours that a zone leaves out.
    fields = F.unix_date(F.to_date("w.start")) * F.lit(86_400_000_000) + F.hour("w.start") * F.lit(3_600_000_000) + F.minute("w.start") * F.lit(60_000_000) + (F.extract(F.lit("SECOND"), "w.start") * 1_000_000).cast("long")
    o = fields if events.schema["ts"].dataType.typeName() == "timestamp_ntz" else F.unix_micros("w.start")
    return meeting_pairs(seen.where("w is not null and x is not null").select(o.alias("o"), "x"))


def meeting_pairs(members: DataFrame, held: int = 500_000) -> DataFrame:
    """(u, v), u < v: distinct members x that share a group o, of distinct rows (o, x). Two
    blocks of members meet in a task, which gives each pair once however many groups hold
    it, so no pair is shuffled and hot groups are spread."""
    members = stored(members, "members")
    rows = members.count()
    p = max(1, -(-rows // held), min(6, rows // 20_000))
    block = F.pmod(F.xxhash64("x"), F.lit(p))
    o = F.explode(F.sequence(F.lit(0), F.lit(p - 1))).alias("p2")
    dealt = members.select("o", "x", block.alias("p1"), o).select("o", "x", "p1", (F.least("p1", "p2") * p + F.greatest("p1", "p2")).alias("task"))
    dealt = dealt.repartition(p * (p + 1) // 2, "task").sortWithinPartitions("task")

    def met(task: int, o: np.ndarray, x: np.ndarray, at: np.ndarray) -> Iterator[pa.RecordBatch]:
        low, high = at == task // p, at == task % p
        names, code = np.unique(x[high], return_inverse=True)
        groups, of = np.unique(o[high], return_inverse=True)
        code = code[np.argsort(of, kind="stable")]  # the other block's members by group
        starts = np.searchsorted(np.sort(of), np.arange(len(groups) + 1))
        xs, os_ = x[low], o[low]
        order = np.argsort(xs, kind="stable")
        xs, os_ = xs[order], os_[order]
        ends = np.flatnonzero(np.append(np.diff(xs), 1)) + 1
        flags = np.zeros(len(names), bool)
        first, out, size = 0, [], 0
        for end in ends.tolist():
            g = np.searchsorted(groups, os_[first:end])
            for k in g[groups[np.minimum(g, len(groups) - 1)] == os_[first:end]].tolist() if len(groups) else ():
                flags[code[starts[k] : starts[k + 1]]] = True
            found = names[flags]
            flags[:] = False
            u = int(xs[first])
            found = found[found > u] if task // p == task % p else found
            out.append((np.minimum(found, u), np.maximum(found, u)))
            size, first = size + len(found), end
            if size > 200_000 or end == len(xs):
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([c[i] for c in out]), pa.int64()) for i in (0, 1)], ["u", "v"])
                out, size = [], 0

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, parts = None, []
        for b in batches:
            columns = [b.column(b.schema.get_field_index(c)).to_numpy() for c in ("task", "o", "x", "p1")]
            cuts = np.flatnonzero(np.diff(columns[0])) + 1
            for a, z in zip([0, *cuts.tolist()], [*cuts.tolist(), b.num_rows], strict=True):
                if a == z:
                    continue
                if task is not None and columns[0][a] != task:
                    yield from met(task, *[np.concatenate(c) for c in zip(*parts, strict=True)])
                    parts = []
                task = int(columns[0][a])
                parts.append([c[a:z] for c in columns[1:]])
        if parts:
            yield from met(task, *[np.concatenate(c) for c in zip(*parts, strict=True)])

    return dealt.mapInArrow(run, RAW)


def knn(embeddings: DataFrame, k: int = 5, block: int = 4096) -> DataFrame:
    """Each vector's ``k`` most cosine-similar others (ties by id), symmetric. Blocks
    of vectors meet pairwise; each pair of blocks returns its k best a vector, so
    only k rows a vector and block reach the final ranking."""
    rows = embeddings.select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").cast("array<double>").alias("e")).where("e is not null")
    blocks = max(1, -(-rows.count() // block))
    own = F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")
    asked = rows.withColumn("q", own).withColumn("t", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumn("side", F.lit(0))
    told = rows.withColumn("t", own).withColumn("q", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).withColumn("side", F.lit(1))

    def best(t: pa.Table) -> pa.Table:
        side, ids = t.column("side").to_numpy(), t.column("id").to_numpy()
        x = np.array(t.column("e").to_pylist(), np.float64)
        x /= np.maximum(np.sqrt((x * x).sum(1, keepdims=True)), 1e-300)
        a, b = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        b = b[np.argsort(ids[b], kind="stable")]
        if not len(a) or not len(b):
            return pa.table({"u": pa.array([], pa.int64()), "v": pa.array([], pa.int64()), "s": pa.array([], pa.float64())})
        sim = x[a] @ x[b].T
        sim[ids[a][:, None] == ids[b][None]] = -np.inf
        top = np.argsort(-sim, axis=1, kind="stable")[:, :k]
        u, v = np.repeat(ids[a], top.shape[1]), ids[b][top].ravel()
        s = np.take_along_axis(sim, top, 1).ravel()
        ok = np.isfinite(s)
        return pa.table({"u": u[ok], "v": v[ok], "s": s[ok]})

    met = asked.unionByName(told).groupBy("q", "t").applyInArrow(best, "u long, v long, s double")
    order = Window.partitionBy("u").orderBy(F.desc("s"), "v")  # at most k rows a block
    near = met.withColumn("r", F.row_number().over(order)).where(F.col("r") <= k)
    return near.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct()


def uniform(spark: SparkSession, n: int, p: float, seed: int = 1) -> DataFrame:
    """The model's random graph: a pair stays when its keyed hash falls under p. The
    pairs are the integers below n (n - 1) / 2, so no cross join is needed."""
    t = F.col("id")
    j = F.floor((1 + F.sqrt(1 + 8 * t.cast("double"))) / 2).cast("long")
    row = spark.range(n * (n - 1) // 2).withColumn("j", j)
    # The square root of a large number is rounded; whole numbers settle it.
    below = F.expr("j * (j - 1) div 2")
    row = row.withColumn("j", F.when(below > t, F.col("j") - 1).when(below + F.col("j") <= t, F.col("j") + 1).otherwise(F.col("j")))
    i = t - below
    keep = F.pmod(F.xxhash64(F.lit(seed), t), F.lit(1 << 30)) < int(p * (1 << 30))
    return row.where(keep).select(i.alias("u"), F.col("j").alias("v"))


def read_edge_list(spark: SparkSession, path: str, fmt: str = "text") -> DataFrame:
    """Edge lists: ``text`` (two ids a line, # comments), ``csv``, ``json`` or
    ``parquet`` with columns u and v (an extension)."""
    if fmt == "text":
        line = F.trim("value")
        parts = F.split(line, r"\s+")
        rows = spark.read.text(path).where((line != "") & ~line.startswith("#"))
        return rows.select(parts[0].cast("long").alias("u"), parts[1].cast("long").alias("v"))
    if fmt == "csv":
        return spark.read.csv(path, schema=RAW, header=True)
    if fmt == "json":
        return spark.read.json(path, schema=RAW)
    if fmt == "parquet":
        return spark.read.parquet(path).select(F.col("u").cast("long"), F.col("v").cast("long"))
    raise ValueError(f"unknown format {fmt!r}")


# Literal graphs of the worked examples.
TINY: dict[str, list[tuple[int, int]]] = {
    "tiny_rect": [(2, 3), (2, 8), (3, 7), (7, 8)],
    "tiny_tailed": [(1, 2), (2, 3), (1, 3), (3, 4)],
    "tiny_k7m": [(i, j) for i in range(7) for j in range(i) if (i, j) != (6, 5)] + [(0, 10), (1, 11), (2, 12)],
    "tiny_k5": [(i, j) for i in range(5) for j in range(i)],
    "tiny_k6": [(i, j) for i in range(6) for j in range(i)],
    "tiny_star": [(0, i) for i in range(1, 11)],
    "tiny_bowtie": [(0, 1), (1, 2), (0, 2), (2, 3), (3, 4), (2, 4)],
    "twin_guard": [(0, 1), (0, 2)],
    "tiny_empty": [],
}


def tiny(spark: SparkSession, name: str) -> DataFrame:
    return spark.createDataFrame(TINY[name], RAW)


def from_tables(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A named stand-in graph from the given tables."""
    t = lambda x: spark.read.parquet(f"{sf_dir}/{x}.parquet")
    if name == "copart_q45":
        return copart(t("lineitem"), min_qty=45)
    if name == "copart_s2":
        return copart(t("lineitem"), min_support=2)
    if name == "copart_all":
        return copart(t("lineitem"))
    if name == "doc_lines":
        return doc_lines(t("documents"))
    if name == "doc_lines_all":
        return doc_lines(t("documents"), max_docs=None)
    if name == "cust_supp":
        return customer_supplier(t("orders"), t("lineitem"))
    if name == "cust_nation":
        return customer_nation(t("customer"))
    if name == "user_chain":
        return user_chain(t("events"))
    if name == "emb_knn":
        return knn(t("embeddings"))
    if name in TINY:
        return tiny(spark, name)
    raise ValueError(f"unknown graph {name!r}")
