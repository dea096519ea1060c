"""Shared plumbing of the training-data operators.

* ``documents``/``pick``: column-pruned views that tolerate extra columns, so a
  clashing name in the caller's table can never reach an operator's plan.
* ``stored``, ``with_global_index``: the library's tables in the shared folder and
  its distributed row numbers, under the names the operators use.
* ``runs``: groups of a sorted stream of Arrow batches.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..scratch import new_path, release, stored, with_global_index

__all__ = ["documents", "keep_rows", "new_path", "partitions_for", "pick", "release", "runs", "stored", "table", "tidy", "utf8", "with_global_index"]


def pick(df: DataFrame, **types: str) -> DataFrame:
    """Exactly the named columns, cast; a column that is missing is null."""
    have = set(df.columns)
    return df.select(*[(F.col(f"`{c}`") if c in have else F.lit(None)).cast(t).alias(c) for c, t in types.items()])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def documents(df: DataFrame) -> DataFrame:
    return pick(df, doc_id="long", text="string")


def keep_rows(docs: DataFrame, grouped: DataFrame, group: str) -> DataFrame:
    """``docs`` with one row of each group, all columns. ``grouped`` has the rows of
    groups by (doc_id, mark, kept): ``mark`` is the xxhash64 of the text, ``kept`` marks
    the rows of the id that stays. Of those the smallest mark stays, and one of rows that
    repeat it. Rows are told apart by id and text, so a text under a repeated or a
    missing id is never lost; texts move once, to meet the rows that go."""
    win = stored(grouped.where("kept").groupBy(group).agg(F.min("mark").alias("win")), "winners")
    judged = stored(grouped.join(win, group).select("doc_id", "mark", (F.col("kept") & (F.col("mark") == F.col("win"))).alias("stays")), "judged")
    gone = judged.where("not stays").select(F.col("doc_id").alias("_gone_id"), F.col("mark").alias("_gone_mark")).distinct()
    twice = stored(judged.where("stays").groupBy(F.col("doc_id").alias("_gone_id"), F.col("mark").alias("_gone_mark")).count().where("count > 1").drop("count"), "twice")
    marked = docs.withColumn("_row_id", F.col("doc_id").cast("long")).withColumn("_row_mark", F.xxhash64(F.col("text").cast("string")))
    same = F.col("_row_id").eqNullSafe(F.col("_gone_id")) & (F.col("_row_mark") == F.col("_gone_mark"))
    # The same plan at every size: the rows that go are many on a large table.
    out = marked.join(gone.hint("merge"), same, "left_anti")
    if not twice.isEmpty():
        once = out.join(twice, same, "left_semi").dropDuplicates(["_row_id", "_row_mark"])
        out = out.join(twice, same, "left_anti").unionByName(once)
    return out.select(*[F.col(f"`{c}`") for c in docs.columns])


def utf8(batch: pa.RecordBatch, name: str = "text") -> list:
    """A text column as Python bytes (None for null), without decoding."""
    return batch.column(batch.schema.get_field_index(name)).cast(pa.large_binary()).to_pylist()


def tidy(run: Callable) -> Callable:
    """A ``mapInArrow`` function that hands freed memory back to the system when its
    task ends: Python workers live on, and stages share an executor's memory."""

    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except (OSError, AttributeError):  # another C library
                pass

    return wrapped


def partitions_for(rows: int, each: int, spark: SparkSession) -> int:
    """Partitions that hold about ``each`` rows, and at least Spark's own number."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-rows // each))


def runs(batches: Iterator[pa.RecordBatch], key: str) -> Iterator[pa.Table]:
    """Whole runs of equal ``key`` from batches sorted by it, joined across batch
    borders, several runs to a table. Callers bound the length of a run."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        at = batch.schema.get_field_index(key)
        values = batch.column(at)
        last = values[batch.num_rows - 1]
        cut = batch.num_rows
        while cut and values[cut - 1].equals(last):
            cut -= 1
        if held and cut == 0 and held[-1].column(at)[held[-1].num_rows - 1].equals(last):
            held.append(batch)
            continue
        held.append(batch.slice(0, cut))
        whole = pa.Table.from_batches([b for b in held if b.num_rows], schema=batch.schema)
        if whole.num_rows:
            yield whole
        held = [batch.slice(cut)]
    rest = [b for b in held if b.num_rows]
    if rest:
        yield pa.Table.from_batches(rest)
