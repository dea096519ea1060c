"""Tables in the cluster's shared folder, and global row numbers.

``stored`` writes a DataFrame below ``spark.checkpoint.dir`` and reads it back: that
cuts lineage, survives the loss of any executor, and is only ever read by Spark.
``with_global_index`` numbers rows in a total order with a range sort and one offset
a partition; there is no window over a single partition.
"""

from __future__ import annotations

import atexit
import gc
import re
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Scratch paths of this process and the sessions they belong to.
_made: dict[str, SparkSession] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir``, or a temporary
    one where a single-machine session names none."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    if not re.fullmatch(r"local(\[.*\])?", spark.conf.get("spark.master", "local")):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    own = spark.conf.get("knotwork.scratch", None)
    if not own:
        own = tempfile.mkdtemp(prefix="knotwork-")
        spark.conf.set("knotwork.scratch", own)
    return own


def new_path(spark: SparkSession, name: str) -> str:
    path = f"{shared_dir(spark).rstrip('/')}/knotwork/{name}-{uuid.uuid4().hex}"
    _made[path] = spark
    return path


def exists(spark: SparkSession, path: str) -> bool:
    """Whether the shared store holds a path, asked of Spark's own file system."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).exists(where)


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` once to the shared folder and read it back (same schema)."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def release(spark: SparkSession | None = None) -> None:
    """Delete the scratch tables of a session (all sessions by default). Call it
    once the results that read them have been consumed."""
    _delete([path for path, owner in _made.items() if spark is None or owner is spark])


def _delete(paths: list[str]) -> None:
    for path in paths:
        try:
            owner = _made[path]
            where = owner._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(owner._jsparkSession.sessionState().newHadoopConf()).delete(where, True)
        except Exception:  # the JVM may be gone at interpreter exit
            pass
        _made.pop(path, None)


@contextmanager
def passing(spark: SparkSession) -> Iterator[None]:
    """Scratch tables made inside are deleted at the end, and the shuffles of plans that
    nothing holds any more."""
    before = set(_made)
    try:
        yield
    finally:
        _delete([path for path, owner in _made.items() if path not in before and owner is spark])
        drop_shuffles(spark)


def drop_shuffles(spark: SparkSession) -> None:
    """Spark deletes a shuffle's files once its plan is collected; a driver with a roomy heap
    would keep those of all runs before."""
    gc.collect()
    spark._jvm.System.gc()


atexit.register(release)


def with_global_index(df: DataFrame, order: list[Column], index: str, name: str) -> tuple[DataFrame, int]:
    """``df`` with a gapless 0-based ``index`` in the given total order, and its
    row count. The order's rows are dealt by range (a hot key is split because
    the order ends in a unique column), numbered inside each partition, and
    lifted by the partitions' offsets, which are as many as the partitions."""
    spark = df.sparkSession
    n_parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    seq = F.monotonically_increasing_id()
    rows = stored(
        df.repartitionByRange(n_parts, *order).sortWithinPartitions(*order).withColumn("_seq", seq), name
    )
    part = F.shiftright("_seq", 33)
    counts = sorted((r["p"], r["n"]) for r in rows.groupBy(part.alias("p")).agg(F.count("*").alias("n")).collect())
    offsets, total = [], 0
    for p, n in counts:
        offsets.append((p, total))
        total += n
    lift = spark.createDataFrame(offsets or [(0, 0)], "_p long, _lift long")
    out = (
        rows.withColumn("_p", part.cast("long"))
        .join(F.broadcast(lift), "_p")  # one row per partition
        .withColumn(index, F.col("_lift") + F.col("_seq").bitwiseAND((1 << 33) - 1))
        .drop("_p", "_lift", "_seq")
    )
    return out, total
