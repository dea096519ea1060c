"""Signed incremental counts over a stream of edges (an extension).

Matching is induced, so a new edge creates instances and destroys others; both kinds
contain its two endpoints. For a batch of new edges only the instances that contain
both ends of a new edge change, and those lie within k - 1 steps of its ends. Each
micro-batch therefore counts the pattern in that neighbourhood before and after by the
planner's plan: instances without a new edge are in both counts, so the difference is the
change, and nothing is listed. It adds the difference, and appends the edges to the stored
state under the batch's own id, so a batch that is retried after a failure writes the same
state again.

Users who meet in windows are linked through these, and their edges grow with the square of a
window's users. So patterns of three labels are counted on the presences (window, user), which
are the state of such a stream, and no edge is made or stored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.pattern import Pattern, parse
from ..operators import mine, motifs
from ..operators.graph import GraphStore, normalise
from ..scratch import exists, stored
from ..sources import graphs, groups

EDGE = "src long, dst long"


def window_edges(events: DataFrame, unit: str = "hour", late: str = "1 hour") -> DataFrame:
    """(w, user_id): deduplicated presence of users in calendar units of an event
    stream, late events beyond the watermark dropped. Pairs are made per
    micro-batch."""
    seen = events.select(F.date_trunc(unit, "ts").cast("timestamp").alias("w"), F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").cast("long").alias("user_id"))
    return seen.withWatermark("ts", late).dropDuplicatesWithinWatermark(["w", "user_id"])


def _near(edges: DataFrame, seeds: DataFrame, steps: int) -> DataFrame:
    """The edges among vertices within ``steps`` of the seed vertices (id)."""
    reached = seeds.distinct()
    for _ in range(steps):
        step = edges.join(reached, edges["src"] == reached["id"], "left_semi").select(F.col("dst").alias("id"))
        reached = stored(reached.unionByName(step).distinct(), "reached")
    a, b = reached.select(F.col("id").alias("src")), reached.select(F.col("id").alias("dst"))
    return edges.join(a, "src", "left_semi").join(b, "dst", "left_semi")


def counted(edges: DataFrame, pattern: Pattern) -> int:
    """The instances of a pattern among symmetric pairs."""
    return mine.count(GraphStore.build(edges.toDF("u", "v"), name="near"), pattern).first()["cnt"]


def counted_meeting(members: DataFrame, pattern: Pattern) -> int:
    """The instances of a pattern of three labels among members x that share a group o."""
    n = len(pattern.edges)
    return motifs.count_merged(groups.merged(members)).where(F.col("edges") == n).first()["cnt"]


def _meeting_near(members: DataFrame, seeds: DataFrame, steps: int) -> DataFrame:
    """The rows (o, x) of members within ``steps`` meetings of the seeds (x)."""
    reached = seeds.distinct()
    for _ in range(steps):
        at = members.join(reached, "x", "left_semi").select("o").distinct()
        reached = stored(members.join(at, "o", "left_semi").select("x").distinct(), "reached")
    return members.join(reached, "x", "left_semi")


class Counter:
    """Keeps a pattern's count while edges arrive in batches."""

    def __init__(self, spark: SparkSession, path: str, pattern: str | Pattern):
        self.spark, self.path = spark, path
        self.pattern = parse(pattern) if isinstance(pattern, str) else pattern

    def _read(self, kind: str, schema: str, before: int | None = None) -> DataFrame:
        if not exists(self.spark, f"{self.path}/{kind}"):
            return self.spark.createDataFrame([], schema)
        all_ = self.spark.read.schema(schema + ", batch long").parquet(f"{self.path}/{kind}")
        if before is not None:
            all_ = all_.where(F.col("batch") < before)
        return all_.drop("batch")

    def edges(self, before: int | None = None) -> DataFrame:
        return self._read("edges", EDGE, before)

    def count(self) -> DataFrame:
        """One row: cnt."""
        return self._read("deltas", "delta long").agg(F.coalesce(F.sum("delta"), F.lit(0)).alias("cnt"))

    def apply(self, raw: DataFrame, batch: int) -> None:
        """One micro-batch of raw (u, v) edges."""
        old = self.edges(before=batch)
        fresh = stored(normalise(raw).join(old, ["src", "dst"], "left_anti"), "fresh")
        if not fresh.isEmpty():
            after = old.unionByName(fresh) if old.isEmpty() else _near(old.unionByName(fresh), fresh.select(F.col("src").alias("id")), self.pattern.k - 1)
            after = stored(after, "after")
            before = stored(after.join(fresh, ["src", "dst"], "left_anti"), "before")
            delta = counted(after, self.pattern) - (0 if before.isEmpty() else counted(before, self.pattern))
        else:
            delta = 0
        fresh.write.mode("overwrite").parquet(f"{self.path}/edges/batch={batch}")
        self._add(delta, batch)

    def _add(self, delta: int, batch: int) -> None:
        self.spark.createDataFrame([(delta,)], "delta long").write.mode("overwrite").parquet(f"{self.path}/deltas/batch={batch}")

    def apply_meeting(self, known: DataFrame, now: DataFrame, batch: int) -> None:
        """One micro-batch of presences (o, x) beside those of before: whatever changes holds
        a user with a new presence."""
        fresh = stored(now.distinct().join(known, ["o", "x"], "left_anti"), "fresh")
        delta = 0
        if not fresh.isEmpty():
            every = stored(known.unionByName(fresh), "every")
            after = stored(_meeting_near(every, fresh.select("x"), self.pattern.k - 1), "after")
            before = after.join(fresh, ["o", "x"], "left_anti")
            if after.count() == every.count():  # all that came before: its count is known
                old = self._read("deltas", "delta long", batch).agg(F.coalesce(F.sum("delta"), F.lit(0))).first()[0]
            else:
                old = 0 if before.isEmpty() else counted_meeting(before, self.pattern)
            delta = counted_meeting(after, self.pattern) - old
        self._add(delta, batch)

    def attach(self, seen: DataFrame, checkpoint: str):
        """Start on a stream of (w, user_id) presences: users of a window meet each other
        and those of the same window that came before."""

        def each(batch: DataFrame, batch_id: int) -> None:
            now = stored(batch.select("w", "user_id"), "seen")
            known = self._read("seen", "w timestamp, user_id long", before=batch_id)
            member = lambda df: df.where("w is not null and user_id is not null").select(F.unix_micros("w").alias("o"), F.col("user_id").alias("x"))
            if self.pattern.k == 3:
                self.apply_meeting(member(known).distinct(), member(now), batch_id)
                now.write.mode("overwrite").parquet(f"{self.path}/seen/batch={batch_id}")
                return
            every = known.unionByName(now).distinct()
            touched = every.join(now.select("w").distinct(), "w", "left_semi")  # windows without a new user have no new pair
            self.apply(graphs.meeting_pairs(member(touched)), batch_id)
            now.write.mode("overwrite").parquet(f"{self.path}/seen/batch={batch_id}")

        return seen.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def run_events(spark: SparkSession, events_path: str, path: str, pattern: str, unit: str = "day") -> DataFrame:
    """Stream a folder or file of events to the end and return the count."""
    known = spark.read.parquet(events_path)
    reader = spark.readStream.schema(known.schema).option("maxFilesPerTrigger", 1)
    folder, _, name = events_path.rstrip("/").rpartition("/")
    if any(f.endswith(f"/{name}") for f in known.inputFiles()):  # one file: its folder, filtered
        stream = reader.option("pathGlobFilter", name).parquet(folder)
    else:
        stream = reader.parquet(events_path)
    counter = Counter(spark, path, pattern)
    counter.attach(window_edges(stream, unit, "3650 days"), f"{path}/checkpoint").awaitTermination()
    return counter.count()
