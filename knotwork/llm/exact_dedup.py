"""Exact deduplication with a cuckoo-filter index of live digests.

Texts are equal when they are identical after each run of ASCII white space is
replaced by one space. The index is a table with one row per bucket of the digest
space: a cuckoo filter (short fingerprints, two candidate slots each) in front of
the bucket's stored keys. A lookup that misses the filter is certainly new and
never touches the keys; a hit is verified against the stored digests; a filter
that overflows is rebuilt at twice the size from those keys. ``CuckooIndex`` keeps
beside the buckets the live rows themselves, so deleting the row that stays of a
group makes the smallest live id the one that stays, and a digest leaves the filter
with its last row. It doubles its buckets when they hold more than ``per_bucket``
digests on average.

Batches are pre-aggregated before they are dealt to buckets, so a group of copies
that holds a third of the rows reaches its bucket as one row per Arrow batch.

Defined cases: null text counts as empty; empty texts are equal to each other; a
null doc_id is kept as a row of its own whose keep_id is the group's smallest
non-null id (null, and kept, where the group has no id); repeated rows are copies of
each other and all marked kept where their id is the smallest; very long texts are
read whole; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import documents, keep_rows, partitions_for, stored, tidy, utf8

_SPACE = frozenset(b" \t\n\r\x0b\x0c")
SLOTS, KICKS, FULLEST = 4, 200, 0.94


def normalise(text: bytes | None) -> bytes:
    """Each run of ASCII white space as one space; null as empty."""
    if not text:
        return b""
    inner = b" ".join(text.split())
    if not inner:
        return b" "
    return (b" " if text[0] in _SPACE else b"") + inner + (b" " if text[-1] in _SPACE else b"")


class CuckooFilter:
    """Partial-key cuckoo filter over digests (bytes), four 16-bit slots a row.

    ``insert`` answers False when the filter is too full; the caller then makes a
    larger one from its stored keys (``grown``)."""

    def __init__(self, rows_log2: int = 6, table: bytes | None = None, held: int = 0):
        self.rows_log2, self.held = rows_log2, held
        size = SLOTS << rows_log2
        self.table = list(np.frombuffer(table, "<u2").tolist()) if table else [0] * size

    def _where(self, digest: bytes) -> tuple[int, int, int]:
        mask = (1 << self.rows_log2) - 1
        mark = int.from_bytes(digest[8:10], "little") or 1
        first = int.from_bytes(digest[:8], "little") & mask
        return mark, first, first ^ self._jump(mark, mask)

    @staticmethod
    def _jump(mark: int, mask: int) -> int:
        return (mark * 0x5BD1E995) & mask

    def might_hold(self, digest: bytes) -> bool:
        mark, a, b = self._where(digest)
        t = self.table
        return mark in t[a * SLOTS : a * SLOTS + SLOTS] or mark in t[b * SLOTS : b * SLOTS + SLOTS]

    def _put(self, mark: int, row: int) -> bool:
        at = row * SLOTS
        for i in range(at, at + SLOTS):
            if not self.table[i]:
                self.table[i] = mark
                return True
        return False

    def insert(self, digest: bytes) -> bool:
        if self.held >= FULLEST * (SLOTS << self.rows_log2):
            return False
        mark, a, b = self._where(digest)
        if self._put(mark, a) or self._put(mark, b):
            self.held += 1
            return True
        mask, row, undo = (1 << self.rows_log2) - 1, b, []
        for k in range(KICKS):
            i = row * SLOTS + (mark + k) % SLOTS
            undo.append((i, self.table[i]))
            self.table[i], mark = mark, self.table[i]
            row ^= self._jump(mark, mask)
            if self._put(mark, row):
                self.held += 1
                return True
        for i, old in reversed(undo):  # leave nothing homeless
            self.table[i] = old
        return False

    def delete(self, digest: bytes) -> bool:
        """Remove one copy of a digest known to be in."""
        mark, a, b = self._where(digest)
        for row in (a, b):
            for i in range(row * SLOTS, row * SLOTS + SLOTS):
                if self.table[i] == mark:
                    self.table[i] = 0
                    self.held -= 1
                    return True
        return False

    @classmethod
    def grown(cls, keys, rows_log2: int) -> CuckooFilter:
        while True:
            out = cls(rows_log2)
            if all(map(out.insert, keys)):
                return out
            rows_log2 += 1

    def to_bytes(self) -> bytes:
        return np.array(self.table, "<u2").tobytes()


class Bucket:
    """A filter in front of its verified content: digest -> [smallest id, copies]."""

    def __init__(self, row: pd.Series | None = None):
        self.filter, self.keys, self.resized = CuckooFilter(), {}, 0
        if row is not None:
            self.filter = CuckooFilter(int(row["rows_log2"]), row["filter"], int(row["held"]))
            digests, ids, copies = row["digests"], np.frombuffer(row["ids"], "<i8"), np.frombuffer(row["copies"], "<i8")
            self.keys = {bytes(digests[32 * i : 32 * i + 32]): [int(ids[i]), int(copies[i])] for i in range(len(ids))}

    def add(self, digest: bytes, doc_id: int, copies: int) -> bool:
        """True if the digest is new."""
        if self.filter.might_hold(digest) and (entry := self.keys.get(digest)) is not None:
            entry[0], entry[1] = min(entry[0], doc_id), entry[1] + copies
            return False
        self.keys[digest] = [doc_id, copies]
        if not self.filter.insert(digest):
            self.filter, self.resized = CuckooFilter.grown(self.keys, self.filter.rows_log2 + 1), self.resized + 1
        return True

    def settle(self, digest: bytes, doc_id: int, copies: int) -> bool:
        """Give a live digest what its live rows say: their smallest id and number. The
        key and its fingerprint go with the last row. False for an unknown digest."""
        if not self.filter.might_hold(digest) or digest not in self.keys:
            return False
        if copies > 0:
            self.keys[digest] = [doc_id, copies]
        else:
            del self.keys[digest]
            self.filter.delete(digest)
        return True

    def row(self, bucket: int) -> dict:
        values = list(self.keys.values())
        return {
            "bucket": bucket, "rows_log2": self.filter.rows_log2, "held": self.filter.held, "filter": self.filter.to_bytes(),
            "digests": b"".join(self.keys), "ids": np.array([v[0] for v in values], "<i8").tobytes(), "copies": np.array([v[1] for v in values], "<i8").tobytes(),
        }


INDEX = "bucket int, rows_log2 int, held long, filter binary, digests binary, ids binary, copies binary"
#: Stands for a missing id, above every real one.
NO_ID = (1 << 63) - 1


def digests(docs: DataFrame) -> DataFrame:
    """doc_id, digest (SHA-256 of the normalised text), mark (hash of the text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = [hashlib.sha256(normalise(t)).digest() for t in utf8(b)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(found, pa.binary()), b.column(2)], ["doc_id", "digest", "mark"])

    return documents(docs).withColumn("mark", F.xxhash64("text")).mapInArrow(tidy(run), "doc_id long, digest binary, mark long")


def _partial(hashed: DataFrame) -> DataFrame:
    """One row per digest and Arrow batch: smallest id and copies."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            t = pa.Table.from_batches([b]).group_by("digest").aggregate([("doc_id", "min"), ([], "count_all")])
            yield from t.select(["digest", "doc_id_min", "count_all"]).rename_columns(["digest", "doc_id", "copies"]).to_batches()

    return hashed.select("doc_id", "digest").mapInArrow(tidy(run), "digest binary, doc_id long, copies long")


def _bucketed(df: DataFrame, buckets: int) -> DataFrame:
    return df.withColumn("bucket", F.pmod(F.xxhash64("digest"), F.lit(buckets)).cast("int"))


def insert(index: DataFrame | None, batch: DataFrame, buckets: int) -> DataFrame:
    """The buckets with (digest, doc_id, copies) rows added. ``buckets`` must be the
    number they were made with; buckets without news pass through."""
    batch = _bucketed(batch, buckets)

    def fresh(pdf: pd.DataFrame) -> pd.DataFrame:
        return merge(None, pdf)

    def merge(old: pd.DataFrame | None, new: pd.DataFrame) -> pd.DataFrame:
        have = old is not None and len(old)
        bucket = Bucket(old.iloc[0] if have else None)
        for digest, doc_id, copies in zip(new["digest"], new["doc_id"], new["copies"], strict=True):
            bucket.add(bytes(digest), NO_ID if pd.isna(doc_id) else int(doc_id), int(copies))
        return pd.DataFrame([bucket.row(int((old if have else new)["bucket"].iloc[0]))])

    if index is None:
        return batch.groupBy("bucket").applyInPandas(fresh, INDEX)
    return index.groupBy("bucket").cogroup(batch.groupBy("bucket")).applyInPandas(merge, INDEX)


def settle(index: DataFrame, truth: DataFrame, buckets: int) -> DataFrame:
    """The buckets with the digests of ``truth`` (digest, doc_id, copies; one row each)
    set to its ids and copies; a digest with none is deleted."""
    truth = _bucketed(truth, buckets)

    def merge(old: pd.DataFrame, new: pd.DataFrame) -> pd.DataFrame:
        if not len(old):
            return pd.DataFrame(columns=[c.split()[0] for c in INDEX.split(", ")])
        bucket = Bucket(old.iloc[0])
        for digest, doc_id, copies in zip(new["digest"], new["doc_id"], new["copies"], strict=True):
            bucket.settle(bytes(digest), NO_ID if pd.isna(doc_id) else int(doc_id), int(copies))
        return pd.DataFrame([bucket.row(int(old["bucket"].iloc[0]))])

    return index.groupBy("bucket").cogroup(truth.groupBy("bucket")).applyInPandas(merge, INDEX)


def entries(index: DataFrame) -> DataFrame:
    """The live content: digest, keep_id, group_size."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for row in b.to_pylist():
                flat = pa.py_buffer(row["digests"])
                n = len(row["ids"]) // 8
                keys = pa.FixedSizeBinaryArray.from_buffers(pa.binary(32), n, [None, flat]).cast(pa.binary())
                ids = np.frombuffer(row["ids"], "<i8")
                yield pa.RecordBatch.from_arrays([keys, pa.array(ids, mask=ids == NO_ID), pa.array(np.frombuffer(row["copies"], "<i8"))], ["digest", "keep_id", "group_size"])

    return index.select("digests", "ids", "copies").mapInArrow(tidy(run), "digest binary, keep_id long, group_size long")


@dataclass(frozen=True)
class CuckooIndex:
    """Buckets of live digests, and the live rows (doc_id, digest) they stand for."""

    table: DataFrame
    rows: DataFrame
    buckets: int
    per_bucket: int

    @classmethod
    def build(cls, hashed: DataFrame, per_bucket: int = 50_000) -> CuckooIndex:
        """From (doc_id, digest) rows, which should be stored: they are read twice."""
        buckets = partitions_for(hashed.count(), per_bucket, hashed.sparkSession)
        return cls(stored(insert(None, _partial(hashed), buckets), "cuckoo"), hashed.select("doc_id", "digest"), buckets, per_bucket)

    def insert(self, hashed: DataFrame) -> CuckooIndex:
        """With a batch of (doc_id, digest) rows; more buckets where they grow full."""
        hashed = stored(hashed.select("doc_id", "digest"), "batch")
        table, buckets = stored(insert(self.table, _partial(hashed), self.buckets), "cuckoo"), self.buckets
        held = table.agg(F.coalesce(F.sum("held"), F.lit(0))).first()[0]
        while held > buckets * self.per_bucket:
            buckets *= 2
        if buckets > self.buckets:
            kept = entries(table).select("digest", F.col("keep_id").alias("doc_id"), F.col("group_size").alias("copies"))
            table = stored(insert(None, kept, buckets), "cuckoo")
        return replace(self, table=table, rows=stored(self.rows.unionByName(hashed), "live"), buckets=buckets)

    def delete(self, hashed: DataFrame) -> CuckooIndex:
        """Without one live row for each row of (doc_id, digest); rows that are not live
        change nothing."""
        key, live = ["doc_id", "digest"], F.greatest(F.col("n") - F.coalesce("less", F.lit(0)), F.lit(0))
        gone = stored(hashed.groupBy(*key).agg(F.count("*").alias("less")), "gone").withColumnsRenamed({"doc_id": "_id", "digest": "_digest"})
        same = F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("digest") == F.col("_digest"))
        left = stored(self.rows.groupBy(*key).agg(F.count("*").alias("n")).join(gone, same, "left").select(*key, live.alias("n")), "left")
        touched = gone.select(F.col("_digest").alias("digest")).distinct()
        truth = left.join(touched, "digest", "left_semi").groupBy("digest").agg(F.min(F.when(F.col("n") > 0, F.col("doc_id"))).alias("doc_id"), F.sum("n").alias("copies"))
        rows = left.where("n > 0").select(*key, F.explode(F.sequence(F.lit(1).cast("long"), "n")).alias("_")).drop("_")
        return replace(self, table=stored(settle(self.table, truth, self.buckets), "cuckoo"), rows=stored(rows, "live"))

    def entries(self) -> DataFrame:
        return entries(self.table)


def _grouped(docs: DataFrame, per_bucket: int) -> DataFrame:
    """doc_id, mark, digest, keep_id, group_size, kept of every document."""
    hashed = stored(digests(docs), "digests")
    index = CuckooIndex.build(hashed, per_bucket)
    kept = F.coalesce(F.col("doc_id") == F.col("keep_id"), F.col("keep_id").isNull())
    return hashed.join(index.entries(), "digest").select("doc_id", "mark", "digest", "keep_id", "group_size", kept.alias("kept"))


def classify(docs: DataFrame, per_bucket: int = 50_000) -> DataFrame:
    """Every document with its group: doc_id, keep_id, group_size, kept,
    text_sha256. ``per_bucket`` bounds the digests that share an index bucket."""
    return _grouped(docs, per_bucket).select("doc_id", "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256"))


def keep_first(docs: DataFrame, per_bucket: int = 50_000) -> DataFrame:
    """The document with its group's smallest id, with all its columns (one of the rows
    that share that id and the group; one row of a group without ids)."""
    return keep_rows(docs, stored(_grouped(docs, per_bucket).where("group_size > 1"), "grouped"), "digest")
