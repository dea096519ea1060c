"""Bound-certified best-fit packing of token pieces into fixed-length sequences.

Every partition packs its pieces by best fit decreasing and computes a lower bound
on its bins from dual-feasible functions. Where bins equal the bound the partition
is certified and its bins are sealed. The others have a gap: they keep bins that
are full but for ``slack`` tokens and release the rest; released pieces are dealt
anew (a different hash, larger partitions) and packed again, until no partition has
a gap or a round does not lower the number of bins (that round is discarded).
Partitions are bounded in pieces, so one document with very many pieces is spread
like any others.

Defined cases: null and empty texts are one end token; null doc_ids keep their
place; repeated rows and equal doc_ids are packed as separate documents (a row number
joins ids and pieces inside one task, never a join on doc_id); pieces of equal length
take places in any order; a very long text is cut into as many pieces as it needs; an
empty table gives no pieces; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from itertools import count

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import documents, stored, tidy
from .tokenization import encoder, tokenizer_path

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
PACKED = PIECES + ", sequence_id long, offset long, fill long, bins long, bound long, sealed boolean"


def cut_lengths(n: int, most: int) -> list[tuple[int, int]]:
    """(start, length) of a document's pieces: all but the first are full."""
    first = n % most or most
    return [(0, min(first, n))] + [(s, most) for s in range(first, n, most)]


def pieces(docs: DataFrame, tokenizer: str = "byte_bpe_50k.json", end_id: int = 0, most: int = 2048, with_ids: bool = False) -> DataFrame:
    """Token pieces of every document; ``with_ids`` adds their ids (binary, u32)."""
    end = np.array([end_id], "<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(tokenizer_path(tokenizer)).encode
        for b in (whole.slice(at, 8192) for whole in batches for at in range(0, whole.num_rows, 8192)):
            out: list[list] = [[], [], [], [], [], []]
            for doc_id, ids in zip(b.column(0).to_pylist(), encode(b.column(1)), strict=True):
                ids += end
                for k, (start, length) in enumerate(cut_lengths(len(ids) // 4, most)):
                    part = ids[4 * start : 4 * (start + length)]
                    for column, value in zip(out, (doc_id, k, start, length, zlib.crc32(part), part if with_ids else None), strict=True):
                        column.append(value)
            kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary()]
            names = ["doc_id", "piece", "start", "length", "ids_crc32", "ids"]
            made = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, kinds, strict=True)], names)
            yield made if with_ids else made.select(names[:5])

    return documents(docs).mapInArrow(tidy(run), PIECES + ", ids binary" * with_ids)


def best_fit(lengths: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Best fit decreasing: each item's bin and offset, and the bins' fill."""
    order = np.argsort(-lengths, kind="stable")
    bins, offsets = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
    fills: list[int] = []
    open_at: list[list[int]] = [[] for _ in range(most + 1)]  # by free space
    free = 0  # bit r: some bin has r tokens free
    for i, size in zip(order.tolist(), lengths[order].tolist(), strict=True):
        fits = free >> size
        if fits:
            room = size + (fits & -fits).bit_length() - 1
            chosen = open_at[room].pop()
            if not open_at[room]:
                free ^= 1 << room
        else:
            chosen, room = len(fills), most
            fills.append(0)
        bins[i], offsets[i] = chosen, fills[chosen]
        fills[chosen] += size
        if room > size:
            open_at[room - size].append(chosen)
            free |= 1 << (room - size)
    return bins, offsets, np.array(fills, np.int64)


def lower_bound(lengths: np.ndarray, most: int) -> int:
    """The best of three families of dual-feasible functions, in whole numbers:
    dropping small items against rounding up large ones, the k-step staircase,
    and rounding down multiples of a unit with the complement for large items."""
    return bound_of_counts(np.bincount(lengths, minlength=most + 1).astype(np.int64), most)


def bound_of_counts(count: np.ndarray, most: int) -> int:
    """The same from the number of items of each length 0..most."""
    if not count.any():
        return 0
    x = np.arange(most + 1, dtype=np.int64)
    up = lambda a, b: -(-int(a) // int(b))
    best = up((count * x).sum(), most)
    # For cut e: items above most - e weigh a whole bin, items below e nothing.
    above, mass = np.cumsum(count[::-1])[::-1], np.cumsum(count * x)
    e = np.arange(0, most // 2 + 1)
    large = np.where(e > 0, above[np.minimum(most - e + 1, most)], 0)
    middle = mass[most - e] - np.where(e > 0, mass[np.maximum(e - 1, 0)], 0)
    best = max(best, int((-(-(large * most + middle) // most)).max()))
    for k in range(1, 101):
        steps = (k + 1) * x
        value = np.where(steps % most == 0, k * x, steps // most * most)
        best = max(best, up((count * value).sum(), k * most))
    for unit in range(1, most // 2 + 1):
        whole = most // unit
        value = np.where(2 * x > most, 2 * (whole - (most - x) // unit), np.where(2 * x == most, whole, 2 * (x // unit)))
        best = max(best, up((count * value).sum(), 2 * whole))
    return best


def _pack_round(rows: DataFrame, turn: int, parts: int, most: int, slack: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]  # a partition is bounded by per_task
        if not held:
            return
        t = pa.Table.from_batches(held).combine_chunks()
        lengths = t.column("length").to_numpy()
        bins, offsets, fills = best_fit(lengths, most)
        bound = lower_bound(lengths, most)
        n, base = len(lengths), (turn << 56) | (TaskContext.get().partitionId() << 32)
        fill = fills[bins]
        sealed = np.ones(n, bool) if len(fills) == bound else fill >= most - slack
        t = t.select(["doc_id", "piece", "start", "length", "ids_crc32"])
        for name, value in (("sequence_id", bins + base), ("offset", offsets), ("fill", fill), ("bins", np.full(n, len(fills))), ("bound", np.full(n, bound)), ("sealed", sealed)):
            t = t.append_column(name, pa.array(value))
        yield from t.to_batches(10_000)

    dealt = rows.select("doc_id", "piece", "start", "length", "ids_crc32").repartition(parts, F.xxhash64(F.lit(turn), "doc_id", "piece", "ids_crc32"))
    return dealt.mapInArrow(tidy(run), PACKED)


def pack(rows: DataFrame, most: int = 2048, per_task: int = 100_000, slack: int = 1) -> DataFrame:
    """Pieces (PIECES columns, lengths 1..most) with sequence_id and offset, and
    the certificate of the partition that packed them (bins, bound, sealed)."""
    spark = rows.sparkSession
    wide = int(spark.conf.get("spark.sql.shuffle.partitions"))
    n = rows.count()
    # The first round is as wide as the cluster; later rounds mix more pieces.
    parts = max(1, min(wide, n // 2000), -(-n // per_task))
    state = stored(_pack_round(rows, 0, parts, most, slack), "packed")
    done: list[DataFrame] = []
    for turn in count(1):
        pool = state.where("not sealed")
        n, bins = pool.agg(F.count("*"), F.count_distinct("sequence_id")).first()
        if not n or (parts == 1 and turn > 1):
            break
        parts = max(1, -(-n // per_task))
        again = stored(_pack_round(pool, turn, parts, most, slack), "packed")
        if again.agg(F.count_distinct("sequence_id")).first()[0] >= bins:
            break
        done.append(state.where("sealed"))
        state = again
    for part in done:
        state = state.unionByName(part)
    return state


def pack_documents(docs: DataFrame, tokenizer: str = "byte_bpe_50k.json", end_id: int = 0, most: int = 2048, **how) -> DataFrame:
    """Every document's pieces with their places."""
    return pack(stored(pieces(docs, tokenizer, end_id, most), "pieces"), most, **how)


def sequences(docs: DataFrame, packed: DataFrame, **how) -> DataFrame:
    """The packed sequences themselves: sequence_id, ids (array<long>), in which
    each piece stands at its offset. A sequence has at most ``most`` ids."""
    cut = pieces(docs, with_ids=True, **how).select("doc_id", "piece", "ids_crc32", "ids").dropDuplicates(["doc_id", "piece", "ids_crc32"])
    on = (F.col("p.doc_id").eqNullSafe(F.col("c.doc_id"))) & (F.col("p.piece") == F.col("c.piece")) & (F.col("p.ids_crc32") == F.col("c.ids_crc32"))
    joined = packed.alias("p").join(cut.alias("c"), on).select("p.sequence_id", "p.offset", "c.ids")

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids = [np.frombuffer(b"".join(x["ids"] for x in parts), "<u4").astype(np.int64) for parts in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(ids, pa.list_(pa.int64()))], ["sequence_id", "ids"])

    grouped = joined.groupBy("sequence_id").agg(F.array_sort(F.collect_list(F.struct("offset", "ids"))).alias("parts"))
    return grouped.mapInArrow(tidy(decode), "sequence_id long, ids array<long>")


def certificate(packed: DataFrame, most: int = 2048) -> DataFrame:
    """One row: sequences used, the lower bound over all pieces' lengths, their
    difference, tokens, and the mean and the largest fill."""
    lengths = packed.groupBy("length").agg(F.count("*").alias("n")).collect()  # `most` rows at most
    held = np.zeros(most + 1, np.int64)
    for length, n in lengths:
        held[length] = n
    bound = F.lit(bound_of_counts(held, most)).cast("long")
    per = packed.groupBy("sequence_id").agg(F.sum("length").alias("fill"))
    total = per.agg(F.count("*").alias("sequences"), F.coalesce(F.sum("fill"), F.lit(0)).alias("tokens"), F.avg("fill").alias("mean_fill"), F.max("fill").alias("fullest"))
    return total.select("sequences", bound.alias("bound"), (F.col("sequences") - bound).alias("gap"), "tokens", "mean_fill", "fullest")
