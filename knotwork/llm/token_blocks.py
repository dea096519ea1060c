"""Token-id files with Elias-Fano document boundaries.

A file is a run of blocks; a block holds the concatenated ids of consecutive
documents (16-bit ids where the vocabulary allows, else 32-bit) and the documents'
end offsets in Elias-Fano form: the low bits packed side by side, the high bits in
unary, and a sparse table of select samples. ``Block.end(i)`` finds one boundary
from the nearest sample; no table of 64-bit offsets is kept.

On a cluster the blocks are rows of a Parquet table (one binary payload a row, in
ascending document order), so any store that Spark writes will do;
``export_files`` puts the same bytes into plain files on the driver's machine. Reading
finds every document's boundaries by ``select``.

Defined cases: null and empty texts are one end id; documents come in ascending
doc_id order, null ids first, equal ids in the order of their texts, repeated rows as
documents of their own; a very long text is one document of one block, whatever the
block size; an id that does not fit the width is refused; an empty table gives no
blocks; other columns are ignored.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import documents, new_path, tidy
from .tokenization import encoder, tokenizer_path

# Fixed values of the file format.
MAGIC = b"KWTB\x01"
HEADER = "<5sBBxQQQQQ"  # magic, bytes an id, low bits, documents, ids, bytes of low part, high part, samples
SAMPLE_EVERY = 256


class EliasFano:
    """A non-decreasing sequence of whole numbers below 2**63 in near-minimal space."""

    def __init__(self, n: int, low_bits: int, low: bytes, high: bytes, samples: np.ndarray):
        self.n, self.low_bits, self.low, self.high, self.samples = n, low_bits, low, high, samples

    @classmethod
    def encode(cls, values: np.ndarray) -> EliasFano:
        v = np.asarray(values, np.uint64)
        n = len(v)
        if not n:
            return cls(0, 0, b"", b"", np.zeros(0, "<u4"))
        low_bits = max(0, (int(v[-1]) // n).bit_length() - 1)
        low = v & np.uint64((1 << low_bits) - 1)
        bits = (low[:, None] >> np.arange(low_bits, dtype=np.uint64)) & np.uint64(1)
        ones = (v >> np.uint64(low_bits)).astype(np.int64) + np.arange(n)
        high = np.zeros(int(ones[-1]) + 1, np.uint8)
        high[ones] = 1
        pack = lambda b: np.packbits(b.astype(np.uint8).ravel(), bitorder="little").tobytes()
        return cls(n, low_bits, pack(bits), pack(high), ones[::SAMPLE_EVERY].astype("<u4"))

    def _low(self, i: int) -> int:
        at = i * self.low_bits
        word = int.from_bytes(self.low[at >> 3 : (at + self.low_bits + 7 >> 3) + 1], "little")
        return word >> (at & 7) & (1 << self.low_bits) - 1

    def select(self, i: int) -> int:
        """Value i: the place of the i-th one in the high part, from its sample."""
        if not 0 <= i < self.n:
            raise IndexError(i)
        at, need = int(self.samples[i // SAMPLE_EVERY]), i % SAMPLE_EVERY
        byte = at >> 3
        word, left = self.high[byte] >> (at & 7) << (at & 7), need
        while (ones := word.bit_count()) <= left:
            left -= ones
            byte += 1
            word = self.high[byte]
        for _ in range(left):
            word &= word - 1
        place = 8 * byte + (word & -word).bit_length() - 1
        return (place - i) << self.low_bits | self._low(i)

    def all(self) -> np.ndarray:
        """Every value, decoded at once."""
        if not self.n:
            return np.zeros(0, np.int64)
        places = np.flatnonzero(np.unpackbits(np.frombuffer(self.high, np.uint8), bitorder="little"))[: self.n]
        out = (places - np.arange(self.n)) << self.low_bits
        if self.low_bits:
            bits = np.unpackbits(np.frombuffer(self.low, np.uint8), bitorder="little")[: self.n * self.low_bits].reshape(self.n, self.low_bits)
            out |= bits.astype(np.int64) @ (np.int64(1) << np.arange(self.low_bits, dtype=np.int64))
        return out


class Block:
    """Ids of consecutive documents with their boundaries."""

    def __init__(self, ids: np.ndarray, ends: EliasFano):
        self.ids, self.ends = ids, ends

    @classmethod
    def build(cls, parts: list[bytes], width: int) -> Block:
        """From each document's ids as 32-bit little-endian bytes."""
        ids = np.frombuffer(b"".join(parts), "<u4")
        if len(ids) and int(ids.max()) >> (8 * width):
            raise ValueError(f"id {int(ids.max())} does not fit {width} bytes")
        return cls(ids.astype(f"<u{width}"), EliasFano.encode(np.cumsum([len(p) // 4 for p in parts])))

    def to_bytes(self) -> bytes:
        e = self.ends
        head = struct.pack(HEADER, MAGIC, self.ids.dtype.itemsize, e.low_bits, e.n, len(self.ids), len(e.low), len(e.high), len(e.samples))
        return head + e.low + e.high + e.samples.tobytes() + self.ids.tobytes()

    @classmethod
    def from_bytes(cls, data: bytes, at: int = 0) -> tuple[Block, int]:
        """The block that starts at ``at``, and where the next one starts."""
        magic, width, low_bits, n, n_ids, n_low, n_high, n_samples = struct.unpack_from(HEADER, data, at)
        if magic != MAGIC:
            raise ValueError("not a token block")
        a = at + struct.calcsize(HEADER)
        b, c, d = a + n_low, a + n_low + n_high, a + n_low + n_high + 4 * n_samples
        ends = EliasFano(n, low_bits, data[a:b], data[b:c], np.frombuffer(data, "<u4", n_samples, c))
        return cls(np.frombuffer(data, f"<u{width}", n_ids, d), ends), d + width * n_ids

    def document(self, i: int) -> np.ndarray:
        return self.ids[self.ends.select(i - 1) if i else 0 : self.ends.select(i)]

    def boundaries(self) -> list[int]:
        """Where each document starts, and where the last one ends."""
        return [0, *map(self.ends.select, range(self.ends.n))]


def width_of(tokenizer: str, end_id: int) -> int:
    """Bytes an id, by the vocabulary file: 2 up to 65,536 ids, else 4."""
    from tokenizers import Tokenizer

    vocabulary = Tokenizer.from_file(tokenizer_path(tokenizer)).get_vocab(with_added_tokens=True)
    return 2 if max(end_id, *vocabulary.values()) < 1 << 16 else 4


BLOCKS = "part int, block int, first long, n_tokens long, doc_ids binary, null_ids int, payload binary"


def write_blocks(docs: DataFrame, path: str, tokenizer: str = "word_bpe_49k.json", end_id: int = 2, block_tokens: int = 1 << 20, width: int | None = None, partitions: int | None = None) -> None:
    """Encode every document and write blocks in ascending doc_id order.

    ``width`` is the bytes of an id (by default what the vocabulary needs). The raw
    texts are dealt by range of doc_id before they are encoded, so tokenizing
    happens once and every task's documents are already in order."""
    end, width = np.array([end_id], "<u4").tobytes(), width or width_of(tokenizer, end_id)
    parts = partitions or int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ordered = documents(docs).repartitionByRange(parts, "doc_id", F.xxhash64("text")).sortWithinPartitions("doc_id", F.xxhash64("text"), "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, part = encoder(tokenizer_path(tokenizer)).encode, TaskContext.get().partitionId()
        block, first, ids, held, size = 0, 0, [], [], 0

        def flush() -> pa.RecordBatch:
            real = [x for x in ids if x is not None]
            row = [[part], [block], [first], [size], [np.array(real, "<i8").tobytes()], [len(ids) - len(real)], [Block.build(held, width).to_bytes()]]
            kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.binary(), pa.int32(), pa.binary()]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(row, kinds, strict=True)], [c.split()[0] for c in BLOCKS.split(", ")])

        for b in batches:
            for at in range(0, b.num_rows, 8192):
                some = b.slice(at, 8192)
                for doc_id, found in zip(some.column(0).to_pylist(), encode(some.column(1)), strict=True):
                    ids.append(doc_id)
                    held.append(found + end)
                    size += len(found) // 4 + 1
                    if size >= block_tokens:
                        yield flush()
                        block, first, ids, held, size = block + 1, first + size, [], [], 0
        if ids:
            yield flush()

    ordered.mapInArrow(tidy(run), BLOCKS).write.option("compression", "zstd").parquet(path)


def read_blocks(spark, path: str) -> DataFrame:
    """One row per document from the files: doc_id, start, n_tokens, ids_crc32 (of
    the ids as 32-bit little-endian)."""
    blocks = spark.read.schema(BLOCKS).parquet(path)
    sums = sorted(blocks.groupBy("part").agg(F.sum("n_tokens").alias("n")).collect())  # a row per writing task
    lifts, total = [], 0
    for part, n in sums:
        lifts.append((part, total))
        total += n
    lift = spark.createDataFrame(lifts or [(0, 0)], "part int, lift long")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(b.num_rows):
                row = {n: b.column(i)[k].as_py() for i, n in enumerate(b.schema.names)}
                block, _ = Block.from_bytes(row["payload"])
                at = block.boundaries()
                wide = memoryview(block.ids.astype("<u4").tobytes())
                crc = [zlib.crc32(wide[4 * a : 4 * z]) for a, z in zip(at, at[1:], strict=False)]
                starts, ends = np.array(at[:-1], np.int64), np.array(at[1:], np.int64)
                doc_ids = [None] * row["null_ids"] + np.frombuffer(row["doc_ids"], "<i8").tolist()
                yield pa.RecordBatch.from_arrays([pa.array(doc_ids, pa.int64()), pa.array(starts + row["first"] + row["lift"]), pa.array(ends - starts), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return blocks.join(F.broadcast(lift), "part").select("first", "lift", "doc_ids", "null_ids", "payload").mapInArrow(tidy(run), "doc_id long, start long, n_tokens long, ids_crc32 long")


def round_trip(docs: DataFrame, **how) -> DataFrame:
    """Write all documents' blocks to the shared folder and read them back."""
    path = new_path(docs.sparkSession, "tokens")
    write_blocks(docs, path, **how)
    return read_blocks(docs.sparkSession, path)


def export_files(spark, path: str, folder: str, per_file: int = 64) -> list[str]:
    """The blocks as plain files of ``per_file`` blocks each, in order, for readers
    without Spark. Runs on the driver, one block at a time; ``folder`` is local."""
    import os

    os.makedirs(folder, exist_ok=True)
    names: list[str] = []
    for k, row in enumerate(spark.read.schema(BLOCKS).parquet(path).orderBy("part", "block").select("payload").toLocalIterator()):
        if k % per_file == 0:
            names.append(os.path.join(folder, f"tokens-{k // per_file:05d}.kwtb"))
        with open(names[-1], "ab" if k % per_file else "wb") as f:
            f.write(row["payload"])
    return names
