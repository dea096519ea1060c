"""Quality selection by importance resampling.

Two hashed n-gram models (word and bigram buckets) describe the target text, a
bounded sample of documents labelled good, and the raw text, all documents. A
document's log importance weight is the sum over its n-grams of the log ratio of
the two; the models' buckets are smoothed towards the raw model, so one unseen
n-gram cannot outweigh a text. A bigram of a word with itself has one bucket of its
own, whatever the word.

The sample is drawn without replacement in proportion to the weights: keyed Gumbel
noise is added to each log weight and the k largest keys stay. ``k`` may be given.
Otherwise it is the number of documents, counted over all of them, whose log weight
reaches a level: what all but ``tail`` of the held-out good labels reach, less
``margin``. The weight of a whole text is a product over its n-grams, so among long
texts the noise decides only between weights that are close. The k-th key is found
exactly by counting key prefixes, never by a sort on one machine.

Parameters that bound a fit: ``sample`` labelled rows at most (those with the
smallest keyed hash of doc_id), one fifth of them held out for the level.

Defined cases: null, empty and wordless texts have no weight and are never sampled;
without good labels every text with words stays unless k is given; equal keys at the
border all stay; null doc_ids take part with a fixed noise; repeated rows get equal keys,
rows of one doc_id with different texts equal noise and their own weights; very long
texts are read whole; an empty table gives an empty result; extra columns pass through
``select``.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import documents, pick, stored, tidy, utf8

_TOKEN = re.compile(rb"[a-z0-9\x80-\xff]+|[^\sa-z0-9\x80-\xff]+")
U64 = np.uint64


class Features:
    """Hashed n-grams: word buckets, then bigram buckets, then the repeat bucket."""

    def __init__(self, buckets: int = 1 << 13, limit: int = 400_000):
        self.buckets, self.limit, self.memory = buckets, limit, {}
        self.size = 2 * buckets + 1

    def __call__(self, text: bytes | None) -> np.ndarray:
        tokens = _TOKEN.findall(text.lower()) if text else []
        memory = self.memory
        if len(memory) > self.limit:
            memory = self.memory = {}
        for t in set(tokens).difference(memory):
            memory[t] = xxhash.xxh3_64_intdigest(t)
        h = np.fromiter(map(memory.__getitem__, tokens), U64, len(tokens))
        pair = h[:-1] * U64(0x9E3779B97F4A7C15) + h[1:]
        second = (pair ^ (pair >> U64(31))) % U64(self.buckets) + U64(self.buckets)
        second[h[:-1] == h[1:]] = U64(2 * self.buckets)
        return np.concatenate([h % U64(self.buckets), second]).astype(np.int64)


def target_ids(labels: DataFrame, sample: int, seed: int) -> list[tuple[int, bool]]:
    """(doc_id, held out) of at most ``sample`` good labels."""
    good = pick(labels, doc_id="long", quality="int").where("quality = 1 and doc_id is not null").select("doc_id").distinct()
    rows = good.orderBy(F.xxhash64(F.lit(seed), "doc_id"), "doc_id").limit(sample).collect()  # bounded by `sample`
    held = [xxhash.xxh3_64_intdigest(f"{seed}:{r[0]}".encode()) % 5 == 0 for r in rows]
    return [(r[0], h) for r, h in zip(rows, held, strict=True)]


def fit(docs: DataFrame, labels: DataFrame, sample: int = 20_000, buckets: int = 1 << 13, smooth: float = 0.02, seed: int = 17) -> dict:
    """Bucket log ratios, with the ids the level is read from."""
    chosen = target_ids(labels, sample, seed)
    held = frozenset(i for i, h in chosen if h) if sum(h for _, h in chosen) >= 20 else frozenset(i for i, _ in chosen)
    fitted = frozenset(i for i, h in chosen if not h)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        features = Features(buckets)
        total = np.zeros((2, features.size), np.int64)
        for b in batches:
            for doc_id, text in zip(b.column(0).to_pylist(), utf8(b), strict=True):
                n = np.bincount(features(text), minlength=features.size)
                total[0] += n
                if doc_id in fitted:
                    total[1] += n
        at = np.flatnonzero(total[0])
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[0, at]), pa.array(total[1, at])], ["bucket", "raw", "target"])

    # As many rows as buckets reach the driver, whatever the corpus.
    rows = documents(docs).mapInArrow(tidy(count), "bucket long, raw long, target long").groupBy("bucket").agg(F.sum("raw"), F.sum("target")).collect()
    raw, target = np.zeros(2 * buckets + 1), np.zeros(2 * buckets + 1)
    for bucket, r, t in rows:
        raw[bucket], target[bucket] = r, t
    ratio = np.zeros(2 * buckets + 1)
    if target.sum():
        for part in (slice(0, buckets), slice(buckets, 2 * buckets + 1)):
            p = (raw[part] + 0.5) / (raw[part].sum() + 0.5 * len(raw[part]))
            q = target[part] / max(1.0, target[part].sum())
            ratio[part] = np.log((1 - smooth) * q + smooth * p) - np.log(p)
    return {"ratio": ratio, "held": held, "buckets": buckets, "seed": seed}


def gumbel(doc_ids: list, seed: int) -> np.ndarray:
    """Keyed Gumbel noise of each id."""
    u = np.array([(xxhash.xxh3_64_intdigest(f"g{seed}:{i}".encode()) >> 11) + 0.5 for i in doc_ids]) / float(1 << 53)
    return -np.log(-np.log(u))


def _weights(batch: pa.RecordBatch, features: Features, model: dict) -> tuple[np.ndarray, np.ndarray]:
    """Log weights (nan: no words) and keys."""
    at, w = batch.schema.get_field_index("doc_id"), []
    for text in utf8(batch):
        f = features(text)
        w.append(model["ratio"][f].sum() if len(f) else np.nan)
    w = np.array(w, float)
    return w, w + gumbel(batch.column(at).to_pylist(), model["seed"])


def ordered_bits(x: np.ndarray) -> np.ndarray:
    """Doubles as longs in the same order."""
    v = (np.asarray(x, np.float64) + 0.0).view(np.int64)
    return v ^ ((v >> 63) & np.int64(0x7FFFFFFFFFFFFFFF))


def score(docs: DataFrame, model: dict) -> DataFrame:
    """doc_id, log_weight (null without words), key, key_bits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        features = Features(model["buckets"])
        for b in batches:
            w, key = _weights(b, features, model)
            none = np.isnan(w)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(w, mask=none), pa.array(key, mask=none), pa.array(ordered_bits(key), mask=none)], ["doc_id", "log_weight", "key", "key_bits"])

    return documents(docs).mapInArrow(tidy(run), "doc_id long, log_weight double, key double, key_bits long")


def kth_largest(df: DataFrame, bits: str, k: int) -> int | None:
    """The k-th largest value of a long column, by four counts of 16-bit prefixes."""
    if k <= 0:
        return None
    prefix, left = None, k
    for shift in (48, 32, 16, 0):
        part = F.shiftright(bits, shift)
        rows = df.where(F.col(bits).isNotNull())
        if prefix is not None:
            rows = rows.where(F.shiftright(bits, shift + 16) == prefix)
        counts = rows.groupBy(part.alias("p")).agg(F.count("*").alias("n")).collect()  # 65,536 rows at most
        for p, n in sorted(((r["p"], r["n"]) for r in counts), reverse=True):
            if left <= n:
                prefix = p
                break
            left -= n
        else:
            return None
    return prefix


def decide(scored: DataFrame, model: dict, tail: float = 0.001, margin: float = 1.0, k: int | None = None) -> int:
    """The smallest key (as bits) that is sampled."""
    if k is not None:
        cut = kth_largest(scored, "key_bits", k)
        return ((1 << 63) - 1 if k <= 0 else -(1 << 63)) if cut is None else cut
    spark = scored.sparkSession
    weights: list[float] = []
    if model["held"]:
        ids = spark.createDataFrame([(i,) for i in model["held"]], "doc_id long")  # bounded by `sample`
        found = scored.join(F.broadcast(ids), "doc_id").where("log_weight is not null")
        weights = [r[1] for r in found.groupBy("doc_id").agg(F.min("log_weight")).collect()]  # a row per held-out id
    if not weights:
        return -(1 << 63)
    level = float(np.quantile(weights, tail)) - margin
    k = scored.where(F.col("log_weight") >= level).count()
    cut = kth_largest(scored, "key_bits", k)
    return (1 << 63) - 1 if cut is None else cut


def resample(docs: DataFrame, labels: DataFrame, tail: float = 0.001, margin: float = 1.0, k: int | None = None, **how) -> DataFrame:
    """Every document's weight, key and decision: doc_id, log_weight, key, kept."""
    model = fit(docs, labels, **how)
    scored = stored(score(docs, model), "scored")
    cut = decide(scored, model, tail, margin, k)
    return scored.select("doc_id", "log_weight", "key", F.coalesce(F.col("key_bits") >= F.lit(cut), F.lit(False)).alias("kept"))


def select(docs: DataFrame, labels: DataFrame, tail: float = 0.001, margin: float = 1.0, k: int | None = None, **how) -> DataFrame:
    """The sampled documents with all their columns. They are scored again where
    they lie, so no text crosses the network."""
    model = fit(docs, labels, **how)
    cut = decide(stored(score(docs, model), "scored"), model, tail, margin, k)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        features = Features(model["buckets"])
        for b in batches:
            w, key = _weights(b, features, model)
            yield b.filter(pa.array(~np.isnan(w) & (ordered_bits(key) >= cut)))

    return docs.mapInArrow(tidy(run), docs.schema)
