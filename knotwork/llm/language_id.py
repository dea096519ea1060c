"""Language identification by a byte convolutional network, trained in numpy.

Bytes are embedded, convolved by filters of several widths, passed through a ramp
and max-pooled over a window of fixed length; a softmax over the pooled features
gives the window's languages, and a text's probabilities are the mean over all its
windows (whole texts, the last window padded). Training is plain stochastic
gradient descent with momentum on a bounded, documented sample.

For prediction the embedding and a filter collapse into one table row per byte and
filter place, so a convolution is a sum of table look-ups; for widths 2 and 3 over
reduced byte classes the sums themselves are tabulated. Both give the trained
network's outputs.

Bounds of the fit: the ``languages`` commonest values of lang, ``per_language``
different texts of each (smallest keyed hashes of the text, so copies count once), and
``per_text`` windows of each text, drawn by keyed hash from the whole of it.

Defined cases: null texts and texts without a letter are ``und`` with score 0; with
no training rows every text is ``und``; language, source and id of a row never
enter its prediction; repeated rows get equal answers; equal probabilities go to the
first language by name; every window of a very long text counts; an empty table gives
an empty result; other columns are ignored by ``predict`` and pass through ``select``.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import pick, stored, tidy

#: Byte classes: lower-case letters (upper case folded), digits, white space, ASCII
#: punctuation, and the bytes of multi-byte characters one by one.
CLASSES = np.zeros(256, np.int64)
for _b in range(256):
    _c = chr(_b)
    if _b >= 128:
        CLASSES[_b] = 30 + (_b - 128)
    elif _c.isalpha():
        CLASSES[_b] = 4 + ord(_c.lower()) - 97
    else:
        CLASSES[_b] = 1 if _c.isspace() else 2 if _c.isdigit() else 3
PAD, N_CLASSES = 0, 30 + 128


def windows(text: bytes, length: int) -> np.ndarray:
    """All windows of a text as class rows, the last one padded."""
    x = CLASSES[np.frombuffer(text, np.uint8)]
    n = max(1, -(-len(x) // length))
    out = np.zeros((n, length), np.int64)
    out.ravel()[: len(x)] = x
    return out


class ByteCNN:
    """Multi-width byte convolutions, max pooling, softmax."""

    def __init__(self, labels: list[str], length: int = 256, widths=(2, 3, 4), filters: int = 12, embed: int = 8, seed: int = 3):
        rng = np.random.default_rng(seed)
        self.labels, self.length, self.widths = labels, length, widths
        self.E = rng.normal(0, 0.3, (N_CLASSES, embed))
        self.W = [rng.normal(0, (w * embed) ** -0.5, (w * embed, filters)) for w in widths]
        self.b = [np.zeros(filters) for _ in widths]
        self.V = rng.normal(0, 0.1, (filters * len(widths), len(labels)))
        self.c = np.zeros(len(labels))

    def parameters(self) -> list[np.ndarray]:
        return [self.E, *self.W, *self.b, self.V, self.c]

    def forward(self, x: np.ndarray):
        e = self.E[x]  # rows, length, embed
        pooled, kept = [], []
        for w, W, b in zip(self.widths, self.W, self.b, strict=True):
            n = x.shape[1] - w + 1
            cols = np.concatenate([e[:, i : i + n] for i in range(w)], axis=2)
            h = cols @ W + b
            at = h.argmax(axis=1)
            top = np.take_along_axis(h, at[:, None, :], 1)[:, 0]
            pooled.append(np.maximum(top, 0))
            kept.append((at, top > 0))
        p = np.concatenate(pooled, axis=1)
        z = p @ self.V + self.c
        z = np.exp(z - z.max(axis=1, keepdims=True))
        return z / z.sum(axis=1, keepdims=True), p, kept, e

    def gradients(self, x: np.ndarray, y: np.ndarray) -> list[np.ndarray]:
        prob, p, kept, e = self.forward(x)
        d = prob.copy()
        d[np.arange(len(y)), y] -= 1
        d /= len(y)
        gV, gc, dp = p.T @ d, d.sum(axis=0), d @ self.V.T
        gE, gW, gb = np.zeros_like(self.E), [], []
        rows, at0 = np.arange(len(y))[:, None], 0
        for w, W, (at, on) in zip(self.widths, self.W, kept, strict=True):
            f = W.shape[1]
            g = dp[:, at0 : at0 + f] * on  # only the winning place of a filter learns
            at0 += f
            gw = np.zeros_like(W)
            embed = self.E.shape[1]
            for i in range(w):
                own = e[rows, at + i]  # rows, filters, embed
                part = slice(i * embed, (i + 1) * embed)
                gw[part] = np.einsum("rfe,rf->ef", own, g)
                np.add.at(gE, x[rows, at + i], g[:, :, None] * W[part].T[None])
            gW.append(gw)
            gb.append(g.sum(axis=0))
        return [gE, *gW, *gb, gV, gc]

    def train(self, x: np.ndarray, y: np.ndarray, epochs: int = 12, batch: int = 64, rate: float = 0.15, seed: int = 5) -> ByteCNN:
        rng = np.random.default_rng(seed)
        speed = [np.zeros_like(p) for p in self.parameters()]
        for epoch in range(epochs):
            step = rate * (1 - epoch / epochs)
            order = rng.permutation(len(y))
            for start in range(0, len(y), batch):
                some = order[start : start + batch]
                for p, v, g in zip(self.parameters(), speed, self.gradients(x[some], y[some]), strict=True):
                    v *= 0.9
                    v -= step * np.clip(g, -1, 1)
                    p += v
        return self

    def compile(self) -> CompiledCNN:
        return CompiledCNN(self)


class CompiledCNN:
    """The trained network with its convolutions as look-ups, in 32-bit floats."""

    def __init__(self, net: ByteCNN):
        self.labels, self.length, self.widths = net.labels, net.length, net.widths
        embed = net.E.shape[1]
        places = [[net.E @ W[i * embed : (i + 1) * embed] for i in range(w)] for w, W in zip(net.widths, net.W, strict=True)]
        # Every two places of a filter become one table over pairs of classes.
        self.tables = []
        for b, rows in zip(net.b, places, strict=True):
            joined = []
            for i in range(0, len(rows), 2):
                t = rows[i][:, None, :] + rows[i + 1][None] if i + 1 < len(rows) else rows[i][:, None, :] + np.zeros((1, N_CLASSES, 1))
                joined.append((i, np.ascontiguousarray((t + (b if i == 0 else 0)).reshape(N_CLASSES**2, -1), np.float32)))
            self.tables.append(joined)
        self.V, self.c = net.V.astype(np.float32), net.c.astype(np.float32)

    def windows_probabilities(self, x: np.ndarray) -> np.ndarray:
        pair = x[:, :-1] * N_CLASSES + x[:, 1:]
        last = x[:, -1:] * N_CLASSES  # a lone last place reads the column of class 0
        pair = np.concatenate([pair, last], axis=1)
        pooled = []
        for w, joined in zip(self.widths, self.tables, strict=True):
            n = x.shape[1] - w + 1
            h = None
            for i, t in joined:
                part = t[pair[:, i : i + n]]
                h = part if h is None else h + part
            pooled.append(np.maximum(h.max(axis=1), 0))
        z = np.concatenate(pooled, axis=1) @ self.V + self.c
        z = np.exp(z - z.max(axis=1, keepdims=True))
        return z / z.sum(axis=1, keepdims=True)

    def predict(self, texts: list[bytes | None], at_once: int = 512) -> list[tuple[str, float]]:
        out: list[tuple[str, float] | None] = [None] * len(texts)
        todo = []
        for i, t in enumerate(texts):
            if t is None or not has_letter(t):
                out[i] = ("und", 0.0)
            else:
                todo.append(i)
        if not self.labels:
            return [("und", 0.0)] * len(texts)
        sums = np.zeros((len(texts), len(self.labels)))
        count = np.zeros(len(texts), np.int64)
        held, owners, size = [], [], 0

        def flush():
            x, who = np.concatenate(held), np.concatenate(owners)
            for s in range(0, len(x), at_once):
                np.add.at(sums, who[s : s + at_once], self.windows_probabilities(x[s : s + at_once]))
            held.clear(), owners.clear()

        for i in todo:
            x = windows(texts[i], self.length)
            count[i] = len(x)
            held.append(x), owners.append(np.full(len(x), i))
            size += len(x)
            if size >= at_once:
                flush()
                size = 0
        if held:
            flush()
        for i in todo:
            p = sums[i] / count[i]
            k = int(p.argmax())
            out[i] = (self.labels[k], float(min(1.0, p[k])))
        return out


_ASCII_LETTER = bytes(range(65, 91)) + bytes(range(97, 123))


def has_letter(text: bytes) -> bool:
    if len(text.translate(None, _ASCII_LETTER)) < len(text):
        return True
    return any(map(str.isalpha, text.decode("utf-8", "replace")))


def drawn_windows(text: bytes, length: int, most: int, seed: int) -> list[bytes]:
    """At most ``most`` windows of a text, by keyed hash of their places."""
    places = range(0, max(1, len(text)), length)
    if len(places) > most:
        places = sorted(places, key=lambda at: xxhash.xxh3_64_intdigest(at.to_bytes(8, "little"), seed))[:most]
    return [text[at : at + length] for at in places]


def training_windows(docs: DataFrame, per_language: int, languages: int, per_text: int, length: int, seed: int = 23) -> list[tuple[bytes, str]]:
    """(window, lang) of the bounded sample outside the held-out fold. A first pass
    over hashes finds each language's border; a second cuts the windows where the
    texts lie."""
    d = pick(docs, doc_id="long", lang="string", text="string").where("doc_id is not null and lang is not null and text is not null")
    d = d.where(F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(3)) != 1).withColumn("h", F.xxhash64(F.lit(seed), "text"))
    hashes = stored(d.groupBy("lang", "h").agg(F.count("*").alias("n")), "hashes")
    found = hashes.groupBy("lang").agg(F.sum("n").alias("n"), F.count("*").alias("texts")).orderBy(F.desc("n"), "lang").limit(languages).collect()
    if not found:
        return []
    # Hashes are even, so a little more than the wanted share of their range holds enough.
    share = {r["lang"]: (per_language + 5 * math.sqrt(per_language) + 5) / r["texts"] for r in found}
    near = {x: min((1 << 63) - 1, int((s - 0.5) * 2.0**64)) if s < 1 else (1 << 63) - 1 for x, s in share.items()}
    upto = lambda cuts: F.create_map(*[F.lit(x) for pair in cuts.items() for x in pair])[F.col("lang")]
    rank = F.row_number().over(Window.partitionBy("lang").orderBy("h"))  # over the bounded sample only
    first = hashes.where(F.col("h") <= upto(near)).withColumn("r", rank).where(F.col("r") <= per_language)
    borders = {r["lang"]: r["h"] for r in first.groupBy("lang").agg(F.max("h").alias("h")).collect()}  # a row a language

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[list] = [[], [], []]
            for lang, h, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).cast(pa.large_binary()).to_pylist(), strict=True):
                for w in drawn_windows(text, length, per_text, h & ((1 << 64) - 1)) if has_letter(text) else []:
                    for column, x in zip(out, (lang, h, w), strict=True):
                        column.append(x)
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.string()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.binary())], ["lang", "h", "piece"])

    some = d.where(F.col("h") <= upto(borders)).select("lang", "h", "text").mapInArrow(tidy(cut), "lang string, h long, piece binary")
    return [(bytes(r["piece"]), r["lang"]) for r in some.distinct().orderBy("lang", "h", "piece").collect()]  # the bounded sample


def train(docs: DataFrame, per_language: int = 750, languages: int = 64, per_text: int = 2, length: int = 256) -> CompiledCNN:
    rows = training_windows(docs, per_language, languages, per_text, length)
    labels = sorted({y for _, y in rows})
    net = ByteCNN(labels, length)
    if rows:
        net.train(np.concatenate([windows(w, length) for w, _ in rows]), np.array([labels.index(y) for _, y in rows]))
    return net.compile()


PREDICTED = "doc_id long, held_out boolean, lang_pred string, score double"


def predict(docs: DataFrame, net: CompiledCNN) -> DataFrame:
    """doc_id, held_out, lang_pred, score for every document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids = b.column(0).to_pylist()
            found = net.predict(b.column(1).cast(pa.large_binary()).to_pylist())
            held = [None if i is None else zlib.crc32(str(i).encode()) % 3 == 1 for i in ids]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(held, pa.bool_()), pa.array([x for x, _ in found], pa.string()), pa.array([p for _, p in found], pa.float64())], ["doc_id", "held_out", "lang_pred", "score"])

    return pick(docs, doc_id="long", text="string").mapInArrow(tidy(run), PREDICTED)


def select(docs: DataFrame, least: float = 0.0, **how) -> DataFrame:
    """The documents with a letter and a predicted language of at least ``least``, all
    columns; a network without labels rejects only those without a letter."""
    net = train(docs, **how)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column(b.schema.get_field_index("text")).cast(pa.large_binary()).to_pylist()
            if net.labels:
                kept = [lang != "und" and p >= least for lang, p in net.predict(texts)]
            else:
                kept = [has_letter(t or b"") for t in texts]
            yield b.filter(pa.array(kept, pa.bool_()))

    return docs.mapInArrow(tidy(run), docs.schema)
