"""Near-duplicate vectors by product quantisation over inverted lists.

Vectors are compared only within a label, by cosine in double precision; pairs of at
least ``threshold`` are links. On unit vectors that is a distance of at most
r = sqrt(2 - 2 * threshold).

* Coarse centroids split the vectors into inverted lists. A vector probes every
  list that could hold a link: with home centroid h, a point of list c lies at
  least (|y-c|^2 - |y-h|^2) / (2 |c-h|) away, so lists beyond r are skipped and
  the probes are sufficient, not a guess. Each pair is met once, in the smaller of
  its two home lists.
* A vector's components are sent to its home list only. The lists it probes get its
  residual code (one number), its home and its coding error. A member of the list,
  with its components, is the query: its table of distances to the codewords gives
  the asymmetric distance of every coded guest by look-up, and guests farther than r
  plus their own coding error cannot be links.
* The components of what is left, members and guests, are then joined and reranked
  by exact cosine. So recall is 1 by construction; the quality of the fit only
  decides how much work the filter saves.

Equal vectors of a label are one representative with a weight. A list of more than
``block`` members is several blocks, and its members then visit the blocks before
their own as coded guests; guests come in blocks too. Per cell only link counts, a
spanning star of each in-cell component, and the ids that need a rerank leave the
task, never all pairs.

Bounds of the fit: every length of more than ``block`` vectors has an index of its
own, fitted on ``sample`` vectors at most and 32 a list if that is more (smallest
hashes of the components). The number of lists is half the 0.4th power of the number
of vectors, whatever that is.

Defined cases: vectors that are null, empty, zero, or hold null or non-finite
components, and rows with a null label or id, link with nothing; vectors of different
lengths link with nothing across lengths (a length without an index is one list); a
cosine of exactly ``threshold`` as computed in double precision is a link; repeated
rows are linked with each other; very long vectors make smaller fits, not other
results; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import pick, runs, stored, tidy
from .components import components, lowest

PARTS, WORDS = 8, 64  # a code is one long: a byte a part


def kmeans(x: np.ndarray, k: int, rounds: int, rng: np.random.Generator) -> np.ndarray:
    """Plain Lloyd iterations from distinct sample points."""
    c = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        at = nearest(x, c)
        total = np.zeros_like(c)
        np.add.at(total, at, x)
        n = np.bincount(at, minlength=len(c))
        c[n > 0] = total[n > 0] / n[n > 0, None]
    return c


def squared(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.maximum((x * x).sum(1)[:, None] - 2 * x @ c.T + (c * c).sum(1), 0)


def nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.concatenate([squared(x[s : s + 4096], c).argmin(1) for s in range(0, len(x), 4096)]) if len(x) else np.zeros(0, np.int64)


class Index:
    """Coarse centroids and residual subspace codebooks of one vector length."""

    def __init__(self, x: np.ndarray, lists: int, parts: int = PARTS, words: int = WORDS, rounds: int = 8, seed: int = 13):
        rng = np.random.default_rng(seed)
        self.dim = x.shape[1]
        self.coarse = kmeans(x, lists, rounds, rng)
        cuts = [self.dim * i // parts for i in range(parts + 1)]
        self.slices = [slice(a, b) for a, b in zip(cuts, cuts[1:], strict=False) if b > a]
        rest = x - self.coarse[nearest(x, self.coarse)]
        self.books = [kmeans(rest[:, s], words, rounds, rng) for s in self.slices]

    def encode(self, x: np.ndarray, home: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Codes and coding errors of vectors against their home centroids."""
        rest = x - self.coarse[home]
        codes = np.stack([nearest(rest[:, s], b) for s, b in zip(self.slices, self.books, strict=True)], axis=1).astype(np.uint8)
        back = np.concatenate([b[codes[:, i]] for i, b in enumerate(self.books)], axis=1)
        return codes, np.sqrt(((rest - back) ** 2).sum(1))

    def probes(self, x: np.ndarray, home: np.ndarray, reach: float) -> np.ndarray:
        """For each vector, which lists below its home may hold points within reach."""
        d = squared(x, self.coarse)
        own = d[np.arange(len(x)), home]
        apart = np.sqrt(squared(self.coarse, self.coarse))[home]
        with np.errstate(divide="ignore", invalid="ignore"):
            away = np.where(apart > 0, (d - own[:, None]) / (2 * apart), 0.0)
        return (away <= reach + 1e-9) & (np.arange(len(self.coarse)) < home[:, None])

    def table_distances(self, queries: np.ndarray, home: int, codes: np.ndarray) -> np.ndarray:
        """Asymmetric distances of queries to vectors coded in one list."""
        rest = queries - self.coarse[home]
        total = np.zeros((len(queries), len(codes)))
        for i, (s, book) in enumerate(zip(self.slices, self.books, strict=True)):
            total += squared(rest[:, s], book)[:, codes[:, i]]
        return np.sqrt(total)


def as_long(codes: np.ndarray) -> np.ndarray:
    out = np.zeros((len(codes), 8), np.uint8)
    out[:, : codes.shape[1]] = codes
    return out.view("<i8")[:, 0]


def as_codes(longs: np.ndarray, parts: int) -> np.ndarray:
    return np.ascontiguousarray(longs).astype("<i8", copy=False).view(np.uint8).reshape(-1, 8)[:, :parts]


def packed(column: pa.Array) -> list[bytes | None]:
    """The components of each vector as bytes after a mark: 32-bit floats where that
    keeps every component exactly, else doubles. Equal vectors have equal bytes; a
    vector that can have no link has none."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    lengths = pc.fill_null(pc.list_value_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    x = pc.cast(column.flatten(), pa.float64()).to_numpy(zero_copy_only=False) + 0.0  # a null component becomes nan
    ends = np.cumsum(lengths)
    begins = ends - lengths
    with np.errstate(over="ignore", invalid="ignore"):
        small = x.astype("<f4")
    upto = [np.concatenate([[0], np.cumsum(flag)]) for flag in (~np.isfinite(x), x != 0, small != x)]
    odd, held, wide = (u[ends] - u[begins] for u in upto)
    short, long = memoryview(small.tobytes()), memoryview(x.astype("<f8").tobytes())
    rows = zip(begins.tolist(), ends.tolist(), ((odd == 0) & (held > 0)).tolist(), (wide == 0).tolist(), strict=True)
    return [(b"f" + short[4 * a : 4 * z] if f else b"d" + long[8 * a : 8 * z]) if ok else None for a, z, ok, f in rows]


def valid_vectors(df: DataFrame) -> DataFrame:
    """vec_id, label, dim, mark (128-bit hash of the components), key (the components,
    see ``packed``); the last three null where a vector can have no link."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            named = pc.and_(pc.is_valid(b.column(0)), pc.is_valid(b.column(1))).to_pylist()
            keys = [k if ok else None for k, ok in zip(packed(b.column(2)), named, strict=True)]
            marks = [None if k is None else xxhash.xxh3_128_digest(k) for k in keys]
            dims = [None if k is None else dim_of(k) for k in keys]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(dims, pa.int32()), pa.array(marks, pa.binary()), pa.array(keys, pa.binary())], ["vec_id", "label", "dim", "mark", "key"])

    return pick(df, vec_id="long", label="long", embedding="array<double>").mapInArrow(tidy(run), "vec_id long, label long, dim int, mark binary, key binary")


def dim_of(key: bytes) -> int:
    return (len(key) - 1) // (4 if key[:1] == b"f" else 8)


def unit(keys: list[bytes], dim: int) -> np.ndarray:
    """Unit vectors in double precision."""
    x = np.empty((len(keys), dim))
    for i, k in enumerate(keys):
        x[i] = np.frombuffer(k, "<f4" if k[:1] == b"f" else "<f8", dim, 1)
    x /= np.abs(x).max(axis=1, keepdims=True)  # so that squares neither overflow nor vanish
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def fit(reps: DataFrame, block: int, sample: int = 20_000, seed: int = 29) -> dict[int, tuple[Index, int]]:
    """An index and the number of its first list for each vector length of more than
    ``block`` vectors, from bounded samples."""
    out, first = {}, 0
    sizes = reps.groupBy("dim").agg(F.count("*").alias("n")).where(F.col("n") > block).orderBy("dim").collect()  # n / block rows at most
    for dim, n in sizes:
        own = reps.where(F.col("dim") == dim).withColumn("h", F.xxhash64(F.lit(seed), "mark"))
        lists = max(1, int(n**0.4 / 2))
        limit = max(1, min(n, max(sample, 32 * lists), (32 << 20) // dim))  # 256 MB of doubles at most
        # Hashes are even, so those below the limit's share of their range are about as many.
        cut = min((1 << 63) - 1, int(((1 + 4 / math.sqrt(limit)) * limit / n - 0.5) * 2.0**64)) if limit < n else (1 << 63) - 1
        keys = [bytes(r[0]) for r in own.where(F.col("h") <= cut).orderBy("h", "label", "key").select("key").limit(limit).collect()]
        if keys:
            out[dim] = Index(unit(keys, dim), min(lists, len(keys))), first
            first += len(out[dim][0].coarse)
    return out


CODED = "rep long, weight long, label long, dim int, key binary, list long, code long, error float, probes array<long>"


def coded(reps: DataFrame, indexes: dict[int, tuple[Index, int]], reach: float) -> DataFrame:
    """Every representative with its list, code, coding error and probed lists. A
    length without an index is the list -dim and has no probes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (whole.slice(at, 1024) for whole in batches for at in range(0, whole.num_rows, 1024)):
            dims, keys = b.column(3).to_numpy(), b.column(4).to_pylist()
            n = len(keys)
            home, code, error, probes = -dims.astype(np.int64), np.zeros(n, np.int64), np.zeros(n), [[]] * n
            for dim in np.unique(dims).tolist():
                if dim not in indexes:
                    continue
                (index, first), mine = indexes[dim], np.flatnonzero(dims == dim)
                x = unit([keys[i] for i in mine], dim)
                own = nearest(x, index.coarse)
                codes, err = index.encode(x, own)
                home[mine], code[mine], error[mine] = own + first, as_long(codes), err
                near = index.probes(x, own, reach)
                for i, row in zip(mine.tolist(), near, strict=True):
                    probes[i] = (np.flatnonzero(row) + first).tolist()
            up = np.nextafter(error.astype(np.float32), np.float32(np.inf))  # never below the error
            made = [pa.array(home), pa.array(code), pa.array(up, pa.float32()), pa.array(probes, pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays([*b.columns, *made], [c.split()[0] for c in CODED.split(", ")])

    return reps.select("rep", "weight", "label", "dim", "key").mapInArrow(tidy(run), CODED)


def matches(queries: np.ndarray, members: np.ndarray, codes: np.ndarray, errors: np.ndarray, index: Index | None, home: int, threshold: float, reach: float):
    """(query, member) pairs that are links, by look-up filter and exact cosine."""
    left, right = [], []
    for s in range(0, len(queries), 256):
        q = queries[s : s + 256]
        if index is not None:
            i, j = np.nonzero(index.table_distances(q, home, codes) <= reach + errors + 1e-9)
        else:
            i, j = [a.ravel() for a in np.indices((len(q), len(members)))]
        for t in range(0, len(i), 1 << 16):
            a, b = i[t : t + (1 << 16)], j[t : t + (1 << 16)]
            hit = np.einsum("ij,ij->i", q[a], members[b]) >= threshold
            left.append(a[hit] + s), right.append(b[hit])
    return (np.concatenate(left), np.concatenate(right)) if left else (np.zeros(0, np.int64),) * 2


def survivors(members: np.ndarray, home: np.ndarray, codes: np.ndarray, errors: np.ndarray, index: Index, first: int, reach: float) -> tuple[np.ndarray, np.ndarray]:
    """Which members and which coded guests the look-up filter leaves a partner."""
    mine, theirs = np.zeros(len(members), bool), np.zeros(len(home), bool)
    for h in np.unique(home).tolist():
        own = np.flatnonzero(home == h)
        for s in range(0, len(members), 256):
            for t in range(0, len(own), 8192):
                some = own[t : t + 8192]
                near = index.table_distances(members[s : s + 256], h - first, codes[some]) <= reach + errors[some] + 1e-9
                mine[s : s + 256] |= near.any(1)
                theirs[some] |= near.any(0)
    return mine, theirs


def roots(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The smallest index each of n rows is connected to by pairs (a, b)."""
    r = np.arange(n)
    while True:
        low = np.minimum(r[a], r[b])
        new = r.copy()
        np.minimum.at(new, a, low)
        np.minimum.at(new, b, low)
        new = new[new]
        if (new == r).all():
            return r
        r = new


def linked(rep: np.ndarray, weight: np.ndarray, a: np.ndarray, b: np.ndarray) -> list[np.ndarray]:
    """rep, links, root of the rows that pairs (a, b) link."""
    links = np.zeros(len(rep), np.int64)
    np.add.at(links, a, weight[b])
    np.add.at(links, b, weight[a])
    order = np.argsort(rep, kind="stable")
    rank = np.empty_like(order)
    rank[order] = np.arange(len(order))
    root = rep[order][roots(len(rep), rank[a], rank[b])[rank]]
    hit = np.flatnonzero(links)
    return [rep[hit], links[hit], root[hit]]


def cells_of(t: pa.Table) -> Iterator[pa.Table]:
    """The cells of a table sorted by ``cell``."""
    cells = t.column("cell").to_numpy()
    edges = (np.flatnonzero(np.diff(cells)) + 1).tolist()
    for lo, hi in zip([0, *edges], [*edges, len(cells)], strict=True):
        yield t.slice(lo, hi - lo)


MET = "cell long, rep long, links long, root long, side int"


def look_up(rows: DataFrame, indexes: dict[int, tuple[Index, int]], threshold: float, reach: float, block: int, guests: int) -> DataFrame:
    """The cells' results: links within a block of members (cell null), and the
    members (side 0) and guests (side 1) of a cell that need a rerank (links null)."""
    wide = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    key = ["label", "list"]
    homes = rows.groupBy(*key).agg(F.count("*").alias("m"))
    visits = rows.select("label", F.explode("probes").alias("list")).groupBy(*key).agg(F.count("*").alias("g"))
    sizes = stored(
        homes.join(visits, key, "left").withColumn("homes", F.ceil(F.col("m") / block))
        .withColumn("guests", F.ceil((F.coalesce("g", F.lit(0)) + F.when(F.col("homes") > 1, F.col("m")).otherwise(0)) / guests)).select(*key, "homes", "guests"),
        "lists",
    )
    none = lambda t: F.lit(None).cast(t)
    upto = lambda n: F.sequence(F.lit(0).cast("long"), n - 1)
    member = (
        rows.join(sizes, key).withColumn("i", F.pmod(F.xxhash64("rep"), F.col("homes"))).withColumn("j", F.explode(upto(F.greatest("guests", F.lit(1)))))
        .select("label", "list", "i", "j", F.lit(0).alias("side"), "rep", "weight", "dim", "code", "error", F.col("list").alias("home"), "key")
    )
    coded_ = rows.select("rep", "label", "dim", F.col("list").alias("home"), "code", "error", F.explode(F.concat(F.array("list"), "probes")).alias("list"))
    guest = (
        coded_.join(sizes, key).withColumn("own", F.pmod(F.xxhash64("rep"), F.col("homes"))).where("list <> home or own > 0")
        .withColumn("j", F.pmod(F.xxhash64("rep", F.lit(5)), F.col("guests")))
        .withColumn("i", F.explode(upto(F.when(F.col("list") == F.col("home"), F.col("own")).otherwise(F.col("homes")))))
        .select("label", "list", "i", "j", F.lit(1).alias("side"), "rep", none("long").alias("weight"), "dim", "code", "error", "home", none("binary").alias("key"))
    )
    met = member.unionByName(guest).withColumn("cell", F.xxhash64("label", "list", "i", "j")).drop("label", "i")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in (c for t in runs(batches, "cell") for c in cells_of(t)):
            side, rep = part.column("side").to_numpy(), part.column("rep").to_numpy()
            base, ask = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
            if not len(base):
                continue
            dim, within = part.column("dim")[int(base[0])].as_py(), part.column("j")[int(base[0])].as_py() == 0
            if not len(ask) and (not within or len(base) < 2):
                continue
            index, first = indexes.get(dim, (None, 0))
            keys = part.column("key").to_pylist()
            x = unit([keys[i] for i in base], dim)
            code, error = part.column("code").to_numpy(), part.column("error").to_numpy().astype(np.float64)
            codes = as_codes(code, len(index.books)) if index else None
            home = part.column("home").to_numpy()
            if within:
                a, b = matches(x, x, codes[base] if index else None, error[base], index, int(home[base[0]]) - first, threshold, reach)
                weight = np.array(part.column("weight").take(pa.array(base)).to_pylist(), np.int64)
                found = linked(rep[base], weight, a[a > b], b[a > b])
                if len(found[0]):
                    yield _met(None, *found, 0)
            if len(ask) and index:
                mine, theirs = survivors(x, home[ask], codes[ask], error[ask], index, first, reach)
                cell = part.column("cell")[0].as_py()
                for s, rows_ in ((0, rep[base][mine]), (1, rep[ask][theirs])):
                    if len(rows_):
                        yield _met(cell, rows_, None, None, s)

    dealt = met.repartition(wide, "cell").sortWithinPartitions("cell", "side", "rep")
    return dealt.mapInArrow(tidy(run), MET)


def _met(cell: int | None, rep: np.ndarray, links, root, side: int) -> pa.RecordBatch:
    n = len(rep)
    full = lambda x: pa.nulls(n, pa.int64()) if x is None else pa.array(x, pa.int64())
    return pa.RecordBatch.from_arrays([full(None if cell is None else np.full(n, cell)), pa.array(rep), full(links), full(root), pa.array(np.full(n, side, np.int32))], ["cell", "rep", "links", "root", "side"])


def rerank(needed: DataFrame, rows: DataFrame, threshold: float) -> DataFrame:
    """rep, links, root from exact cosines of the members and guests that the look-up
    left in a cell (cell, rep, side)."""
    wide = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    met = needed.join(rows.select("rep", "weight", "dim", "key"), "rep")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in (c for t in runs(batches, "cell") for c in cells_of(t)):
            side, rep, weight = (part.column(c).to_numpy() for c in ("side", "rep", "weight"))
            x = unit(part.column("key").to_pylist(), part.column("dim")[0].as_py())
            base, ask = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
            a, b = matches(x[ask], x[base], None, None, None, 0, threshold, 0.0)
            found = linked(rep, weight, ask[a], base[b])
            if len(found[0]):
                yield pa.RecordBatch.from_arrays([pa.array(f) for f in found], ["rep", "links", "root"])

    return met.repartition(wide, "cell").sortWithinPartitions("cell", "side", "rep").mapInArrow(tidy(run), "rep long, links long, root long")


def near_vectors(df: DataFrame, threshold: float = 0.98, block: int = 4096, guests: int = 1 << 16, **how) -> DataFrame:
    """vec_id, n_links, component_id, kept for every vector. ``block`` and ``guests``
    bound the members and the coded guests of a cell."""
    valid = valid_vectors(df)
    vectors = stored(valid.select("vec_id", "label", "mark"), "vectors")
    # Numbered, since rows of one vec_id may hold different vectors.
    reps = stored(
        valid.where("key is not null").groupBy("label", "mark")
        .agg(F.min("vec_id").alias("low"), F.count("*").alias("weight"), F.first("dim").alias("dim"), F.first("key").alias("key"))
        .withColumn("rep", F.monotonically_increasing_id()), "vector_reps",
    )
    reach = math.sqrt(max(0.0, 2 - 2 * threshold)) + 1e-7
    indexes = fit(reps, block, **how)
    rows = stored(coded(reps, indexes, reach), "coded")
    first = stored(look_up(rows, indexes, threshold, reach, block, guests), "met")
    exact = rerank(first.where("cell is not null").select("cell", "rep", "side"), rows, threshold)
    met = stored(first.where("cell is null").select("rep", "links", "root").unionByName(exact), "linked")
    names = reps.select("rep", "weight", "low", "label", "mark")
    groups = lowest(components(met.select(F.col("rep").alias("a"), F.col("root").alias("b"))).withColumnRenamed("node", "rep"), names)
    counts = met.groupBy("rep").agg(F.sum("links").alias("links"))
    named = names.join(counts, "rep", "left").join(groups, "rep", "left").select(
        "label", "mark", (F.coalesce("links", F.lit(0)) + F.col("weight") - 1).alias("n_links"), F.coalesce("component_id", "low").alias("component_id")
    )
    own = F.coalesce("component_id", "vec_id")
    return vectors.join(named, ["label", "mark"], "left").select(
        "vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), own.alias("component_id"), F.coalesce(F.col("vec_id") == own, F.lit(False)).alias("kept")
    )
