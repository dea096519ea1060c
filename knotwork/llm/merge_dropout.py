"""SentencePiece merge-type encoding with seeded merge dropout, and its decoder.

A segment (a run of spaces with the characters after it) starts as single
characters. The agenda takes the best-scored neighbouring pair, leftmost first; a
keyed hash of (seed, draw, document, the segment's place in the text, merged piece,
place) decides whether that candidate is skipped, and a skipped candidate is not
taken again unless a neighbour changes. With rate 0 the ids are the model's own.
Characters that are not pieces become byte pieces, so decoding gives back every text
exactly.

Every occurrence of a word is drawn anew. What a worker remembers of a word is not
drawn: the candidates of its agenda in order when none is skipped, and the same after
each set of skips that several occurrences of a block have met. The hashes of all
occurrences are compared at once, and those whose skips nobody shares run the agenda
by themselves. ``draw`` numbers a pass over the corpus: another number draws all
occurrences again, and any run with the same seed and draw gives the same ids. A
literal U+2581 in a text, which the model would confuse with a space, is written as
bytes.

Defined cases: null and empty texts have no ids and decode to the empty text; a null
doc_id draws by a hash of the text; repeated rows get the same ids; pieces of equal
score merge leftmost first; a very long text is encoded whole, a very long word by a
heap; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import heapq
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame

from .common import documents, tidy
from .tokenization import PieceEncoder, tokenizer_path

SPACE = "▁"
_LITERAL = SPACE + "\n"  # stands for a U+2581 of the text; no segment holds a newline beside others
_SEGMENT = re.compile(r" +[^ \n▁]*|\n|▁|[^ \n▁]+")
_MARK = "\x01"
_M64 = (1 << 64) - 1
_PIECE, _PLACE, _MIX = 0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0xD6E8FEB86659FD93
_NONE = 1 << 30
_SHORT = 40  # characters of a segment whose agenda is remembered
_AT_ONCE = 1 << 17  # occurrences whose hashes are compared at once


class Vocabulary:
    """Pieces, scores and byte pieces of a model file."""

    def __init__(self, path: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        self.ids, self.rank, self.raw, self.bytes_ = {}, {}, [], [0] * 256
        for i in range(sp.get_piece_size()):
            piece = sp.id_to_piece(i)
            if sp.is_byte(i):
                self.bytes_[int(piece[3:5], 16)] = i
                self.raw.append(bytes([int(piece[3:5], 16)]))
            elif sp.is_control(i) or sp.is_unknown(i):
                self.raw.append(b"")
            else:
                self.raw.append(piece.replace(SPACE, " ").encode())
                self.ids[piece] = i
                self.rank[piece] = (-sp.get_score(i), i)
        if any("\n" in p or SPACE in p.lstrip(SPACE) for p in self.ids if len(p) > 1):
            raise ValueError("pieces of this model cross a space or a line")
        order = sorted(self.rank, key=self.rank.__getitem__)
        #: Merge priority as one number; pieces of equal score are taken leftmost first.
        level, last, self.level = -1, None, {}
        for p in order:
            if self.rank[p][0] != last:
                level, last = level + 1, self.rank[p][0]
            self.level[p] = level
        self._tables()

    def _tables(self) -> None:
        """Pieces of one character by code point, and all pairs that merge in a table
        of linear probing, for many segments at once."""
        self.single = np.full(0x110000, -1, np.int32)
        pairs: dict[int, tuple[int, int]] = {}
        for p, i in self.ids.items():
            if len(p) == 1:
                self.single[ord(p)] = i
            for at in range(1, len(p)):
                a, b = self.ids.get(p[:at]), self.ids.get(p[at:])
                if a is not None and b is not None:
                    pairs[a << 32 | b] = self.level[p], i
        self.bits = max(8, (8 * len(pairs)).bit_length())
        self.pair = np.full(1 << self.bits, _M64, np.uint64)
        self.pair_level, self.pair_piece = np.full(1 << self.bits, _NONE, np.int32), np.zeros(1 << self.bits, np.int32)
        for k, (level, i) in pairs.items():
            at = (k * _PIECE & _M64) >> 64 - self.bits
            while int(self.pair[at]) != _M64:
                at = at + 1 & (1 << self.bits) - 1
            self.pair[at], self.pair_level[at], self.pair_piece[at] = k, level, i

    def merges(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Level and piece of pairs of pieces; a pair that does not merge has level _NONE."""
        k = a.astype(np.uint64) << np.uint64(32) | b.astype(np.uint64)
        at = (k * np.uint64(_PIECE) >> np.uint64(64 - self.bits)).astype(np.int64)
        there = self.pair[at]
        off = np.flatnonzero((there != k) & (there != np.uint64(_M64)))
        while len(off):
            at[off] = at[off] + 1 & (1 << self.bits) - 1
            there = self.pair[at[off]]
            off = off[(there != k[off]) & (there != np.uint64(_M64))]
        return self.pair_level[at], self.pair_piece[at]

    def decode(self, ids) -> bytes:
        """The text of ids, without the space that encoding puts in front."""
        return b"".join(map(self.raw.__getitem__, ids))[1:]


def _mixed(x: np.ndarray) -> np.ndarray:
    x = x * np.uint64(_MIX)
    return (x ^ x >> np.uint64(32)) * np.uint64(_MIX)


class MergeDropout(PieceEncoder):
    """The encoder of one seed and draw.

    A slot is a path: a segment, the steps of its agenda that were skipped, the
    candidates met after the last of them (``steps``, as terms of the hash), the path
    to follow where one of these is skipped too (``after``), and the ids when none is."""

    def __init__(self, vocabulary: Vocabulary, rate: float, seed: int, draw: int, limit: int = 600_000, longest: int = 48):
        self.vocabulary, self.limit, self.longest = vocabulary, limit, longest
        self.cut, self.key = int(rate * (1 << 53)), xxhash.xxh3_64_intdigest(f"{seed}:{draw}")
        self._clear()

    def _clear(self) -> None:
        super()._clear()
        self.paths: list[tuple[str, tuple[int, ...]]] = []
        self.first, self.many = np.zeros((2, 1 << 16), np.int64)  # a path's steps
        self.stepped = 0
        self.steps, self.after = np.zeros(1 << 18, np.uint64), np.zeros(1 << 18, np.int32)

    def _pieces(self, texts: pa.Array) -> pa.ListArray:
        full = pc.binary_join_element_wise(pa.scalar(" "), texts, "")
        odd = pc.fill_null(pc.match_substring_regex(texts, "^ |  |\x01|" + SPACE), False)
        spaced = pc.replace_substring(pc.replace_substring(full, " ", _MARK + SPACE), "\n", f"{_MARK}\n{_MARK}")
        out = pc.split_pattern(spaced, _MARK).to_pylist() if pc.any(odd).as_py() else None
        if out is not None:
            pairs = zip(texts.to_pylist(), odd.to_pylist(), out, strict=True)
            cut = [[_LITERAL if s == SPACE else s.replace(" ", SPACE) for s in _SEGMENT.findall(" " + t)] if o else p for t, o, p in pairs]
            lists = pa.array([[] if not t else p for t, p in zip(texts.to_pylist(), cut, strict=True)], pa.list_(pa.string()))
            return lists
        lists = pc.split_pattern(spaced, _MARK)
        empty = pc.fill_null(pc.equal(texts, ""), True)
        return pc.if_else(empty, pa.scalar([], lists.type), lists) if pc.any(empty).as_py() else lists

    def _learn(self, pieces: list[str]) -> None:
        self._add(pieces, skips=[()] * len(pieces))
        self.slots.update(zip(pieces, range(self.next - len(pieces), self.next), strict=True))

    def _add(self, texts: list[str], bases: np.ndarray | None = None, skips: list[tuple[int, ...]] | None = None) -> None:
        """The next slots, without names: of occurrences with their hashes, or of paths
        with their skips and steps."""
        found = self._segments(texts, bases, skips)
        begins, lengths, ids = found[:3]
        slots, self.slots = self.slots, {}
        k, n = self.next, len(texts)
        self._append(list(range(n)), ids, begins, lengths)
        self.slots = slots
        if bases is not None:
            return
        begins, lengths, steps = found[3:]
        while k + n > len(self.first):
            self.first, self.many = [np.concatenate([x, np.zeros_like(x)]) for x in (self.first, self.many)]
        while self.stepped + len(steps) > len(self.steps):
            self.steps, self.after = [np.concatenate([x, np.zeros_like(x)]) for x in (self.steps, self.after)]
        self.first[k : k + n], self.many[k : k + n] = begins + self.stepped, lengths
        self.steps[self.stepped : self.stepped + len(steps)] = steps
        self.after[self.stepped : self.stepped + len(steps)] = -1
        self.stepped += len(steps)
        self.paths += zip(texts, skips, strict=True)

    def _segments(self, texts: list[str], bases: np.ndarray | None, skips: list[tuple[int, ...]] | None) -> list[np.ndarray]:
        """``segment`` of many texts: begin, length and ids, and the same of the steps."""
        n = len(texts)
        begins, lengths, first, many = np.zeros((4, n), np.int64)
        ids, steps, used, stepped = [np.zeros(0, np.int64)], [np.zeros(0, np.uint64)], 0, 0
        sizes = np.fromiter(map(len, texts), np.int64, n)
        chars = self.vocabulary.single[np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), "<u4")]
        starts = np.cumsum(sizes) - sizes
        plain = (sizes > 1) & (sizes <= _SHORT)
        if len(chars):
            full = np.flatnonzero(sizes)
            plain[full] &= np.minimum.reduceat(chars, starts[full]) >= 0
        for at in np.flatnonzero(~plain).tolist():
            path = None if skips is None else (frozenset(skips[at]), [])
            got = self.segment(texts[at], 0 if bases is None else int(bases[at]), path)
            begins[at], lengths[at], first[at], many[at] = used, len(got), stepped, len(path[1]) if path else 0
            ids.append(np.array(got, np.int64))
            used += len(got)
            if path:
                steps.append(np.array(path[1], np.uint64))
                stepped += len(path[1])
        rows = np.flatnonzero(plain)
        rows = rows[np.argsort(sizes[rows], kind="stable")]
        cuts = np.flatnonzero(np.diff(sizes[rows], prepend=0, append=_NONE)).tolist()
        for low, high in zip(cuts, cuts[1:], strict=False):
            for start in range(low, high, 8192):
                some = rows[start : min(high, start + 8192)]
                pieces = chars[starts[some][:, None] + np.arange(sizes[some[0]])]
                got, count, terms, each = self._merge(pieces, None if bases is None else bases[some], skips and [skips[i] for i in some.tolist()])
                begins[some], lengths[some], first[some], many[some] = used + np.cumsum(count) - count, count, stepped + np.cumsum(each) - each, each
                ids.append(got)
                steps.append(terms)
                used, stepped = used + len(got), stepped + len(terms)
        return [begins, lengths, np.concatenate(ids), first, many, np.concatenate(steps)]

    def _merge(self, pieces: np.ndarray, bases: np.ndarray | None, skips: list[tuple[int, ...]] | None) -> tuple[np.ndarray, ...]:
        """The agendas of segments of one length side by side: ids and their number, the
        steps of paths and their number. Every row takes one step a round; the column
        after the last stands for a missing neighbour."""
        n, size = pieces.shape
        width = size + 1
        symbol = np.full((n, width), -1, np.int32)
        symbol[:, :size] = pieces
        level, piece = np.full((n, width), _NONE, np.int32), np.zeros((n, width), np.int32)
        found = self.vocabulary.merges(pieces[:, :-1].ravel(), pieces[:, 1:].ravel())
        level[:, : size - 1], piece[:, : size - 1] = (x.reshape(n, size - 1) for x in found)
        after, before = np.tile(np.arange(1, width + 1), (n, 1)), np.tile(np.arange(-1, size), (n, 1))
        before[:, 0] = size
        live, terms, whose, turn = np.arange(n), [], [], 0
        if skips is not None:
            skipped = np.full((n, max(map(len, skips), default=0) or 1), -1)
            for at, own in enumerate(skips):
                skipped[at, : len(own)] = own
            last = skipped.max(1)
        symbol_, level_, piece_, after_, before_ = (x.reshape(-1) for x in (symbol, level, piece, after, before))
        while True:
            i = level[live].argmin(1)
            at = live * width + i
            more = np.flatnonzero(level_[at] < _NONE)
            if not len(more):
                break
            live, i, at = live[more], i[more], at[more]
            term = piece_[at].astype(np.uint64) * np.uint64(_PIECE) + i.astype(np.uint64) * np.uint64(_PLACE)
            if skips is None:
                skip = _mixed(bases[live] ^ term) >> np.uint64(11) < np.uint64(self.cut)
            else:
                skip = (skipped[live] == turn).any(1)
                noted = np.flatnonzero(last[live] < turn)
                terms.append(term[noted])
                whose.append(live[noted])
            turn += 1
            level_[at] = _NONE
            go = np.flatnonzero(~skip)
            row, i, at = live[go] * width, i[go], at[go]
            j = row + after_[at]
            merged, right = piece_[at], after_[j]
            symbol_[at], symbol_[j], level_[j], after_[at] = merged, -1, _NONE, right
            before_[row + right] = i
            level_[at], piece_[at] = self.vocabulary.merges(merged, symbol_[row + right])
            left = row + before_[at]
            level_[left], piece_[left] = self.vocabulary.merges(symbol_[left], merged)
        kept = symbol >= 0
        if not terms:
            return symbol[kept], kept.sum(1), np.zeros(0, np.uint64), np.zeros(n, np.int64)
        rows = np.concatenate(whose)
        return symbol[kept], kept.sum(1), np.concatenate(terms)[np.argsort(rows, kind="stable")], np.bincount(rows, minlength=n)

    def _trim(self) -> None:
        """At the limit at most half of the segments stay, by the use of their blocks;
        paths with skips are found again."""
        pieces, at = list(self.slots), np.fromiter(self.slots.values(), np.int64, len(self.slots))
        used = self.blocks[at]
        stay = np.argsort(-used, kind="stable")[: min(len(used), self.limit) // 4]
        stay = stay[used[stay] > 1]
        self._clear()
        self._learn([pieces[i] for i in stay.tolist()])
        self.blocks[: len(stay)] = used[stay] // 2

    def _skips(self, slots: np.ndarray, bases: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The occurrences that skip a step of their path, and the first such step."""
        begins = self.first[slots]
        counts = self.many[slots]
        ends = np.cumsum(counts)
        own = np.repeat(np.arange(len(slots)), counts)
        at = np.arange(len(own)) + np.repeat(begins - (ends - counts), counts)
        hit = np.flatnonzero(_mixed(bases[own] ^ self.steps[at]) >> np.uint64(11) < np.uint64(self.cut))
        hit = hit[np.flatnonzero(np.diff(own[hit], prepend=-1))]
        return own[hit], at[hit]

    def _draw(self, slots: np.ndarray, bases: np.ndarray) -> np.ndarray:
        """Move every occurrence's slot (from 0 on) to its path's end; the places of
        occurrences whose skips no other one has, which are on no remembered path."""
        alone = []
        for start in range(0, len(slots), _AT_ONCE):
            live = start + np.flatnonzero(slots[start : start + _AT_ONCE] >= 0)
            while len(live):
                some, at = self._skips(slots[live], bases[live])
                live = live[some]
                if len(fresh := np.flatnonzero(self.after[at] < 0)):
                    new, where, times = np.unique(at[fresh], return_index=True, return_counts=True)
                    shared = np.flatnonzero(times > 1)
                    parents = slots[live[fresh[where[shared]]]].tolist()
                    texts, after, k = [], [], self.next
                    for p, step in zip(parents, (new[shared] - self.first[parents]).tolist(), strict=True):
                        text, skips = self.paths[p]
                        texts.append(text)
                        after.append((*skips, (skips[-1] + 1 if skips else 0) + step))
                    self._add(texts, skips=after)
                    self.after[new[shared]] = np.arange(k, self.next)
                to = self.after[at]
                slots[live] = to
                alone.append(live[to < 0])
                live = live[to >= 0]
        return np.concatenate(alone) if alone else np.zeros(0, np.int64)

    def keys(self, ids: list[int | None], texts: pa.Array) -> np.ndarray:
        """What a document's draws depend on."""
        whole = texts.cast(pa.large_binary()) if None in ids else None
        return np.array([xxhash.xxh3_64_intdigest(str(i), self.key) if i is not None else xxhash.xxh3_64_intdigest(whole[at].as_py() or b"", ~self.key & _M64) for at, i in enumerate(ids)], np.uint64)

    def encode(self, texts: pa.Array, at_once: int = 8192, gather: int = 1024, keys: np.ndarray | None = None) -> list[bytes]:
        """The ids of each text, as bytes; an empty or null text has none. Without
        keys the texts are drawn as those of documents without an id."""
        if not self.cut:
            return super().encode(texts, at_once, gather)
        if keys is None:
            keys = self.keys([None] * len(texts), texts)
        out: list[bytes] = []
        for start in range(0, len(texts), at_once):
            if self.next > self.limit or self.used > 8 * self.limit:
                self._trim()
            pieces = self._pieces(texts.slice(start, at_once))
            counts = pc.fill_null(pc.list_value_length(pieces), 0).to_numpy().astype(np.int64)
            coded = pieces.flatten().dictionary_encode()
            del pieces
            words, codes = coded.dictionary.to_pylist(), coded.indices.to_numpy()
            del coded
            ends = np.concatenate([[0], np.cumsum(counts)])
            bases = np.repeat(keys[start : start + at_once], counts)
            bases += (np.arange(len(codes)) - np.repeat(ends[:-1], counts) + 1).astype(np.uint64) * np.uint64(_PIECE)
            bases = _mixed(bases)
            bases ^= bases >> np.uint64(32)
            # A segment that is long, or new and met once, is not remembered.
            often = (np.bincount(codes, minlength=len(words)) > 1).tolist()
            self._learn([w for w, o in zip(words, often, strict=True) if o and w not in self.slots and len(w) <= _SHORT])
            own = np.fromiter((self.slots.get(w, -1) for w in words), np.int64, len(words))
            self.blocks[own[own >= 0]] += 1
            slots = own[codes]
            alone = np.concatenate([np.flatnonzero(slots < 0), self._draw(slots, bases)])
            held = self.used, self.next
            self._add([words[c] for c in codes[alone].tolist()], bases[alone])
            slots[alone] = np.arange(held[1], self.next)
            for row in range(0, len(counts), gather):
                at = ends[row : row + gather + 1]
                ids, lengths = self._gather(slots[at[0] : at[-1]])
                upto = (np.concatenate([[0], np.cumsum(lengths)])[at - at[0]] * 4).tolist()
                data = ids.tobytes()
                out += [data[i:j] for i, j in zip(upto, upto[1:], strict=False)]
            self.used, self.next = held
        return out

    def _skipped(self, base: int, piece: int, place: int) -> bool:
        h = (base ^ (piece * _PIECE + place * _PLACE)) * _MIX & _M64
        return ((h ^ h >> 32) * _MIX & _M64) >> 11 < self.cut

    def segment(self, text: str, base: int | None = None, path: tuple[frozenset[int], list[int]] | None = None) -> list[int]:
        """Ids of one segment: of the occurrence whose hash is ``base`` (none: by the
        segment alone), or along a path, whose steps are noted."""
        v = self.vocabulary
        if text == _LITERAL:
            return [v.bytes_[b] for b in SPACE.encode()]
        if not text:
            return []
        symbols = list(text)
        if len(symbols) > 1:
            if base is None:
                base = xxhash.xxh3_64_intdigest(text.encode(), self.key)
            symbols = self._short(symbols, base, path) if len(symbols) <= _SHORT else self._long(symbols, base)
        out = []
        for s in symbols:
            i = v.ids.get(s)
            if i is None:
                out += [v.bytes_[b] for b in s.encode()]
            else:
                out.append(i)
        return out

    def _short(self, symbols: list[str], base: int, path: tuple[frozenset[int], list[int]] | None = None) -> list[str]:
        """The agenda as a list of the pairs' levels, searched for its smallest. With a
        path its steps are skipped instead of drawn ones, and the hash terms of the
        candidates after the last of them are noted in its list."""
        level, ids, none, cut = self.vocabulary.level, self.vocabulary.ids, 1 << 40, self.cut
        skips, steps = path or (frozenset(), [])
        step = 0
        places = list(range(len(symbols)))
        agenda = [level.get(a + b, none) for a, b in zip(symbols, symbols[1:], strict=False)]
        while agenda:
            best = min(agenda)
            if best == none:
                break
            i = agenda.index(best)
            merged = symbols[i] + symbols[i + 1]
            if path:
                step += 1
                if step - 1 in skips:
                    agenda[i] = none
                    steps.clear()
                    continue
                steps.append((ids[merged] * _PIECE + places[i] * _PLACE) & _M64)
            elif cut:
                h = (base ^ (ids[merged] * _PIECE + places[i] * _PLACE)) * _MIX & _M64  # as _skipped
                if ((h ^ h >> 32) * _MIX & _M64) >> 11 < cut:
                    agenda[i] = none
                    continue
            symbols[i] = merged
            del symbols[i + 1], places[i + 1], agenda[i]
            if i:
                agenda[i - 1] = level.get(symbols[i - 1] + merged, none)
            if i < len(agenda):
                agenda[i] = level.get(merged + symbols[i + 1], none)
        return symbols

    def _long(self, symbols: list[str], base: int) -> list[str]:
        """The same with a heap, for long segments."""
        level, ids, n = self.vocabulary.level, self.vocabulary.ids, len(symbols)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap: list[tuple[int, int, str, str]] = []

        def offer(i: int) -> None:
            if i >= 0 and after[i] < n:
                a, b = symbols[i], symbols[after[i]]
                if (at := level.get(a + b)) is not None:
                    heapq.heappush(heap, (at, i, a, b))

        for i in range(n - 1):
            offer(i)
        while heap:
            _, i, a, b = heapq.heappop(heap)
            if symbols[i] != a or after[i] >= n or symbols[after[i]] != b or not a:
                continue
            merged, j = a + b, after[i]
            if self.cut and self._skipped(base, ids[merged], i):
                continue
            symbols[i], symbols[j] = merged, ""
            after[i] = after[j]
            if after[i] < n:
                before[after[i]] = i
            offer(before[i])
            offer(i)
        return [s for s in symbols if s]


_made: dict[tuple, MergeDropout] = {}


def encoder(model: str, rate: float, seed: int, draw: int) -> MergeDropout:
    """Once per worker process and setting."""
    key = (model, rate, seed, draw)
    if key not in _made:
        _made[key] = MergeDropout(Vocabulary(tokenizer_path(model)), rate, seed, draw)
    return _made[key]


def _encode_batch(b: pa.RecordBatch, one: MergeDropout) -> list[bytes]:
    return one.encode(b.column(1), keys=one.keys(b.column(0).to_pylist(), b.column(1)))


def encode(docs: DataFrame, model: str = "piece_bpe_32k.model", rate: float = 0.1, seed: int = 1, draw: int = 0) -> DataFrame:
    """doc_id, ids (array<int>) of every document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one = encoder(model, rate, seed, draw)
        for b in (whole.slice(at, 8192) for whole in batches for at in range(0, whole.num_rows, 8192)):
            values = [np.frombuffer(x, "<u4").astype(np.int32) for x in _encode_batch(b, one)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(values, pa.list_(pa.int32()))], ["doc_id", "ids"])

    return documents(docs).mapInArrow(tidy(run), "doc_id long, ids array<int>")


def decode(encoded: DataFrame, model: str = "piece_bpe_32k.model") -> DataFrame:
    """doc_id, text from (doc_id, ids)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = Vocabulary(tokenizer_path(model))
        for b in batches:
            texts = [None if x is None else vocabulary.decode(x).decode("utf-8") for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(texts, pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(tidy(run), "doc_id long, text string")


def round_trip(docs: DataFrame, model: str = "piece_bpe_32k.model", rate: float = 0.1, seed: int = 1, draw: int = 0) -> DataFrame:
    """Encode and decode every document: doc_id, draw, n_ids, ids_crc32 (of the ids
    as 32-bit little-endian), text_crc32 (of the decoded UTF-8), lossless."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one = encoder(model, rate, seed, draw)
        for b in (whole.slice(at, 8192) for whole in batches for at in range(0, whole.num_rows, 8192)):
            ids = _encode_batch(b, one)
            back = [one.vocabulary.decode(np.frombuffer(x, "<u4").tolist()) for x in ids]
            texts = b.column(1).cast(pa.large_binary()).to_pylist()
            columns = [
                pa.array([draw] * b.num_rows, pa.int32()),
                pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array([zlib.crc32(x) for x in ids], pa.int64()),
                pa.array([zlib.crc32(x) for x in back], pa.int64()), pa.array([x == (t or b"") for x, t in zip(back, texts, strict=True)]),
            ]
            yield pa.RecordBatch.from_arrays([b.column(0), *columns], ["doc_id", "draw", "n_ids", "ids_crc32", "text_crc32", "lossless"])

    return documents(docs).mapInArrow(tidy(run), "doc_id long, draw int, n_ids long, ids_crc32 long, text_crc32 long, lossless boolean")
