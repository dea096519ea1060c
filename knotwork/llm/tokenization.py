"""Batch encoding with a public tokenizer file and a memory of repeated pieces.

Natural text repeats its words, and a byte-pair tokenizer never merges across a
pre-token border. Encoding a text as the concatenation of its space-separated
pieces is therefore exact where each cut is a pre-token border, and each distinct
piece needs the tokenizer only once per worker. The cuts per kind of file:

* ``lead_space`` (byte-level regex, a space belongs to the word after it): before
  every space and on both sides of every newline of a text in which no two white
  space characters touch; a run of white space stays inside one piece.
* ``gap`` (white space is dropped): at spaces and newlines.
* both: before a comma or full stop that follows a letter or digit and precedes
  white space, in texts where each of them follows a digit or a Latin letter.

Anything else goes to the tokenizer as a whole. Tokenizers are never trained here.
"""

from __future__ import annotations

import json
import re
import os
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # one thread a worker; Spark runs the workers

_MARK = "\x01"
#: Two white space characters that touch, for Arrow's regular expressions.
_RUN = r"[\s\x0b\x1c-\x1f\x{85}\x{a0}\x{1680}\x{2000}-\x{200a}\x{2028}\x{2029}\x{202f}\x{205f}\x{3000}]{2}|\x01"
#: A comma or full stop at the start or after anything but a digit or a Latin letter
#: that lower-casing and composing leave one letter.
_TOUCHING = r"[^0-9A-Za-z\x{C0}-\x{D6}\x{D8}-\x{F6}\x{F8}-\x{12F}\x{131}-\x{17F}][,.]|^[,.]"
#: Spaces between two visible characters, for texts that also hold runs of white space.
_SAFE_SPACE = re.compile(r"(?<=\S)(?= \S)")


class PieceEncoder:
    """Encodes columns of texts to little-endian unsigned 32-bit ids.

    Pieces are told apart by Arrow's dictionary encoding, a block of texts at a
    time; only a block's distinct pieces are looked up, and only new ones reach the
    tokenizer. The ids of all remembered pieces lie in one flat array, from which a
    block's ids are gathered. ``limit`` bounds the remembered pieces, ``longest``
    the length of one."""

    def __init__(self, path: str, limit: int = 400_000, longest: int = 48):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.limit, self.longest = limit, longest
        self._clear()
        with open(path, encoding="utf-8") as f:
            made = json.load(f)
        self.kind = _kind(made.get("normalizer"), made.get("pre_tokenizer"))
        self.lower = any(n.get("type") == "Lowercase" for n in (made.get("normalizer") or {}).get("normalizers", []))
        #: What joins pieces for one call, its id, and what no such piece may hold:
        #: nothing, white space after the first character, the separator, an added token.
        self.joint: tuple[str, int, object] | None = None
        if glue := {"lead_space": "\n", "gap": " \x02 "}.get(self.kind):
            ids = self.tokenizer.encode(glue, add_special_tokens=False).ids
            added = [re.escape(t["content"]) for t in made.get("added_tokens", [])]
            odd = re.compile("|".join([r".\s", r"^[^\S ]", "^ ?$", "\x02", *added]), re.DOTALL).search
            if len(ids) == 1:
                self.joint = (glue, ids[0], odd)

    def _clear(self) -> None:
        self.slots: dict[str, int] = {}
        self.begin, self.length, self.blocks = (np.zeros(1 << 16, np.int32) for _ in range(3))
        self.flat, self.used, self.next = np.zeros(1 << 18, "<u4"), 0, 0

    def _pieces(self, texts: pa.Array) -> pa.ListArray:
        """A list of pieces for every text (none for null)."""
        if self.kind not in ("gap", "lead_space"):
            return pa.array([[t] if t else [] for t in texts.to_pylist()], pa.list_(pa.string()))
        # A comma or full stop after a letter or digit and before white space is a
        # pre-token of its own; without it "word" and "word," are one piece.
        tidy = pc.invert(pc.match_substring_regex(texts, _TOUCHING))
        if self.kind == "gap":
            if self.lower:  # the file lower-cases; "<|" may begin an added token
                texts = pc.if_else(pc.match_substring(texts, "<|"), texts, pc.ascii_lower(texts))
            plain = pc.replace_substring(texts, "\n", " ")
            apart = pc.replace_substring(pc.replace_substring(plain, ", ", " , "), ". ", " . ")
            return pc.split_pattern(pc.if_else(tidy, apart, plain), " ")
        odd = pc.fill_null(pc.match_substring_regex(texts, _RUN), False)
        plain = pc.replace_substring(pc.replace_substring(texts, " ", _MARK + " "), "\n", f"{_MARK}\n{_MARK}")
        apart = pc.replace_substring(pc.replace_substring(plain, "," + _MARK, f"{_MARK},{_MARK}"), "." + _MARK, f"{_MARK}.{_MARK}")
        out = pc.split_pattern(pc.if_else(tidy, apart, plain), _MARK)
        if not pc.any(odd).as_py():
            return out
        return pa.array([_SAFE_SPACE.split(t) if o else p for t, o, p in zip(texts.to_pylist(), odd.to_pylist(), out.to_pylist(), strict=True)], pa.list_(pa.string()))

    def _append(self, pieces: list[str], ids: np.ndarray, begins: np.ndarray, lengths: np.ndarray) -> None:
        n, k = len(pieces), self.next
        while k + n > len(self.begin):
            self.begin, self.length, self.blocks = [np.concatenate([x, np.zeros_like(x)]) for x in (self.begin, self.length, self.blocks)]
        while self.used + len(ids) > len(self.flat):
            self.flat = np.concatenate([self.flat, np.zeros_like(self.flat)])
        self.flat[self.used : self.used + len(ids)] = ids
        self.begin[k : k + n], self.length[k : k + n], self.blocks[k : k + n] = begins + self.used, lengths, 0
        self.slots.update(zip(pieces, range(k, k + n), strict=True))
        self.used, self.next = self.used + len(ids), k + n

    def _learn(self, pieces: list[str]) -> None:
        """Ids of new pieces by few calls: joined by a separator that is a pre-token
        and an id of its own, and cut at that id. Odd pieces go one by one."""
        odd = self.joint[2] if self.joint else (lambda _: True)
        plain = [p for p in pieces if not odd(p)]
        rest = [p for p in pieces if odd(p)] if len(plain) < len(pieces) else []
        for start in range(0, len(plain), 4096):
            glue, mark, _ = self.joint
            some = plain[start : start + 4096]
            ids = np.array(self.tokenizer.encode_batch_fast([glue.join(some)], add_special_tokens=False)[0].ids, "<u4")
            cuts = np.flatnonzero(ids == mark)
            if len(cuts) != len(some) - 1:
                raise ValueError("the separator is not a token of its own")
            begins = np.concatenate([[0], cuts + 1])
            self._append(some, ids, begins, np.concatenate([cuts, [len(ids)]]) - begins)
        for start in range(0, len(rest), 1024):
            some = rest[start : start + 1024]
            found = [e.ids for e in self.tokenizer.encode_batch_fast(some, add_special_tokens=False)]
            lengths = np.array([len(f) for f in found], np.int64)
            self._append(some, np.fromiter(chain.from_iterable(found), "<u4", int(lengths.sum())), np.cumsum(lengths) - lengths, lengths)

    def _trim(self) -> None:
        """At the limit at most half of the pieces stay: those that most blocks have
        used, with their counts halved, so that old fame fades."""
        pieces, at = list(self.slots), np.fromiter(self.slots.values(), np.int64, len(self.slots))
        used = self.blocks[at]
        cut = max(2, int(np.partition(used, len(used) // 2)[len(used) // 2]) + 1)
        stay = np.flatnonzero(used >= cut)
        kept = [pieces[i] for i in stay.tolist()] + [""]
        at = np.append(at[stay], self.slots.get("", 0))
        ids, lengths = self._gather(at)
        if "" not in self.slots:
            lengths[-1] = 0
        self.slots, self.used, self.next = {}, 0, 0
        self._append(kept, ids, np.cumsum(lengths) - lengths, lengths)
        self.blocks[: len(stay)] = used[stay] // 2

    def _gather(self, slots: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The ids of the slots one after the other, and how many each has."""
        lengths = self.length[slots]
        ends = np.cumsum(lengths, dtype=np.int32)  # a block's ids stay far below 2**31
        shift = np.repeat(self.begin[slots] - (ends - lengths), lengths)
        shift += np.arange(len(shift), dtype=np.int32)
        return self.flat[shift], lengths

    def encode(self, texts: pa.Array, at_once: int = 8192, gather: int = 1024) -> list[bytes]:
        """The ids of each text, as bytes; an empty or null text has none."""
        out: list[bytes] = []
        for start in range(0, len(texts), at_once):
            if len(self.slots) > self.limit or self.used > 8 * self.limit:
                self._trim()
            pieces = self._pieces(texts.slice(start, at_once))
            counts = pc.fill_null(pc.list_value_length(pieces), 0).to_numpy()
            coded = pieces.flatten().dictionary_encode()
            del pieces
            words, codes = coded.dictionary.to_pylist(), coded.indices.to_numpy()
            del coded
            fresh = [w for w in words if w not in self.slots]
            if fresh:
                self._learn(fresh)
            slots = np.fromiter(map(self.slots.__getitem__, words), np.int32, len(words))
            self.blocks[slots] += 1
            ends = np.concatenate([[0], np.cumsum(counts)])
            for row in range(0, len(counts), gather):
                own = ends[row : row + gather + 1]
                ids, lengths = self._gather(slots[codes[own[0] : own[-1]]])
                upto = (np.concatenate([[0], np.cumsum(lengths)])[own - own[0]] * 4).tolist()
                data = ids.tobytes()
                out += [data[i:j] for i, j in zip(upto, upto[1:], strict=False)]
            for w in fresh:
                if len(w) > self.longest:
                    del self.slots[w]
        return out


def _kind(normalizer: dict | None, pre: dict | None) -> str:
    """How the file's texts may be cut; empty: not at all."""
    pre, normalizer = pre or {}, normalizer or {}
    if pre.get("type") == "ByteLevel" and pre.get("use_regex") and not pre.get("add_prefix_space") and not normalizer:
        return "lead_space"
    steps = pre.get("pretokenizers") or []
    first = steps[0] if steps else {}
    plain = {n.get("type") for n in normalizer.get("normalizers", [])} <= {"NFC", "Replace", "Lowercase"}
    dropped = first.get("type") == "Split" and first.get("behavior") == "Removed" and first.get("invert")
    if plain and dropped and len(steps) == 2 and steps[1].get("type") == "ByteLevel" and not steps[1].get("use_regex") and not steps[1].get("add_prefix_space"):
        return "gap"
    return ""


_encoders: dict[str, PieceEncoder] = {}


def encoder(path: str) -> PieceEncoder:
    """One encoder per worker process and file."""
    if path not in _encoders:
        _encoders[path] = PieceEncoder(path)
    return _encoders[path]


def tokenizer_path(name: str) -> str:
    """Where a public tokenizer file is installed. Resolved on the worker that
    reads it, so machines may keep it in different places."""
    import os

    if os.path.isabs(name):
        return name
    import public_tokenizers

    return public_tokenizers.path(name)
