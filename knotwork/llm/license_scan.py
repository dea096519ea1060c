"""Fuzzy search for short licence notices.

A notice of up to e edits is cut into e + 1 pieces; by the pigeonhole principle one
of them stands unchanged in every match. Exact search for the pieces locates the
candidate regions, and only there the ``regex`` library's bounded-error matching
runs: it verifies the edits (insertions, deletions, substitutions of characters)
and gives the span. A match starts and ends at word borders of the normalised text
(words joined by single spaces).

Whole texts are scanned. Exact phrases ("base" places) are counted separately: all
places where a phrase's words stand consecutively. ``best`` names each notice's best
span: the fewest edits, then the first word, then the fewest words.

Defined cases: null text counts as empty (no words, no labels, score 0); empty
tables give no rows; repeated rows and null doc_ids are scanned like any other; of
overlapping matches of a notice the one with fewer edits is a span; very long texts
are scanned whole, by exact search for the pieces; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .common import documents, tidy, utf8

# The exact phrases and their labels.
BASE = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}

# Notices of the fuzzy search (label, words, most edits).
NOTICES = (
    ("apache", "apache license", 2),
    ("apache", "licensed under the apache license", 4),
    ("bsd", "bsd license", 1),
    ("bsd", "redistribution and use in source and binary forms", 5),
    ("cc", "creative commons attribution", 3),
    ("cc", "licensed under cc by", 2),
    ("gpl", "general public license", 3),
    ("mit", "mit license", 1),
    ("mit", "permission is hereby granted free of charge", 4),
    ("mpl", "mozilla public license", 2),
)

_WORDS = bytes(
    (c + 32 if 65 <= c <= 90 else c) if 48 <= c <= 57 or 65 <= c <= 90 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256)
)


def normalise(text: bytes | None) -> bytes:
    """The words, A-Z lower-cased, joined by single spaces (UTF-8)."""
    return b" ".join(text.translate(_WORDS).split()) if text else b""


@dataclass(frozen=True)
class Notice:
    label: str
    words: str
    edits: int

    def pieces(self) -> list[tuple[int, bytes]]:
        """(offset, piece) of the edits + 1 near-equal parts."""
        raw, n = self.words.encode(), self.edits + 1
        cuts = [len(raw) * i // n for i in range(n + 1)]
        return [(a, raw[a:b]) for a, b in zip(cuts, cuts[1:], strict=False)]


class Scanner:
    def __init__(self, notices=NOTICES, base: dict[str, str] = BASE):
        self.notices = [Notice(*n) for n in notices]
        self.base = {f" {p} ".encode(): label for p, label in base.items()}
        self.seeds = [n.pieces() for n in self.notices]
        self.patterns = [[regex.compile(rf"(?<![^ ])(?:{regex.escape(n.words)}){{e<={e}}}(?![^ ])") for e in range(n.edits + 1)] for n in self.notices]

    def base_places(self, words: bytes) -> list[tuple[int, str]]:
        """(word index, label) of all exact phrases."""
        padded, out = b" " + words + b" ", []
        for phrase, label in self.base.items():
            at = padded.find(phrase)
            done = index = 0
            while at >= 0:
                index += padded.count(b" ", done, at)
                done = at
                out.append((index, label))
                at = padded.find(phrase, at + 1)
        return out

    def regions(self, words: bytes, k: int) -> list[tuple[int, int]]:
        """Merged candidate regions of notice k, cut to word borders."""
        notice, found = self.notices[k], []
        slack, length = 4 * notice.edits, len(notice.words.encode())  # an edit is a character of up to 4 bytes
        for offset, piece in self.seeds[k]:
            at = words.find(piece)
            while at >= 0:
                found.append((max(0, at - offset - slack), min(len(words), at - offset + length + 2 * slack)))
                at = words.find(piece, at + 1)
        out: list[tuple[int, int]] = []
        for a, b in sorted(found):
            if out and a <= out[-1][1]:
                out[-1] = (out[-1][0], max(b, out[-1][1]))
            else:
                out.append((a, b))
        return [(a, b) for a, b in (self._trim(words, *r) for r in out) if a < b]

    @staticmethod
    def _trim(words: bytes, a: int, b: int) -> tuple[int, int]:
        """Matches begin and end at word borders, so partial words at the ends go."""
        if a and words[a - 1] != 32:
            a = words.find(b" ", a, b) + 1 or b
        if b < len(words) and words[b] != 32:
            b = words.rfind(b" ", a, b)
        return a, b

    def spans(self, words: bytes) -> list[tuple[str, str, int, int, int]]:
        """(label, notice, first word, words, edits) of verified matches, the least
        edited first in each region and not overlapping within a notice."""
        out = []
        for k, notice in enumerate(self.notices):
            for a, b in self.regions(words, k):
                text, before = words[a:b].decode("utf-8", "replace"), words.count(b" ", 0, a)
                taken: list[tuple[int, int]] = []
                for e, pattern in enumerate(self.patterns[k]):
                    for m in pattern.finditer(text):
                        if all(m.end() <= x or m.start() >= y for x, y in taken):
                            taken.append(m.span())
                            out.append((notice.label, notice.words, before + text.count(" ", 0, m.start()), m.group().count(" ") + 1, e))
        return out

    def best(self, words: bytes, spans: list[tuple[str, str, int, int, int]]) -> str:
        """notice:first word:words:edits of each notice's best span, joined by |."""
        out = []
        for notice in self.notices:
            own = min(((e, at) for label, text, at, _, e in spans if (label, text) == (notice.label, notice.words)), default=None)
            if own is not None:
                e, at = own
                rest = words.split(b" ", at + len(notice.words) + e)[at:]
                n = next(n for n in range(1, len(rest) + 1) if edits(" ".join(w.decode("utf-8", "replace") for w in rest[:n]), notice.words) == e)
                out.append(f"{notice.words}:{at}:{n}:{e}")
        return "|".join(sorted(out))


def edits(a: str, b: str) -> int:
    """The least number of inserted, deleted or substituted characters."""
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


SCANNED = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, best string, spans array<struct<label:string,notice:string,first_word:long,n_words:long,edits:int>>"
_SPAN = pa.list_(pa.struct([("label", pa.string()), ("notice", pa.string()), ("first_word", pa.int64()), ("n_words", pa.int64()), ("edits", pa.int32())]))


def scan(docs: DataFrame, notices=NOTICES, base: dict[str, str] = BASE) -> DataFrame:
    """One row per document: word and base-place counts, labels, score (the best
    similarity of any notice; 1 for an exact one), each notice's best span (see
    ``Scanner.best``) and all fuzzy spans."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(notices, base)
        kinds = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.float64(), pa.string(), _SPAN]
        for b in batches:
            rows: list[list] = [[] for _ in kinds]
            for text in utf8(b):
                words = normalise(text)
                places, spans = scanner.base_places(words), scanner.spans(words)
                own = {label for _, label in places}
                score = max([1 - s[4] / len(s[1]) for s in spans] + [1.0] * bool(places), default=0.0)
                starts = [i for i, _ in places]
                row = (
                    words.count(b" ") + 1 if words else 0, len(places), min(starts, default=None), max(starts, default=None),
                    ",".join(sorted(own)), ",".join(sorted(own | {s[0] for s in spans})), score, scanner.best(words, spans),
                    [dict(zip(("label", "notice", "first_word", "n_words", "edits"), s, strict=True)) for s in spans],
                )
                for column, value in zip(rows, row, strict=True):
                    column.append(value)
            names = [c.split()[0] for c in SCANNED.split("array")[0].split(", ")]
            yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array(c, t) for c, t in zip(rows, kinds, strict=True)]], names)

    return documents(docs).mapInArrow(tidy(run), SCANNED)
