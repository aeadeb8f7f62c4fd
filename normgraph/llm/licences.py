"""Fuzzy search for short licence notices.

Each notice of L characters that may hold k edits is cut into k+1 pieces: a match with at most k edits
leaves one piece untouched (pigeonhole).  One Aho-Corasick pass over the canonical text (lower case, words
joined by single blanks) finds all pieces; only the windows around them go to the regex library's
bounded-error matching, which confirms the edits and gives the span.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame

from normgraph.llm.common import chunks, prune, text_bytes
from normgraph.llm.wordhash import LOWER


@dataclass(frozen=True)
class Notice:
    label: str
    phrase: str
    edits: int
    base: bool = False


#: The three base phrases with their labels.
BASE_NOTICES = (
    Notice("mit", "under the mit license", 2, True),
    Notice("apache-2", "apache license version 2", 2, True),
    Notice("cc-by-nc", "cc by nc", 0, True),
)
MORE_NOTICES = (
    Notice("mit", "permission is hereby granted free of charge", 4),
    Notice("apache-2", "licensed under the apache license", 3),
    Notice("gpl", "gnu general public license", 3),
    Notice("lgpl", "gnu lesser general public license", 3),
    Notice("mpl-2", "mozilla public license version 2", 3),
    Notice("bsd", "redistribution and use in source and binary forms", 4),
    Notice("bsd-3-clause", "bsd 3 clause license", 1),
    Notice("cc-by-sa", "creative commons attribution sharealike", 3),
    Notice("cc-by-nc", "creative commons attribution noncommercial", 3),
    Notice("public-domain", "released into the public domain", 3),
    Notice("proprietary", "all rights reserved", 1),
)
NOTICES = BASE_NOTICES + MORE_NOTICES

#: Bytes that belong to words: 0-9, A-Z, a-z and everything past ASCII; the others part words.
_WORD_BYTES = bytes(b if b >= 0x80 or chr(b).isalnum() else 0x20 for b in LOWER)

SCHEMA = (
    "{id}, n_words bigint, n_base bigint, first_word bigint, last_word bigint, base_labels string, labels string,"
    " score double, spans array<struct<label:string,first_word:bigint,end_word:bigint,edits:int,matched:string>>"
)


def pieces(phrase: str, edits: int) -> list[tuple[int, str]]:
    """``edits + 1`` adjoining pieces of nearly equal length, with their offsets."""
    n, parts = len(phrase), edits + 1
    cuts = [n * i // parts for i in range(parts + 1)]
    return [(a, phrase[a:b]) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]


class NoticeMatcher:
    """Finds notices in one canonical text at a time."""

    def __init__(self, notices: tuple[Notice, ...]):
        import ahocorasick
        import regex

        self.notices = notices
        self.patterns = [regex.compile(f"(?b)(?:{regex.escape(n.phrase)}){{e<={n.edits}}}") for n in notices]
        table: dict[str, list[tuple[int, int]]] = {}
        for i, n in enumerate(notices):
            for at, piece in pieces(n.phrase, n.edits):
                table.setdefault(piece, []).append((i, at))
        self.automaton = ahocorasick.Automaton()
        for piece, uses in table.items():
            self.automaton.add_word(piece, (len(piece), uses))
        self.automaton.make_automaton()

    def windows(self, text: str) -> dict[int, list[list[int]]]:
        """Merged windows for each notice, in text order."""
        found: dict[int, list[list[int]]] = {}
        for end, (size, uses) in self.automaton.iter(text):
            start = end + 1 - size
            for i, at in uses:
                n = self.notices[i]
                lo, hi = max(0, start - at - n.edits), min(len(text), start - at + len(n.phrase) + n.edits)
                spans = found.setdefault(i, [])
                if spans and lo <= spans[-1][1]:
                    spans[-1][0] = min(lo, spans[-1][0])
                    spans[-1][1] = max(hi, spans[-1][1])
                else:
                    spans.append([lo, hi])
        return found

    def best_first(self, i: int, text: str, lo: int, hi: int) -> Iterator:
        """The best match of a window, then those of what is left of it and right of it."""
        open_ = [(lo, hi)]
        least = len(self.notices[i].phrase) - self.notices[i].edits
        while open_:
            lo, hi = open_.pop()
            m = self.patterns[i].search(text, lo, hi) if hi - lo >= least else None
            if m:
                yield m
                open_ += [(lo, m.start()), (m.end(), hi)]

    def match(self, raw: bytes) -> dict:
        words = raw.translate(_WORD_BYTES).split()
        text = (b" " + b" ".join(words) + b" ").decode("latin-1")  # one character a byte
        base: set[tuple[int, str]] = set()
        spans = {}
        score = 0.0
        for i, places in self.windows(text).items():
            n = self.notices[i]
            exact = f" {n.phrase} "
            for lo, hi in places:
                if n.base:
                    at = text.find(exact, max(0, lo - 1), hi + 1)
                    while at >= 0:
                        base.add((text.count(" ", 0, at), n.label))
                        at = text.find(exact, at + 1, hi + 1)
                for m in self.best_first(i, text, lo, hi):
                    inner = m[0].strip(" ")
                    if not inner:
                        continue
                    edits = sum(m.fuzzy_counts)
                    begin = m.start() + len(m[0]) - len(m[0].lstrip(" "))
                    end = m.end() - (len(m[0]) - len(m[0].rstrip(" ")))
                    if edits == 0 and not (text[begin - 1] == " " == text[end]):  # part of longer words: their other letters are edits
                        left, right = text.rfind(" ", 0, begin) + 1, text.find(" ", end)
                        edits = begin - left + right - end
                        if edits > n.edits:
                            continue
                        begin, end, inner = left, right, text[left:right]
                    before = text.count(" ", 0, begin) - 1
                    span = {"label": n.label, "first_word": before, "end_word": before + 1 + inner.count(" "), "edits": edits, "matched": inner.encode("latin-1").decode("utf-8", "replace")}
                    key = (before, n.label, span["end_word"])
                    if key not in spans or edits < spans[key]["edits"]:
                        spans[key] = span
                    score = max(score, 1.0 - edits / len(n.phrase))
        if base:
            score = 1.0
        base_labels = sorted({b for _, b in base})
        return {
            "n_words": len(words),
            "n_base": len(base),
            "first_word": min((b for b, _ in base), default=None),
            "last_word": max((b for b, _ in base), default=None),
            "base_labels": ",".join(base_labels),
            "labels": ",".join(sorted({k[1] for k in spans} | set(base_labels))),
            "score": score,
            "spans": [spans[k] for k in sorted(spans)],
        }


def search_notices(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", notices: tuple[Notice, ...] = NOTICES) -> DataFrame:
    """Licence notices of every whole text, with spans in words and the number of edits.

    One row for each input row, repeated rows included.  A null or empty text has no words, no labels and
    score 0.  ``n_base`` counts all places where a base phrase's words stand consecutively without any edit;
    ``score`` is one less the edits per character of the best match, 0 without any.  Extra columns are dropped.
    """
    kind = dict(docs.dtypes)[id_col]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matcher = NoticeMatcher(notices)
        for part in chunks(batches, text_col):
            rows = [matcher.match(raw) for raw in text_bytes(part.column(1))]
            cols = {k: [r[k] for r in rows] for k in ("n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "spans")}
            long, text = pa.int64(), pa.string()
            kinds = [long, long, long, long, text, text, pa.float64(), pa.list_(pa.struct([("label", text), ("first_word", long), ("end_word", long), ("edits", pa.int32()), ("matched", text)]))]
            yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(v, k) for v, k in zip(cols.values(), kinds, strict=True))], names=[id_col, *cols])

    return prune(docs, id_col, text_col).mapInArrow(run, SCHEMA.format(id=f"`{id_col}` {kind}"))
