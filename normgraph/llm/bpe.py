"""Distinct-word byte-pair encoding of whole batches with the tokenizers library.

Texts are cut into the words of the byte-level pre-tokenizer with numpy on code points, each distinct word
of a batch is looked up or encoded once, and ids return to their positions by a gather.  The result equals
``Tokenizer.encode(text, add_special_tokens=False).ids``, special-token strings in a text included.
"""

from __future__ import annotations

import json

import numpy as np
import regex

from normgraph.llm.common import ragged_take
from normgraph.llm.wordhash import range_hash

_OTHER, _LETTER, _NUMBER, _SPACE, _STOP = 0, 1, 2, 3, 4
_classes: np.ndarray | None = None
#: Endings that the pre-tokenizer splits off after an apostrophe, in its order.
CONTRACTIONS = ("s", "t", "re", "ve", "m", "ll", "d")
_CACHE_WORDS = 1_500_000
_encoders: dict[str, BlockEncoder] = {}


def _class_table() -> np.ndarray:
    """Class of each code point: letter, number, white space or other; surrogates are stops of ours."""
    global _classes
    if _classes is None:
        table = np.zeros(0x110000, dtype=np.uint8)
        every = "".join(map(chr, [c for c in range(0x110000) if not 0xD800 <= c < 0xE000]))
        for code, pattern in ((_LETTER, r"\p{L}+"), (_NUMBER, r"\p{N}+"), (_SPACE, r"\s+")):
            for m in regex.finditer(pattern, every):
                lo, hi = ord(m[0][0]), ord(m[0][-1])
                if lo < 0xD800 <= hi:
                    table[lo:0xD800] = code
                    table[0xE000 : hi + 1] = code
                else:
                    table[lo : hi + 1] = code
        table[0xD800:0xE000] = _STOP
        _classes = table
    return _classes


def word_starts(points: np.ndarray) -> np.ndarray:
    """Start offsets of the pre-tokenizer's words in an array of code points; stop points are words of their own."""
    n = len(points)
    if not n:
        return np.zeros(0, dtype=np.int64)
    cls = _class_table()[points]
    start = np.ones(n, dtype=bool)
    start[1:] = (cls[1:] != cls[:-1]) | (cls[1:] == _STOP)
    space = cls == _SPACE
    # the last white space before a visible character: a blank joins that character, another stands alone
    last = np.flatnonzero(space[:-1] & (cls[1:] <= _NUMBER))
    start[last] = True
    start[last[points[last] == 32] + 1] = False
    quote = np.flatnonzero((points[:-1] == 39) & (cls[1:] == _LETTER))
    if len(quote):
        quote = quote[start[quote]]  # one that opens a word of its own
        stop = np.append(points[:], [0xD800] * 3)
        for q in quote.tolist():
            for tail in CONTRACTIONS:
                if all(stop[q + 1 + i] == ord(c) for i, c in enumerate(tail)):
                    start[q + 1] = False
                    after = q + 1 + len(tail)
                    if after < n and cls[after] == _LETTER:
                        start[after] = True
                    break
    return np.flatnonzero(start)


def joined(texts: list[str], names: list[str]) -> str:
    """All texts in one string, the special tokens ``names`` as stop points of their own, each text ended by the stop point D800."""
    out = []
    for t in texts:
        for i, name in enumerate(names):
            if name in t:
                t = t.replace(name, chr(0xD801 + i))
        out.append(t)
    return "\ud800".join(out) + "\ud800"


class WordEncoder:
    """Cuts texts into words and encodes single words; holds nothing but the vocabulary."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        spec = json.loads(self.tokenizer.to_str())
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        if len(self.special) > 0x400:
            raise ValueError("more special tokens than stop points")
        self.names = list(self.special)
        self.model = self.tokenizer.model
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]  # bytes that the byte alphabet shows as themselves
        hidden = [b for b in range(256) if b not in set(shown)]
        self.alphabet = {b: chr(b) for b in shown} | {b: chr(256 + i) for i, b in enumerate(hidden)}

    def join(self, texts: list[str]) -> str:
        """``joined`` with the vocabulary's special tokens."""
        return joined(texts, self.names)

    def ids_of(self, word: str) -> list[int]:
        """Ids of one word of ``word_starts``; a stop point is its special token, or nothing at the end of a text."""
        if 0xD800 <= ord(word[0]) < 0xDC00:
            k = ord(word[0]) - 0xD801
            return [self.special[self.names[k]]] if k >= 0 else []
        return [x.id for x in self.model.tokenize(word.encode().decode("latin-1").translate(self.alphabet))]

    def piece_list(self) -> list[bytes]:
        """Bytes of each id; ids without a piece have none."""
        back = {c: b for b, c in self.alphabet.items()}
        named = {i: name for name, i in self.special.items()}
        size = max([self.tokenizer.get_vocab_size(with_added_tokens=True), *(i + 1 for i in named)])
        return [named[i].encode() if i in named else bytes(back[c] for c in self.tokenizer.id_to_token(i) or "") for i in range(size)]


def word_keys(points: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """64-bit hash of the code points of each word."""
    keys = np.empty(len(lo), dtype=np.uint64)
    at = 0
    while at < len(lo):  # the power tables stay small whatever the batch holds
        to = max(at + 1, int(np.searchsorted(hi, lo[at] + (1 << 20) - 8, side="right")))
        a = int(lo[at])
        keys[at:to] = range_hash(points[a : int(hi[to - 1])].astype(np.uint64) + np.uint64(1), lo[at:to] - a, hi[at:to] - a)
        at = to
    return keys


def points_of(whole: str) -> np.ndarray:
    return np.frombuffer(whole.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)


class BlockEncoder(WordEncoder):
    """Encodes batches; keeps the ids of words seen before, up to a bounded number of words."""

    def __init__(self, path: str):
        super().__init__(path)
        self._reset()
        self._pieces: tuple[np.ndarray, np.ndarray] | None = None

    def _reset(self) -> None:
        self.index: dict[int, int] = {}
        self.flat = np.zeros(1 << 16, dtype=np.uint32)
        self.offs = np.zeros(1 << 14, dtype=np.int64)
        self.n = 0

    def _add(self, key: int, ids: list[int]) -> int:
        at, i = int(self.offs[self.n]), self.n
        if at + len(ids) > len(self.flat):
            self.flat = np.concatenate([self.flat, np.zeros(max(len(self.flat), len(ids)), dtype=np.uint32)])
        if i + 2 > len(self.offs):
            self.offs = np.concatenate([self.offs, np.zeros(len(self.offs), dtype=np.int64)])
        self.flat[at : at + len(ids)] = ids
        self.offs[i + 1] = at + len(ids)
        self.n += 1
        self.index[key] = i
        return i

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """All ids of all texts in order, and how many ids each text has."""
        whole = self.join(texts)
        points = points_of(whole)
        lo = word_starts(points)
        hi = np.append(lo[1:], len(points))
        keys = word_keys(points, lo, hi)
        distinct, first, inverse = np.unique(keys, return_index=True, return_inverse=True)
        if self.n > _CACHE_WORDS:
            self._reset()
        get = self.index.get
        rows = np.empty(len(distinct), dtype=np.int64)
        for j, (key, f) in enumerate(zip(distinct.tolist(), first.tolist(), strict=True)):
            i = get(key)
            if i is None:
                i = self._add(key, self.ids_of(whole[lo[f] : hi[f]]))
            rows[j] = i
        ids, lens = ragged_take(self.flat, self.offs[: self.n + 1], rows[inverse.ravel()])
        ends = np.cumsum(lens)
        stop = np.flatnonzero(points[lo] == 0xD800)
        upto = ends[stop]
        return ids, np.diff(upto, prepend=0)

    def pieces(self) -> tuple[np.ndarray, np.ndarray]:
        """The id-to-piece table: bytes of all pieces and their offsets, by id."""
        if self._pieces is None:
            parts = self.piece_list()
            offs = np.zeros(len(parts) + 1, dtype=np.int64)
            np.cumsum([len(p) for p in parts], out=offs[1:])
            self._pieces = np.frombuffer(b"".join(parts), dtype=np.uint8), offs
        return self._pieces

    def decode(self, ids: np.ndarray, counts: np.ndarray) -> list[bytes]:
        """UTF-8 text of each run of ids; ids outside the vocabulary add nothing, broken sequences become U+FFFD."""
        flat, offs = self.pieces()
        keep = ids < len(offs) - 1
        if not keep.all():
            upto = np.concatenate([[0], np.cumsum(keep)])[np.concatenate([[0], np.cumsum(counts)])]
            ids, counts = ids[keep], np.diff(upto)
        out, lens = ragged_take(flat, offs, ids.astype(np.int64))
        byte_ends = np.concatenate([[0], np.cumsum(lens)])
        edges = byte_ends[np.concatenate([[0], np.cumsum(counts)])].tolist()
        raw = out.tobytes()
        return [raw[a:b].decode("utf-8", "replace").encode() for a, b in zip(edges[:-1], edges[1:], strict=True)]


_plain: dict[str, WordEncoder] = {}


def word_encoder(path: str) -> WordEncoder:
    """One a worker process and vocabulary file; its size is that of the vocabulary."""
    if path not in _plain:
        _plain[path] = WordEncoder(path)
    return _plain[path]


def block_encoder(path: str) -> BlockEncoder:
    """One encoder a worker process and vocabulary file."""
    if path not in _encoders:
        _encoders[path] = BlockEncoder(path)
    return _encoders[path]
