"""Byte-level BPE ids of many texts at once.

A text is split into pre-tokens (runs of letters, of digits, of other signs, each with one blank before it, and runs of
white space) with array operations; the distinct pre-tokens of a piece are merged in one call, as one text with a zero
byte after each, and copied to their places; a worker keeps the first ``_KEPT`` and more of them.  Rows that need more
than that (contractions, code points from U+0300, zero bytes, special tokens' strings, broken UTF-8) go through the
tokenizers library as whole texts.  Both ways give the same ids.
"""

from __future__ import annotations

import sys
import unicodedata

import numpy as np
from pyspark.cloudpickle import register_pickle_by_value

from . import kernels as K

_KEPT = 1 << 17
_LETTER, _DIGIT, _OTHER, _SPACE = range(4)


def _classes() -> np.ndarray:
    if "classes" not in K._cache:
        out = np.full(0x300, _OTHER, np.uint8)
        for c in range(0x300):
            kind = unicodedata.category(chr(c))[0]
            out[c] = _LETTER if kind == "L" else _DIGIT if kind == "N" else _SPACE if c in (9, 10, 11, 12, 13, 32, 0x85, 0xA0) else _OTHER
        K._cache["classes"] = out
    return K._cache["classes"]


class Encoder:
    """name: a vocabulary of public_tokenizers, as ranks and as a tokenizer's file."""

    def __init__(self, name: str = "byte_bpe_50k"):
        import base64

        import public_tokenizers
        import tiktoken
        from tokenizers import Tokenizer

        with open(public_tokenizers.path(f"{name}.tiktoken"), "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.merge = tiktoken.Encoding("own", pat_str=r"[^\x00]+|\x00", mergeable_ranks=ranks, special_tokens={}).encode_to_numpy
        self.stop = ranks[b"\x00"]
        self.known, self.begin, self.size, self.flat = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint32)
        self.whole = Tokenizer.from_file(public_tokenizers.path(f"{name}.json"))
        self.special = [s.encode() for s in (t.content for t in self.whole.get_added_tokens_decoder().values())]

    def encode(self, piece: K.Piece) -> list[np.ndarray]:
        """The ids of each row."""
        data, off = piece.data, piece.off
        out: list[np.ndarray | None] = [None] * piece.n
        odd = self._odd(piece)
        for r in np.flatnonzero(odd):
            out[r] = np.array(self.whole.encode(piece.text(r), add_special_tokens=False).ids, np.uint32)
        if not odd.all() and len(data):
            ids, bound = self._split(data, off, odd)
            for r in np.flatnonzero(~odd):
                out[r] = ids[bound[r]:bound[r + 1]]
        return [np.zeros(0, np.uint32) if x is None else x for x in out]

    def _odd(self, piece: K.Piece) -> np.ndarray:
        data, off = piece.data, piece.off
        odd = np.zeros(piece.n + 1, bool)
        at = np.flatnonzero((data >= 0xCC) | (data == 0xC0) | (data == 0xC1) | (data == 0))
        quote = np.flatnonzero(data[:-1] == 39) if len(data) else np.zeros(0, np.int64)
        quote = quote[np.isin(data[quote + 1], np.frombuffer(b"stmdrvl", np.uint8))]
        body = data.tobytes()
        marks = []
        for s in self.special:
            k = body.find(s)
            while k >= 0:
                marks.append(k)
                k = body.find(s, k + 1)
        odd[np.searchsorted(off, np.concatenate([at, quote, np.array(marks, np.int64)]), "right") - 1] = True
        # a lead byte must be followed by just one continuation byte
        lead, cont = data >= 0xC2, (data & 0xC0) == 0x80
        wrong = np.flatnonzero(np.concatenate([[False], lead[:-1]]) != cont) if len(data) else np.zeros(0, np.int64)
        odd[np.searchsorted(off, wrong, "right") - 1] = True
        if len(data) and lead[-1]:
            odd[piece.n - 1] = True
        return odd[:-1]

    def _split(self, data: np.ndarray, off: np.ndarray, odd: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        first = np.flatnonzero((data & 0xC0) != 0x80)  # bytes at which code points begin
        point = data[first].astype(np.int64)
        two = np.flatnonzero(point >= 0xC2)
        after = np.minimum(first[two] + 1, len(data) - 1)
        point[two] = np.minimum(((point[two] & 0x1F) << 6) | (data[after] & 0x3F), 0x2FF)
        kind = _classes()[np.minimum(point, 0x2FF)]
        n = len(first)
        rows = np.searchsorted(first, off)
        edge = np.zeros(n + 1, bool)
        edge[rows] = True
        edge = edge[:-1]
        space = kind == _SPACE
        start = edge.copy()
        change = np.zeros(n, bool)
        change[1:] = kind[1:] != kind[:-1]
        start |= change & space  # a run of white space begins
        last = np.zeros(n, bool)  # the last of a run before something else in the row
        last[:-1] = space[:-1] & ~space[1:] & ~edge[1:]
        start |= last
        before = np.zeros(n, bool)  # begins without a blank of its own
        before[1:] = change[1:] & ~space[1:] & (~space[:-1] | (point[:-1] != 32))
        start |= before
        a = first[start]
        b = np.append(a[1:], len(data))
        row = np.searchsorted(off, a, "right") - 1
        good = ~odd[row]
        a, b, row = a[good], b[good], row[good]
        h = K.span_hashes(data, a, b)
        h, where, back = np.unique(h, return_index=True, return_inverse=True)
        begin, size, flat = self._merged(data, a[where], b[where], h)
        own = size[back]
        ends = np.cumsum(own)
        ids = flat[np.repeat(begin[back] - (ends - own), own) + np.arange(int(ends[-1]) if len(ends) else 0)]
        count = np.bincount(row, own, len(off) - 1).astype(np.int64)
        return ids, np.concatenate([[0], np.cumsum(count)])

    def _merged(self, data: np.ndarray, a: np.ndarray, b: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Where the ids of the pre-tokens at a to b, with sorted hashes h, begin, how many they are, and all ids."""
        at = np.searchsorted(self.known, h)
        old = np.append(self.known, np.uint64(0))[at] == h
        old &= at < len(self.known)
        a, b = a[~old], b[~old]
        size = b - a + 1
        ends = np.cumsum(size)
        body = np.append(data, np.uint8(0))[np.repeat(a - (ends - size), size) + np.arange(int(ends[-1]) if len(ends) else 0)]
        body[ends - 1] = 0
        new = self.merge(body.tobytes().decode())
        stop = np.flatnonzero(new == self.stop)
        first = np.concatenate([np.zeros(1, np.int64), stop + 1])[:-1]
        flat = np.concatenate([self.flat, new])
        begin, size = np.empty(len(h), np.int64), np.empty(len(h), np.int64)
        begin[old], size[old] = self.begin[at[old]], self.size[at[old]]
        begin[~old], size[~old] = first + len(self.flat), stop - first
        if len(self.known) < _KEPT and len(stop):
            known = np.concatenate([self.known, h[~old]])
            order = np.argsort(known)
            self.known, self.flat = known[order], flat
            self.begin, self.size = np.concatenate([self.begin, begin[~old]])[order], np.concatenate([self.size, size[~old]])[order]
        return begin, size, flat


def encoder(name: str = "byte_bpe_50k") -> Encoder:
    """One for each worker process."""
    if ("encoder", name) not in K._cache:
        K._cache["encoder", name] = Encoder(name)
    return K._cache["encoder", name]


register_pickle_by_value(sys.modules[__name__])
