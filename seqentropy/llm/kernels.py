"""Array kernels over Arrow text batches: words, n-gram hashes and runs without a loop over words.

A batch's text column is one byte buffer with offsets, so every word of many documents is found and hashed
by a few passes of numpy.  Batches are cut in pieces of about ``PIECE`` bytes, which bounds the memory of a
Python worker whatever the batch size (one text longer than that is a piece of its own; hashes are taken in stretches of
it, and what is kept besides is a few bytes for each of its bytes, and some numbers for each of its words).

All functions here are pickled by value: executors need numpy and pyarrow, not this package.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.cloudpickle import register_pickle_by_value

PIECE = 1 << 20
_MULT = 0x9E3779B97F4A7C15 | 1
_cache: dict = {}


class Piece:
    """Consecutive rows of a batch: ``data`` bytes, ``off`` the rows' bounds in it, ``null`` flags."""

    def __init__(self, data: np.ndarray, off: np.ndarray, null: np.ndarray, first: int):
        self.data, self.off, self.null, self.first = data, off, null, first
        self.n = len(off) - 1

    def text(self, row: int) -> str:
        return self.data[self.off[row]:self.off[row + 1]].tobytes().decode("utf-8", "replace")


def pieces(column: pa.Array, limit: int = PIECE) -> Iterator[Piece]:
    """Cuts a string column in pieces of whole rows."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if pa.types.is_null(column.type):
        column = column.cast(pa.string())
    n = len(column)
    if not n:
        return
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, body = column.buffers()
    off = np.frombuffer(offsets, np.int64 if wide else np.int32, n + 1, column.offset * (8 if wide else 4)).astype(np.int64)
    data = np.frombuffer(body, np.uint8) if body is not None else np.zeros(0, np.uint8)
    null = column.is_null().to_numpy(zero_copy_only=False)
    lo = 0
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(off, off[lo] + limit, "right")) - 1)
        yield Piece(data[off[lo]:off[hi]], off[lo:hi + 1] - off[lo], null[lo:hi], lo)
        lo = hi


def table(kind: str) -> np.ndarray:
    """Byte classes.  ``space``: words are runs outside blanks \\x20 \\x09-\\x0D; ``alnum``: runs of letters, digits and non-ASCII."""
    if kind not in _cache:
        b = np.arange(256)
        if kind == "space":
            _cache[kind] = ~((b == 32) | ((b >= 9) & (b <= 13)))
        elif kind == "alnum":
            _cache[kind] = ((b >= 48) & (b <= 57)) | ((b >= 97) & (b <= 122)) | (b >= 128)
        elif kind == "lower":
            _cache[kind] = np.where((b >= 65) & (b <= 90), b + 32, b).astype(np.uint8)
        elif kind == "byte":
            _cache[kind] = mix(np.arange(1, 257, dtype=np.uint64))
    return _cache[kind]


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _powers() -> tuple[np.ndarray, np.ndarray]:
    """Powers of the running hash's factor and of its inverse, for stretches of up to 2 * PIECE values."""
    if "powers" not in _cache:
        _cache["powers"] = tuple(np.cumprod(np.concatenate([np.ones(1, np.uint64), np.full(2 * PIECE, m, np.uint64)]), dtype=np.uint64) for m in (_MULT, pow(_MULT, -1, 1 << 64)))
    return _cache["powers"]


class Words:
    """Words of a piece: byte ``start`` and ``end``, ``bound[r]:bound[r + 1]`` the words of row r."""

    def __init__(self, piece: Piece, kind: str, lower: bool):
        self.piece = piece
        self.body = table("lower")[piece.data] if lower else piece.data
        inside = table(kind)[self.body]
        n = len(inside)
        starts, ends = np.empty(n, bool), np.empty(n, bool)
        if n:
            starts[0], ends[-1] = inside[0], inside[-1]
            np.greater(inside[1:], inside[:-1], out=starts[1:])
            np.greater(inside[:-1], inside[1:], out=ends[:-1])
            cut = piece.off[1:-1]
            cut = cut[(cut > 0) & (cut < n)]
            starts[cut] = inside[cut]
            ends[cut - 1] = inside[cut - 1]
        self.inside = inside
        self.start = np.flatnonzero(starts)
        self.end = np.flatnonzero(ends) + 1
        self.bound = np.searchsorted(self.start, piece.off)
        self.count = np.diff(self.bound)
        self._hashes: np.ndarray | None = None

    def row(self) -> np.ndarray:
        return np.repeat(np.arange(self.piece.n), self.count)

    def hashes(self) -> np.ndarray:
        if self._hashes is None:
            self._hashes = span_hashes(self.body, self.start, self.end)
        return self._hashes


def span_hashes(body: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hashes of byte spans."""
    return run_hashes(body, start, end, table("byte"))


def run_hashes(values: np.ndarray, start: np.ndarray, end: np.ndarray, of: np.ndarray | None = None) -> np.ndarray:
    """64-bit hashes of runs of 64-bit values (of ``of[values]``, if given): differences of one running polynomial, shifted back to power 0.

    Runs stand in order and don't overlap; they are taken in stretches of about ``PIECE`` values, so a very long text
    needs no more memory than that besides its words.
    """
    power, back = _powers()
    out, lo, n = np.empty(len(start), np.uint64), 0, len(start)
    while lo < n:
        base = int(start[lo])
        hi = max(lo + 1, int(np.searchsorted(end, base + PIECE, "right")))
        stop = int(end[hi - 1])
        if stop - base > 2 * PIECE:
            out[lo] = _long_run(values, base, stop, of)
            lo += 1
            continue
        own = values[base:stop] if of is None else of[values[base:stop]]
        run = np.zeros(len(own) + 1, np.uint64)
        np.cumsum(own * power[:len(own)], out=run[1:])
        a, b = start[lo:hi] - base, end[lo:hi] - base
        out[lo:hi] = (run[b] - run[a]) * back[a] + (b - a).astype(np.uint64)
        lo = hi
    return mix(out)


def _long_run(values: np.ndarray, start: int, end: int, of: np.ndarray | None) -> np.uint64:
    power, _ = _powers()
    total, mask = 0, (1 << 64) - 1
    for k in range(start, end, PIECE):
        own = values[k:min(end, k + PIECE)]
        own = own if of is None else of[own]
        total += int(np.add.reduce(own * power[:len(own)])) * pow(_MULT, k - start, 1 << 64)
    return np.uint64((total + end - start) & mask)


def grams(h: np.ndarray, k: int) -> np.ndarray:
    """Hashes of k consecutive word hashes; entry i starts at word i (across rows too: see ``within``)."""
    n = max(0, len(h) - k + 1)
    out = np.full(n, k, np.uint64)
    for j, factor in enumerate(mix(np.arange(1000 * k, 1000 * k + k, dtype=np.uint64)) | np.uint64(1)):
        out += h[j:j + n] * factor
    return mix(out)


def within(words_bound: np.ndarray, k: int, n: int) -> np.ndarray:
    """Of the n gram starts, those that don't leave their row."""
    ok = np.ones(n, bool)
    for j in range(1, k):
        cut = words_bound[1:-1] - j
        ok[cut[(cut >= 0) & (cut < n)]] = False
    return ok


def sliding_min(h: np.ndarray, w: int) -> np.ndarray:
    """Position of the smallest of each w consecutive hashes, the last one of equals."""
    n = len(h) - w + 1
    if n <= 0:
        return np.zeros(0, np.int64)
    best, at = h[:n].copy(), np.arange(n)
    for j in range(1, w):
        less = h[j:j + n] <= best
        best[less] = h[j:j + n][less]
        at[less] = np.flatnonzero(less) + j
    return at


def code_points(data: np.ndarray) -> np.ndarray:
    """For each byte position (and the end) the number of code points that begin before it."""
    out = np.zeros(len(data) + 1, np.int64)
    np.cumsum((data & 0xC0) != 0x80, out=out[1:])
    return out


def row_sums(values: np.ndarray, bound: np.ndarray) -> np.ndarray:
    """Sums of values[bound[r]:bound[r + 1]]."""
    run = np.zeros(len(values) + 1, np.int64 if values.dtype.kind in "bui" else np.float64)
    np.cumsum(values, out=run[1:])
    return run[bound[1:]] - run[bound[:-1]]


register_pickle_by_value(sys.modules[__name__])
