"""Secret scans: base patterns, and a linear-chain conditional random field over words.

Words (runs without blanks) are tagged B, I or O by a chain model whose features are a word's shape, length, mix of
characters and beginning, the same of its neighbours, and features of the whole file.  It is trained by maximum
likelihood (forward-backward, AdaGrad) on windows around the spans of the base patterns and on windows without any, and
decoded by Viterbi.  Its spans are added to the base ones where they don't overlap them.

Decoding is exact but skips: a word whose score for O leads by more than any change of two transitions can bring is O
in the best path, which cuts the text; a stretch between such words is decoded only if a span could begin in it.

Bound: the ``WINDOWS`` windows with the smallest hashes of either kind train the model; every text is tagged whole.

Defined cases: null and empty texts have no spans; without any base span in the table the model adds none; repeated
rows are each scanned; equal spans of two kinds are both reported; other columns pass through the pipeline's stage.
"""

from __future__ import annotations

import hashlib
import heapq
import re
import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import kernels as K
from .common import read

# The task's base patterns.
ASSIGN = r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]{16,}"
KINDS = ["assign", "access", "hex", "crf"]
MASK = {"assign": "<secret>", "access": "<key>", "hex": "<hex>", "crf": "<secret>"}

WINDOWS, AROUND, ROUNDS, RATE, DECAY = 1200, 16, 80, 0.4, 1e-4
SHARES = 16
CAUTION = 1.5  # added to the score of O when texts are tagged: precision before recall
B, I, O = 0, 1, 2
_SIZES = [32 * 8, 5 * 8, 64, 4096, 4096, 256, 256, 64]
_BASES = np.concatenate([[0], np.cumsum(_SIZES)])
N_FEATURES = int(_BASES[-1])


def _column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the base patterns that hold, by start and kind."""
    out = []
    if "=" in text or ":" in text:
        out += [(m.start(), m.end(), "assign") for m in _pattern(ASSIGN, re.I | re.A).finditer(text) if m.end(2) - m.start(2) >= 12]
    if "AKIA" in text:
        out += [(m.start(), m.end(), "access") for m in _pattern(ACCESS).finditer(text) if m.end() - m.start() >= 18]
    out += [(m.start(), m.end(), "hex") for m in _pattern(HEX).finditer(text)]
    return in_order(out)


def _pattern(source: str, flags: int = 0) -> re.Pattern:
    return K._cache.setdefault(("re", source), re.compile(source, flags))


def in_order(spans: list[tuple[int, int, str]]) -> list[tuple[int, int, str]]:
    return sorted(spans, key=lambda s: (s[0], KINDS.index(s[2]), s[1]))


def written(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in spans)


def piece_base(piece: K.Piece) -> dict[int, list[tuple[int, int, str]]]:
    """Base spans of the rows of a piece that have any: rows without ``=``, ``:``, ``AKIA`` or 16 hex digits in a row are passed over."""
    data = piece.data
    if "hex" not in K._cache:
        t = np.zeros(256, bool)
        t[list(b"0123456789abcdef")] = True
        K._cache["hex"] = t
    hexed = K._cache["hex"][data]
    # runs end at the rows' borders
    opens, closes = hexed.copy(), hexed.copy()
    opens[1:] &= ~hexed[:-1]
    closes[:-1] &= ~hexed[1:]
    filled = piece.off[:-1] < piece.off[1:]
    head, last = piece.off[:-1][filled], piece.off[1:][filled] - 1
    opens[head], closes[last] = hexed[head], hexed[last]
    begin, stop = np.flatnonzero(opens), np.flatnonzero(closes) + 1
    some = np.zeros(piece.n + 1, bool)
    for at in (begin[stop - begin >= 16], np.flatnonzero((data == 61) | (data == 58))):
        some[np.searchsorted(piece.off, at, "right") - 1] = True
    if data.tobytes().find(b"AKIA") >= 0:
        some[:] = True
    return {int(r): s for r in np.flatnonzero(some[:-1]) if (s := base_spans(piece.text(r)))}


def features(piece: K.Piece, words: K.Words) -> np.ndarray:
    """Feature numbers of every word, one column for each family."""
    s, e = words.start, words.end
    n, size = len(s), e - s
    if "shape" not in K._cache:
        b = np.arange(256)
        kinds = [(b >= 97) & (b <= 122), (b >= 65) & (b <= 90), (b >= 48) & (b <= 57), (b > 32) & (b < 128) & ~((b >= 97) & (b <= 122)) & ~((b >= 65) & (b <= 90)) & ~((b >= 48) & (b <= 57)), b >= 128]
        K._cache["shape"] = [sum(k.astype(np.uint64) << np.uint64(16 * i) for i, k in enumerate(kinds[:4])), sum(k.astype(np.uint64) << np.uint64(16 * i) for i, k in enumerate([kinds[4], np.isin(b, list(b"0123456789abcdefABCDEF")), np.isin(b, list(b"=:"))])), sum(k.astype(np.uint8) * i for i, k in enumerate(kinds))]
    first, second, classes = K._cache["shape"]
    data = piece.data
    counts = []
    for table in (first, second):
        run = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(table[data], out=run[1:])
        both = run[e] - run[s]
        counts += [((both >> np.uint64(16 * i)) & np.uint64(0xFFFF)).astype(np.int64) for i in range(4)]
    low, up, dig, sym, high, hexed, sign, _ = counts
    cls = classes[data]
    turn = np.zeros(len(data) + 1, np.int64)
    np.cumsum(cls[1:] != cls[:-1], out=turn[2:]) if len(data) > 1 else None
    turns = turn[e] - turn[np.minimum(s + 1, e)]
    length = np.searchsorted([4, 8, 12, 16, 20, 28, 40], size, "right")
    shape = ((low > 0) * 1 + (up > 0) * 2 + (dig > 0) * 4 + (sym > 0) * 8 + (high > 0) * 16) * 8 + length
    mix = np.minimum(4, dig * 5 // np.maximum(1, size)) * 8 + np.minimum(7, hexed * 8 // np.maximum(1, size))
    quote = np.isin(data[s], list(b"\"'")) if n else np.zeros(0, bool)
    look = np.minimum(7, turns) * 8 + (sign > 0) * 1 + (np.isin(data[e - 1], list(b"=:")) * 2 if n else 0) + quote * 4
    head = np.full(n, 7, np.uint64)
    lower = K.table("lower")[data]
    for k in range(4):
        head = K.mix(head + np.where(size > k, lower[np.minimum(s + k, max(0, len(data) - 1))] if n else 0, 0).astype(np.uint64))
    begin = (head % np.uint64(4095)).astype(np.int64)
    row = words.row()
    first_word = np.zeros(n, bool)
    first_word[words.bound[:-1][words.count > 0]] = True
    last_word = np.zeros(n, bool)
    last_word[words.bound[1:][words.count > 0] - 1] = True
    back = lambda x, none: np.where(first_word, none, np.roll(x, 1))
    ahead = lambda x, none: np.where(last_word, none, np.roll(x, -1))
    share = K.row_sums(dig > 0, words.bound) * 8 // np.maximum(1, words.count)
    file = np.minimum(7, np.log2(np.maximum(1, words.count)).astype(np.int64) // 2) * 8 + np.minimum(7, share)
    return np.stack([shape, mix, look, begin, back(begin, 4095), back(shape, 255), ahead(shape, 255), file[row]], 1) + _BASES[:-1]


class Chain:
    """Weights of the features for the three tags, and of the transitions."""

    def __init__(self, emit: np.ndarray, move: np.ndarray, start: np.ndarray):
        self.emit, self.move, self.start = emit, move, start
        t = move
        pairs = [(p, y, q) for p in (B, I, O) for y in (B, I) for q in (B, I, O)]
        self.lead = max(0.0, *(t[p, y] + t[y, q] - t[p, O] - t[O, q] for p, y, q in pairs), *(start[y] + t[y, q] - start[O] - t[O, q] for _, y, q in pairs), *(t[p, y] - t[p, O] for p, y, _ in pairs))
        enter = [t[O, O] + t[O, q] - t[O, y] - t[y, q] for y in (B, I) for q in (B, I, O)] + [start[O] + t[O, q] - start[y] - t[y, q] for y in (B, I) for q in (B, I, O)] + [t[O, O] - t[O, y] for y in (B, I)] + [start[O] - start[y] for y in (B, I)]
        self.enter = min(enter)

    def scores(self, f: np.ndarray) -> np.ndarray:
        out = np.zeros((len(f), 3), np.float32)
        for k in range(f.shape[1]):
            out += self.emit[f[:, k]]
        out[:, O] += CAUTION
        return out


def viterbi(scores: np.ndarray, move: np.ndarray, start: np.ndarray) -> list[int]:
    """The best tags; ties go to the smaller tag."""
    t, back = move.tolist(), []
    s = [a + b for a, b in zip(start.tolist(), scores[0].tolist(), strict=True)]
    for row in scores[1:].tolist():
        best = [max(((s[p] + t[p][y]), -p) for p in range(3)) for y in range(3)]
        back.append([-b[1] for b in best])
        s = [b[0] + x for b, x in zip(best, row, strict=True)]
    y = max(range(3), key=lambda k: (s[k], -k))
    tags = [y]
    for choice in reversed(back):
        y = choice[y]
        tags.append(y)
    return tags[::-1]


def tag_spans(scores: np.ndarray, bound: np.ndarray, chain: Chain) -> list[tuple[int, int, int]]:
    """(row, first word, word after the last) of the spans of the best paths; words count from the piece's first."""
    gain = np.maximum(scores[:, B], scores[:, I]) - scores[:, O]
    seeds = np.flatnonzero(gain >= chain.enter - 1e-4)
    if not len(seeds):
        return []
    cuts = np.flatnonzero(gain < -chain.lead - 1e-4)
    row = np.searchsorted(bound, seeds, "right") - 1
    place = np.searchsorted(cuts, seeds)
    a = np.maximum(bound[row], np.where(place > 0, cuts[np.maximum(place - 1, 0)] if len(cuts) else 0, 0))
    b = np.minimum(bound[row + 1], np.where(place < len(cuts), (cuts[np.minimum(place, len(cuts) - 1)] if len(cuts) else 0) + 1, bound[-1]))
    out = []
    for lo, hi, r in sorted(set(zip(a.tolist(), b.tolist(), row.tolist(), strict=True))):
        begin = chain.start if lo == bound[r] else np.array([-1e9, -1e9, 0.0])
        tags = viterbi(scores[lo:hi].astype(np.float64), chain.move, begin)
        at = None
        for k, y in enumerate([*tags, O]):
            if at is not None and y != I:
                out.append((r, lo + at, lo + k))
                at = None
            if y == B or y == I and at is None:
                at = k
    return out


def _sampler(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of a task, the WINDOWS windows of either kind with the smallest hashes."""
    heaps: dict[int, list] = {0: [], 1: []}

    def offer(label: int, f: np.ndarray, tags: np.ndarray, h: np.ndarray) -> None:
        rank = -int(K.mix(h.sum(keepdims=True))[0] >> np.uint64(1))
        item = (rank, f.ravel().astype(int).tolist(), tags.astype(int).tolist())
        if len(heaps[label]) < WINDOWS:
            heapq.heappush(heaps[label], item)
        elif item[0] > heaps[label][0][0]:
            heapq.heapreplace(heaps[label], item)

    for batch in batches:
        for piece in K.pieces(_column(batch, "text")):
            spans = piece_base(piece)
            words = K.Words(piece, "space", False)
            if not len(words.start):
                continue
            f, h, points = features(piece, words), words.hashes(), None
            tags = np.full(len(f), O)
            if spans:
                points = K.code_points(piece.data)
            for r, own in spans.items():
                lo, hi = words.bound[r], words.bound[r + 1]
                zero = points[piece.off[r]]
                s, e = points[words.start[lo:hi]] - zero, points[words.end[lo:hi]] - zero
                for a, b, _ in own:
                    w = np.flatnonzero((s < b) & (e > a)) + lo
                    tags[w[1:]] = np.where(tags[w[1:]] == O, I, tags[w[1:]])
                    tags[w[0]] = B if tags[w[0]] == O else tags[w[0]]
                for w in np.flatnonzero(tags[lo:hi] == B) + lo:
                    x, y = max(lo, w - AROUND), min(hi, w + AROUND)
                    offer(1, f[x:y], tags[x:y], h[x:y])
            for r in np.flatnonzero(words.count):
                if r not in spans:
                    lo, n = int(words.bound[r]), int(words.count[r])
                    x = lo + int(h[lo] % np.uint64(n))
                    y = min(lo + n, x + 2 * AROUND)
                    offer(0, f[x:y], tags[x:y], h[x:y])
    rows = [(label, -rank, f, t) for label, heap in heaps.items() for rank, f, t in heap]
    columns = list(zip(*rows, strict=True)) if rows else [[], [], [], []]
    yield pa.RecordBatch.from_arrays([pa.array(columns[0], pa.int32()), pa.array(columns[1], pa.int64()), pa.array(columns[2], pa.list_(pa.int32())), pa.array(columns[3], pa.list_(pa.int32()))], ["label", "rank", "f", "tags"])


def fit(docs: DataFrame, windows: int = WINDOWS) -> Chain | None:
    found = docs.select("text").mapInArrow(_sampler, "label int, rank long, f array<int>, tags array<int>")
    rows = _smallest(found, windows)
    if not any(r[0] for r in rows):
        return None
    return train([(np.array(f).reshape(-1, len(_SIZES)), np.array(t)) for _, _, f, t in rows])


def _smallest(table: DataFrame, windows: int) -> list[tuple]:
    """Both kinds' windows with the smallest ranks, in one pass.

    Each task has sent its smallest alone; they are thinned in ``SHARES`` shares first, so the last step reads at most
    2 * SHARES * windows rows however many tasks there were.
    """
    order = ["rank", "tags", "f"]
    share = F.pmod(F.xxhash64("rank"), F.lit(SHARES))
    thin = table.withColumn("share", share).withColumn("place", F.row_number().over(Window.partitionBy("label", "share").orderBy(*order))).where(F.col("place") <= windows)
    last = F.row_number().over(Window.partitionBy("label").orderBy(*order))
    rows = thin.withColumn("place", last).where(F.col("place") <= windows).collect()
    return sorted(((r.label, r["rank"], list(r.f), list(r.tags)) for r in rows), key=lambda r: (-r[0], r[1], r[3], r[2]))


def train(windows: list[tuple[np.ndarray, np.ndarray]], rounds: int = ROUNDS) -> Chain:
    """Maximum likelihood with all windows at once, padded to the longest."""
    most = max(len(t) for _, t in windows)
    n = len(windows)
    f = np.zeros((n, most, len(_SIZES)), np.int64)
    tags = np.full((n, most), O)
    real = np.zeros((n, most), bool)
    for k, (own, t) in enumerate(windows):
        f[k, :len(t)], tags[k, :len(t)], real[k, :len(t)] = own, t, True
    emit, move, start = np.zeros((N_FEATURES, 3)), np.zeros((3, 3)), np.zeros(3)
    seen = [np.full_like(x, 1e-6) for x in (emit, move, start)]
    flat = f[real]
    gold = np.eye(3)[tags] * real[..., None]
    gold_moves = np.einsum("npa,npb->ab", gold[:, :-1], gold[:, 1:])
    for _ in range(rounds):
        scores = emit[f].sum(2)
        ahead, behind = np.zeros((n, most, 3)), np.zeros((n, most, 3))
        ahead[:, 0] = start + scores[:, 0]
        for t in range(1, most):
            x = _lse(ahead[:, t - 1, :, None] + move, 1) + scores[:, t]
            ahead[:, t] = np.where(real[:, t, None], x, ahead[:, t - 1])
        for t in range(most - 2, -1, -1):
            x = _lse(move[None] + (scores[:, t + 1] + behind[:, t + 1])[:, None, :], 2)
            behind[:, t] = np.where(real[:, t + 1, None], x, behind[:, t + 1])
        total = _lse(ahead[:, -1], 1)
        p = np.exp(ahead + behind - total[:, None, None]) * real[..., None]
        pair = np.exp(ahead[:, :-1, :, None] + move + (scores[:, 1:] + behind[:, 1:])[:, :, None, :] - total[:, None, None, None]) * real[:, 1:, None, None]
        error = (p - gold)[real]
        grads = [np.stack([sum(np.bincount(flat[:, k], error[:, y], N_FEATURES) for k in range(len(_SIZES))) for y in range(3)], 1), pair.sum((0, 1)) - gold_moves, p[:, 0].sum(0) - gold[:, 0].sum(0)]
        for x, g, h in zip((emit, move, start), grads, seen, strict=True):
            g = g / n + DECAY * x
            h += g * g
            x -= RATE * g / np.sqrt(h)
    return Chain(np.round(emit, 6).astype(np.float32), np.round(move, 6), np.round(start, 6))


def _lse(x: np.ndarray, axis: int) -> np.ndarray:
    top = x.max(axis, keepdims=True)
    return np.log(np.exp(x - top).sum(axis)) + top.squeeze(axis)


def piece_spans(piece: K.Piece, chain: Chain | None) -> tuple[dict[int, list], dict[int, list]]:
    """Base spans and all spans of the rows that have any."""
    base = piece_base(piece)
    every = {r: list(s) for r, s in base.items()}
    if chain is not None:
        words = K.Words(piece, "space", False)
        found = tag_spans(chain.scores(features(piece, words)), words.bound, chain) if len(words.start) else []
        points = K.code_points(piece.data) if found else None
        for r, a, b in found:
            zero = points[piece.off[r]]
            x, y = int(points[words.start[a]] - zero), int(points[words.end[b - 1]] - zero)
            if not any(p < y and q > x for p, q, _ in base.get(r, ())):
                every.setdefault(r, []).append((x, y, "crf"))
    return base, {r: in_order(s) for r, s in every.items()}


SCHEMA = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_crf long"


def _scanner(chain: Chain | None):
    none = hashlib.sha256(b"").hexdigest()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            counts = np.zeros((4, n), np.int64)
            digest, spans = [none] * n, [""] * n
            for piece in K.pieces(_column(batch, "text")):
                base, every = piece_spans(piece, chain)
                for r, own in every.items():
                    k = piece.first + r
                    for _, _, kind in own:
                        counts[KINDS.index(kind), k] += 1
                    digest[k], spans[k] = hashlib.sha256(written(base.get(r, [])).encode()).hexdigest(), written(own)
            yield pa.RecordBatch.from_arrays([_column(batch, "doc_id").cast(pa.int64()), *(pa.array(c) for c in counts[:3]), pa.array(digest, pa.string()), pa.array(spans, pa.string()), pa.array(counts[3])], ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_crf"])

    return run


def scan(docs: DataFrame, chain: Chain | None) -> DataFrame:
    return docs.select("doc_id", "text").mapInArrow(_scanner(chain), SCHEMA)


def op5_crf_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``documents``."""
    docs = read(spark, sf_dir, "documents")
    return scan(docs, fit(docs)).drop("n_crf")


def masked(text: str, spans: list[tuple[int, int, str]]) -> str:
    """The text with its spans masked; of overlapping ones, the union by the first one's mask."""
    out, at, last = [], 0, 0
    for a, b, kind in spans:
        if a >= last:
            out += [text[at:a], MASK[kind]]
            at = last = b
        else:
            at = last = max(last, b)
    return "".join([*out, text[at:]])


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: all documents stay, with secrets masked in their texts and n_chars counted anew for those."""
    chain = fit(docs)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            new: dict[int, str] = {}
            for piece in K.pieces(_column(batch, "text")):
                for r, own in piece_spans(piece, chain)[1].items():
                    new[piece.first + r] = masked(piece.text(r), own)
            if new:
                for name, fill in (("text", lambda t: t), ("n_chars", len)):
                    k = batch.schema.get_field_index(name)
                    if k >= 0:
                        values = batch.column(k).to_pylist()
                        for r, t in new.items():
                            values[r] = fill(t)
                        batch = batch.set_column(k, batch.schema.field(k), pa.array(values, batch.schema.field(k).type))
            yield batch

    return docs.mapInArrow(run, docs.schema)


register_pickle_by_value(sys.modules[__name__])
