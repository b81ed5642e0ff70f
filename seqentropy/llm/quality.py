"""Quality rules: counts per document, and a hashed n-gram log-likelihood ratio of trusted against raw text.

Every document's words and byte trigrams are hashed into ``BINS`` bins a family.  Two
multinomials over the bins are counted: over all documents (raw), and over the trusted ones (label quality 1 and not
toxic).  A document's score is the sum over the families of its mean log ratio: a length-normalised log-likelihood
ratio.  A document whose score is under the threshold is rejected; the threshold separates the labelled documents that
pass the base rules best: trusted ones that were not counted (one in ``HELD_OUT`` is held out) against bad ones (quality
0 or toxic), by balanced accuracy over a histogram of all of them, among those that reject at most ``CLEAN_LOSS`` of the
trusted.

Bounds: raw counts cover every document; the trusted that are counted are the ``TARGET_DOCS`` labelled documents with
the smallest hashed ids outside the held-out fold; the threshold is set on all bad and all held-out trusted documents
(on all trusted ones if none is held out).  What the driver gathers is 2 * BINS counts, those ids and the bins of the
histogram (3 * CELLS at most).

Defined cases: null or empty text has no words and fails the base rules (n_words < 20); without trusted or without bad
labelled documents that pass the base rules, only these decide; several labels of a document: all must be trusted, and
one bad label makes it bad; null labels or ids count as none; repeated rows are each judged; other columns pass through
the pipeline's stage.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K
from .common import read

BINS = 1 << 18
SMOOTHING = [1.0, 0.1]  # of words, of byte trigrams
FAMILIES = len(SMOOTHING)
TARGET_DOCS, HELD_OUT, CLEAN_LOSS = 20_000, 5, 0.03
CELLS, SPAN = 1 << 16, 16.0
SYMBOLS = b"#*$%&|<>"
MIN_WORDS, REPEAT_WINDOW, REPEAT_PERCENT = 20, 8, 30


def _column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def base_counts(piece: K.Piece, words: K.Words, h: np.ndarray) -> dict[str, np.ndarray]:
    """The counts of the base rules for each row."""
    data, off = piece.data, piece.off
    symbol = np.zeros(256, bool)
    symbol[list(SYMBOLS)] = True
    first = (data & 0xC0) != 0x80
    inside = np.zeros(len(data) + 1, np.int64)
    np.cumsum(words.inside, out=inside[1:])
    breaks = np.flatnonzero(data == 10)
    start = np.union1d(off[:-1][off[:-1] < off[1:]], breaks[breaks + 1 < len(data)] + 1)
    row = np.searchsorted(off, start, "right") - 1
    end = np.minimum(off[row + 1], np.append(breaks, len(data))[np.searchsorted(breaks, start)])
    some = inside[end] > inside[start]
    start, end, row = start[some], end[some], row[some]
    key = np.sort(np.stack([K.mix(K.span_hashes(data, start, end) + row.astype(np.uint64)), row.astype(np.uint64)], 1).view([("h", np.uint64), ("r", np.uint64)]).ravel(), order="h")
    again = np.flatnonzero(key["h"][1:] == key["h"][:-1]) + 1
    g = K.grams(h, REPEAT_WINDOW)
    at = np.flatnonzero(K.within(words.bound, REPEAT_WINDOW, len(g)))
    key2 = K.mix(g[at] + words.row()[at].astype(np.uint64))
    order = np.argsort(key2)
    same = key2[order][1:] == key2[order][:-1]
    twice = np.zeros(len(order), bool)
    twice[1:] |= same
    twice[:-1] |= same
    places = at[order[twice]]
    marks = np.zeros(len(h) + 1, np.int64)
    np.add.at(marks, places, 1)
    np.add.at(marks, places + REPEAT_WINDOW, -1)
    return {
        "word_chars": K.row_sums(words.inside & first, off),
        "n_symbols": K.row_sums(symbol[data], off),
        "n_dup_lines": np.bincount(key["r"][again].astype(np.int64), minlength=piece.n),
        "n_repeat_words": K.row_sums(np.cumsum(marks)[:-1] > 0, words.bound),
    }


def base_failed(n_words: np.ndarray, n_repeat: np.ndarray) -> np.ndarray:
    return (n_words < MIN_WORDS) | (100 * n_repeat > REPEAT_PERCENT * n_words)


def bins(piece: K.Piece, words: K.Words, h: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each family the bins of its grams and the bounds of the rows in them."""
    size = BINS.bit_length() - 1
    b = piece.data.astype(np.uint32)
    n = max(0, len(b) - 2)
    three = ((b[:n] * 0x9E3779B1 + b[1:n + 1] * 0x85EBCA77 + b[2:n + 2] * 0xC2B2AE3D) & 0xFFFFFFFF).astype(np.uint32)
    three ^= three >> 15
    three = (three * np.uint32(0x2C1B3C6D)) >> np.uint32(32 - size)
    ok = K.within(piece.off, 3, n)
    run = np.concatenate([[0], np.cumsum(ok)])
    return [((h >> np.uint64(64 - size)).astype(np.int32), words.bound), (three[ok].astype(np.int32) + BINS, run[np.minimum(piece.off, n)])]


def _counter(trusted: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        raw, own = (np.zeros(FAMILIES * BINS, np.int64) for _ in range(2))
        for batch in batches:
            ids = _column(batch, "doc_id")
            known = np.isin(ids.fill_null(-1).to_numpy(), trusted) & ids.is_valid().to_numpy(zero_copy_only=False)
            for piece in K.pieces(_column(batch, "text")):
                words = K.Words(piece, "space", False)
                mine = known[piece.first:piece.first + piece.n]
                for b, bound in bins(piece, words, words.hashes()):
                    raw += np.bincount(b, minlength=len(raw))
                    if mine.any():
                        own += np.bincount(b[np.repeat(mine, np.diff(bound))], minlength=len(raw))
        at = np.flatnonzero(raw)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(raw[at]), pa.array(own[at])], ["bin", "raw", "own"])

    return run


def _scorer(ratio: np.ndarray, threshold: float | None):
    names = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "score"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = score_batch(_column(batch, "text"), ratio, threshold)
            yield pa.RecordBatch.from_arrays([_column(batch, "doc_id").cast(pa.int64()), *(pa.array(got[k]) for k in names[1:])], names)

    return run


def score_batch(texts: pa.Array, ratio: np.ndarray | None, threshold: float | None) -> dict[str, np.ndarray]:
    out: dict[str, list] = {}
    for piece in K.pieces(texts):
        words = K.Words(piece, "space", False)
        h = words.hashes()
        own = base_counts(piece, words, h) | {"n_words": words.count}
        own["base_failed"] = base_failed(own["n_words"], own["n_repeat_words"])
        own["score"] = np.zeros(piece.n)
        if ratio is not None:
            for b, bound in bins(piece, words, h):
                own["score"] += K.row_sums(ratio[b].astype(np.float64), bound) / np.maximum(1, np.diff(bound))
        own["score"] = np.round(own["score"], 9)
        own["kept"] = ~own["base_failed"] & ((threshold is None) | (own["score"] >= (threshold or 0.0)))
        for k, v in own.items():
            out.setdefault(k, []).append(v.astype(np.int64) if v.dtype.kind in "iu" else v)
    if not out:
        return {k: np.zeros(0, t) for k, t in (("n_words", np.int64), ("word_chars", np.int64), ("n_symbols", np.int64), ("n_dup_lines", np.int64), ("n_repeat_words", np.int64), ("base_failed", bool), ("score", float), ("kept", bool))}
    return {k: np.concatenate(v) for k, v in out.items()}


SCORE_SCHEMA = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, score double"


class Model:
    """Log ratios of the bins, and the threshold (None: no verdict of its own)."""

    def __init__(self, ratio: np.ndarray, threshold: float | None):
        self.ratio, self.threshold = ratio, threshold


def _labels(labels: DataFrame) -> DataFrame:
    """doc_id, good (all labels trusted), bad (a label says quality 0 or toxic)."""
    good = F.coalesce((F.col("quality") == 1) & (F.col("toxic") == 0), F.lit(False))
    bad = F.coalesce(F.col("quality") == 0, F.lit(False)) | F.coalesce(F.col("toxic") == 1, F.lit(False))
    return labels.where("doc_id is not null").groupBy("doc_id").agg(F.min(good).alias("good"), F.max(bad).alias("bad"))


def _trusted(judged: DataFrame, most: int) -> np.ndarray:
    rows = judged.where("good and not held").select("doc_id").orderBy(F.xxhash64("doc_id"), "doc_id").limit(most).collect()
    return np.array(sorted(r.doc_id for r in rows), np.int64)


def fit(docs: DataFrame, labels: DataFrame) -> Model:
    """Counts over all documents; the threshold on all labelled ones."""
    docs = docs.select("doc_id", "text")
    known = _labels(labels).withColumn("held", F.pmod(F.xxhash64(F.lit("held"), "doc_id"), F.lit(HELD_OUT)) == 0)
    trusted = _trusted(known, TARGET_DOCS)
    counts = docs.mapInArrow(_counter(trusted), "bin int, raw long, own long").groupBy("bin").agg(F.sum("raw").alias("raw"), F.sum("own").alias("own")).toArrow()
    raw, own = (np.zeros(FAMILIES * BINS) for _ in range(2))
    for x, name in ((raw, "raw"), (own, "own")):
        x[counts["bin"].to_numpy()] = counts[name].to_numpy()
    ratio = np.concatenate([np.log((o + s) / (o.sum() + s * BINS)) - np.log((a + s) / (a.sum() + s * BINS)) for a, o, s in zip(raw.reshape(FAMILIES, BINS), own.reshape(FAMILIES, BINS), SMOOTHING, strict=True)]).astype(np.float32)
    if not own.sum():
        return Model(np.zeros_like(ratio), None)
    cell = F.greatest(F.lit(0), F.least(F.lit(CELLS - 1), F.floor((F.col("score") + SPAN) / (2 * SPAN) * CELLS)))
    scored = docs.mapInArrow(_scorer(ratio, None), SCORE_SCHEMA).where("not base_failed and doc_id is not null").select("doc_id", cell.cast("int").alias("cell"))
    hist = np.zeros((3, CELLS))  # trusted and counted, bad, trusted and held out
    kind = F.when(F.col("bad"), 1).when(F.col("held"), 2).otherwise(0)
    for r in scored.join(known.where("good or bad"), "doc_id").groupBy(kind.alias("kind"), "cell").agg(F.count("*").alias("n")).collect():
        hist[r.kind, r.cell] = r.n
    return Model(ratio, threshold_of(hist[2] if hist[2].any() else hist[0], hist[1]))


def threshold_of(good: np.ndarray, bad: np.ndarray, loss: float = CLEAN_LOSS) -> float | None:
    """The lowest of the cells' borders with the best balanced accuracy, from which documents are kept, of those under which at most ``loss`` of the good ones are; None without either kind."""
    if not good.sum() or not bad.sum():
        return None
    lost = np.cumsum(good) / good.sum()
    gain = np.where(lost <= loss, np.round(np.cumsum(bad) / bad.sum() - lost, 12), -1)
    at = int(gain.argmax())
    return float((at + 1) / CELLS * 2 * SPAN - SPAN) if gain[at] > 0 else None


def judged(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """One row per document with its counts, score and verdict."""
    model = fit(docs, labels)
    return docs.select("doc_id", "text").mapInArrow(_scorer(model.ratio, model.threshold), SCORE_SCHEMA)


def op6_hashed_ratio_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judged(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: rejected documents go, the others keep all columns, whatever their names.

    Null, empty and blank texts fail the base rules and go; repeated rows are each judged; without labels, or without
    documents, only the base rules decide.
    """
    model = fit(docs, read(spark, sf_dir, "labels"))
    ratio, threshold = model.ratio, model.threshold

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(score_batch(_column(batch, "text"), ratio, threshold)["kept"]))

    return docs.mapInArrow(run, docs.schema)


register_pickle_by_value(sys.modules[__name__])
