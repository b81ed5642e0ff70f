"""Benchmark decontamination by winnowing.

Of every ``w`` neighbouring hashes of k-word grams the smallest is kept as a fingerprint, in the benchmark and in
the documents alike.  Two texts that share ``window = k + w - 1`` words therefore share a fingerprint: nothing that
long is missed.  A document's fingerprints are joined to the benchmark's, and each hit is extended to the whole window
around it (128-bit hashes of all its words); the words of windows that occur in an item are marked.

Items shorter than a window are one window of their own length, which is its own fingerprint.

Before the join, a filter of a fixed size (``2 ** FILTER_BITS`` bits of the benchmark's fingerprints, whatever their
number) drops the documents' windows that can't match; a crowded filter only lets more of them through to the join.
Nothing else of the benchmark leaves its table, and there is one plan for benchmarks of any size.  Equal texts have equal
hits, so hits are gathered by text: copies cost one group.

Defined cases: a null or empty text has no words, hits nothing and is not contaminated; items with a null id or without
words are left out; equal items with different ids are all reported; an id that occurs in several rows is one item;
repeated document rows are each judged; empty tables give no rows, or no hits; other columns are ignored.
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
from .common import cut, read, wrapped

WINDOW, GRAM, FILTER_BITS = 10, 5, 24
_SECOND = np.uint64(0x5851F42D4C957F2D)
_PLACE = "size int, mark long, high long, low long"
_SCANNED = "doc_id long, text_a long, text_b long, n_words long, places array<struct<start: int, size: int, mark: long, high: long, low: long>>"
_WINDOW = ["size", "mark", "high", "low"]


def _column(batch, name: str):
    return batch.column(batch.schema.get_field_index(name))


def windows(words: K.Words, size: int, window: int, gram: int) -> tuple[np.ndarray, ...]:
    """Of all windows of ``size`` words that stay in their row: first word, fingerprint, and the two halves of the window's hash."""
    h = words.hashes()
    n = max(0, len(h) - size + 1)
    at = np.flatnonzero(K.within(words.bound, size, n))
    high, low = K.grams(h, size)[at], K.grams(K.mix(h ^ _SECOND), size)[at]
    if size < window:
        return at, high, high, low
    small = K.grams(h, gram)
    return at, small[K.sliding_min(small, window - gram + 1)][at] if len(at) else high, high, low


def _item_windows(window: int, gram: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names = _column(batch, "item").to_pylist()
            for piece in K.pieces(_column(batch, "text")):
                words = K.Words(piece, "alnum", True)
                for size in sorted({min(window, int(c)) for c in words.count if c}):
                    at, mark, high, low = windows(words, size, window, gram)
                    row = np.searchsorted(words.bound, at, "right") - 1
                    own = np.minimum(words.count[row], window) == size
                    k = [names[piece.first + r] for r in row[own].tolist()]
                    yield pa.RecordBatch.from_arrays([pa.array(k, pa.string()), pa.array(np.full(len(k), size, np.int32)), *(pa.array(x[own].view(np.int64)) for x in (mark, high, low))], ["item", *_WINDOW])

    return run


def item_windows(benchmark: DataFrame, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """size, mark (fingerprint), high, low, items: every distinct window of the items, with the sorted ids of those that hold it."""
    items = benchmark.where("item_id is not null and text is not null").select(F.col("item_id").cast("string").alias("item"), "text")
    rows = items.mapInArrow(_item_windows(window, gram), f"item string, {_PLACE}")
    return rows.groupBy(*_WINDOW).agg(F.array_sort(F.collect_set("item")).alias("items"))


def mark_filter(known: DataFrame, bits: int = FILTER_BITS) -> np.ndarray:
    """The fingerprints' first bits as a bit set of a fixed size."""
    first = F.shiftrightunsigned("mark", 64 - bits)
    cells = known.groupBy(F.shiftrightunsigned(first, 6).cast("int").alias("cell")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), first.bitwiseAND(F.lit(63)).cast("int"))).alias("set")).toArrow()
    out = np.zeros(1 << max(0, bits - 6), np.int64)
    out[cells["cell"].to_numpy()] = cells["set"].to_numpy()
    return out


def _scanner(sizes: list[int], marks: np.ndarray, bits: int, window: int, gram: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = np.unpackbits(marks.view(np.uint8), bitorder="little").view(bool)
        for batch in batches:
            n = batch.num_rows
            count, found = np.zeros(n, np.int64), []
            for piece in K.pieces(_column(batch, "text")):
                words = K.Words(piece, "alnum", True)
                count[piece.first:piece.first + piece.n] = words.count
                for size in sizes:
                    at, mark, high, low = windows(words, size, window, gram)
                    may = known[(mark >> np.uint64(64 - bits)).astype(np.int64)]
                    at, row = at[may], np.searchsorted(words.bound, at[may], "right") - 1
                    found.append((row + piece.first, at - words.bound[row], np.full(len(at), size), *(x[may].view(np.int64) for x in (mark, high, low))))
            columns = [np.concatenate(c) for c in zip(*found, strict=True)] if found else [np.zeros(0, np.int64)] * 6
            order = np.argsort(columns[0], kind="stable")
            bound = np.concatenate([[0], np.cumsum(np.bincount(columns[0], minlength=n))]).astype(np.int32)
            place = pa.StructArray.from_arrays([pa.array(c[order].astype(t)) for c, t in zip(columns[1:], [np.int32, np.int32, np.int64, np.int64, np.int64], strict=True)], ["start", *_WINDOW])
            yield pa.RecordBatch.from_arrays([_column(batch, "doc_id").cast(pa.int64()), _column(batch, "text_a"), _column(batch, "text_b"), pa.array(count), pa.ListArray.from_arrays(pa.array(bound), place)], ["doc_id", "text_a", "text_b", "n_words", "places"])

    return run


def _text_key() -> list[F.Column]:
    return [F.xxhash64("text").alias("text_a"), F.xxhash64(F.lit("bench"), F.col("text")).alias("text_b")]


def _hits(docs: DataFrame, benchmark: DataFrame, window: int, gram: int, bits: int) -> tuple[DataFrame, DataFrame]:
    """The scanned documents (with their words and places that may match), and for every text with hits its spans and items."""
    known = cut(item_windows(benchmark, window, gram), "bench-windows")
    sizes = sorted(r.size for r in known.select("size").distinct().collect())
    scanner = _scanner(sizes, mark_filter(known, bits), bits, window, gram)
    scanned = cut(docs.select("doc_id", "text", *_text_key()).mapInArrow(scanner, _SCANNED), "bench-places")
    places = scanned.select("text_a", "text_b", F.explode("places").alias("p")).select("text_a", "text_b", "p.*")
    hits = places.join(known, _WINDOW).groupBy("text_a", "text_b").agg(F.collect_set(F.struct("start", (F.col("start") + F.col("size")).alias("end"))).alias("spans"), F.collect_set("items").alias("items"))
    return scanned, hits


def _covered(spans: F.Column) -> F.Column:
    """How many words lie in at least one of the spans."""
    zero = F.struct(F.lit(0).cast("long").alias("words"), F.lit(0).alias("last"))
    step = lambda a, s: F.struct((a["words"] + F.greatest(F.lit(0), s["end"] - F.greatest(s["start"], a["last"]))).alias("words"), F.greatest(a["last"], s["end"]).alias("last"))
    return F.aggregate(F.array_sort(spans), zero, step)["words"]


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, gram: int = GRAM, bits: int = FILTER_BITS) -> DataFrame:
    """One row per document: its words, those inside windows of the benchmark, and the items they are of."""
    scanned, hits = _hits(docs, benchmark, window, gram, bits)
    names = F.array_sort(F.array_distinct(F.flatten("items")))
    named = hits.select("text_a", "text_b", _covered(F.col("spans")).alias("n_hit"), F.size(names).cast("long").alias("n_items"), F.sha2(F.array_join(names, ",").cast("binary"), 256).alias("items_sha256"))
    out = scanned.select("doc_id", "n_words", "text_a", "text_b").join(named, ["text_a", "text_b"], "left")
    zero, none = F.lit(0).cast("long"), F.sha2(F.lit("").cast("binary"), 256)
    return out.select("doc_id", "n_words", F.coalesce("n_hit", zero).alias("n_hit"), F.coalesce("n_items", zero).alias("n_items"), F.coalesce("items_sha256", none).alias("items_sha256"), F.col("n_hit").isNotNull().alias("contaminated"))


def op1_winnowing_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``documents`` against all of ``benchmark``."""
    return contamination(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark"))


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: documents without a window of the benchmark stay, with all their columns.

    Null and empty texts stay; every copy of a contaminated text goes; without items, or without documents, all that is
    there stays; columns of any names pass through.
    """
    _, hits = _hits(docs, read(spark, sf_dir, "benchmark"), WINDOW, GRAM, FILTER_BITS)
    whole = wrapped(docs).select("whole", F.xxhash64("whole.text").alias("text_a"), F.xxhash64(F.lit("bench"), F.col("whole.text")).alias("text_b"))
    return whole.join(cut(hits.select("text_a", "text_b"), "bench-hits"), ["text_a", "text_b"], "left_anti").select("whole.*")


OP1_SQL = r"""
WITH words AS (
  SELECT doc_id, coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), []) AS w FROM documents),
items AS (
  SELECT CAST(item_id AS VARCHAR) AS item, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark WHERE item_id IS NOT NULL AND text IS NOT NULL),
windows AS (
  SELECT DISTINCT item, size, array_to_string(w[i:i + size - 1], ' ') AS g
  FROM (SELECT item, w, least(len(w), 10) AS size, unnest(range(1, len(w) - least(len(w), 10) + 2)) AS i FROM items WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT size FROM windows),
places AS (
  SELECT doc_id, size, i, array_to_string(w[i:i + size - 1], ' ') AS g
  FROM (SELECT doc_id, w, size, unnest(range(1, len(w) - size + 2)) AS i FROM words, sizes WHERE len(w) >= size)),
hits AS (SELECT doc_id, p.size, i, item FROM places p JOIN windows USING (size, g)),
marked AS (SELECT doc_id, count(DISTINCT pos) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + size)) AS pos FROM hits) GROUP BY doc_id),
named AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS names FROM (SELECT DISTINCT doc_id, item FROM hits) GROUP BY doc_id)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
  sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM words LEFT JOIN marked USING (doc_id) LEFT JOIN named USING (doc_id)
"""

register_pickle_by_value(sys.modules[__name__])
