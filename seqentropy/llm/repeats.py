"""Substring dedup by hashing lines, in sentences.

Lines are cut after words that end in ``.``, ``!`` or ``?``; a unit is normalised (A-Z in lower case, white space as one
blank) and hashed to 128 bits.  Digests are grouped over all documents: the unit of the earliest document (smallest
doc_id) stays, and so does the first one within it; all others are removed, with their offsets in the original text.
A line whose units are all repeated is removed, whatever its length; in other lines repeated sentences of at least
``MIN_SENTENCE`` words are (shorter ones, often single words, are ordinary language there).

A digest that a large part of all rows share costs one partial aggregate row for each task, and its join is split by
adaptive execution; repeats within a text never leave the kernel that reads it.

Defined cases: null or empty texts and texts of blanks have no units; of rows with equal ids one counts as earlier; null
ids rank last; an empty table gives no rows; other columns, whatever their names, are ignored by the search and kept by
``remove``; a unit that another document keeps is removed at all its places, and each names that document.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import kernels as K
from .common import cut, read, wrapped

MIN_SENTENCE = 8
_LAST = 2**63 - 1
_UNITS = "row long, doc_id long, line int, line_units int, unit int, start long, end long, words int, high long, low long, local boolean"


def _column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def cut_units(piece: K.Piece) -> dict[str, np.ndarray]:
    """The units of a piece: row in it, number in the row, code point offsets, words, digests, whether an earlier one of the row is equal."""
    words = K.Words(piece, "space", True)
    n = len(words.start)
    row = words.row()
    first, lines = np.ones(n, bool), np.concatenate([[0], np.cumsum(piece.data == 10)])
    if n:
        stop = np.isin(piece.data[words.end - 1], np.frombuffer(b".!?", np.uint8))
        first[1:] = stop[:-1] | (lines[words.start[1:]] > lines[words.end[:-1]]) | (row[1:] != row[:-1])
    a = np.flatnonzero(first)
    b = np.append(a[1:], n)[:len(a)]
    h = words.hashes()
    high, low = K.run_hashes(h, a, b), K.run_hashes(K.mix(h ^ np.uint64(0x5851F42D4C957F2D)), a, b)
    of = row[a]
    number = np.arange(len(a)) - np.searchsorted(of, np.arange(piece.n))[of] if len(a) else np.zeros(0, np.int64)
    order = np.lexsort((number, low, high, of))
    local = np.zeros(len(a), bool)
    if len(a) > 1:
        x, y = order[1:], order[:-1]
        local[x] = (of[x] == of[y]) & (high[x] == high[y]) & (low[x] == low[y])
    points = K.code_points(piece.data)
    zero = points[piece.off[:-1]][of]
    line = lines[words.start[a]]
    begins = np.ones(len(a), bool)
    begins[1:] = (line[1:] != line[:-1]) | (of[1:] != of[:-1])
    which = np.cumsum(begins) - 1
    return {"of": of, "line": line - lines[piece.off[:-1]][of], "line_units": np.bincount(which)[which] if len(a) else number, "unit": number, "start": points[words.start[a]] - zero if n else number, "end": points[words.end[b - 1]] - zero if n else number, "words": b - a, "high": high.view(np.int64), "low": low.view(np.int64), "local": local}


def _units(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows, ids = _column(batch, "row").to_numpy(), _column(batch, "doc_id").cast(pa.int64()).fill_null(_LAST).to_numpy()
        for piece in K.pieces(_column(batch, "text")):
            u = cut_units(piece)
            of = u["of"] + piece.first
            yield pa.RecordBatch.from_arrays([pa.array(rows[of]), pa.array(ids[of]), pa.array(u["line"].astype(np.int32)), pa.array(u["line_units"].astype(np.int32)), pa.array(u["unit"].astype(np.int32)), pa.array(u["start"]), pa.array(u["end"]), pa.array(u["words"].astype(np.int32)), pa.array(u["high"]), pa.array(u["low"]), pa.array(u["local"])], ["row", "doc_id", "line", "line_units", "unit", "start", "end", "words", "high", "low", "local"])


def numbered(docs: DataFrame) -> DataFrame:
    """row, whole: the documents with a number each, written once, so that every later read has the same numbers."""
    return cut(wrapped(docs).select(F.monotonically_increasing_id().alias("row"), "whole"), "numbered")


def repeats(rows: DataFrame, min_sentence: int = MIN_SENTENCE) -> DataFrame:
    """Of numbered documents, a row for every removed unit: row, doc_id, first_doc_id (the document that keeps it), unit, start, end, words, and the words of its run of neighbours."""
    units = rows.select("row", F.col("whole.doc_id").alias("doc_id"), F.col("whole.text").alias("text")).mapInArrow(_units, _UNITS)
    fresh = units.where("not local")
    known = fresh.groupBy("high", "low").agg(F.count("*").alias("n"), F.min_by("row", "doc_id").alias("first_row"), F.min("doc_id").alias("first_doc_id")).where("n > 1").drop("n")
    found = units.join(known, ["high", "low"], "left").where("local or (first_row is not null and row <> first_row)")
    in_line = F.count("*").over(Window.partitionBy("row").orderBy("line").rangeBetween(0, 0))
    found = found.withColumn("repeated", in_line).where((F.col("repeated") == F.col("line_units")) | (F.col("words") >= min_sentence))
    both = found.select("row", "doc_id", F.coalesce("first_doc_id", "doc_id").alias("first_doc_id"), "unit", "start", "end", "words")
    order = Window.partitionBy("row").orderBy("unit")
    runs = both.withColumn("run", F.col("unit") - F.row_number().over(order)).withColumn("run_words", F.sum("words").over(Window.partitionBy("row", "run")))
    real = lambda c: F.when(F.col(c) != _LAST, F.col(c)).alias(c)
    return runs.select("row", real("doc_id"), real("first_doc_id"), "unit", "start", "end", "words", "run_words")


def cut_spans(text: str, spans: list[tuple[int, int]]) -> str:
    """The text without the spans (code points)."""
    out, at = [], 0
    for a, b in sorted(spans):
        out.append(text[at:max(at, a)])
        at = max(at, b)
    return "".join([*out, text[at:]])


def remove(rows: DataFrame, removed: DataFrame) -> DataFrame:
    """Of numbered documents and their removed units: the documents without them, with all their columns."""
    spans = removed.groupBy("row").agg(F.collect_list(F.struct("start", "end")).alias("spans"))

    @F.pandas_udf("string")
    def clean(texts, own):
        import pandas as pd

        return pd.Series([t if s is None or t is None else cut_spans(t, [(x["start"], x["end"]) for x in s]) for t, s in zip(texts, own, strict=True)], dtype=object)

    text = F.when(F.col("spans").isNull(), F.col("whole.text")).otherwise(clean("whole.text", "spans"))
    return rows.join(spans, "row", "left").select(F.col("whole").withField("text", text).alias("whole")).select("whole.*")


def op8_line_hash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The removed units of all ``documents``."""
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    return repeats(numbered(docs)).drop("row")


register_pickle_by_value(sys.modules[__name__])
