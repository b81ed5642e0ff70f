"""Lexical retrieval packing: documents are cut into sequences of at most ``LENGTH`` tokens, neighbours together.

A document's ids, with id 0 at the end, fill whole sequences first; what is over is its tail, shorter than a sequence.
Tails are written once and the document frequencies of their ids counted over all of them (a number for each id of the
vocabulary).  A tail's ``ROUTE`` ids of the largest BM25 weight are its route: tails are range-partitioned and sorted by
it, so tails about the same things stand together wherever their documents were, and a route that very many tails share
goes on over several partitions (a hash of the row breaks its ties).

A partition is packed in shards of ``SHARD_DOCS`` consecutive tails.  A shard's tails are indexed by their ids (postings
with BM25 weights); the longest unused tail seeds a sequence, all its ids are the query, and unused tails are taken in
order of their scores until the sequence is full; the last one is cut there and what is left of it stays unused.  What
can't fill a sequence goes on to the partition's next shard; the end of a partition is cut into sequences whose lengths
are powers of two, which need no padding.

Defined cases: null and empty texts are the single id 0; null doc_ids are kept; repeated rows are packed each; equal
scores go by order in the shard; an empty table gives no pieces; other columns are ignored.
"""

from __future__ import annotations

import sys
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K
from .common import cut, read
from .tokens import encoder

LENGTH, SHARD_DOCS, ROUTE, K1, NORM = 1024, 1024, 3, 1.2, 0.75
VOCABULARY = "byte_bpe_50k"
TAILS_A_TASK = 1 << 14
_CUT = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, salt long, ids binary"
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def _column(batch, name: str):
    return batch.column(batch.schema.get_field_index(name))


def crc(ids: np.ndarray) -> int:
    return zlib.crc32(ids.astype("<u4").tobytes())


def _task() -> int:
    from pyspark import TaskContext

    context = TaskContext.get()
    return context.partitionId() if context else 0


def _cutter(vocabulary: str, length: int):
    """Whole sequences with their numbers (odd ones), and tails with their ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = _task() << 40
        encode = encoder(vocabulary).encode
        for batch in batches:
            ids_of = _column(batch, "doc_id").cast(pa.int64()).to_pylist()
            for piece in K.pieces(_column(batch, "text")):
                rows = []
                for r, ids in enumerate(encode(piece)):
                    ids = np.append(ids, np.uint32(0)).astype(np.uint32)
                    n, doc = len(ids), ids_of[piece.first + r]
                    whole = n - n % length
                    for a in range(0, whole, length):
                        rows.append((doc, a, length, crc(ids[a:a + length]), n, 2 * number + 1, None, None))
                        number += 1
                    if whole < n:
                        own = ids[whole:]
                        salt = number * 0x9E3779B97F4A7C15 % (1 << 63)
                        rows.append((doc, whole, n - whole, None, n, None, salt, own.astype("<u4").tobytes() if ids.max() > 65535 else own.astype("<u2").tobytes()))
                        number += 1
                columns = list(zip(*rows, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, [pa.int64()] * 7 + [pa.binary()], strict=True)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "salt", "ids"])

    return run


def ids_of(stored: bytes, n: int) -> np.ndarray:
    return np.frombuffer(stored, "<u4" if len(stored) == 4 * n else "<u2")


def _frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """How many of a task's tails hold each id."""
    total = np.zeros(1 << 16, np.int64)
    for batch in batches:
        for stored, n in zip(_column(batch, "ids").to_pylist(), _column(batch, "length").to_pylist(), strict=True):
            own = np.unique(ids_of(stored, n))
            if len(own) and own[-1] >= len(total):
                total = np.concatenate([total, np.zeros(int(own[-1]) + 1, np.int64)])
            total[own] += 1
    at = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], ["id", "n"])


def inverse_frequency(df: np.ndarray, n: int) -> np.ndarray:
    return np.log(1 + (n - df + 0.5) / (df + 0.5))


def route(ids: np.ndarray, df: np.ndarray, idf: np.ndarray, mean: float) -> list[int]:
    """The ids of the largest BM25 weight that other tails hold too, best first; -1 where there are fewer."""
    own, tf = np.unique(ids, return_counts=True)
    own, tf = own[df[own] > 1], tf[df[own] > 1]
    weight = np.round(idf[own] * tf * (K1 + 1) / (tf + K1 * (1 - NORM + NORM * len(ids) / mean)), 9)
    best = own[np.lexsort((own, -weight))[:ROUTE]].tolist()
    return [int(x) for x in best] + [-1] * (ROUTE - len(best))


def _router(df: np.ndarray, tails: int, mean: float):
    idf = inverse_frequency(df, tails)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            routes = [route(ids_of(s, n), df, idf, mean) for s, n in zip(_column(batch, "ids").to_pylist(), _column(batch, "length").to_pylist(), strict=True)]
            columns = [pa.array([r[k] for r in routes], pa.int32()) for k in range(ROUTE)]
            yield pa.RecordBatch.from_arrays([*columns, *(batch.column(k) for k in range(batch.num_columns))], [*(f"route{k}" for k in range(ROUTE)), *batch.schema.names])

    return run


class Index:
    """Postings of a shard's tails with BM25 weights."""

    def __init__(self, tails: list[np.ndarray]):
        n = len(tails)
        size = np.array([len(t) for t in tails], np.int64)
        doc = np.repeat(np.arange(n), size)
        pairs, tf = np.unique(np.concatenate(tails).astype(np.int64) * n + doc, return_counts=True)
        term, doc = pairs // n, pairs % n
        _, begin, df = np.unique(term, return_index=True, return_counts=True)
        number = np.repeat(np.arange(len(df)), df)
        weight = inverse_frequency(df, n)[number] * tf * (K1 + 1) / (tf + K1 * (1 - NORM + NORM * size[doc] / size.mean()))
        shared = df[number] > 1  # an id that one tail alone holds finds no neighbour
        self.n, self.n_terms = n, len(df)
        self.doc, self.number, self.weight = doc[shared].astype(np.int32), number[shared].astype(np.int32), weight[shared]
        order = np.argsort(self.doc, kind="stable")
        self.query, self.bound = self.number[order], np.searchsorted(self.doc[order], np.arange(n + 1))
        self.begin = np.searchsorted(self.number, np.arange(self.n_terms + 1))  # an id's postings stand together

    def keep(self, unused: np.ndarray) -> None:
        """Drops the postings of used tails."""
        live = unused[self.doc]
        self.doc, self.number, self.weight = self.doc[live], self.number[live], self.weight[live]
        self.begin = np.searchsorted(self.number, np.arange(self.n_terms + 1))

    def neighbours(self, seed: int) -> np.ndarray:
        """Tails with a positive score for all of the seed's ids, best first."""
        asked = self.query[self.bound[seed]:self.bound[seed + 1]]
        begin = self.begin[asked]
        size = self.begin[asked + 1] - begin
        ends = np.cumsum(size)
        at = np.repeat(begin - (ends - size), size) + np.arange(int(ends[-1]) if len(ends) else 0)
        score = np.bincount(self.doc[at], self.weight[at], self.n)
        hit = np.flatnonzero(score)
        return hit[np.lexsort((hit, -np.round(score[hit], 9)))]


def pack_tails(tails: list[np.ndarray], length: int = LENGTH, last: bool = True) -> tuple[list[list[tuple[int, int, int]]], list[tuple[int, int]]]:
    """Sequences as lists of (tail, begin, end), and what is left, (tail, begin); nothing is left of the last shard."""
    if not tails:
        return [], []
    n = len(tails)
    at, left = [0] * n, [len(t) for t in tails]
    order = sorted(range(n), key=lambda k: (-left[k], k))
    out, now, seed_at, total = [], [], 0, sum(left)
    index, unused, live = Index(tails) if total >= length else None, np.ones(n, bool), n

    def take(k: int, most: int) -> int:
        nonlocal live
        size = min(most, left[k])
        now.append((k, at[k], at[k] + size))
        at[k] += size
        left[k] -= size
        if not left[k]:
            unused[k] = False
            live -= 1
        return size

    indexed = n
    while total >= length:
        while not left[order[seed_at]]:
            seed_at += 1
        if live < 0.9 * indexed:
            index.keep(unused)
            indexed = live
        seed, room, now = order[seed_at], length, []
        room -= take(seed, room)
        for k in index.neighbours(seed).tolist() if room else ():
            if left[k]:
                room -= take(k, room)
                if not room:
                    break
        next_ = seed_at
        while room:
            if left[order[next_]]:
                room -= take(order[next_], room)
            else:
                next_ += 1
        total -= length
        out.append(now)
    if not last:
        return out, [(k, at[k]) for k in range(n) if left[k]]
    size = length
    rest = [k for k in order if left[k]]
    while total:
        while size > total:
            size //= 2
        room, now = size, []
        while room:
            room -= take(rest[0], room)
            if not left[rest[0]]:
                rest.pop(0)
        total -= size
        out.append(now)
    return out, []


def _packer(length: int, shard_docs: int):
    names = SCHEMA.replace(" long", "").split(", ")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = _task() << 40
        held: list[tuple] = []  # doc_id, start, doc_tokens, ids

        def packed_rows(last: bool) -> pa.RecordBatch:
            nonlocal number, held
            sequences, left = pack_tails([h[3] for h in held], length, last)
            out = []
            for sequence in sequences:
                offset = 0
                for k, a, b in sequence:
                    doc, start, tokens, ids = held[k]
                    out.append((doc, start + a, b - a, crc(ids[a:b]), tokens, 2 * number, offset))
                    offset += b - a
                number += 1
            held = [(held[k][0], held[k][1] + a, held[k][2], held[k][3][a:]) for k, a in left]
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (zip(*out, strict=True) if out else [[]] * len(names))], names)

        for batch in batches:
            for r in batch.to_pylist():
                held.append((r["doc_id"], r["start"], r["doc_tokens"], ids_of(r["ids"], r["length"])))
                if len(held) >= shard_docs:
                    yield packed_rows(False)
        yield packed_rows(True)

    return run


def packed(docs: DataFrame, vocabulary: str = VOCABULARY, length: int = LENGTH, shard_docs: int = SHARD_DOCS) -> DataFrame:
    """One row per piece of a document."""
    pieces = cut(docs.select("doc_id", "text").mapInArrow(_cutter(vocabulary, length), _CUT), "pieces")
    names = SCHEMA.replace(" long", "").split(", ")
    whole = pieces.where("ids is null").select(*names[:-1], F.lit(0).cast("long").alias("offset"))
    tails = pieces.where("ids is not null").select("doc_id", "start", "length", "doc_tokens", "salt", "ids")
    seen = tails.agg(F.count("*").alias("n"), F.sum("length").alias("ids")).first()
    counted = tails.select("length", "ids").mapInArrow(_frequencies, "id long, n long").groupBy("id").agg(F.sum("n").alias("n")).toArrow()
    df = np.zeros(1 + (max(counted["id"].to_pylist()) if len(counted) else 0), np.int64)
    df[counted["id"].to_numpy()] = counted["n"].to_numpy()
    order = [*(f"route{k}" for k in range(ROUTE)), "salt"]
    routed = tails.mapInArrow(_router(df, seen.n, (seen.ids or 1) / max(1, seen.n)), f"{', '.join(f'route{k} int' for k in range(ROUTE))}, doc_id long, start long, length long, doc_tokens long, salt long, ids binary")
    tasks = max(1, -(-seen.n // TAILS_A_TASK), min(-(-seen.n // shard_docs), docs.sparkSession.sparkContext.defaultParallelism))
    placed = cut(routed, "routed").repartitionByRange(tasks, *order).sortWithinPartitions(*order)
    return whole.unionAll(placed.mapInArrow(_packer(length, shard_docs), SCHEMA))


def op7_bm25_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``documents``."""
    return packed(read(spark, sf_dir, "documents"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: the pieces."""
    return packed(docs)


register_pickle_by_value(sys.modules[__name__])
