"""Language identification: sparse multinomial logistic regression on TF-IDF character n-grams.

Texts are counted as hashed n-grams of 1 to ``ORDER`` code points (A-Z in lower case); term frequencies are relative
within an order, times an inverse document frequency.  The weights are learnt by follow-the-regularised-leader with
an elastic-net penalty (most of them stay exactly zero) and the probabilities are calibrated by one temperature, set
on a part of the sample that the weights have not seen.

Document frequencies are counted over all learnable documents.  Bound: of every language the ``SAMPLE`` / languages (at
least ``LEAST``) learnable documents with the smallest hashes are learnt from, with whole texts, so a rare language is
not lost in a large table; rows that are equal in id, language and text are one.  What the driver gathers is the
frequencies of ``ORDER * BUCKETS`` buckets and those documents' non-zero counts.  Weights are kept for buckets with a
non-zero one only.  Every document is predicted from its whole text.

Defined cases: null texts and texts without any letter are ``und`` with score 0; null ids are neither held out nor
learnt from; where nothing can be learnt all is ``und``; ties go to the alphabetically first language; repeated rows
are each predicted; other columns are ignored.
"""

from __future__ import annotations

import sys
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import kernels as K
from .common import read

ORDER, BUCKETS, SAMPLE, LEAST, FOLDS, HELD = 3, 1 << 16, 4000, 50, 3, 1
EPOCHS, ALPHA, BETA, L1, L2, SCALE = 3, 0.3, 1.0, 0.02, 0.001, 30.0
SCHEMA = "doc_id long, held_out boolean, lang_pred string, score double"


def _column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def gram_buckets(piece: K.Piece) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each order, the buckets of its n-grams and the rows' bounds in them."""
    body = K.table("lower")[piece.data]
    points = np.frombuffer(body.tobytes().decode("utf-8", "replace").encode("utf-32-le"), np.uint32)
    off = K.code_points(body)[piece.off]
    if len(points) != off[-1]:  # not UTF-8: each row on its own
        rows = [np.frombuffer(body[a:b].tobytes().decode("utf-8", "replace").encode("utf-32-le"), np.uint32) for a, b in zip(piece.off[:-1], piece.off[1:], strict=True)]
        points = np.concatenate(rows)
        off = np.concatenate([[0], np.cumsum([len(r) for r in rows])])
    out = []
    state = np.zeros(len(points), np.uint32)
    for n in range(1, ORDER + 1):
        size = max(0, len(points) - n + 1)
        state = (state[:size] * np.uint32(0x01000193)) ^ (points[n - 1:n - 1 + size] + np.uint32(0x9E3779B9 * n & 0xFFFFFFFF))
        h = state * np.uint32(0x85EBCA6B)
        h ^= h >> np.uint32(13)
        h *= np.uint32(0xC2B2AE35)
        ok = K.within(off, n, size)
        run = np.zeros(size + 1, np.int64)
        np.cumsum(ok, out=run[1:])
        out.append(((h[ok] >> np.uint32(16)).astype(np.int64), run[np.minimum(off, size)]))
    return out


def has_letter(piece: K.Piece) -> np.ndarray:
    data = piece.data
    folded = data | 32
    some = K.row_sums((folded >= 97) & (folded <= 122), piece.off) > 0
    for r in np.flatnonzero(~some & (K.row_sums(data >= 128, piece.off) > 0)):
        some[r] = any(c.isalpha() for c in piece.text(r))
    return some


def _features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        at, tf = [], []
        for piece in K.pieces(_column(batch, "text")):
            grams = gram_buckets(piece)
            for r in range(piece.n):
                ids, values = [], []
                for n, (b, bound) in enumerate(grams):
                    own, count = np.unique(b[bound[r]:bound[r + 1]], return_counts=True)
                    ids.append(own + n * BUCKETS)
                    values.append(count / max(1, count.sum()))
                at.append(np.concatenate(ids).astype(np.int32))
                tf.append(np.concatenate(values))
        yield pa.RecordBatch.from_arrays([_column(batch, "doc_id").cast(pa.int64()), _column(batch, "lang").cast(pa.string()), pa.array(at, pa.list_(pa.int32())), pa.array(tf, pa.list_(pa.float64()))], ["doc_id", "lang", "at", "tf"])


def _frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """How many of a task's documents hold each bucket; at -1 the documents."""
    total, docs = np.zeros(ORDER * BUCKETS, np.int64), 0
    for batch in batches:
        docs += batch.num_rows
        for piece in K.pieces(_column(batch, "text")):
            for n, (b, bound) in enumerate(gram_buckets(piece)):
                pairs = np.repeat(np.arange(piece.n), np.diff(bound)) * BUCKETS + b
                total[n * BUCKETS:(n + 1) * BUCKETS] += np.bincount(_distinct(pairs) % BUCKETS, minlength=BUCKETS)
    at = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(np.append(at, -1)), pa.array(np.append(total[at], docs))], ["bucket", "n"])


def _distinct(x: np.ndarray) -> np.ndarray:
    x = np.sort(x)
    return x[np.concatenate([[True], x[1:] != x[:-1]])] if len(x) else x


class Model:
    """Languages, the buckets with a weight, their weights (idf included), intercepts, temperature."""

    def __init__(self, langs: list[str], weights: np.ndarray, bias: np.ndarray, temperature: float):
        self.langs, self.bias, self.temperature = langs, bias, temperature
        self.at = np.flatnonzero(weights.any(1)).astype(np.int32)
        self.weights = weights[self.at].astype(np.float32)
        self.size = len(weights)

    def table(self) -> np.ndarray:
        """For every bucket its row in ``rows()``; the last one, of zeros, for buckets without weights."""
        out = np.full(self.size, len(self.at), np.int32)
        out[self.at] = np.arange(len(self.at))
        return out

    def rows(self) -> np.ndarray:
        return np.concatenate([self.weights, np.zeros((1, len(self.langs)), np.float32)])

    def probabilities(self, logits: np.ndarray) -> np.ndarray:
        return softmax((logits + self.bias) / self.temperature)


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


class FollowTheLeader:
    """Per-coordinate FTRL-proximal for softmax regression with L1 and L2 penalties."""

    def __init__(self, size: int, classes: int, alpha: float = ALPHA, beta: float = BETA, l1: float = L1, l2: float = L2):
        self.z, self.n = np.zeros((size, classes)), np.zeros((size, classes))
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2

    def weights(self, at=slice(None)) -> np.ndarray:
        z, n = self.z[at], self.n[at]
        return np.where(np.abs(z) <= self.l1, 0.0, (np.sign(z) * self.l1 - z) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2))

    def learn(self, at: np.ndarray, x: np.ndarray, label: int) -> None:
        w = self.weights(at)
        p = softmax(x @ w)
        p[label] -= 1
        g = np.outer(x, p)
        n = self.n[at]
        self.z[at] += g - (np.sqrt(n + g * g) - np.sqrt(n)) / self.alpha * w
        self.n[at] = n + g * g


def train(rows: list[tuple[str, np.ndarray, np.ndarray]], df: np.ndarray, n_docs: int) -> Model | None:
    """rows: language, buckets and term frequencies, in a fixed order; df: the buckets' document frequencies."""
    langs = sorted({r[0] for r in rows})
    if not langs:
        return None
    size = ORDER * BUCKETS
    idf = np.log((1 + n_docs) / (1 + df)) + 1
    cut = [r for k, r in enumerate(rows) if k % 5] or rows
    held = [r for k, r in enumerate(rows) if k % 5 == 0]
    ftrl = FollowTheLeader(size + 1, len(langs))
    for _ in range(EPOCHS):
        for lang, at, tf in cut:
            ftrl.learn(np.append(at, size), np.append(tf * idf[at] * SCALE, 1.0), langs.index(lang))
    w = ftrl.weights()
    logits = np.array([tf * idf[at] * SCALE @ w[at] + w[size] for _, at, tf in held])
    truth = np.array([langs.index(r[0]) for r in held])
    grid = np.exp(np.linspace(np.log(0.2), np.log(5), 65))
    loss = [-np.log(np.maximum(softmax(logits / t)[np.arange(len(truth)), truth], 1e-12)).sum() for t in grid]
    return Model(langs, w[:size] * (idf * SCALE)[:, None], w[size], float(grid[int(np.argmin(loss))]))


def learnable(docs: DataFrame) -> DataFrame:
    fold = F.crc32(F.col("doc_id").cast("string").cast("binary")) % FOLDS
    return docs.where((fold != HELD) & F.col("lang").isNotNull() & F.col("text").isNotNull())


def _chosen(rows: DataFrame, sample: int) -> DataFrame:
    """Of every language the documents with the smallest hashes; equal rows once.

    A language's share of hashes that holds twice its quota is read off its count, so the window that orders them sees
    a bounded number of rows, however many the language has.
    """
    counts = rows.groupBy("lang").agg(F.count("*").alias("n"))
    langs = counts.agg(F.count("*").alias("langs"))
    quota = F.greatest(F.floor(F.lit(sample) / F.col("langs")), F.lit(LEAST))
    limits = counts.crossJoin(F.broadcast(langs)).select("lang", quota.alias("quota"), F.least(F.lit(1.0), (2 * quota + 20) / F.col("n")).alias("share"))
    ranked = rows.withColumn("rank", F.xxhash64("doc_id", "text"))
    few = ranked.join(F.broadcast(limits), "lang").where((F.col("rank") / F.lit(2.0**64) + 0.5) <= F.col("share"))
    once = few.groupBy("lang", "rank", "doc_id", "quota").agg(F.first("text").alias("text"))
    place = F.row_number().over(Window.partitionBy("lang").orderBy("rank", "doc_id"))
    return once.withColumn("place", place).where("place <= quota").select("doc_id", "text", "lang")


def fit(docs: DataFrame, sample: int = SAMPLE) -> Model | None:
    rows = learnable(docs.select("doc_id", "text", "lang"))
    counted = rows.select("text").mapInArrow(_frequencies, "bucket long, n long").groupBy("bucket").agg(F.sum("n").alias("n")).toArrow()
    df, n_docs = np.zeros(ORDER * BUCKETS + 1, np.int64), 0
    df[counted["bucket"].to_numpy()] = counted["n"].to_numpy()
    df, n_docs = df[:-1], int(df[-1])
    if not n_docs:
        return None
    got = _chosen(rows, sample).mapInArrow(_features, "doc_id long, lang string, at array<int>, tf array<double>").toArrow()
    at, tf = (got[c].combine_chunks() for c in ("at", "tf"))
    rows_ = [(lang, at[k].values.to_numpy().astype(np.int64), tf[k].values.to_numpy(), doc) for k, (lang, doc) in enumerate(zip(got["lang"].to_pylist(), got["doc_id"].to_pylist(), strict=True))]
    rows_.sort(key=lambda r: (zlib.crc32(f"{r[3]}/order".encode()), r[3], r[0], len(r[1]), r[1].tobytes()))
    return train([r[:3] for r in rows_], df, n_docs)


def predict_batch(texts: pa.Array, model: Model | None, tables: tuple[np.ndarray, np.ndarray] | None = None) -> tuple[list[str], np.ndarray]:
    names, scores = [], []
    table, rows = tables or ((model.table(), model.rows()) if model else (None, None))
    for piece in K.pieces(texts):
        some = has_letter(piece) & ~piece.null
        if model is None:
            names += ["und"] * piece.n
            scores.append(np.zeros(piece.n))
            continue
        logits = np.zeros((piece.n, len(model.langs)))
        for n, (b, bound) in enumerate(gram_buckets(piece)):
            full = np.flatnonzero(np.diff(bound))
            own = table[n * BUCKETS:(n + 1) * BUCKETS][b]
            for k in range(0, len(model.langs), 8) if len(full) else ():
                logits[full, k:k + 8] += np.add.reduceat(rows[:, k:k + 8][own], bound[:-1][full], axis=0, dtype=np.float64) / np.diff(bound)[full][:, None]
        p = model.probabilities(logits)
        best = p.argmax(1)
        names += [model.langs[k] if ok else "und" for k, ok in zip(best, some, strict=True)]
        scores.append(np.where(some, np.round(p[np.arange(piece.n), best], 9), 0.0))
    return names, np.concatenate(scores) if scores else np.zeros(0)


def _predictor(model: Model | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = (model.table(), model.rows()) if model else None
        for batch in batches:
            names, scores = predict_batch(_column(batch, "text"), model, tables)
            ids = _column(batch, "doc_id").cast(pa.int64())
            held = [i is not None and zlib.crc32(str(i).encode()) % FOLDS == HELD for i in ids.to_pylist()]
            yield pa.RecordBatch.from_arrays([ids, pa.array(held, pa.bool_()), pa.array(names, pa.string()), pa.array(scores)], ["doc_id", "held_out", "lang_pred", "score"])

    return run


def predict(docs: DataFrame, model: Model | None) -> DataFrame:
    return docs.select("doc_id", "text").mapInArrow(_predictor(model), SCHEMA)


def op9_ftrl_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    return predict(docs, fit(docs))


register_pickle_by_value(sys.modules[__name__])
