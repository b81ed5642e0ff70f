"""Block entropies: word counts and their estimators.

Words are counted over chunks, so a sequence's length doesn't matter; the counts are an aggregate with map-side
partial sums.  Every estimator needs the counts' counts only (how many words occur c times), so it is evaluated once for
each distinct count.
"""

from __future__ import annotations

import math
import sys
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.mathx import digamma, unit

METHODS = ["plugin", "first_order", "digamma_parity", "laplace_block", "dirichlet_mean"]


def block_counts(chunked: DataFrame, n_max: int, by: list[str] | None = None) -> DataFrame:
    """[by,] n, word, cnt: the words of 1 to n_max symbols; chunks must have n_max - 1 symbols to their left.

    Each batch is counted in arrays first, so only distinct words are shuffled, and no position copies its chunk.
    """
    by = by or []
    types = dict(chunked.dtypes)
    schema = ", ".join([*(f"`{c}` {types[c]}" for c in by), "n int", "word string", "cnt long"])
    return chunked.select(*by, "left", "body").mapInArrow(_chunk_words(n_max, by), schema).groupBy(*by, "n", "word").agg(F.sum("cnt").alias("cnt"))


def _chunk_words(n_max: int, by: list[str]):
    """Kernel: counts of the words that end in the bodies of a batch of chunks, some chunks at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (piece for whole in batches for piece in _pieces(whole)):
            table = pa.Table.from_batches([batch])
            keys = table.select(by).group_by(by).aggregate([]).to_pylist() if by else [{}]
            for key in keys:
                mask = np.ones(table.num_rows, bool)
                for c in by:
                    mask &= (pc.is_null(table[c]) if key[c] is None else pc.fill_null(pc.equal(table[c], key[c]), False)).to_numpy(zero_copy_only=False)
                own = table.filter(pa.array(mask)) if by else table
                for n, words, count in count_words(own["left"], own["body"], n_max):
                    columns = [pa.array([key[c]] * len(words), table.schema.field(c).type) for c in by]
                    yield pa.RecordBatch.from_arrays([*columns, pa.array(np.full(len(words), n, np.int32)), pa.array(words, pa.string()), pa.array(count, pa.int64())], [*by, "n", "word", "cnt"])

    return run


def _pieces(batch: pa.RecordBatch, limit: int = 1 << 21) -> Iterator[pa.RecordBatch]:
    """Slices of about so many symbols at most (a chunk at least)."""
    size = np.cumsum(pc.fill_null(pc.binary_length(batch.column(batch.schema.get_field_index("body"))), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    k = 0
    while k < batch.num_rows:
        end = max(k + 1, int(np.searchsorted(size, (size[k - 1] if k else 0) + limit, "right")))
        yield batch.slice(k, end - k)
        k = end


def count_words(left: pa.ChunkedArray, body: pa.ChunkedArray, n_max: int) -> Iterator[tuple[int, list[str], np.ndarray]]:
    """(n, words, counts): packed in 64 bits for up to 8 symbols of one byte, by slices otherwise."""
    both = pc.binary_join_element_wise(left, body, "").combine_chunks().cast(pa.large_string()) if len(body) else pa.array([], pa.large_string())
    if not len(both):
        return
    _, offsets, data = both.buffers()
    off = np.frombuffer(offsets, np.int64, len(both) + 1, both.offset * 8)
    data = np.frombuffer(data, np.uint8)[off[0]:off[-1]] if data is not None else np.zeros(0, np.uint8)
    off = off - off[0]
    if n_max > 8 or (len(data) and data.max() > 127):
        counts: list[Counter] = [Counter() for _ in range(n_max + 1)]
        for text, have in zip(both.to_pylist(), pc.utf8_length(left).to_pylist(), strict=True):
            for n in range(1, n_max + 1):
                counts[n].update(text[k - n + 1:k + 1] for k in range(max(have, n - 1), len(text)))
        yield from ((n, list(c), np.array(list(c.values()), np.int64)) for n, c in enumerate(counts) if c)
        return
    row = np.repeat(np.arange(len(both)), np.diff(off))
    at = np.arange(len(data)) - off[row]
    first = pc.utf8_length(left).combine_chunks().to_numpy(zero_copy_only=False)[row]
    code = data.astype(np.uint64)
    wide = code
    for n in range(1, n_max + 1):
        if n > 1:
            code = (code[:-1] << np.uint64(8)) | wide[n - 1:]
        words, count = np.unique(code[at[n - 1:] >= np.maximum(first[n - 1:], n - 1)], return_counts=True)
        text = words.astype(">u8").tobytes()
        yield n, [text[8 * k + 8 - n:8 * k + 8].decode("ascii") for k in range(len(words))], count


def _packed_words(n_max: int):
    """Kernel: counts of the words of a batch of sequences of one-byte symbols, up to 8 symbols long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column(0)
            if not len(column):
                continue
            if isinstance(column, pa.ChunkedArray):
                column = column.combine_chunks()
            column = column.cast(pa.large_string())
            _, offsets, body = column.buffers()
            off = np.frombuffer(offsets, np.int64, len(column) + 1, column.offset * 8)
            data = np.frombuffer(body, np.uint8)[off[0]:off[-1]].astype(np.uint64) if body is not None else np.zeros(0, np.uint64)
            off = off - off[0]
            inside = np.ones(len(data), bool)
            code = data
            for n in range(1, n_max + 1):
                if n > 1:
                    code = (code[:-1] << np.uint64(8)) | data[n - 1:]
                    cut = off[1:-1] - (n - 1)
                    inside = inside[:len(code)].copy()
                    inside[cut[(cut >= 0) & (cut < len(code))]] = False
                words, count = np.unique(code[inside], return_counts=True)
                text = words.astype(">u8").tobytes()
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(words), n, np.int32)), pa.array([text[8 * k + 8 - n:8 * k + 8].decode("ascii") for k in range(len(words))], pa.string()), pa.array(count.astype(np.int64))], ["n", "word", "cnt"])

    return run


def block_counts_arrow(seqs: DataFrame, n_max: int) -> DataFrame:
    """The same for sequences of ASCII symbols and n_max up to 8: counted in batches before anything is shuffled."""
    if n_max > 8:
        raise ValueError("words of more than 8 symbols: use block_counts")
    return seqs.select("t").mapInArrow(_packed_words(n_max), "n int, word string, cnt long").groupBy("n", "word").agg(F.sum("cnt").alias("cnt"))


def spectrum(counts: DataFrame, by: list[str] | None = None) -> DataFrame:
    """[by,] n, cnt, mult: how many words occur cnt times."""
    return counts.groupBy(*(by or []), "n", "cnt").agg(F.count("*").alias("mult"))


def block_entropy(counts: DataFrame, d: int, units: str = "bits", methods: list[str] | None = None, beta: float = 0.5, by: list[str] | None = None, denominator: str = "windows", length: int | None = None) -> DataFrame:
    """[by,] n, method, n_windows, n_words, h_block, h_diff, h_per_symbol.

    plugin: likelihood; first_order: plus (M - 1) / 2N for M seen words; digamma_parity: the digamma estimator with its
    alternating term; laplace_block: add-one over all d^n words, unseen ones in closed form; dirichlet_mean: posterior
    mean under a symmetric prior.  denominator 'length' divides by the sequence's length instead of its windows.
    """
    by, methods = by or [], methods or METHODS
    s = spectrum(counts, by)
    c, m = F.col("cnt").cast("double"), F.col("mult").cast("double")
    lg = F.lit(math.log(d))
    k = F.exp(F.first("n") * lg)  # d^n
    parts = s.groupBy(*by, "n").agg(
        F.sum(F.col("cnt") * F.col("mult")).alias("n_windows"), F.sum("mult").alias("n_words"), F.sum(m * c * F.ln(c)).alias("clogc"),
        F.sum(m * c * (digamma(c) + F.when(F.col("cnt") % 2 == 0, 1.0).otherwise(-1.0) / (c * (c + 1)))).alias("cpsi"),
        F.sum(m * (c + 1) * F.ln(c + 1)).alias("laplace"), F.sum(m * (c + beta) * digamma(c + beta + 1)).alias("dirichlet"), k.alias("k"),
    )
    w = F.col("n_windows").cast("double")
    if denominator == "length" and length:
        w = F.lit(float(length))
    unseen = F.col("k") - F.col("n_words")
    total = w + F.col("k")
    a = w + beta * F.col("k")
    value = {
        "plugin": F.ln(w) - F.col("clogc") / w,
        "first_order": F.ln(w) - F.col("clogc") / w + (F.col("n_words") - 1) / (2 * w),
        "digamma_parity": F.ln(w) - F.col("cpsi") / w,
        "laplace_block": F.ln(total) - F.col("laplace") / total,
        "dirichlet_mean": digamma(a + 1) - (F.col("dirichlet") + unseen * beta * digamma(F.lit(beta + 1.0))) / a,
    }
    u = unit(units, d)
    long = parts.select(*by, "n", "n_windows", "n_words", F.explode(F.array(*(F.struct(F.lit(x).alias("method"), (value[x] / u).alias("h_block")) for x in methods))).alias("v")).select(*by, "n", "v.method", "n_windows", "n_words", "v.h_block")
    return differential(long, by)


def differential(h: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Adds h_diff (the last symbol's part) and h_per_symbol; a window holds at most n_max rows."""
    own = Window.partitionBy(*(by or []), "method").orderBy("n")
    return h.withColumn("h_diff", F.col("h_block") - F.coalesce(F.lag("h_block").over(own), F.lit(0.0))).withColumn("h_per_symbol", F.col("h_block") / F.col("n"))


def conditional_entropy(counts: DataFrame, d: int, units: str = "bits", laplace: bool = False) -> DataFrame:
    """n, h: the last symbol's entropy given the others, by likelihood, or with the add-one rule for the conditional probability."""
    own = F.sum("cnt").over(Window.partitionBy("n", F.substring(F.col("word"), F.lit(1), F.col("n") - 1)))
    rows = counts.withColumn("ctx", own)
    p = (F.col("cnt") + 1) / (F.col("ctx") + d) if laplace else F.col("cnt") / F.col("ctx")
    total = rows.groupBy("n").agg(F.sum(-F.col("cnt") * F.ln(p)).alias("s"), F.sum("cnt").alias("w"))
    return total.select("n", (F.col("s") / F.col("w") / unit(units, d)).alias("h"))


def min_count_entropy(counts: DataFrame, least: int, units: str = "bits") -> DataFrame:
    """n, h_block without the information of words seen fewer than ``least`` times (their share of the sum is left out)."""
    total = counts.groupBy("n").agg(F.sum("cnt").alias("w"), F.sum(F.when(F.col("cnt") >= least, F.col("cnt") * F.ln("cnt"))).alias("s"), F.sum(F.when(F.col("cnt") >= least, F.col("cnt"))).alias("kept"))
    return total.select("n", ((F.coalesce("kept", F.lit(0)) * F.ln("w") - F.coalesce("s", F.lit(0.0))) / F.col("w") / unit(units)).alias("h_block"))


def assumed_tail_entropy(counts: DataFrame, n_words: float, units: str = "bits") -> DataFrame:
    """Experimental: the mass of words seen once is spread evenly over an assumed number of words in all."""
    total = counts.groupBy("n").agg(F.sum("cnt").cast("double").alias("w"), F.sum(F.when(F.col("cnt") > 1, F.col("cnt") * F.ln("cnt"))).alias("s"), F.sum(F.when(F.col("cnt") > 1, F.col("cnt")).otherwise(0)).alias("kept"), F.sum(F.when(F.col("cnt") == 1, 1).otherwise(0)).alias("once"), F.sum(F.when(F.col("cnt") > 1, 1).otherwise(0)).alias("often"))
    tail = F.greatest(F.lit(float(n_words)) - F.col("often"), F.col("once").cast("double"), F.lit(1.0))
    mass = F.col("once") / F.col("w")
    h = (F.col("kept") * F.ln("w") - F.coalesce("s", F.lit(0.0))) / F.col("w") + F.when(mass > 0, -mass * F.ln(mass / tail)).otherwise(0.0)
    return total.select("n", (h / unit(units)).alias("h_block"))


def description_bound(h: DataFrame, d: int, units: str = "bits") -> DataFrame:
    """Length of a safe description: the data by its block entropy and all d^n counts, in the same units."""
    size = F.col("n_windows") * F.col("h_block") + F.exp(F.col("n") * math.log(d)) * F.ln("n_windows") / unit(units, d)
    return h.select("n", "method", size.alias("total"), (size / F.col("n_windows")).alias("per_window"))


def bias_expected(true_p: DataFrame, length: int) -> DataFrame:
    """Of known word probabilities (n, p): the expected error of the likelihood estimate to second order, in nats."""
    g = true_p.where("p > 0").groupBy("n").agg(F.count("*").alias("m"), F.sum(1 / F.col("p")).alias("inverse"))
    return g.select("n", (-(F.col("m") - 1) / (2 * length) + (1 - F.col("inverse")) / (12 * length * length)).alias("bias"))


def block_rate(h: DataFrame, how: str = "last") -> DataFrame:
    """method, rate: the last h_diff, or h_per_symbol, of the largest n."""
    column = {"last": "h_diff", "per_symbol": "h_per_symbol"}[how]
    return h.groupBy("method").agg(F.max_by(column, "n").alias("rate"))


def block_curve(chunked: DataFrame, n_list: list[int], grid: list[int], d: int, units: str = "bits", methods: list[str] | None = None, by: list[str] | None = None) -> DataFrame:
    """Estimates over prefixes of the lengths in grid: one count by bin, then running sums over the bins.

    Words are put in the bin of their last position, so a longer prefix adds bins; grid is a short list.  Chunks are cut
    where bins end, and counted in arrays.
    """
    by = by or []
    n_max = max(n_list)
    ends = sorted(grid)
    cut = F.explode(F.array(*(F.struct(F.lit(low).cast("long").alias("low"), F.lit(high).cast("long").alias("bin")) for low, high in zip([0, *ends], ends, strict=False)))).alias("cut")
    text = chunked.select(*by, "start", F.length("left").alias("l"), (F.col("start") + F.length("body") - 1).alias("end"), F.concat("left", "body").alias("s"), cut).where("cut.low < end and cut.bin >= start")
    begin = (F.col("l") + F.greatest(F.col("start"), F.col("cut.low") + 1) - F.col("start")).cast("int")  # symbols before the part
    have = F.least(begin, F.lit(n_max - 1))
    size = (F.least("end", "cut.bin") - F.greatest(F.col("start"), F.col("cut.low") + 1) + 1).cast("int")
    parts = text.select(*by, F.col("cut.bin").alias("bin"), F.substring(F.col("s"), begin - have + 1, have).alias("left"), F.substring(F.col("s"), begin + 1, size).alias("body"))
    binned = block_counts(parts, n_max, [*by, "bin"]).where(F.col("n").isin(*{*n_list, *(n - 1 for n in n_list if n > 1)})).withColumnRenamed("cnt", "c")
    bins = F.array(*(F.lit(g).cast("long") for g in ends))
    spread = binned.select(*by, "n", "word", "c", F.explode(F.filter(bins, lambda g: g >= F.col("bin"))).alias("length"))
    counts = spread.groupBy(*by, "n", "length", "word").agg(F.sum("c").alias("cnt"))
    h = block_entropy(counts, d, units, methods, by=[*by, "length"])
    return h.where(F.col("n").isin(n_list)) if n_max else h


def check_monotone(h: DataFrame, slack: float = 1e-9) -> DataFrame:
    """Rows where h_diff exceeds that of the shorter block (there should be none while the counts suffice)."""
    own = Window.partitionBy("method").orderBy("n")
    return h.withColumn("before", F.lag("h_diff").over(own)).where(F.col("h_diff") > F.col("before") + slack)


register_pickle_by_value(sys.modules[__name__])
