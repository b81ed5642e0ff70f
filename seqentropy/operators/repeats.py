"""Repeat lengths and parsings: entropy from how soon sequences repeat themselves.

The kernels take all sequences of a piece at once: ranks of words of doubling length (each from pairs of the last), a
suffix order from the ranks, and common prefixes by descending through the ranks.
"""

from __future__ import annotations

import sys

import numpy as np
import pyarrow as pa
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.mathx import unit
from .predict import batch_sequences


def word_ranks(sym: np.ndarray, bound: np.ndarray) -> list[np.ndarray]:
    """Order-preserving ranks of the words of 1, 2, 4, ... symbols at each position, until all differ; 0 is past the end."""
    n = len(sym)
    row = np.repeat(np.arange(len(bound) - 1), np.diff(bound))
    end = bound[row + 1]
    base = int(sym.max()) + 1 if n else 1
    rank = np.unique(row * base + sym, return_inverse=True)[1] + 1 if n else np.zeros(0, np.int64)
    out, size = [rank], 1
    while n and rank.max() < n:
        at = np.arange(n) + size
        after = np.where(at < end, rank[np.minimum(at, n - 1)], 0)
        rank = np.unique(rank.astype(np.int64) * (n + 2) + after, return_inverse=True)[1] + 1
        out.append(rank)
        size *= 2
    return out


def common_prefix(ranks: list[np.ndarray], i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Length of the common prefix of the suffixes at i and j (different positions); -1 partners give 0."""
    n = len(ranks[0])
    length = np.zeros(len(i), np.int64)
    ok = j >= 0
    for k in range(len(ranks) - 1, -1, -1):
        a, b = i + length, j + length
        inside = ok & (a < n) & (b < n)
        same = inside.copy()
        same[inside] = ranks[k][a[inside]] == ranks[k][b[inside]]
        length[same] += 1 << k
    return length


def longest_matches(sym: np.ndarray, bound: np.ndarray, side: str = "past") -> np.ndarray:
    """For each position the longest match with an earlier start ('past') or any other start ('both')."""
    n = len(sym)
    if not n:
        return np.zeros(0, np.int64)
    ranks = word_ranks(sym, bound)
    order = np.argsort(ranks[-1], kind="stable")
    if side == "both":
        before, after = np.full(n, -1), np.full(n, -1)
        before[order[1:]], after[order[:-1]] = order[:-1], order[1:]
    else:
        before, after = np.full(n, -1), np.full(n, -1)
        for target, line in ((before, order), (after, order[::-1])):
            stack: list[int] = []
            for p in line.tolist():
                while stack and stack[-1] > p:
                    stack.pop()
                target[p] = stack[-1] if stack else -1
                stack.append(p)
    i = np.arange(n)
    return np.maximum(common_prefix(ranks, i, before), common_prefix(ranks, i, after))


def match_lengths(seqs: DataFrame, side: str = "past", end: str = "drop") -> DataFrame:
    """seq_id, pos, len: the shortest word at pos that has no earlier (or no other) start.

    Where the sequence's end comes before that word does, there is no row (end 'drop'), or the end counts as a symbol of
    its own ('sentinel').
    """

    def run(batches):
        for batch in batches:
            for names, sym, bound in batch_sequences(batch):
                row = np.repeat(np.arange(len(names)), np.diff(bound))
                length = longest_matches(sym, bound, side) + 1
                at = np.arange(len(sym))
                keep = np.ones(len(sym), bool) if end == "sentinel" else at + length <= bound[row + 1]
                yield pa.RecordBatch.from_arrays([pa.array(np.array(names, np.int64)[row][keep]), pa.array((at - bound[row] + 1)[keep]), pa.array(length[keep].astype(np.int32))], ["seq_id", "pos", "len"])

    return seqs.select("seq_id", "t").mapInArrow(run, "seq_id long, pos long, len int")


def repeat_rate(lengths: DataFrame, units: str = "bits", by: list[str] | None = None) -> DataFrame:
    """n, sum_len, rate: n log n / sum of the lengths.  Not a bound, and proven only for chains of finite order."""
    g = lengths.groupBy(*(by or [])).agg(F.count("*").alias("n"), F.sum("len").cast("long").alias("sum_len"))
    return g.withColumn("rate", F.col("n") * F.ln("n") / F.col("sum_len") / unit(units))


def repeat_curve(lengths: DataFrame, grid: list[int], units: str = "bits", by: list[str] | None = None) -> DataFrame:
    """[by,] n, rate over prefixes (past lengths only look back, so one pass gives all prefixes).

    A length counts for a prefix if its word ends inside.
    """
    by = by or []
    points = F.array(*(F.lit(g).cast("long") for g in sorted(grid)))
    binned = lengths.select(*by, "len", F.array_min(F.filter(points, lambda g: g >= F.col("pos") + F.col("len") - 1)).alias("bin")).where("bin is not null").groupBy(*by, "bin").agg(F.count("*").alias("c"), F.sum("len").alias("s"))
    w = Window.partitionBy(*by).orderBy("bin")
    run = binned.select(*by, F.col("bin").alias("n"), F.sum("c").over(w).alias("c"), F.sum("s").over(w).alias("s"))
    return run.select(*by, "n", (F.col("c") * F.ln("c") / F.col("s") / unit(units)).alias("h"))


def first_occurrences(seqs: DataFrame, p_max: int) -> DataFrame:
    """seq_id, p, word, first, cnt: where each word of p symbols first starts and how often it does (levels in joins and aggregates)."""
    ends = seqs.select("seq_id", "t", F.explode(F.sequence(F.lit(1), F.length("t"))).alias("i"))
    words = ends.select("seq_id", "t", "i", F.explode(F.sequence(F.lit(1), F.least(F.lit(p_max), F.length("t") - F.col("i") + 1))).alias("p"))
    return words.groupBy("seq_id", "p", F.substring(F.col("t"), F.col("i"), F.col("p")).alias("word")).agg(F.min("i").alias("first"), F.count("*").alias("cnt"))


def match_lengths_levels(chunked: DataFrame, p_max: int) -> DataFrame:
    """seq_id, pos, len for sequences of any length, level by level; lengths beyond p_max are null.

    chunked has p_max - 1 symbols to the left.  A position is resolved at the first level at which it is the first start
    of its word.  Sequences of up to ``LEVELS_AT_ONCE`` symbols are put together and resolved in arrays.  Of longer ones
    the first starts are partial minima, found in arrays for some chunks at a time; they name the positions that they
    resolve, so words are not brought back to positions, and no join may broadcast them.
    """
    chunked = chunked.select("seq_id", "start", "left", "body")
    long = chunked.where(F.col("start") + F.length("body") - 1 > LEVELS_AT_ONCE).select("seq_id").distinct()
    parts = F.array_sort(F.collect_list(F.struct("start", "body")))
    short = chunked.join(long, "seq_id", "left_anti").groupBy("seq_id").agg(F.array_join(F.transform(parts, lambda r: r["body"]), "").alias("t")).mapInArrow(_resolved(p_max), "seq_id long, pos long, len int")
    rest = chunked.join(long, "seq_id", "left_semi")
    first = rest.mapInArrow(_first_starts(p_max), "seq_id long, p int, word string, pos long").groupBy("seq_id", "p", "word").agg(F.min("pos").alias("pos"))
    every = rest.select("seq_id", F.explode(F.sequence(F.col("start"), F.col("start") + F.length("body") - 1)).alias("pos"), F.lit(None).cast("int").alias("p"))
    return short.unionAll(first.select("seq_id", "pos", "p").unionAll(every).groupBy("seq_id", "pos").agg(F.min("p").alias("len")))


LEVELS_AT_ONCE = 1 << 16


def _level_words(sym: np.ndarray, row: np.ndarray, inside: np.ndarray, p_max: int):
    """For each p the numbers of the words of p symbols that end at each place (of another row: another word), and where they fit."""
    base = int(sym.max()) + 1
    word = np.unique(row * base + sym, return_inverse=True)[1]
    for p in range(1, p_max + 1):
        if p > 1:
            longer = np.full(len(sym), -1, np.int64)
            longer[p - 1:] = np.where(inside[p - 1:] >= p - 1, word[p - 2:len(sym) - 1] * base + sym[p - 1:], -1)
            word = np.unique(longer, return_inverse=True)[1]
        yield p, word, inside >= p - 1


def _resolved(p_max: int):
    def run(batches):
        for batch in batches:
            for names, sym, bound in batch_sequences(batch):
                row = np.repeat(np.arange(len(names)), np.diff(bound))
                inside = np.arange(len(sym)) - bound[row]
                length = np.zeros(len(sym), np.int32)
                for p, word, fits in _level_words(sym, row, inside, p_max):
                    at = np.flatnonzero(fits)
                    begin = at[np.unique(word[at], return_index=True)[1]] - p + 1
                    length[begin[length[begin] == 0]] = p
                yield pa.RecordBatch.from_arrays([pa.array(np.array(names, np.int64)[row]), pa.array(inside + 1), pa.array(length, mask=length == 0)], ["seq_id", "pos", "len"])

    return run


def _first_starts(p_max: int):
    def run(batches):
        """The first start, in some chunks, of each word of 1 to p_max symbols that ends in a body."""
        for batch in (whole.slice(k, 512) for whole in batches for k in range(0, whole.num_rows, 512)):
            ids, starts, lefts, bodies = (batch.column(k).to_pylist() for k in range(4))
            own = [left + body for left, body in zip(lefts, bodies, strict=True)]
            if not sum(map(len, own)):
                continue
            sym = np.unique(np.frombuffer("".join(own).encode("utf-32-le"), np.uint32), return_inverse=True)[1].astype(np.int64)
            size, skip = (np.array([len(x) for x in rows], np.int64) for rows in (own, lefts))
            row = np.repeat(np.arange(len(own)), size)
            inside = np.arange(len(sym)) - np.repeat(np.cumsum(size) - size, size)
            end = np.array(starts, np.int64)[row] + inside - skip[row]
            names, name = np.unique(np.array(ids, np.int64), return_inverse=True)
            whole = "".join(own)
            for p, word, fits in _level_words(sym, name[row], inside, p_max):
                at = np.flatnonzero(fits & (inside >= skip[row]))
                if not len(at):
                    continue
                at = at[np.lexsort((end[at], word[at]))]
                at = at[np.concatenate([[True], word[at][1:] != word[at][:-1]])]
                yield pa.RecordBatch.from_arrays([pa.array(names[name[row[at]]]), pa.array(np.full(len(at), p, np.int32)), pa.array([whole[e - p + 1:e + 1] for e in at.tolist()], pa.string()), pa.array(end[at] - p + 1)], ["seq_id", "p", "word", "pos"])

    return run


def tree_nodes(t: str, n: int) -> list[tuple[str, int, bool, int | None, int]]:
    """(node, depth, whether a leaf, start of a leaf, visits) of the prefix tree of the first n starts; only words that several starts share are made longer."""
    out, groups, p = [], [list(range(min(n, len(t))))], 0
    while groups:
        p += 1
        longer = []
        for group in groups:
            split: dict[str, list[int]] = {}
            for i in group:
                if i + p <= len(t):
                    split.setdefault(t[i + p - 1], []).append(i)
            for starts in split.values():
                single = len(starts) == 1
                out.append((t[starts[0]:starts[0] + p], p, single, starts[0] + 1 if single else None, len(starts)))
                if not single:
                    longer.append(starts)
        groups = longer
    return out


def _rows(batch: pa.RecordBatch, make, schema: pa.Schema):
    """``make``'s rows of each sequence (seq_id, t), in batches of those of many sequences."""
    rows: list[tuple] = []
    for name, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
        rows += [(name, *r) for r in make(t or "")]
        if len(rows) >= ROWS_AT_ONCE:
            yield pa.RecordBatch.from_arrays([pa.array(c, x.type) for c, x in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)
            rows = []
    if rows:
        yield pa.RecordBatch.from_arrays([pa.array(c, x.type) for c, x in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)


ROWS_AT_ONCE = 1 << 15


def prefix_tree(seqs: DataFrame, n: int) -> DataFrame:
    """seq_id, node, depth, is_leaf, key_pos, visits of the prefix tree of the starts 1..n: leaves are shortest words that tell a start from all others."""
    schema = pa.schema([("seq_id", pa.int64()), ("node", pa.string()), ("depth", pa.int32()), ("is_leaf", pa.bool_()), ("key_pos", pa.int32()), ("visits", pa.int64())])

    def run(batches):
        for batch in batches:
            yield from _rows(batch, lambda t: tree_nodes(t, n), schema)

    return seqs.select("seq_id", "t").mapInArrow(run, "seq_id long, node string, depth int, is_leaf boolean, key_pos int, visits long")


def suffix_words(seqs: DataFrame, precursor: str = "") -> DataFrame:
    """seq_id, k, word: the leaf of each position in the suffix tree of a sequence after a precursor: the shortest word ending at k that ends at no other of its positions."""
    ends = seqs.select("seq_id", F.concat(F.lit(precursor), "t").alias("s"), F.explode(F.sequence(F.lit(1), F.length("t"))).alias("k")).withColumn("e", F.col("k") + len(precursor))
    words = ends.select("seq_id", "k", F.expr("explode(sequence(1, e))").alias("p"), "s", "e").select("seq_id", "k", "p", F.expr("substring(s, e - p + 1, p)").alias("word"))
    own = words.groupBy("seq_id", "word").agg(F.count("*").alias("n"), F.min("k").alias("k"), F.min("p").alias("p")).where("n = 1")
    return own.groupBy("seq_id", "k").agg(F.min_by("word", "p").alias("word"))


# --- parsings --------------------------------------------------------------------------------------------------------

_PHRASES = "seq_id long, k long, start long, len int, ref long, new_sym string, complete boolean"


def dictionary_phrases(t: str) -> list[tuple[int, int, int, str | None, bool]]:
    """(start, len, ref, new symbol, complete): each phrase is a known one (ref, 0 for none) and a symbol more."""
    known: dict[tuple[int, str], int] = {}
    out, at, start, size = [], 0, 0, 0
    for k, c in enumerate(t):
        size += 1
        child = known.get((at, c))
        if child is None:
            out.append((start + 1, size, at, c, True))
            known[at, c] = len(out)
            at, start, size = 0, k + 1, 0
        else:
            at = child
    if size:
        out.append((start + 1, size, at, None, False))
    return out


def substring_phrases(t: str, match: list[int] | None = None) -> list[tuple[int, int, int, str | None, bool]]:
    """Each phrase is the shortest word that has not started before; ref is the start of a longest earlier match (0: none).  match: the longest matches with earlier starts, if they are known."""
    if match is None:
        sym = np.frombuffer(t.encode("utf-32-le"), np.uint32).astype(np.int64)
        match = longest_matches(sym, np.array([0, len(sym)])).tolist()
    out, i = [], 0
    while i < len(t):
        full = i + match[i] < len(t)
        size = match[i] + 1 if full else len(t) - i
        ref = t.find(t[i:i + match[i]]) + 1 if match[i] else 0
        out.append((i + 1, size, ref, t[i + match[i]] if full else None, full))
        i += size
    return out


def parse(seqs: DataFrame, kind: str = "dictionary", text: bool = False) -> DataFrame:
    """seq_id, k, start, len, ref, new_sym, complete (and w, the phrase's text); kind dictionary or substring.  Sequential by nature: one pass for each sequence."""
    schema = pa.schema([("seq_id", pa.int64()), ("k", pa.int64()), ("start", pa.int64()), ("len", pa.int32()), ("ref", pa.int64()), ("new_sym", pa.string()), ("complete", pa.bool_()), *([("w", pa.string())] if text else [])])
    numbered = lambda t, phrases: [(k, *p, *([t[p[0] - 1:p[0] - 1 + p[1]]] if text else [])) for k, p in enumerate(phrases, 1)]

    def run(batches):
        for batch in batches:
            if kind == "dictionary":
                yield from _rows(batch, lambda t: numbered(t, dictionary_phrases(t)), schema)
                continue
            done = 0
            for names, sym, bound in batch_sequences(batch):
                match, begin = longest_matches(sym, bound), iter(zip(bound.tolist(), bound[1:].tolist(), strict=False))

                def phrases(t, match=match, begin=begin):
                    i, j = next(begin)
                    return numbered(t, substring_phrases(t, match[i:j].tolist()))

                yield from _rows(batch.slice(done, len(names)), phrases, schema)
                done += len(names)

    return seqs.select("seq_id", "t").mapInArrow(run, _PHRASES + (", w string" if text else ""))


def parse_rate(phrases: DataFrame, units: str = "bits", by: list[str] | None = None) -> DataFrame:
    """phrases, n, mean_len, rate = log n / mean length; unfinished phrases don't count."""
    g = phrases.where("complete").groupBy(*(by or [])).agg(F.count("*").alias("phrases"), F.sum("len").cast("long").alias("n"))
    mean = F.col("n") / F.col("phrases")
    return g.select(*(by or []), "phrases", "n", mean.alias("mean_len"), (F.ln("n") / mean / unit(units)).alias("rate"))


def parse_code_bits(phrases: DataFrame, d: int, kind: str = "dictionary") -> DataFrame:
    """seq_id, bits: dictionary: log2 k for the pointer of phrase k and log2 d; substring: log2 of the start, an integer code for the length and log2 d."""
    pointer = F.log2(F.col("k").cast("double")) if kind == "dictionary" else F.log2(F.greatest(F.col("start"), F.lit(1)).cast("double")) + 2 * F.floor(F.log2(F.col("len").cast("double"))) + 1
    return phrases.groupBy("seq_id").agg(F.sum(pointer + F.log2(F.lit(float(d)))).alias("bits"))


def unparse(phrases: DataFrame, kind: str = "dictionary") -> DataFrame:
    """seq_id, t from phrases."""

    def join(key, table):
        import pandas as pd

        out: list[str] = []
        text = ""
        for r in table.sort_values("k").itertuples():
            last = r.new_sym if isinstance(r.new_sym, str) else ""
            if kind == "dictionary":
                word = (out[r.ref - 1] if r.ref else "") + last
                out.append(word)
                text += word
            else:
                size, begin = r.len - len(last), r.ref - 1
                for k in range(size):  # a match may reach into itself
                    text += text[begin + k]
                text += last
        return pd.DataFrame({"seq_id": [key[0]], "t": [text]})

    return phrases.groupBy("seq_id").applyInPandas(join, "seq_id long, t string")


def phrases_text(phrases: list[tuple[int, int, int, str | None, bool]], kind: str = "dictionary") -> str:
    """The text of the phrases of one sequence, in order."""
    if kind == "dictionary":
        words = [""]
        for _, _, ref, last, _ in phrases:
            words.append(words[ref] + (last or ""))
        return "".join(words)
    text = ""
    for _, size, ref, last, _ in phrases:
        size -= len(last or "")
        while size:  # a match may reach into itself
            part = text[ref - 1:ref - 1 + size]
            if not part:
                raise ValueError("a phrase refers to what isn't there yet")
            text += part
            ref += len(part)
            size -= len(part)
        text += last or ""
    return text


def decoded(seqs: DataFrame) -> DataFrame:
    """seq_id, dictionary, substring: the texts that the phrases of both parses decode to; a sequence's phrases fit its row, so nothing is shuffled."""

    def run(batches):
        for whole in batches:
            for batch in (whole.slice(k, 256) for k in range(0, whole.num_rows, 256)):
                texts = batch.column(1).to_pylist()
                both = [pa.array([phrases_text(cut(t or ""), kind) for t in texts], pa.string()) for kind, cut in (("dictionary", dictionary_phrases), ("substring", substring_phrases))]
                yield pa.RecordBatch.from_arrays([batch.column(0), *both], ["seq_id", "dictionary", "substring"])

    return seqs.select("seq_id", "t").mapInArrow(run, "seq_id long, dictionary string, substring string")


def lzw_bits(data: bytes) -> int:
    """Length in bits of a growing-width dictionary code, as of the classic UNIX-style tool."""
    known = {bytes([k]): k for k in range(256)}
    size, w, bits = 256, b"", 0
    for k in range(len(data)):
        c = data[k:k + 1]
        if w + c in known:
            w += c
        else:
            bits += size.bit_length()
            known[w + c] = size
            size += 1
            w = c
    return bits + (size.bit_length() if w else 0)


def compressor_bits(seqs: DataFrame, tool: str = "zlib") -> DataFrame:
    """seq_id, n, bits of general compressors: zlib, bz2, lzma or lzw."""

    def run(batches):
        import bz2
        import lzma
        import zlib

        size = {"zlib": lambda x: 8 * len(zlib.compress(x, 9)), "bz2": lambda x: 8 * len(bz2.compress(x, 9)), "lzma": lambda x: 8 * len(lzma.compress(x, preset=6)), "lzw": lzw_bits}[tool]
        for batch in batches:
            texts = batch.column(1).to_pylist()
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(t or "") for t in texts], pa.int64()), pa.array([size((t or "").encode()) for t in texts], pa.int64())], ["seq_id", "n", "bits"])

    return seqs.select("seq_id", "t").mapInArrow(run, "seq_id long, n long, bits long")


register_pickle_by_value(sys.modules[__name__])
