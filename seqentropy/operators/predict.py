"""Sequential prediction over context trees: the arrays' engine and the windows' engine.

``kernel``: sequences that fit a row (documents, histories, replicas); one pass, no shuffle.  ``windows``: rows of
events in DataFrame windows, for sequences of any length (a corpus as one sequence); where a context holds a large part
of all positions, running counts are taken in blocks of positions and summed over the blocks, so no task gets them all.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.symbols import events as symbol_events
from ..sources.scratch import written
from . import context_kernel as C
from .blocks import block_counts
from .context_kernel import Tree

PIECE = 200_000


def batch_sequences(batch: pa.RecordBatch, limit: int = PIECE) -> Iterator[tuple[list, np.ndarray, np.ndarray]]:
    """(seq_ids, symbols, bounds) of pieces of a batch of seq_id, t."""
    ids, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
    k = 0
    while k < len(ids):
        own, size, names = [], 0, []
        while k < len(ids) and (not own or size + len(texts[k] or "") <= limit):
            own.append(np.frombuffer((texts[k] or "").encode("utf-32-le"), np.uint32).astype(np.int64))
            names.append(ids[k])
            size += len(own[-1])
            k += 1
        yield names, np.concatenate(own), np.concatenate([[0], np.cumsum([len(x) for x in own])]).astype(np.int64)


def predictions(seqs: DataFrame, t: Tree) -> DataFrame:
    """seq_id, pos, sym, order_used, p for every symbol of every sequence (kernel engine)."""

    def run(batches):
        for batch in batches:
            for names, sym, bound in batch_sequences(batch):
                p, used = C.predict(sym, bound, t)
                row = np.repeat(np.arange(len(names)), np.diff(bound))
                yield pa.RecordBatch.from_arrays([pa.array(np.array(names, np.int64)[row]), pa.array(np.arange(len(sym)) - bound[row] + 1), pa.array([chr(s) for s in sym], pa.string()), pa.array(used), pa.array(p)], ["seq_id", "pos", "sym", "order_used", "p"])

    return seqs.select("seq_id", "t").mapInArrow(run, "seq_id long, pos long, sym string, order_used int, p double")


def gamble(seqs: DataFrame, trees: dict[str, Tree], grid: list[int] | None = None) -> DataFrame:
    """seq_id, method, n, nats: the code length of the first n symbols for every n of grid that a sequence has, and of all of them."""

    def run(batches):
        for batch in batches:
            for names, sym, bound in batch_sequences(batch):
                rows = []
                for method, (p, _) in zip(trees, C.predict_many(sym, bound, list(trees.values())), strict=True):
                    code = np.concatenate([[0.0], np.cumsum(-np.log(p))])
                    for k, name in enumerate(names):
                        size = int(bound[k + 1] - bound[k])
                        for n in sorted({size, *(g for g in grid or () if g < size)}):
                            rows.append((name, method, n, float(code[bound[k] + n] - code[bound[k]])))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), [pa.int64(), pa.string(), pa.int64(), pa.float64()], strict=True)], ["seq_id", "method", "n", "nats"])

    return seqs.select("seq_id", "t").mapInArrow(run, "seq_id long, method string, n long, nats double")


def tree_mixture(seqs: DataFrame, depth: int, d: int) -> DataFrame:
    """seq_id, n (symbols after the first ``depth``), nats: the mixture over all context trees of a depth."""

    def run(batches):
        for batch in batches:
            for names, sym, bound in batch_sequences(batch):
                nats = C.mixture_rate(sym, bound, depth, d)
                yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array(np.maximum(0, np.diff(bound) - depth)), pa.array(nats)], ["seq_id", "n", "nats"])

    return seqs.select("seq_id", "t").mapInArrow(run, "seq_id long, n long, nats double")


def tree_statistics(seqs: DataFrame, t: Tree) -> DataFrame:
    """seq_id, depth, nodes, visits of the trees that sequences leave."""

    def run(batches):
        for batch in batches:
            for names, sym, bound in batch_sequences(batch):
                for k, name in enumerate(names):
                    own = sym[bound[k]:bound[k + 1]]
                    rows = [(name, j, nodes, len(alive)) for j, alive, _, _, _, _, nodes in C.levels(own, np.array([0, len(own)]), t)]
                    if rows:
                        yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64() if i != 1 else pa.int32()) for i, c in enumerate(zip(*rows, strict=True))], ["seq_id", "depth", "nodes", "visits"])

    return seqs.select("seq_id", "t").mapInArrow(run, "seq_id long, depth int, nodes long, visits long")


def static_weights(seqs: DataFrame, t: Tree, rounds: int = 20) -> list[float]:
    """Level weights with the shortest code over all sequences (expectation-maximisation)."""
    return static_fit(seqs, t, rounds)[0]


def static_fit(seqs: DataFrame, t: Tree, rounds: int = 20) -> tuple[list[float], int, float]:
    """Level weights with the shortest code over all sequences, the number of symbols, and their code length in nats.

    Levels are made once.  What a round needs of a symbol is how the levels' probabilities stand to each other: a point
    with t.order coordinates.  All symbols' points are summed up by cells (``Cells``), whose number doesn't grow with the
    text, and the rounds go over those.  Trees deeper than three, or without beta, make their levels in each round.
    """
    if t.order > 3 or t.beta <= 0:
        return _static_fit_by_rounds(seqs, t, rounds)
    sums = Cells(t.order)
    names = ["head", *(f"m{k}" for k in range(len(sums.powers)))]

    def run(batches):
        own = Cells(t.order)
        for batch in batches:
            for _, sym, bound in batch_sequences(batch):
                own.add(C.level_probabilities(sym, bound, t))
        yield pa.RecordBatch.from_arrays([pa.array(own.cell), *(pa.array(x) for x in own.sums)], ["cell", *names])

    each = seqs.select("seq_id", "t").mapInArrow(run, ", ".join(["cell long", *(f"{x} double" for x in names)]))
    got = each.groupBy("cell").agg(*(F.sum(x).alias(x) for x in names)).orderBy("cell").toArrow()
    sums.cell, sums.sums = got["cell"].to_numpy(), np.array([got[x].to_numpy() for x in names])
    c = np.full(t.order + 1, 1.0 / (t.order + 1))
    if not len(sums.cell):
        return c.tolist(), 0, 0.0
    size = round(float(sums.sums[1].sum()))
    points, weight = sums.points()
    for _ in range(rounds):
        part = c[:, None] * points
        part /= part.sum(0)
        new = part @ weight / size
        if np.abs(new - c).max() < 1e-5:
            break
        c = new
    return c.tolist(), size, -float(sums.sums[0].sum() + np.log(c @ points) @ weight)


class Cells:
    """Sums over the logarithms of the ratios of neighbouring levels' probabilities.

    A cell is a cube of side ``SIDE`` and keeps all moments of its symbols up to ``DEGREE``.  ``points`` gives it fixed points
    with weights that have the same moments, so a sum over symbols of any polynomial of that degree is exact; for the
    sums of the rounds the error is about 1e-8 (weights) and 1e-10 (nats a symbol).  The first row of sums has the logarithms of level 0.
    """

    DEGREE, SIDE, AT_ONCE = 6, 0.5, 5_000
    _HALF = 1 << 19

    def __init__(self, dims: int):
        self.dims = dims
        self.powers = [x for x in product(range(self.DEGREE + 1), repeat=dims) if sum(x) <= self.DEGREE]
        self.cell, self.sums = np.zeros(0, np.int64), np.zeros((len(self.powers) + 1, 0))
        # products of the powers up to half the degree are all of them
        self.half = [x for x in self.powers if 2 * sum(x) <= self.DEGREE]
        pairs = {tuple(map(sum, zip(x, y, strict=True))): (i, j) for i, x in enumerate(self.half) for j, y in enumerate(self.half)}
        self.left, self.right = np.array([pairs[x] for x in self.powers]).T
        self.steps = []
        for x in self.half[1:]:
            k = max(k for k in range(dims) if x[k])
            self.steps.append((self.half.index((*x[:k], x[k] - 1, *x[k + 1:])), k))

    def add(self, p: np.ndarray) -> None:
        if not p.shape[1]:
            return
        log = np.log(p)
        y = np.diff(log, axis=0) / self.SIDE
        near = np.rint(y)
        y = 2 * (y - near)  # -1 to 1 inside the cell
        near = near.astype(np.int64)
        lowest, span = near.min(1, initial=self._HALF), np.ptp(near, 1) + 1 if self.dims else []
        key = np.zeros(p.shape[1], np.int64)
        for k in range(self.dims):
            key = key * span[k] + near[k] - lowest[k]
        if np.prod(np.array(span, float)) < 1 << 24:
            known = np.flatnonzero(np.bincount(key))
            place = np.zeros(known[-1] + 1, np.uint16 if len(known) <= 1 << 16 else np.int64)  # short numbers are sorted by digits
            place[known] = np.arange(len(known))
            key = place[key]
        else:
            known, key = np.unique(key, return_inverse=True)
        order = np.argsort(key, kind="stable")
        key = key[order].astype(np.int64)
        found = np.zeros((len(self.powers) + 1, len(known)))
        for lo in range(0, len(order), self.AT_ONCE):  # few enough to stay in a core's cache
            own, part = order[lo:lo + self.AT_ONCE], key[lo:lo + self.AT_ONCE]
            begin = np.flatnonzero(np.diff(part, prepend=-1))
            to, x = slice(part[0], part[-1] + 1), y[:, own]
            found[0, to] += np.add.reduceat(log[0, own], begin)
            half = np.ones((len(self.half), len(own)))
            for row, (earlier, k) in enumerate(self.steps, 1):
                np.multiply(half[earlier], x[k], out=half[row])
            tall = np.ascontiguousarray(half.T)  # as a matrix of its own: faster here than a product with itself
            squares = np.empty((len(begin), len(half), len(half)))
            for k, (first, last) in enumerate(zip(begin.tolist(), [*begin[1:].tolist(), len(own)], strict=True)):
                np.matmul(half[:, first:last], tall[first:last], out=squares[k])
            found[1:, to] += squares[:, self.left, self.right].T
        cell, rest = np.zeros(len(known), np.int64), known
        for k in reversed(range(self.dims)):
            cell += (rest % span[k] + lowest[k] + self._HALF) << (20 * (self.dims - 1 - k))
            rest = rest // span[k]
        every = np.union1d(self.cell, cell)
        if len(every) > len(self.cell):
            sums = np.zeros((len(found), len(every)))
            sums[:, np.searchsorted(every, self.cell)] = self.sums
            self.cell, self.sums = every, sums
        self.sums[:, np.searchsorted(self.cell, cell)] += found

    def points(self) -> tuple[np.ndarray, np.ndarray]:
        """Probabilities of all levels, in parts of level 0's, and weights."""
        around = np.cos(np.arange(self.DEGREE + 1) * np.pi / self.DEGREE)
        order = [0]  # each next one is as far from those before as can be
        while len(order) <= self.DEGREE:
            order.append(max((k for k in range(self.DEGREE + 1) if k not in order), key=lambda k: np.prod(np.abs(around[k] - around[order]))))
        nodes = np.array([[around[order[x]] for x in power] for power in self.powers]).reshape(len(self.powers), self.dims)
        moments = np.array([np.prod(nodes ** np.array(power), axis=1) for power in self.powers])
        weight = np.linalg.solve(moments, self.sums[1:])
        out = [np.zeros(weight.shape)]
        for k in range(self.dims):
            centre = ((self.cell >> (20 * (self.dims - 1 - k))) & ((1 << 20) - 1)) - self._HALF
            out.append(out[-1] + (centre[None, :] + nodes[:, k, None] / 2) * self.SIDE)
        return np.exp(np.array(out)).reshape(self.dims + 1, -1), weight.ravel()


def _static_fit_by_rounds(seqs: DataFrame, t: Tree, rounds: int) -> tuple[list[float], int, float]:
    """The same for any order: each round is one distributed aggregate of order + 1 sums."""

    def sums(c: list[float]):
        def run(batches, c=np.array(c)):
            total, size, nats = np.zeros(t.order + 1), 0, 0.0
            for batch in batches:
                for _, sym, bound in batch_sequences(batch):
                    part = c[:, None] * C.level_probabilities(sym, bound, t)
                    whole = part.sum(0)
                    total += (part / whole).sum(1)
                    size, nats = size + len(sym), nats - float(np.log(whole).sum())
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(t.order + 1, dtype=np.int32)), pa.array(total), pa.array([size] * (t.order + 1), pa.int64()), pa.array([nats] * (t.order + 1))], ["level", "s", "n", "nats"])

        got = seqs.select("seq_id", "t").mapInArrow(run, "level int, s double, n long, nats double").groupBy("level").agg(F.sum("s").alias("s"), F.sum("n").alias("n"), F.sum("nats").alias("nats")).orderBy("level").collect()
        return [r.s / r.n for r in got if r.n], *((got[0].n, got[0].nats) if got else (0, 0.0))

    c = [1.0 / (t.order + 1)] * (t.order + 1)
    for _ in range(rounds):
        new, size, nats = sums(c)
        if not new or max(abs(a - b) for a, b in zip(new, c, strict=True)) < 1e-5:
            return c, size, nats
        c = new
    return c, *sums(c)[1:]


# --- windows' engine -------------------------------------------------------------------------------------------------


def _before(df: DataFrame, name: str, value: Column, keys: list[str], block: int | None) -> DataFrame:
    """Adds the sum of ``value`` over the earlier rows of the same keys."""
    if block is None:
        w = Window.partitionBy(*keys).orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
        return df.withColumn(name, F.coalesce(F.sum(value).over(w), F.lit(0)))
    df = df.withColumn("_v", value).withColumn("_block", F.floor(F.col("pos") / block))
    # a row for each key and block, written, so that plans don't double at every sum
    sums = written(df.groupBy(*keys, "_block").agg(F.sum("_v").alias("_s")), "sums")
    running = Window.partitionBy(*keys).orderBy("_block").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.select(*keys, "_block", F.coalesce(F.sum("_s").over(running), F.lit(0)).alias("_earlier"))
    w = Window.partitionBy(*keys, "_block").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    return df.join(sums, [*keys, "_block"]).withColumn(name, F.col("_earlier") + F.coalesce(F.sum("_v").over(w), F.lit(0))).drop("_v", "_block", "_earlier")


def _born(df: DataFrame, may: Column, deep: Column) -> DataFrame:
    """alive and born at a level of the incremental tree: a key is born at the first event that may make it (an aggregate with partial minima, so a common key is no task's alone)."""
    births = written(df.where(may).groupBy("seq_id", "key").agg(F.min("pos").alias("birth")), "births")
    df = df.join(births, ["seq_id", "key"], "left")
    return df.withColumn("alive", F.coalesce(F.col("alive") & deep & (F.col("pos") >= F.col("birth")), F.lit(False))).withColumn("born", F.coalesce("birth", "born")).drop("birth")


def window_predictions(events: DataFrame, t: Tree, block: int | None = None, crowded: int = 2) -> DataFrame:
    """seq_id, pos, sym, p for events (seq_id, pos, sym, past) with pasts of t.order symbols; contexts of up to ``crowded`` symbols are counted in blocks if a block size is given."""
    df = events.select("seq_id", "pos", "sym", "past")
    one, zero = F.lit(1), F.lit(0)
    uniform = F.lit(1.0 / t.d)
    df = df.withColumns({"born": F.lit(-1).cast("long"), "alive": F.lit(True), "run": F.lit(0).cast("long"), "p_up": uniform, "out": uniform, "flag": F.lit(False), "cand": uniform, "done": F.lit(False), "going": F.lit(True), "total": F.lit(0.0), "best": F.lit(0.0), "novel": F.lit(1.0)})
    for j in range(t.order + 1):
        b = block if j <= crowded else None
        deep = F.length("past") >= j  # the others share the empty key, and are not alive
        df = df.withColumn("key", F.when(deep, F.substring(F.col("past"), F.length("past") - j + 1, F.lit(j))).otherwise("") if j else F.lit(""))
        if j and t.tree == "incremental":
            may = F.col("alive") & (F.col("pos") > F.col("born")) & (F.col("run") >= 2)
            df = _born(df, may, deep)
        else:
            df = df.withColumn("alive", deep)
        live = F.when(F.col("alive"), one).otherwise(zero)
        df = _before(df, "n", live, ["seq_id", "key"], b)
        df = _before(df, "na", live, ["seq_id", "key", "sym"], b)
        df = df.withColumn("p", (F.col("na") + t.beta) / (F.col("n") + t.beta * t.d))
        if j:
            step = F.ln("p_up") - F.ln("p")
            counts = F.col("alive") & (F.col("n") > 0) if t.gain_from == "second" else F.col("alive")
            df = _before(df, "gain", F.when(counts, step).otherwise(0.0), ["seq_id", "key"], b).withColumn("gain", F.round("gain", 9))
        else:
            df = df.withColumn("gain", F.lit(-1.0))
        df = _fold(df, j, t)
        df = df.withColumn("run", F.when(F.col("alive"), F.col("na") + 1).otherwise(0)).withColumn("p_up", F.when(F.col("alive"), F.col("p")).otherwise(F.col("p_up")))
    out = F.col("out")
    if t.rule == "shortest_gain":
        out = F.when(F.col("flag") & ~F.col("done"), F.col("cand")).otherwise(out)
    if t.rule == "blend" and t.residual == "renormalise":
        out = F.when(F.col("novel") < 1, (out - F.col("novel") / t.d) / (1 - F.col("novel"))).otherwise(out)
    return df.select("seq_id", "pos", "sym", out.alias("p"))


def largest_groups(chunked: DataFrame, order: int) -> dict[int, int]:
    """For each context length, how often the most frequent context occurs."""
    c = block_counts(chunked, order) if order else None
    return {0: 1 << 62} | ({r.n: r.m for r in c.groupBy("n").agg(F.max("cnt").alias("m")).collect()} if order else {})


def choose_split(chunked: DataFrame, order: int, most: int) -> int:
    """The least context length of which no context occurs more than ``most`` times (order + 1: there is none)."""
    largest = largest_groups(chunked, min(order, 8))
    return next((j for j in range(1, min(order, 8) + 1) if largest.get(j, 0) <= most), order + 1)


def _earlier(sums: DataFrame, keys: list[str], name: str) -> DataFrame:
    """Of sums _s by keys and block: what the earlier blocks hold."""
    running = Window.partitionBy(*keys).orderBy("_block").rowsBetween(Window.unboundedPreceding, -1)
    return sums.select(*keys, "_block", F.sum("_s").over(running).alias(name)).where(F.col(name).isNotNull())


def corpus_levels(chunked: DataFrame, t: Tree, split: int = 2, block: int = 16_384) -> DataFrame:
    """seq_id, pos, sym, past, n, p, gain: for every symbol of sequences of any length, the levels of its contexts as arrays.

    Contexts of fewer than ``split`` symbols hold large parts of all positions: they are counted in blocks of positions,
    to which what the earlier blocks hold is added.  Rows are partitioned by block, so all windows sort where they are.
    All longer contexts of an event end in its last ``split`` symbols, so one shuffle by those brings whole subtrees
    together, and an array kernel takes all further levels there.  ``choose_split`` finds a split whose groups fit a task;
    beyond the order, everything is done in blocks.
    """
    placed = symbol_events(chunked, t.order).withColumn("_block", F.floor(F.col("pos") / block))
    df = placed.withColumns({"born": F.lit(-1).cast("long"), "alive": F.lit(True), "run": F.lit(0).cast("long"), "p_up": F.lit(1.0 / t.d), "levels": F.array().cast("array<struct<n:bigint,p:double,gain:double>>")}).repartition("seq_id", "_block")
    by_key, by_sym = ["seq_id", "key"], ["seq_id", "key", "sym"]
    top = min(split, t.order + 1) - 1
    for j in range(top + 1):
        deep = F.length("past") >= j
        df = df.withColumn("key", F.when(deep, F.right("past", F.lit(j))).otherwise("") if j else F.lit(""))
        if j and t.tree == "incremental":
            df = _born(df, F.col("alive") & (F.col("pos") > F.col("born")) & (F.col("run") >= 2), deep)
        else:
            df = df.withColumn("alive", deep)
        live = F.when(F.col("alive"), F.lit(1)).otherwise(F.lit(0))
        cells = written(df.groupBy(*by_sym, "_block").agg(F.sum(live).alias("_s")), "cells")
        per_key = _earlier(cells.groupBy(*by_key, "_block").agg(F.sum("_s").alias("_s")), by_key, "_n")
        df = df.join(per_key, [*by_key, "_block"], "left").join(_earlier(cells, by_sym, "_na"), [*by_sym, "_block"], "left")
        before = lambda keys: Window.partitionBy(*keys, "_block").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
        count = lambda name, keys: F.coalesce(name, F.lit(0)) + F.coalesce(F.sum(live).over(before(keys)), F.lit(0))
        df = df.withColumn("n", count("_n", by_key)).withColumn("na", count("_na", by_sym)).drop("_n", "_na")
        df = df.withColumn("p", (F.col("na") + t.beta) / (F.col("n") + t.beta * t.d))
        if j:
            df = written(df, "level").repartition("seq_id", "_block")
            counts = F.col("alive") & (F.col("n") > 0) if t.gain_from == "second" else F.col("alive")
            step = F.when(counts, F.ln("p_up") - F.ln("p")).otherwise(0.0)
            sums = written(df.groupBy(*by_key, "_block").agg(F.sum(step).alias("_s")), "gains")
            df = df.join(_earlier(sums, by_key, "_gain"), [*by_key, "_block"], "left")
            df = df.withColumn("gain", F.round(F.coalesce("_gain", F.lit(0.0)) + F.coalesce(F.sum(step).over(before(by_key)), F.lit(0.0)), 9)).drop("_gain")
        else:
            df = df.withColumn("gain", F.lit(-1.0))
        own = F.struct(F.col("n").cast("long").alias("n"), "p", "gain")
        df = df.withColumn("levels", F.when(F.col("alive"), F.concat("levels", F.array(own))).otherwise(F.col("levels")))
        df = df.withColumn("run", F.when(F.col("alive"), F.col("na") + 1).otherwise(0)).withColumn("p_up", F.when(F.col("alive"), F.col("p")).otherwise(F.col("p_up"))).drop("n", "na", "p", "gain", "key")
        if j < top:
            df = written(df, "level").repartition("seq_id", "_block")
    out = "seq_id long, pos long, sym string, past string, n array<long>, p array<double>, gain array<double>"
    plain = ["seq_id", "pos", "sym", "past", F.col("levels.n").alias("n"), F.col("levels.p").alias("p"), F.col("levels.gain").alias("gain")]
    if split > t.order:
        return df.select(*plain)
    going = F.col("alive") & (F.length("past") >= split)
    state = df.select(*plain, "born", F.col("run").cast("long").alias("run"), "p_up", F.when(going, F.right("past", F.lit(split))).otherwise("").alias("key"), F.when(going, 0).otherwise(F.pmod("pos", F.lit(64))).alias("salt"))
    return state.groupBy("seq_id", "key", "salt").applyInArrow(_subtrees(t, split), out)


def _subtrees(t: Tree, split: int):
    def run(table: pa.Table) -> pa.Table:
        names = ["seq_id", "pos", "sym", "past", "n", "p", "gain"]
        if not table["key"][0].as_py():  # events that have no longer context
            return table.select(names)
        table = table.sort_by("pos")
        size = table.num_rows
        point = lambda texts: np.frombuffer("".join(texts).encode("utf-32-le"), np.uint32).astype(np.int64)
        sym, past = point(table["sym"].to_pylist()), table["past"].to_pylist()
        width = np.array([len(x) for x in past])
        older = point([x.rjust(t.order, "\0") for x in past]).reshape(size, t.order)[:, ::-1].copy()
        older[np.arange(t.order)[None, :] >= width[:, None]] = -1
        at, born, run_, p_up = (table[c].to_numpy() for c in ("pos", "born", "run", "p_up"))
        rows = []
        for _, alive, n, _, p, gain, _ in C.deeper(sym, older, at, t, split, born, run_, p_up):
            rows.append((alive, n, p, gain))
        if not rows:
            return table.select(names)
        owner = np.concatenate([r[0] for r in rows])
        order = np.argsort(owner, kind="stable")
        more = np.bincount(owner, minlength=size)
        have = table["n"].combine_chunks().value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
        bound = np.concatenate([[0], np.cumsum(have + more)])
        first, place = np.cumsum(more) - more, np.empty(len(owner), np.int64)
        place[:] = bound[:-1][owner[order]] + have[owner[order]] + np.arange(len(owner)) - first[owner[order]]
        old = np.repeat(bound[:-1] - np.concatenate([[0], np.cumsum(have)[:-1]]), have) + np.arange(int(have.sum()))
        lists = []
        for k, c in enumerate(("n", "p", "gain"), 1):
            flat = np.empty(int(bound[-1]), np.int64 if c == "n" else np.float64)
            flat[old] = table[c].combine_chunks().flatten().to_numpy()
            flat[place] = np.concatenate([r[k] for r in rows])[order]
            lists.append(pa.ListArray.from_arrays(pa.array(bound.astype(np.int32)), pa.array(flat)))
        return pa.Table.from_arrays([*(table[c] for c in names[:4]), *lists], names)

    return run


def choose(leveled: DataFrame, trees: dict[str, Tree]) -> DataFrame:
    """seq_id, pos, sym, and for each tree's name its probability: rules (and smaller orders) over rows of ``corpus_levels``."""

    def run(batches):
        for batch in batches:
            k = batch.schema.get_field_index
            n, p, gain = (batch.column(k(c)) for c in ("n", "p", "gain"))
            have = n.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
            start = np.cumsum(have) - have
            n, p, gain = (x.flatten().to_numpy() for x in (n, p, gain))
            folds = [C.Fold(batch.num_rows, t) for t in trees.values()]
            for j in range(int(have.max(initial=0))):
                alive = np.flatnonzero(have > j)
                at = start[alive] + j
                for f in folds:
                    f.step(j, alive, n[at], p[at], gain[at])
            yield pa.RecordBatch.from_arrays([*(batch.column(k(c)) for c in ("seq_id", "pos", "sym")), *(pa.array(f.finish()[0]) for f in folds)], ["seq_id", "pos", "sym", *trees])

    return leveled.select("seq_id", "pos", "sym", "n", "p", "gain").mapInArrow(run, "seq_id long, pos long, sym string, " + ", ".join(f"`{name}` double" for name in trees))


def trained_tree(leveled: DataFrame, t: Tree) -> tuple[DataFrame, DataFrame]:
    """The tree that sequences leave: nodes (depth, ctx, n, gain) and counts (depth, ctx, sym, cnt).

    A node's gain is the sum of what it has saved over its parent at all its events; both are sums over events, counted in
    batches before they are shuffled.
    """

    def run(batches):
        for batch in batches:
            k = batch.schema.get_field_index
            n, p = (batch.column(k(c)) for c in ("n", "p"))
            have = n.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
            start = np.cumsum(have) - have
            n, p = n.flatten().to_numpy(), p.flatten().to_numpy()
            sym, past = batch.column(k("sym")).to_pylist(), batch.column(k("past")).to_pylist()
            for j in range(min(t.order + 1, int(have.max(initial=0)))):
                alive = np.flatnonzero(have > j)
                at = start[alive] + j
                step = np.log(p[at - 1]) - np.log(p[at]) if j else np.zeros(len(at))
                if t.gain_from == "second":
                    step[n[at] == 0] = 0.0
                words, back, count = np.unique(np.array([past[i][len(past[i]) - j:] + sym[i] for i in alive.tolist()]), return_inverse=True, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(words), j, np.int32)), pa.array([w[:-1] for w in words.tolist()], pa.string()), pa.array([w[-1] for w in words.tolist()], pa.string()), pa.array(count), pa.array(np.bincount(back, step, len(words)))], ["depth", "ctx", "sym", "cnt", "gain"])

    cells = leveled.select("sym", "past", "n", "p").mapInArrow(run, "depth int, ctx string, sym string, cnt long, gain double").groupBy("depth", "ctx", "sym").agg(F.sum("cnt").alias("cnt"), F.sum("gain").alias("gain"))
    nodes = cells.groupBy("depth", "ctx").agg(F.sum("cnt").alias("n"), F.round(F.sum("gain"), 9).alias("gain"))
    return nodes, cells.drop("gain")


def _fold(df: DataFrame, j: int, t: Tree) -> DataFrame:
    alive, p, gain, out = F.col("alive"), F.col("p"), F.col("gain"), F.col("out")
    ok = alive & (F.col("n") >= max(1, t.n_min)) if j else F.lit(True)
    good = ok & (gain < -t.delta)
    put = lambda take: df.withColumn("out", F.when(take, p).otherwise(out))
    if t.rule == "fixed":
        return df.withColumn("out", F.when(alive, p).otherwise(1.0 / t.d)) if j == t.order else df
    if t.rule == "deepest":
        return put(ok)
    if t.rule == "deepest_gain":
        return put(good if j else ok)
    if t.rule == "walk_gain":
        df = df.withColumn("going", F.col("going") & ok & (gain <= 0) if j else F.lit(True))
        return df.withColumn("out", F.when((good if j else ok) & F.col("going"), p).otherwise(out))
    if t.rule == "min_total_gain":
        if not j:
            return put(ok)
        df = df.withColumn("total", F.when(ok, F.col("total") + gain).otherwise(F.col("total")))
        take = ok & (F.col("total") < F.col("best") - t.delta)
        return df.withColumn("out", F.when(take, p).otherwise(out)).withColumn("best", F.when(take, F.col("total")).otherwise(F.col("best")))
    if t.rule == "shortest_gain":
        if j:
            stop = ~ok | (gain >= 0 if t.tie == "stop" else gain > 0)
            end = F.col("flag") & stop & ~F.col("done")
            df = df.withColumn("out", F.when(end, F.col("cand")).otherwise(out)).withColumn("done", F.col("done") | end)
        else:
            df = put(ok)
        return df.withColumn("flag", good).withColumn("cand", F.when(alive, p).otherwise(F.col("cand")))
    if t.rule == "blend":
        e = F.when(alive & (F.col("n") > 0), t.q / (F.col("n") + t.q)).otherwise(1.0)
        return df.withColumn("out", (1 - e) * p + e * out).withColumn("novel", F.col("novel") * e)
    raise ValueError(t.rule)


def additive(c: Column, n: Column, d: int, beta: float | str = 0.5) -> Column:
    """(c + beta) / (n + beta d); beta may be 'laplace', 'half' or 'inverse_d'.  Zero gives infinite code lengths: refused."""
    beta = {"laplace": 1.0, "half": 0.5, "inverse_d": 1.0 / d}.get(beta, beta)
    if not beta > 0:
        raise ValueError("a symbol that has not occurred would get probability 0 and an infinite code length")
    return (c + beta) / (n + beta * d)


def context_counts(chunked: DataFrame, order: int) -> DataFrame:
    """depth, ctx, sym, cnt: how often each symbol followed each context of up to ``order`` symbols (superposed tree in long form); counts of words that are one longer."""
    words = block_counts(chunked, order + 1)
    return words.select((F.col("n") - 1).alias("depth"), F.expr("substring(word, 1, n - 1)").alias("ctx"), F.expr("substring(word, n, 1)").alias("sym"), "cnt")


def forecast(counts: DataFrame, context: str, d: int, beta: float, alphabet: list[str]) -> DataFrame:
    """sym, p: the whole distribution after a context (its longest suffix that has been seen)."""
    depth = F.length("ctx")
    found = counts.where(F.lit(context).endswith(F.col("ctx")))
    best = found.agg(F.max(depth).alias("most"))
    own = found.join(F.broadcast(best), depth == F.col("most")).groupBy("sym").agg(F.sum("cnt").alias("c"))
    total = own.agg(F.sum("c").alias("n"))
    letters = counts.sparkSession.createDataFrame([(a,) for a in alphabet], "sym string")
    return letters.join(own, "sym", "left").crossJoin(F.broadcast(total)).select("sym", additive(F.coalesce("c", F.lit(0)), F.coalesce("n", F.lit(0)), d, beta).alias("p"))


register_pickle_by_value(sys.modules[__name__])
