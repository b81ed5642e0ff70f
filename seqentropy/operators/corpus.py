"""Sequences of any length (a corpus as one), bet on in arrays: what the corpus engine of ``predict`` finds, as sums.

Contexts of no or one symbol hold large parts of all positions: they are counted in blocks of positions (one row each),
and what earlier blocks hold is added.  All longer contexts of an event end in its last two symbols, so one shuffle by
those brings whole subtrees together.  It moves a few packed numbers for each event, not its text nor its levels, and
what comes back are sums (of bins of positions, or of a tree's contexts), so no row is made for a symbol.  A task takes
a pair's events in order, a part at a time, and keeps its contexts (``Kept``): no task holds all events of a pair.

A block is read four times or more: for its symbols and the births of contexts, its counts, its gains, and its events of
each round.  What the driver keeps of each block are its counts of pairs of symbols that it has.
"""

from __future__ import annotations

import sys
from types import SimpleNamespace

import numpy as np
import pyarrow as pa
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.scratch import small_batches, written
from . import context_kernel as C
from .context_kernel import Tree

#: Symbols in a block.
BLOCK = 1 << 18
NEVER = np.iinfo(np.int64).max


def _layout(t: Tree, bits: int, sign: bool, letters: bool) -> list[tuple[str, int]]:
    """What is moved of an event, and how many bytes it takes: its place, symbol, the symbols before its last two (the nearest in the highest bits), place in the word, counts at levels 0 and 1, gain there (a number or its sign), and whether that context is born."""
    if bits * (t.order - 1) > 62:
        raise ValueError("contexts of this order don't fit a number")
    return [("at", 3), ("sym", 1), ("code", (bits * max(0, t.order - 2) + 8) // 8), ("letter", 5 * letters), ("na0", 5), ("n", 5), ("na", 5), ("alive", 1), ("gain", 1 if sign else 8)]


#: Columns that rise in a pair's events of a symbol: differences are moved.
RISING = ("at", "na0", "n", "na")
#: Events that a round moves, about; rounds go by the last symbol, and what one has shuffled is removed after it.
ROUND = 1 << 28
#: Rounds of smaller corpora, of this many events at least.
LEAST_ROUNDS, LEAST_ROUND = 4, 1 << 25
#: Events of a pair that a task has in memory at once, about.
AT_ONCE = 1 << 18
#: Blocks from one whole count of pairs to the next.
HOP = 32


def _blocks(batches):
    """(seq_id, start, left, body) of rows; symbols are bytes."""
    for batch in batches:
        ids, starts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
        for k, (name, start) in enumerate(zip(ids, starts, strict=True)):
            left, body = (np.frombuffer(batch.column(c)[k].as_py().encode(), np.uint8) for c in (2, 3))
            if len(body):
                if body.max() > 127:
                    raise ValueError("the corpus engine takes symbols of one byte")
                yield name, start, left, body


def _first(code: np.ndarray, size: int) -> np.ndarray:
    """Where each code is first (the length: nowhere)."""
    out = np.full(size, len(code))
    out[code[::-1]] = np.arange(len(code) - 1, -1, -1)
    return out


def _symbols(batches):
    """Of each block: counts and last places of symbols, the first place of each pair, and the first place after each symbol whose own symbol the block has had before."""
    for name, start, left, body in _blocks(batches):
        skip = 0 if len(left) else 1  # the first symbol of all has no context
        before = np.concatenate([left[-1:], body[:-1]]) if len(left) else body[:-1]
        own, fresh = body[skip:], np.ones(len(body), bool)
        first = _first(body, 128)
        fresh[first[first < len(body)]] = False
        again = np.flatnonzero(fresh[skip:])
        birth = _first(before[again], 128)
        birth = np.where(birth < len(again), start + skip + np.append(again, 0)[birth], NEVER)
        pair = _first(before.astype(np.int64) * 128 + own, 1 << 14)
        cells = np.flatnonzero(pair < len(own))
        last = len(body) - 1 - _first(body[::-1], 128)
        columns = [np.bincount(body, minlength=128), np.where(last >= 0, start + last, 0), birth, cells, start + skip + pair[cells]]
        yield pa.RecordBatch.from_arrays([pa.array([name], pa.int64()), pa.array([start], pa.int64()), *(pa.array([c.astype(np.int64).tobytes()], pa.binary()) for c in columns)], ["seq_id", "start", "a", "b", "c", "d", "e"])


class Running:
    """Of sparse sums by block: what the earlier blocks of the sequence hold (whole for every ``HOP``-th block, summed up from there for others), and the sequences' totals."""

    def __init__(self, rows: list, size: int, kind):
        self.rows, self.whole, self.place, self.total = [], {}, {}, {}
        for r in sorted(rows, key=lambda r: (r.seq_id, r.start)):
            k = self.place[r.seq_id, r.start] = len(self.rows)
            so_far = self.total.setdefault(r.seq_id, np.zeros(size, kind))
            if k % HOP == 0 or not so_far.any():
                self.whole[k] = so_far.copy()
            self.rows.append((np.frombuffer(r.a, np.int32), np.frombuffer(r.b, np.int32 if kind == np.int64 else kind)))
            so_far[self.rows[-1][0]] += self.rows[-1][1]

    def __getitem__(self, block: tuple[int, int]) -> np.ndarray:
        last = first = self.place[block]
        while first not in self.whole:
            first -= 1
        out = self.whole[first].copy()
        for cells, sums in self.rows[first:last]:
            out[cells] += sums
        return out


def _shallow(known, t: Tree, name: int, start: int, left: np.ndarray, body: np.ndarray, pairs_only: bool = False, turn: np.ndarray | None = None):
    """A block's symbols with up to order + 1 before them (size of the alphabet: none), and of its events n and na at level 0, and (indices), n, na, log p_up - log p at level 1; turn: of events after some symbols alone."""
    size = len(known.names)
    place = np.full(128, size)
    place[known.names] = np.arange(size)
    width = max(t.order, 2)
    left = left[len(left) - min(len(left), width):]
    line = np.concatenate([np.full(width - len(left), size), place[left], place[body]])
    own, last = line[width:], line[width - 1:-1]
    pos = start + np.arange(len(own))
    alive = pos >= np.append(known.births[name], NEVER)[last]
    alive = np.flatnonzero(alive if turn is None else alive & turn[last])
    if pairs_only:
        return line, own, last, pos, None, alive, None, None, None
    na0 = known.symbols[name, start][own] + C._rank(own)
    p0 = (na0 + t.beta) / (pos - 1 + t.beta * t.d)
    pairs = known.pairs[name, start]
    cell = last[alive] * size + own[alive]
    na = pairs[cell] + C._rank(cell)
    n = pairs.reshape(size, size).sum(1)[last[alive]] + C._rank(last[alive])
    step = np.log(p0[alive]) - np.log((na + t.beta) / (n + t.beta * t.d))
    if t.gain_from == "second":
        step[n == 0] = 0.0
    return line, own, last, pos, na0, alive, n, na, step


def _block_sums(known, t: Tree, what: str):
    """Kernel: counts of pairs, or gains of one-symbol contexts, of each block."""

    def run(batches):
        for name, start, left, body in _blocks(batches):
            k, (_, own, last, _, _, alive, _, _, step) = len(known.value.names), _shallow(known.value, t, name, start, left, body, what == "pairs")
            sums = np.bincount(last[alive] * k + own[alive], minlength=k * k).astype(np.int32) if what == "pairs" else np.bincount(last[alive], step, k)
            some = np.flatnonzero(sums)
            yield pa.RecordBatch.from_arrays([pa.array([name], pa.int64()), pa.array([start], pa.int64()), pa.array([some.astype(np.int32).tobytes()], pa.binary()), pa.array([sums[some].tobytes()], pa.binary())], ["seq_id", "start", "a", "b"])

    return run


def known_of(chunked: DataFrame, t: Tree) -> tuple[SimpleNamespace, dict, dict, dict]:
    """What blocks need to know of all others, and the sequences' totals of symbols, pairs and gains.

    That is the alphabet, for each sequence the births of one-symbol contexts, and for each block (sequence, start) what
    the earlier blocks hold: counts of symbols and of pairs, gains, and the last blank's place.
    """
    context = chunked.sparkSession.sparkContext
    frame = chunked.select("seq_id", "start", "left", "body")
    array = lambda x: np.frombuffer(x, np.int64)

    def blocks(kernel, schema: str) -> list:
        with small_batches(chunked.sparkSession):
            return frame.mapInArrow(kernel, schema).collect()

    rows = sorted(blocks(_symbols, "seq_id long, start long, a binary, b binary, c binary, d binary, e binary"), key=lambda r: (r.seq_id, r.start))
    names = np.flatnonzero(sum((array(r.a) for r in rows), np.zeros(128, np.int64)))
    known, total, blank = SimpleNamespace(names=names, births={}, symbols={}, blank={}, pairs={}, gains={}), {}, {}
    for r in rows:
        so_far = total.setdefault(r.seq_id, np.zeros(128, np.int64))
        known.symbols[r.seq_id, r.start] = so_far[names]
        known.blank[r.seq_id, r.start] = blank.get(r.seq_id, 0)
        blank[r.seq_id] = max(blank.get(r.seq_id, 0), int(array(r.b)[32]))
        birth = known.births.setdefault(r.seq_id, np.full(128, NEVER) if t.tree == "incremental" else np.zeros(128, np.int64))
        cells, place = array(r.d), array(r.e)
        old = so_far[cells % 128] > 0
        np.minimum.at(birth, cells[old] // 128, place[old])
        np.minimum(birth, array(r.c), out=birth)
        total[r.seq_id] = so_far + array(r.a)
    known.births = {s: b[names] for s, b in known.births.items()}
    total = {s: x[names] for s, x in total.items()}
    sums = lambda what: blocks(_block_sums(context.broadcast(known), t, what), "seq_id long, start long, a binary, b binary")
    known.pairs = Running(sums("pairs"), len(names) ** 2, np.int64)
    known.gains = Running(sums("gains"), len(names), np.float64)
    return known, total, known.pairs.total, known.gains.total


def _events(known, t: Tree, bits: int, sign: bool, letters: bool, plain: bool, turn: np.ndarray):
    """Kernel: a row for each block and pair of last symbols (turn: whether the last one is of the round), with what its events need; plain: where level 1 has gained, level 0 doesn't matter."""

    def run(batches):
        k = known.value
        size, codec = len(k.names), pa.Codec("zstd", 1)
        for name, start, left, body in _blocks(batches):
            line, own, last, pos, na0, alive, n, na, step = _shallow(k, t, name, start, left, body, turn=turn)
            width, count = len(line) - len(own), len(own)
            columns = {"na0": na0, "at": np.arange(count), "alive": np.zeros(count, np.uint8), "n": np.zeros(count, np.int64), "na": np.zeros(count, np.int64), "letter": np.zeros(count, np.int64), "gain": np.zeros(count)}
            columns["alive"][alive], columns["n"][alive], columns["na"][alive] = 1, n, na
            order = np.argsort(last[alive].astype(np.uint8), kind="stable")
            run_ = np.cumsum(step[order])
            begin = np.flatnonzero(np.diff(last[alive][order], prepend=-1))
            run_ = np.concatenate([[0.0], run_])[:-1] if len(run_) else run_
            base = np.repeat(run_[begin], np.diff(np.append(begin, len(order))))
            gain = np.round(k.gains[name, start][last[alive][order]] + run_ - base, 9)
            columns["gain"][alive[order]] = np.sign(gain) if sign else gain
            if plain:
                columns["na0"] = np.where(columns["gain"] < 0, 0, na0)
            code = np.zeros(count, np.int64)
            for j in range(3, t.order + 1):
                code |= line[width - j:len(line) - j].astype(np.int64) << (bits * (t.order - j))
            columns["code"] = code
            if letters:
                columns["letter"] = pos - np.maximum.accumulate(np.where(body == 32, pos, k.blank[name, start]))
            group = line[width - 2:-2] * (size + 1) + last
            mine = np.flatnonzero(turn[last])
            if not len(mine):
                continue
            # by pair and symbol, then in order: places and counts rise, and their differences are small
            order = (((group[mine] * size + own[mine]) << 32) | mine)
            order.sort()
            order &= (1 << 32) - 1
            begin = np.flatnonzero(np.diff(group[order], prepend=-1))
            end = np.append(begin[1:], len(order))
            columns["sym"] = own
            planes, there = [], []
            for c, wide in _layout(t, bits, sign, letters):
                x = columns[c][order]
                if c == "gain":
                    z = (x + 1).astype(np.int64) if sign else x
                else:
                    z = x.astype(np.int64)
                if c in RISING:
                    d = np.diff(z, prepend=0)
                    d[begin] = z[begin]
                    z = (d << 1) ^ (d >> 63)
                used = wide if c == "gain" else min(wide, (int(z.max()).bit_length() + 7) // 8)  # what is 0 in all events isn't moved
                planes.append(z.view(np.uint8).reshape(len(z), 8)[:, :used].T)
                there += [True] * used + [False] * (wide - used)
            planes = np.concatenate(planes)  # all lowest bytes of a column first: those that are mostly 0 lie together
            there = sum(1 << k for k, x in enumerate(there) if x)
            blobs = [codec.compress(planes[:, i:j].tobytes(), asbytes=True) for i, j in zip(begin.tolist(), end.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(begin), name)), pa.array(group[order[begin]].astype(np.int64)), pa.array(np.full(len(begin), start)), pa.array(end - begin), pa.array(np.full(len(begin), there)), pa.array(blobs, pa.binary())], ["seq_id", "pair", "start", "n", "planes", "events"])

    return run


def _unpacked(rows: list[tuple[int, int, int, bytes]], layout: list[tuple[str, int]]) -> dict[str, np.ndarray]:
    """The events of some blocks' rows of a pair (start, n, which planes, packed events), in order."""
    high, codec = sum(wide for _, wide in layout), pa.Codec("zstd")
    size = np.array([n for _, n, _, _ in rows])
    begin, out, k = np.cumsum(size) - size, {}, 0
    planes = np.zeros((high, int(size.sum())), np.uint8)
    for i, (_, n, there, blob) in zip(begin.tolist(), rows, strict=True):
        some = [x for x in range(high) if there >> x & 1]
        planes[some, i:i + n] = np.frombuffer(codec.decompress(blob, n * len(some), asbytes=True), np.uint8).reshape(len(some), n)
    for c, wide in layout:
        if c == "gain" and wide == 8:
            out[c] = np.ascontiguousarray(planes[k:k + 8].T).view(np.float64).ravel()
        elif wide:
            x = planes[k].astype(np.int64)
            for i in range(1, wide):
                if planes[k + i].any():
                    x |= planes[k + i].astype(np.int64) << (8 * i)
            if c in RISING:
                d = (x >> 1) ^ -(x & 1)
                x = np.cumsum(d)
                x -= np.repeat(x[begin] - d[begin], size)
            out[c] = x - 1 if c == "gain" else x
        k += wide
    del planes
    out["at"] += np.repeat(np.array([start for start, *_ in rows]), size)
    order = np.argsort(out["at"])
    return {c: x[order] for c, x in out.items()}


def _descent(e: dict, t: Tree, bits: int, size: int, last: bool, prune: bool, kept: C.Kept | None):
    """The levels from 2 on of a pair's events."""
    p0 = (e["na0"] + t.beta) / (e["at"] - 1 + t.beta * t.d)
    alive = np.flatnonzero(e["alive"])
    n, na = (e[c][alive] for c in ("n", "na"))
    p = (na + t.beta) / (n + t.beta * t.d)
    yield 0, np.arange(len(p0)), e["at"] - 1, p0, np.full(len(p0), -1.0)
    if t.order >= 1:
        yield 1, alive, n, p, e["gain"][alive]
    if t.order >= 2 and last:
        may, up, code = np.zeros(len(p0), bool), p0, e["code"]
        may[alive], up[alive] = na >= 1, p
        del alive, n, na, p, p0
        word = lambda alive, j: code[alive] >> (bits * (t.order - j))

        def older(alive, j):
            back = word(alive, j) & ((1 << bits) - 1)
            return back < size, back

        if kept:
            kept.word = word
        for j, alive, n, _, p, gain, _ in C._descend(e["sym"], size + 1, np.arange(len(up)), np.zeros(len(up), np.int64), t, 2, older, may, up, prune and not kept, kept):
            yield j, alive, n, p, gain


def _pairs_parts(layout: list[tuple[str, int]], bits: int, run):
    """Kernel: what ``run`` (sequence, pair, events, what is kept or none, whether these are the last) makes of the parts of each sequence and pair, which come in order; run.keeps: a pair in one part keeps its contexts too."""

    def parts(batches):
        key, rows, held, kept = None, [], 0, None
        for batch in batches:
            names, pairs, starts, sizes, planes = (batch.column(k).to_pylist() for k in range(5))
            for k in range(len(names)):
                if (names[k], pairs[k]) != key or held >= AT_ONCE:
                    same = (names[k], pairs[k]) == key
                    if rows:
                        kept = kept or (C.Kept(bits, None) if same or run.keeps else None)
                        yield from run(*key, _unpacked(rows, layout), kept, not same)
                    key, rows, held, kept = (names[k], pairs[k]), [], 0, kept if same else None
                rows.append((starts[k], sizes[k], planes[k], batch.column(5)[k].as_py()))
                held += sizes[k]
        if rows:
            yield from run(*key, _unpacked(rows, layout), kept or (C.Kept(bits, None) if run.keeps else None), True)

    return parts


def _turns(total: dict[int, np.ndarray]) -> list[np.ndarray]:
    """For each round, which last symbols are its own (the place after them: none, at a sequence's first event); rounds have about as many events."""
    if not total:
        return []
    count = sum(total.values())
    events = int(count.sum())
    rounds = min(len(count), max(-(-events // ROUND), min(LEAST_ROUNDS, -(-events // LEAST_ROUND))))
    turn, held = np.zeros(len(count) + 1, np.int64), np.zeros(rounds, np.int64)
    for k in np.argsort(-count, kind="stable").tolist():
        turn[k] = np.argmin(held)
        held[turn[k]] += count[k]
    return [turn == k for k in range(rounds)]


def _in_rounds(chunked: DataFrame, t: Tree, known, total: dict[int, np.ndarray], sign: bool, letters: bool, plain: bool, run, schema: str) -> DataFrame:
    """What ``run`` makes of the events of each sequence and pair of last symbols."""
    bits = max(1, len(known.names).bit_length())
    shared, out = chunked.sparkSession.sparkContext.broadcast(known), None
    for turn in _turns(total) or [np.ones(1, bool)]:
        rows = chunked.select("seq_id", "start", "left", "body").mapInArrow(_events(shared, t, bits, sign, letters, plain, turn), "seq_id long, pair long, start long, n long, planes long, events binary")
        rows = rows.repartition("seq_id", "pair").sortWithinPartitions("seq_id", "pair", "start")
        with small_batches(chunked.sparkSession):
            part = written(rows.mapInArrow(_pairs_parts(_layout(t, bits, sign, letters), bits, run), schema), "sums")
        out = part if out is None else out.unionAll(part)
    return out


def code_lengths(chunked: DataFrame, trees: dict[str, Tree], bins: str | list[int] | None = None) -> DataFrame:
    """seq_id, bin, n, last, and for each tree's name the nats of the events of a bin; last is its largest position.

    Trees differ in the rule and order alone.  bins: none (one for all), ``letter`` (the place after the last blank; a
    blank's own is 0), or a grid of lengths (a bin ends at each; what lies behind the last is in none).  Chunks have as
    many symbols to their left as the largest order.
    """
    most = max(trees.values(), key=lambda t: t.order)
    grid = np.array(sorted(bins), np.int64) if isinstance(bins, list) else None
    sign = all(t.rule in ("deepest", "blend", "fixed") or t.rule == "shortest_gain" and t.delta == 0 for t in trees.values())
    plain = all(t.rule == "shortest_gain" and t.delta == 0 and t.n_min <= 1 and t.order for t in trees.values())
    known, total = known_of(chunked, most)[:2]
    bits = max(1, len(known.names).bit_length())
    size, prune = len(known.names), all(t.rule in C.BY_GAIN for t in trees.values())

    def run(name, pair, e, kept, _):
        folds = [C.Fold(len(e["at"]), t) for t in trees.values()]
        for j, alive, n, p, gain in _descent(e, most, bits, size, pair // (size + 1) < size, prune, kept):
            for f in folds:
                f.step(j, alive, n, p, gain)
        nats = [-np.log(f.finish()[0]) for f in folds]
        where = np.zeros(len(e["at"]), np.int64) if bins is None else e["letter"].astype(np.int64) if bins == "letter" else np.searchsorted(grid, e["at"])
        inside = where < (len(grid) if grid is not None else NEVER)
        some, back = np.unique(where[inside], return_inverse=True)
        last = np.zeros(len(some), np.int64)
        np.maximum.at(last, back, e["at"][inside])
        values = grid[some] if grid is not None else some
        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), name)), pa.array(values), pa.array(np.bincount(back, minlength=len(some))), pa.array(last), *(pa.array(np.bincount(back, x[inside], len(some)), pa.float64()) for x in nats)], ["seq_id", "bin", "n", "last", *trees])

    run.keeps = False
    sums = _in_rounds(chunked, most, known, total, sign, bins == "letter", plain, run, "seq_id long, bin long, n long, last long, " + ", ".join(f"`{c}` double" for c in trees))
    return sums.groupBy("seq_id", "bin").agg(F.sum("n").alias("n"), F.max("last").alias("last"), *(F.sum(c).alias(c) for c in trees))


def tree_of(chunked: DataFrame, t: Tree) -> tuple[DataFrame, DataFrame]:
    """The tree that sequences leave: nodes (depth, ctx, n, gain) and counts (depth, ctx, sym, cnt)."""
    known, total, pairs, gains = known_of(chunked, t)
    bits = max(1, len(known.names).bit_length())
    names, size = [chr(c) for c in known.names.tolist()], len(known.names)
    columns = ["depth", "ctx", "sym", "cnt", "gain"]

    def run(name, pair, e, kept, last):
        """The contexts that a pair's last part leaves; a context's gain stands at its first symbol."""
        tail = "".join(names[x] for x in (pair // (size + 1), pair % (size + 1)) if x < size)
        for _ in _descent(e, t, bits, size, len(tail) == 2, False, kept):
            pass
        for j, (contexts, cells) in kept.levels.items() if last else ():
            for i in range(0, len(cells[0]), AT_ONCE):
                word, count = (c[i:i + AT_ONCE] for c in cells)
                place = np.searchsorted(contexts[0], word >> bits)
                gain = np.where(np.diff(word >> bits, prepend=cells[0][i - 1] >> bits if i else -1) != 0, contexts[2][place], 0.0)
                if t.tree == "full":  # a context that comes once is none
                    some = contexts[1][place] > 1
                    word, count, gain = word[some], count[some], gain[some]
                letter = [[names[x] for x in ((word >> (bits * k)) & ((1 << bits) - 1)).tolist()] for k in range(j - 1)]
                ctx = map("".join, zip(*letter[1:], strict=True)) if j > 2 else [""] * len(word)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(word), j, np.int32)), pa.array([w + tail for w in ctx], pa.string()), pa.array(letter[0], pa.string()), pa.array(count), pa.array(gain)], columns)

    run.keeps = True
    top = [(0, "", names[k], int(c), 0.0) for x in total.values() for k, c in enumerate(x) if c]
    for s, x in pairs.items():
        for y, row in enumerate(x.reshape(size, size)):
            some = np.flatnonzero(row).tolist()
            top += [(1, names[y], names[k], int(row[k]), float(gains[s][y]) if k == some[0] else 0.0) for k in some]
    schema = "depth int, ctx string, sym string, cnt long, gain double"
    below = _in_rounds(chunked, t, known, total, True, False, False, run, schema)
    cells = below.unionAll(below.sparkSession.createDataFrame(top, schema)).groupBy("depth", "ctx", "sym").agg(F.sum("cnt").alias("cnt"), F.sum("gain").alias("gain"))
    nodes = cells.groupBy("depth", "ctx").agg(F.sum("cnt").alias("n"), F.round(F.sum("gain"), 9).alias("gain"))
    return nodes, cells.drop("gain")


register_pickle_by_value(sys.modules[__name__])
