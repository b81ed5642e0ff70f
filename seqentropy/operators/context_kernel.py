"""Context trees level by level over arrays: all sequences of a batch at once, no loop over symbols.

Level j numbers the contexts of length j of all positions; counts before a position are ranks inside a context's
group, and a context's gain (how much shorter it has coded the symbols after it than its parent did; negative is good)
is a running sum in the same order.  The incremental tree lets a context count only from its birth: when its parent,
older than that, has seen the same symbol twice.  Rules fold the levels into one probability for each position.
"""

from __future__ import annotations

import sys
from dataclasses import dataclass

import numpy as np
from pyspark.cloudpickle import register_pickle_by_value

RULES = ["shortest_gain", "deepest_gain", "walk_gain", "min_total_gain", "deepest", "blend", "fixed"]
BY_GAIN = RULES[:4]


@dataclass
class Tree:
    """How contexts are grown, estimated and chosen.

    tree: full or incremental; beta: added to every count; rule: how levels make one probability; delta: the gain (in
    nats) that a context must have reached; n_min: contexts seen less often are left out; q: novelty of the blend;
    tie: whether a child with gain 0 stops the search for the shortest context; gain_from: whether a context's first
    event counts in its gain; residual: what the blend's left-over weight goes to; order: length of the longest
    context (None: as long as any context repeats).
    """

    d: int
    order: int | None = None
    tree: str = "full"
    beta: float = 0.5
    rule: str = "shortest_gain"
    delta: float = 0.0
    n_min: int = 1
    q: float = 1.0
    tie: str = "stop"
    gain_from: str = "second"
    residual: str = "uniform"
    static: list[float] | None = None


def _number(values: np.ndarray) -> np.ndarray:
    return np.unique(values, return_inverse=True)[1] if len(values) else values


def _sorted(code: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The places by code, then in order; where each code begins there, and how many it has."""
    if len(code) and code.max() < 1 << 16:
        code = code.astype(np.uint16)
        at = np.argsort(code, kind="stable")  # by digits: faster
        code = code[at]
    else:
        bits = max(1, len(code).bit_length())
        packed = (code << bits) | np.arange(len(code))
        packed.sort()
        at, code = packed & ((1 << bits) - 1), packed >> bits
    begin = np.flatnonzero(np.concatenate([[True], code[1:] != code[:-1]])) if len(code) else code
    return at, begin, np.diff(np.append(begin, len(code)))


def _rank(code: np.ndarray) -> np.ndarray:
    """How many earlier entries have the same code."""
    at, begin, size = _sorted(code)
    out = np.empty(len(code), np.int64)
    out[at] = np.arange(len(code)) - np.repeat(begin, size)
    return out


class Kept:
    """What the events before have left: of each level the born contexts (as sorted words) with n and gain, and the cells (word, then symbol) with their counts.

    Events then come part by part, in order, and memory grows with the contexts, not with the events.
    """

    def __init__(self, bits: int, word):
        self.bits, self.word, self.levels = bits, word, {}

    def level(self, j: int) -> tuple[list[np.ndarray], list[np.ndarray]]:
        whole = np.zeros(0, np.int64)
        return self.levels.setdefault(j, ([whole, whole, np.zeros(0)], [whole, whole]))

    @staticmethod
    def find(table: list[np.ndarray], words: np.ndarray) -> list[np.ndarray]:
        """Whether words (sorted) are in a table, and their columns there (0: not there)."""
        at = np.searchsorted(table[0], words)
        had = np.zeros(len(words), bool)
        inside = at < len(table[0])
        had[inside] = table[0][at[inside]] == words[inside]
        out = [had]
        for column in table[1:]:
            found = np.zeros(len(words), column.dtype)
            found[had] = column[at[had]]
            out.append(found)
        return out

    @staticmethod
    def add(table: list[np.ndarray], words: np.ndarray, *more: np.ndarray) -> None:
        at = np.searchsorted(table[0], words)
        had = np.zeros(len(words), bool)
        inside = at < len(table[0])
        had[inside] = table[0][at[inside]] == words[inside]
        new = ~had
        for k, column in enumerate(more, 1):
            table[k][at[had]] += column[had]
        if new.any():
            for k, column in enumerate((words, *more)):
                table[k] = np.insert(table[k], at[new], column[new])


def _descend(sym: np.ndarray, base: int, alive: np.ndarray, key: np.ndarray, t: Tree, start: int, older, may: np.ndarray, p_up: np.ndarray, prune: bool = False, kept: Kept | None = None):
    """Levels from ``start`` on: j, the positions alive (by context, then in order), n, na, p, gain, number of contexts.

    A context and a place in order are packed into one number, so that each level sorts plain numbers.  key: the contexts
    of the alive positions at ``start``; older(alive, j): where there is a j-th symbol back, and which; may: the positions
    whose symbol their context of the level before has seen since its birth (then a child can be born); p_up: what that
    context gave.

    prune: for the rules by gains.  Where all events of a context have the same symbol, no context below it ever gains
    (it has seen that symbol no more often), so these rules need its children, and nothing below them: else a sequence
    that ends in a cycle would have as many levels as symbols.

    kept: the events are a part of all, after those that it knows; words of contexts are in the order of the keys.
    """
    settled = np.zeros(len(sym), bool)
    bits = max(1, len(sym).bit_length())
    low = (1 << bits) - 1
    log_up = np.log(p_up)
    j = start
    while len(alive) and (t.order is None or j <= t.order):
        if j > start:
            ok, back = older(alive, j)
            if not ok.all():
                alive, key, back = alive[ok], key[ok], back[ok]
            key = key * base + back
        packed = (key << bits) | alive
        packed.sort()
        alive, key = packed & low, packed >> bits
        del packed
        if not len(alive):
            return
        begin = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        size = np.diff(np.append(begin, len(key)))
        if kept:
            contexts, cells = kept.level(j)
            words = kept.word(alive[begin], j)
            had, n_before, gain_before = kept.find(contexts, words)
        if j:
            if t.tree == "incremental":
                birth = np.minimum.reduceat(np.where(may[alive], np.arange(len(key)), len(key)), begin)
                if kept:
                    birth = np.where(had, begin, birth)
                left = np.minimum(begin + size, birth)
                size, begin = begin + size - left, left
            elif not kept:  # else it may come again
                size = np.where(size > 1, size, 0)
            born = size > 0
            begin, size = begin[born], size[born]
            if kept:
                words, n_before, gain_before = words[born], n_before[born], gain_before[born]
            rank = np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size, size)
            if len(rank) < len(alive):
                alive = alive[np.repeat(begin, size) + rank]
            if not len(alive):
                return
        else:
            rank = np.arange(len(alive)) - np.repeat(begin, size)
        key = np.repeat(np.arange(len(size)), size)
        first = np.repeat(np.cumsum(size) - size, size)
        own = sym[alive]
        if kept:
            rank += np.repeat(n_before, size)
            at, head, count = _sorted(key * base + own)
            cell = (words[key[at[head]]] << kept.bits) | own[at[head]]
            na = np.empty(len(key), np.int64)
            na[at] = np.arange(len(key)) - np.repeat(head - kept.find(cells, cell)[1], count)
            kept.add(cells, cell, count)
            del at, head
        elif base == 2:
            ones = np.cumsum(own) - own
            ones -= ones[first]
            na = np.where(own == 1, ones, rank - ones)
        else:
            na = _rank(key * base + own)
        p = (na + t.beta) / (rank + t.beta * t.d)
        log = np.log(p)
        step = log_up[alive] - log
        if t.gain_from == "second":
            step[rank == 0] = 0.0
        run = np.cumsum(step) - step
        run -= run[first]
        if kept:
            kept.add(contexts, words, size, np.add.reduceat(step, np.cumsum(size) - size))
            run += np.repeat(gain_before, size)
        gain = np.round(run, 9) if j else np.full(len(alive), -1.0)  # sums that cancel out are ties
        yield j, alive, rank, na, p, gain, len(size)
        log_up[alive] = log
        may[:] = False
        may[alive] = na >= 1
        if prune:
            begin = np.cumsum(size) - size
            same = np.repeat(np.minimum.reduceat(own, begin) == np.maximum.reduceat(own, begin), size)
            rest = ~settled[alive]
            settled[alive] = same
            if not rest.all():
                alive, key = alive[rest], key[rest]
        j += 1


def levels(sym: np.ndarray, bound: np.ndarray, t: Tree, prune: bool = False):
    """Yields for each level: j, the positions alive, n, na, p, gain, and the tree's nodes at the level (prune: without levels that don't matter to rules by gains)."""
    row = np.repeat(np.arange(len(bound) - 1), np.diff(bound))
    at = np.arange(len(sym)) - bound[row]
    names, dense = np.unique(sym, return_inverse=True)

    def older(alive: np.ndarray, j: int):
        return at[alive] >= j, dense[alive - j]  # places before a sequence are masked

    yield from _descend(dense, max(2, len(names)), np.arange(len(sym)), row, t, 0, older, np.zeros(len(sym), bool), np.full(len(sym), 1.0 / t.d), prune)


def deeper(sym: np.ndarray, older: np.ndarray, at: np.ndarray, t: Tree, start: int, born: np.ndarray, run_parent: np.ndarray, p_parent: np.ndarray):
    """Levels from ``start`` on of events, in order, that share their last ``start`` symbols: what ``levels`` yields.

    older: column k has the symbol k + 1 places back, -1 before the sequence; born, run_parent and p_parent are the
    events' state after the level before (the birth of its context, its count of the event's symbol, its probability).
    """
    names, dense = np.unique(np.concatenate([sym, older.ravel()]), return_inverse=True)
    dense, back = dense[:len(sym)], dense[len(sym):].reshape(older.shape)
    yield from _descend(dense, max(2, len(names)), np.arange(len(sym)), np.zeros(len(sym), np.int64), t, start, lambda alive, j: (older[alive, j - 1] >= 0, back[alive, j - 1]), (at > born) & (run_parent >= 2), p_parent)


class Fold:
    """One probability for each event from the levels, which come one after the other."""

    def __init__(self, size: int, t: Tree):
        self.t, self.size = t, size
        self.p, self.used = np.full(size, 1.0 / t.d), np.zeros(size, np.int32)
        self.flag, self.candidate, self.level, self.done = np.zeros(size, bool), self.p.copy(), np.zeros(size, np.int32), np.zeros(size, bool)
        self.total, self.best, self.novel, self.going = np.zeros(size), np.zeros(size), np.ones(size if t.rule == "blend" else 0), np.ones(size, bool)

    def step(self, j: int, alive: np.ndarray, n: np.ndarray, pj: np.ndarray, gain: np.ndarray) -> None:
        t, p, used = self.t, self.p, self.used
        if t.order is not None and j > t.order:
            return
        ok = (n >= max(1, t.n_min)) | (j == 0)
        good = ok & (gain < -t.delta) if j else np.ones(len(alive), bool) & (gain < -t.delta)
        if t.rule == "fixed":
            if j == t.order:
                p[:] = 1.0 / t.d
                p[alive], used[alive] = pj, j
        elif t.rule == "deepest":
            p[alive[ok]], used[alive[ok]] = pj[ok], j
        elif t.rule == "deepest_gain":
            take = good if j else ok
            p[alive[take]], used[alive[take]] = pj[take], j
        elif t.rule == "walk_gain":
            if j:
                self.going[alive[ok & (gain > 0)]] = False
                self.going[alive[~ok]] = False
            take = (good if j else ok) & self.going[alive]
            p[alive[take]], used[alive[take]] = pj[take], j
        elif t.rule == "min_total_gain":
            if j == 0:
                p[alive] = pj
            else:
                self.total[alive[ok]] += gain[ok]
                take = ok & (self.total[alive] < self.best[alive] - t.delta)
                self.best[alive[take]] = self.total[alive[take]]
                p[alive[take]], used[alive[take]] = pj[take], j
        elif t.rule == "shortest_gain":
            if j == 0:
                p[alive] = pj
            else:
                stop = np.ones(self.size, bool)  # a missing child ends the search
                stop[alive] = ~ok | (gain >= 0 if t.tie == "stop" else gain > 0)
                end = self.flag & stop & ~self.done
                p[end], used[end] = self.candidate[end], self.level[end]
                self.done |= end
            self.flag = np.zeros(self.size, bool)
            self.flag[alive] = good
            self.candidate[alive], self.level[alive] = pj, j
        elif t.rule == "blend":
            if t.static is not None:
                if j == 0:
                    p[:] = 0.0
                    self.candidate[:] = 1.0 / t.d
                self.candidate[alive[ok]] = pj[ok]
                p += (t.static[j] if j < len(t.static) else 0.0) * self.candidate
            else:
                e = np.where(n > 0, t.q / (n + t.q), 1.0)
                p[alive] = (1 - e) * pj + e * p[alive]
                self.novel[alive] *= e
            used[alive[n > 0]] = j
        else:
            raise ValueError(t.rule)

    def finish(self) -> tuple[np.ndarray, np.ndarray]:
        t, p = self.t, self.p
        if t.rule == "shortest_gain":
            end = self.flag & ~self.done
            p[end], self.used[end] = self.candidate[end], self.level[end]
        if t.rule == "blend" and t.residual == "renormalise" and t.static is None:
            rest = self.novel < 1
            p[rest] = (p[rest] - self.novel[rest] / t.d) / (1 - self.novel[rest])
        return p, self.used


def predict_many(sym: np.ndarray, bound: np.ndarray, trees: list[Tree]) -> list[tuple[np.ndarray, np.ndarray]]:
    """``predict`` for several rules; trees that differ in the rule alone are grown once."""
    folds = [Fold(len(sym), t) for t in trees]
    alike: dict[tuple, list[int]] = {}
    for k, t in enumerate(trees):
        alike.setdefault((t.d, t.order, t.tree, t.beta, t.gain_from), []).append(k)
    for group in alike.values():
        for j, alive, n, _, pj, gain, _ in levels(sym, bound, trees[group[0]], all(trees[k].rule in BY_GAIN for k in group)):
            for k in group:
                folds[k].step(j, alive, n, pj, gain)
        for k in group:
            if trees[k].static is not None:  # levels that no position has reached
                for later in range(j + 1, len(trees[k].static)) if len(sym) else ():
                    folds[k].step(later, np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0), np.zeros(0))
    return [f.finish() for f in folds]


def predict(sym: np.ndarray, bound: np.ndarray, t: Tree) -> tuple[np.ndarray, np.ndarray]:
    """The probability given to each symbol, and the length of the context it is from (the deepest one for blends)."""
    return predict_many(sym, bound, [t])[0]


def level_probabilities(sym: np.ndarray, bound: np.ndarray, t: Tree) -> np.ndarray:
    """What each level up to t.order gives each symbol, a row for a level; a context not seen yet gives what the level before does.

    In a full tree a context of length j + 1 has been seen before a symbol as often as its last symbol has followed the j
    symbols before that: so one rank for each level, of words of j + 1 symbols, is all there is to count.
    """
    n = len(sym)
    out = np.full((t.order + 1, n), 1.0 / t.d)
    if t.tree != "full":
        for j, alive, seen, _, pj, _, _ in levels(sym, bound, t):
            ok = (seen >= 1) | (j == 0)
            out[j:, alive[ok]] = pj[ok]
        return out
    if not n:
        return out
    row = np.repeat(np.arange(len(bound) - 1), np.diff(bound))
    every = np.arange(n)
    at = every - bound[row]
    names = np.flatnonzero(np.bincount(sym))
    place = np.zeros(names[-1] + 1, np.int64)
    place[names] = np.arange(len(names))
    dense, base = place[sym], len(names)
    bits = n.bit_length()
    low = (1 << bits) - 1
    key = row * base + dense
    for j in range(t.order + 1):
        if j:
            seen = np.zeros(n, np.int64)
            seen[1:] = na[:-1]
            word = np.empty(n, np.int64)
            word[order] = np.cumsum(first) - 1
            key = np.empty(n, np.int64)
            key[1:] = word[:-1] * base + dense[1:]
            short = np.flatnonzero(at < j)  # no word of j + 1 symbols ends here
            seen[short] = 0
            key[short] = n * base + short
        else:
            seen = at
        packed = (key << bits) | every
        packed.sort()
        order, key = packed & low, packed >> bits
        first = np.empty(n, bool)
        first[0] = True
        np.not_equal(key[1:], key[:-1], out=first[1:])
        begin = np.flatnonzero(first)
        na = np.empty(n, np.int64)
        na[order] = every - np.repeat(begin, np.diff(np.append(begin, n)))
        p = (na + t.beta) / (seen + t.beta * t.d)
        out[j] = np.where(seen >= 1, p, out[j - 1]) if j else p
    return out


def fit_static(sym: np.ndarray, bound: np.ndarray, t: Tree, rounds: int = 50, tol: float = 1e-6) -> list[float]:
    """Weights of the levels, the same for all positions, with the shortest code (expectation-maximisation)."""
    rows, now = [], np.full(len(sym), 1.0 / t.d)
    for j, alive, n, _, pj, _, _ in levels(sym, bound, t):
        ok = (n >= max(1, t.n_min)) | (j == 0)
        now = now.copy()
        now[alive[ok]] = pj[ok]
        rows.append(now)
    p = np.array(rows)
    c = np.full(len(p), 1.0 / max(1, len(p)))
    for _ in range(rounds):
        part = c[:, None] * p
        new = (part / part.sum(0)).mean(1)
        if np.abs(new - c).max() < tol:
            return new.tolist()
        c = new
    return c.tolist()


def mixture_rate(sym: np.ndarray, bound: np.ndarray, depth: int, d: int) -> np.ndarray:
    """For each sequence, the code length in nats of the half-and-half mixture over all trees up to a depth.

    Every node weighs its own Dirichlet(1/2) block probability against the product of its children; the first ``depth``
    symbols of a sequence are conditioned on (they are contexts only).
    """
    from math import lgamma

    row = np.repeat(np.arange(len(bound) - 1), np.diff(bound))
    at = np.arange(len(sym)) - bound[row]
    pos = np.flatnonzero(at >= depth)
    base = int(sym.max()) + 1 if len(sym) else 1
    keys = [row[pos]]
    for j in range(1, depth + 1):
        keys.append(_number(keys[-1] * base + sym[pos - j]))
    table = np.array([lgamma(k + 0.5) - lgamma(0.5) for k in range(len(pos) + 1)])
    total = np.array([lgamma(k + 0.5 * d) - lgamma(0.5 * d) for k in range(len(pos) + 1)])
    below = None
    for j in range(depth, -1, -1):
        key = keys[j]
        size = int(key.max()) + 1 if len(key) else 0
        cells, counts = np.unique(key * base + sym[pos], return_counts=True)
        own = np.bincount(cells // base, table[counts], size) - total[np.bincount(key, minlength=size)]
        if below is None:
            w = own
        else:
            parent = np.zeros(len(below), np.int64)
            parent[keys[j + 1]] = key
            children = np.bincount(parent, below, size)
            w = np.log(0.5) + np.logaddexp(own, children)
        below = w
    out = np.zeros(len(bound) - 1)
    if below is not None and len(pos):
        out[np.unique(row[pos])] = -below[np.unique(keys[0])]
    return out


register_pickle_by_value(sys.modules[__name__])
