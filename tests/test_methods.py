"""Worked examples, ground truth, invariants and brute force."""

import math
import random
from fractions import Fraction
from itertools import product

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from seqentropy.functions import symbols as S
from seqentropy.operators import blocks as B
from seqentropy.operators import context_kernel as C
from seqentropy.operators import corpus as K
from seqentropy.operators import dynamics as D
from seqentropy.operators import gambling as G
from seqentropy.operators import language as L
from seqentropy.operators import predict as P
from seqentropy.operators import repeats as R
from seqentropy.operators.context_kernel import Tree

GOLDEN = "110101001111"


def seqs(spark, *texts):
    return spark.createDataFrame(list(enumerate(texts)), "seq_id long, t string")


def brute_lengths(t, side):
    out = {}
    for i in range(len(t)):
        for p in range(1, len(t) - i + 1):
            others = range(i) if side == "past" else [j for j in range(len(t)) if j != i]
            if not any(t[j:j + p] == t[i:i + p] for j in others):
                out[i + 1] = p
                break
    return out


def reference_predict(text, t):
    """The trees symbol by symbol, as a dictionary of contexts."""
    nodes = {"": {"c": {}, "gain": -1.0, "born": -1}}
    out = []
    for k, s in enumerate(text):
        path, j = [], 0
        while j <= min(k, t.order) and (ctx := text[k - j:k]) in nodes:
            path.append(ctx)
            j += 1
        p = [(nodes[c]["c"].get(s, 0) + t.beta) / (sum(nodes[c]["c"].values()) + t.beta * t.d) for c in path]
        chosen = p[0]
        if t.rule == "deepest_gain":
            for c, x in zip(path, p):
                n = sum(nodes[c]["c"].values())
                if c == "" or n > 0 and round(nodes[c]["gain"], 9) < -t.delta:
                    chosen = x
        out.append(chosen)
        for j, c in enumerate(path):
            n = sum(nodes[c]["c"].values())
            if j and n:
                nodes[c]["gain"] += math.log(p[j - 1]) - math.log(p[j])
            nodes[c]["c"][s] = nodes[c]["c"].get(s, 0) + 1
        deep = len(path) - 1
        if t.tree == "full":
            for j in range(deep + 1, min(k, t.order) + 1):
                nodes[text[k - j:k]] = {"c": {s: 1}, "gain": 0.0}
        elif deep + 1 <= min(k, t.order) and nodes[path[-1]]["c"][s] >= 2:
            nodes[text[k - deep - 1:k]] = {"c": {s: 1}, "gain": 0.0}
    return out, len(nodes)


def test_golden_context_rates():
    x = 0.3
    for _ in range(1000):
        x = 1 - 1.8 * x * x
    s = []
    for _ in range(3000):
        x = 1 - 1.8 * x * x
        s.append(int(x > 0))
    s, b = np.array(s), np.array([0, 3000])
    for tree, order, rule, delta, expected in (("full", 12, "deepest_gain", 2, 0.45126088), ("incremental", 12, "deepest_gain", 2, 0.45094790), ("full", 8, "shortest_gain", 0, 0.48179623), ("incremental", 8, "shortest_gain", 0, 0.47858509)):
        p, _ = C.predict(s, b, Tree(2, order, tree, 0.5, rule, delta))
        assert abs(-np.log(p).mean() - expected) < 1e-8


@settings(max_examples=40, deadline=None)
@given(st.text("ab", min_size=1, max_size=60), st.sampled_from(["full", "incremental"]), st.integers(0, 6))
def test_kernel_equals_trees_symbol_by_symbol(text, tree, order):
    t = Tree(2, order, tree, 0.5, "deepest_gain", 0.3)
    sym = np.array([ord(c) for c in text])
    p, _ = C.predict(sym, np.array([0, len(text)]), t)
    assert np.allclose(p, reference_predict(text, t)[0], atol=1e-9)


def test_incremental_nodes_equal_reference():
    text = D.markov_sequence([[0.8, 0.2], [0.3, 0.7]], 1500, 5)
    t = Tree(2, 40, "incremental", 0.5, "deepest_gain", 2.0)
    sym = np.array([ord(c) for c in text])
    nodes = sum(x[-1] for x in C.levels(sym, np.array([0, len(sym)]), t))
    assert nodes == reference_predict(text, t)[1]


@pytest.mark.parametrize(("rule", "tree"), [("shortest_gain", "full"), ("walk_gain", "incremental"), ("min_total_gain", "full"), ("blend", "incremental"), ("fixed", "full")])
def test_windows_equal_kernel(spark, rule, tree):
    t = Tree(2, 2, tree, 0.5, rule, 0.1)
    frame = seqs(spark, D.markov_sequence([[0.9, 0.1], [0.2, 0.8]], 90, 1), "0", "0101010101")
    ours = {(r.seq_id, r.pos): r.p for r in P.window_predictions(S.events(S.chunks(frame, 2, 16), 2), t, block=32, crowded=1).collect()}
    theirs = {(r.seq_id, r.pos): r.p for r in P.predictions(frame, t).collect()}
    assert ours.keys() == theirs.keys() and all(abs(ours[k] - theirs[k]) < 1e-9 for k in ours)


@pytest.mark.parametrize("rule", C.RULES)
def test_probabilities_sum_to_one(rule):
    past = D.markov_sequence([[0.9, 0.1], [0.2, 0.8]], 200, 3)
    for residual in ("uniform", "renormalise"):
        t = Tree(2, 3, "full", 0.5, rule, 0.0, residual=residual)
        total = sum(C.predict(np.array([ord(c) for c in past + a]), np.array([0, len(past) + 1]), t)[0][-1] for a in "01")
        assert abs(total - 1) < 1e-9


def test_blend_weights_fixture():
    n, q = (10, 4, 2), 1.0
    e = [q / (k + q) for k in n]
    assert abs(sum((1 - e[j]) * np.prod(e[j + 1:]) for j in range(3)) - 0.993939) < 1e-6


@settings(max_examples=40, deadline=None)
@given(st.lists(st.text("ab", min_size=1, max_size=30), min_size=1, max_size=3), st.sampled_from(["past", "both"]))
def test_match_lengths_by_brute_force(texts, side):
    sym = np.array([ord(c) for t in texts for c in t])
    bound = np.concatenate([[0], np.cumsum([len(t) for t in texts])])
    got = R.longest_matches(sym, bound, side) + 1
    for k, t in enumerate(texts):
        own = got[bound[k]:bound[k + 1]]
        want = brute_lengths(t, side)
        assert {i + 1: int(x) for i, x in enumerate(own) if i + x <= len(t)} == want


@settings(max_examples=60, deadline=None)
@given(st.text("abc", max_size=60))
def test_parses_cover_the_text(text):
    for cut in (R.dictionary_phrases, R.substring_phrases):
        assert "".join(text[s - 1:s - 1 + n] for s, n, *_ in cut(text)) == text


def test_round_trip_of_parses(spark):
    frame = seqs(spark, GOLDEN, "aaaaaaa", "abababababc", "x")
    for kind in ("dictionary", "substring"):
        got = {r.seq_id: r.t for r in R.unparse(R.parse(frame, kind), kind).collect()}
        assert got == {r.seq_id: r.t for r in frame.collect()}


def test_arithmetic_coder():
    def p_of(past):
        ones = sum(past)
        return [Fraction(2 * (len(past) - ones) + 1, 2 * len(past) + 2), Fraction(2 * ones + 1, 2 * len(past) + 2)]

    text = [int(c) for c in GOLDEN * 2]
    bits, back = G.arithmetic_round_trip(text, p_of)
    ideal = -sum(math.log2(p_of(text[:k])[s]) for k, s in enumerate(text))
    assert back == text and len(bits) <= math.ceil(ideal) + 2


def test_block_entropy_fixtures(spark):
    """The published numbers of the smallest English corpus."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").where("lang = 'en'")
    line = S.corpus_chunks(S.sequences(docs, "doc_id", S.normalise_27(F.col("text"))), 5)
    got = {(r.n, r.method): r for r in B.block_entropy(B.block_counts(line, 6), 27).collect()}
    for n, words, likelihood, first, parity in ((1, 26, 3.6692, 3.6693, 3.6693), (4, 5812, 2.0821, 2.0929, 2.0948), (6, 55757, 1.7718, 1.8527, 1.8881)):
        assert got[n, "plugin"].n_words == words
        for method, h in (("plugin", likelihood), ("first_order", first), ("digamma_parity", parity)):
            assert abs(got[n, method].h_diff - h) < 2e-4
    for n in range(1, 7):
        assert got[n, "plugin"].h_block <= got[n, "first_order"].h_block <= got[n, "laplace_block"].h_block + 1e-9


def test_arrow_counts_equal_columns(spark):
    frame = seqs(spark, "the cat the hat", "a", "bb")
    one = {tuple(r) for r in B.block_counts(S.chunks(frame, 3, 4), 4).collect()}
    assert one == {tuple(r) for r in B.block_counts_arrow(frame, 4).collect()}


def test_order_and_partitions_do_not_matter(spark):
    frame = seqs(spark, "abracadabra", "banana", "abc")
    t = Tree(26, 3)
    rates = lambda f: {(r.seq_id, r.n, round(r.nats, 9)) for r in P.gamble(f, {"r": t}).collect()}
    assert rates(frame) == rates(frame.repartition(3).orderBy(F.desc("seq_id")))


def test_edge_sequences(spark):
    frame = S.sequences(spark.createDataFrame([(1, None), (2, ""), (3, "a"), (4, "123 !!"), (5, "éé"), (6, "aaaaaaaaaaaaaaaaaaaa")], "id long, x string"), "id", S.normalise_27(F.col("x")))
    assert {r.seq_id for r in frame.collect()} == {3, 6}
    rates = {r.seq_id: r.nats / r.n for r in P.gamble(frame, {"r": Tree(27, 3, beta=1 / 27)}).collect()}
    assert abs(rates[3] - math.log(27)) < 1e-9 and rates[6] < 0.5
    assert R.match_lengths(frame).count() == 2


def test_known_sources():
    assert abs(D.entropy_bernoulli(0.05) - 0.2864) < 1e-4
    p = [[0.9, 0.1], [0.3, 0.7]]
    text = D.markov_sequence(p, 20000, 42)
    sym = np.array([ord(c) for c in text])
    h = D.entropy_markov(p)
    for t in (Tree(2, 1, rule="fixed"), Tree(2, 8, rule="min_total_gain", delta=2.0)):
        rate = -np.log2(C.predict(sym, np.array([0, len(sym)]), t)[0]).mean()
        assert h - 0.02 < rate < h + 0.02
    nats = C.mixture_rate(sym - 48, np.array([0, len(sym)]), 4, 2)[0]
    assert abs(nats / len(sym) / math.log(2) - h) < 0.02


def test_lyapunov_exponents():
    x0 = np.array([0.3, 0.1])
    assert abs(D._slopes("quadratic", x0, 50000, 1000, 1.8).mean() - 0.405) < 0.006
    assert abs(D._slopes("plane", x0 * 0.1, 50000, 1000, 1.4).mean() - 0.4199) < 0.01
    assert abs(D._slopes("laser", x0, 50000, 1000, 0.0).mean() - 0.5076) < 0.02


def test_automaton_offsets():
    assert D.odd_offsets(2) == [-2, 0, 2] and D.odd_offsets(4) == [-4, 0, 4] and D.odd_offsets(6) == [-6, -4, 0, 4, 6]


def test_fit_recovers_planted_limit(spark):
    rows = [("a", n, 0.4 + 0.9 * math.log(n) / n**0.6) for n in G.geometric_grid(200000, 1000)]
    bad = [("b", n, 0.5) for n in G.geometric_grid(200000, 1000)]
    fit = {r.k: r for r in G.fit_tail(spark.createDataFrame(rows + bad, "k string, n long, h double"), by=["k"]).collect()}
    assert fit["a"].ok and abs(fit["a"].h - 0.4) < 1e-3 and abs(fit["a"].gamma - 0.6) < 0.01
    assert not fit["b"].ok and fit["b"].h == 0.5
    zero = G.fit_tail(spark.createDataFrame([(n, 2.0 * math.log(n) / n**0.9) for n in G.geometric_grid(50000, 1000)], "n long, h double"), h0=0.0).first()
    assert abs(zero.c - 2.0) < 1e-2 and abs(zero.gamma - 0.9) < 0.01


def test_zero_probability_is_refused():
    with pytest.raises(ValueError):
        P.additive(F.lit(0), F.lit(0), 2, 0.0)


def test_generation_and_forecast(spark):
    frame = seqs(spark, "abcabcabcabcabcabcabc")
    chunked, t = S.chunks(frame, 2), Tree(3, 2)
    nodes, cells = P.trained_tree(P.corpus_levels(chunked, t, 1, 4), t)
    out = L.generate_greedy(seqs(spark, "ab"), nodes, cells, 6, 2).first().continuation
    assert out == "cabcab"
    table = L.forecast_table(S.events(S.chunks(seqs(spark, "abc"), 2), 2), nodes, cells, 2, 3, 1 / 3).where("rank = 1").collect()
    assert {r.pos: r.letter for r in table if r.pos > 1} == {2: "b", 3: "c"} and all(r.p >= 0.6 for r in table if r.pos > 1)
    with pytest.raises(ValueError):
        L.model_table(nodes, cells, 2)


def test_chosen_context_is_that_of_the_joins(spark):
    rng = random.Random(12)
    nodes = {"": 0.0} | {w: rng.choice([-1.5, -0.2, 0.0, 0.7]) for n in (1, 2, 3) for w in map("".join, product("ab", repeat=n)) if rng.random() < 0.8}
    frame = spark.createDataFrame([(len(k), k, 5, g) for k, g in nodes.items()], "depth int, ctx string, n long, gain double")
    texts = ["".join(rng.choices("ab", k=9)) for _ in range(20)]
    ev = S.events(S.chunks(seqs(spark, *texts), 3), 3)
    for delta in (0.0, 1.0):
        got = {(r.seq_id, r.pos): r.ctx for r in L.choose_contexts(ev, frame, 3, delta).collect()}
        table = {k: (g, {"a": 1}) for k, g in nodes.items()}
        assert got == {(i, k + 1): L.chosen_context(table, t[:k], 3, delta) for i, t in enumerate(texts) for k in range(9)}


@pytest.mark.parametrize("tree", ["full", "incremental"])
@pytest.mark.parametrize("split", [1, 2, 9])
def test_corpus_engine_is_the_kernel(spark, tree, split):
    rng = random.Random(5)
    texts = ["".join(rng.choices("abc", weights=[6, 3, 1], k=400)), "abcab" * 60, "c"]
    frame = seqs(spark, *texts)
    trees = {rule: Tree(3, 4, tree, 0.5, rule, delta) for rule, delta in (("shortest_gain", 0.0), ("deepest_gain", 2.0), ("walk_gain", 0.0), ("min_total_gain", 2.0), ("deepest", 0.0), ("blend", 0.0), ("fixed", 0.0))}
    trees["shorter"] = Tree(3, 2, tree, 0.5)
    got = P.choose(P.corpus_levels(S.chunks(frame, 4, 32), Tree(3, 4, tree, 0.5), split, 50), trees).collect()
    assert len(got) == sum(map(len, texts))
    for name, t in trees.items():
        want = {(r.seq_id, r.pos): r.p for r in P.predictions(frame, t).collect()}
        assert all(abs(r[name] - want[r.seq_id, r.pos]) < 1e-9 for r in got), name


def test_split_and_word_counts(spark):
    frame = seqs(spark, "abab" * 50, "çab", "a")
    assert P.choose_split(S.chunks(frame, 3), 3, 120) == 1 and P.choose_split(S.chunks(frame, 3), 3, 10) == 4
    from collections import Counter

    want = Counter((n, t[k:k + n]) for t in ("abab" * 50, "çab", "a") for n in (1, 2, 3) for k in range(len(t) - n + 1))
    assert {(r.n, r.word): r.cnt for r in B.block_counts(S.chunks(frame, 2, 7), 3).collect()} == dict(want)
    by = S.chunks(frame, 9, 7).withColumn("odd", F.when(F.col("seq_id") > 0, F.col("seq_id") % 2))
    got = {(r.odd, r.n, r.word): r.cnt for r in B.block_counts(by, 10, ["odd"]).collect()}
    assert got[None, 10, "ababababab"] == 96 and got[1, 3, "çab"] == 1 and got[0, 1, "a"] == 1


def test_scramble_keeps_words(spark):
    frame = seqs(spark, "one two three two one")
    assert sorted(S.scramble_words(frame).first().t.split()) == sorted("one two three two one".split())
    w = L.words(frame).orderBy("word_idx").collect()
    assert [(r.word, r.start_pos) for r in w] == [("one", 1), ("two", 5), ("three", 9), ("two", 15), ("one", 19)]


def test_precursor():
    assert S.root_half(5) == "01101"


def test_sql_names(spark):
    from seqentropy.plans.sql import choose_engine, explain_plan, register_all

    register_all(spark)
    assert spark.sql("select text27('A b--C')").first()[0] == "a b c"
    assert abs(spark.sql("select seq_entropy(t) from values ('ab'), ('ab') v(t)").first()[0] - 1) < 1e-12
    assert [tuple(r) for r in spark.sql(f"select * from phrases('{GOLDEN}')").collect()][:3] == [(1, 1, 1), (2, 2, 2), (3, 4, 3)]
    assert [r.word for r in spark.sql("select * from block_words('abc', 2)").collect()] == ["ab", "bc"]
    assert choose_engine(10**9, 10**12, Tree(2, 8))["engine"] == "windows"
    assert explain_plan(seqs(spark, "ab"), Tree(2, 8))["engine"] == "kernel"


@pytest.mark.parametrize("at_once", [1, 20, 1 << 16])
def test_repeat_lengths_in_levels_by_brute_force(spark, monkeypatch, at_once):
    """Over chunks' borders, of short and of long sequences, and no words are joined to positions."""
    monkeypatch.setattr(R, "LEVELS_AT_ONCE", at_once)
    rng = random.Random(3)
    texts = ["".join(rng.choice("ab ") for _ in range(n)) for n in (150, 1, 40, 3)]
    got = R.match_lengths_levels(S.chunks(seqs(spark, *texts), 3, 16).repartition(5), 4)
    want = {(k, i): None for k, t in enumerate(texts) for i in range(1, len(t) + 1)} | {(k, i): n for k, t in enumerate(texts) for i, n in brute_lengths(t, "past").items() if n <= 4}
    assert {(r.seq_id, r.pos): r.len for r in got.collect()} == want
    joins = [x for x in got._jdf.queryExecution().optimizedPlan().toString().splitlines() if "Join " in x]
    assert joins and all("LeftAnti" in x or "LeftSemi" in x for x in joins)


@pytest.mark.parametrize("tree", ["full", "incremental"])
def test_cycles_need_no_deep_levels(tree):
    """Sequences that end in a cycle (F14): rules by gains get the same from the first levels; all levels would be quadratic."""
    rng = np.random.default_rng(5)
    for cycle in ("1", "10", "1101"):
        sym = np.array([*rng.integers(0, 2, 40), *(int(c) for c in cycle * 60)]) + 48
        bound = np.array([0, len(sym)])
        for rule in C.BY_GAIN:
            for delta in (0.0, 2.0):
                t = Tree(2, tree=tree, rule=rule, delta=delta)
                fold = C.Fold(len(sym), t)
                for j, alive, n, _, pj, gain, _ in C.levels(sym, bound, t):
                    fold.step(j, alive, n, pj, gain)
                assert np.array_equal(fold.finish()[0], C.predict(sym, bound, t)[0])
    long = np.full(60_000, 49)
    assert sum(1 for _ in C.levels(long, np.array([0, len(long)]), Tree(2, tree=tree), True)) <= 3


def test_automaton_on_long_rows(spark):
    """400,000 cells a row, by steps of the rule itself."""
    bits = np.random.default_rng(6).integers(0, 2, 400_000).astype(np.uint8)
    row = spark.createDataFrame([(1, (bits + 48).tobytes().decode())], "seq_id long, t string")
    for steps in (2, 4, 6):
        cells = bits
        for _ in range(steps):
            cells = cells[:-2] ^ cells[1:-1] ^ cells[2:]
        assert D.automaton_150(row, steps).first().t == (cells + 48).tobytes().decode()


@pytest.mark.parametrize("tree", ["full", "incremental"])
def test_corpus_sums_are_the_kernels(spark, tree):
    """F6 to F13: code lengths by bins, and trained trees, of sequences in blocks; no row for a symbol."""
    rng = random.Random(7)
    texts = ["".join(rng.choices("abc ", weights=[6, 3, 1, 2], k=900)), "abcab " * 60, "c", "aa", " "]
    frame = seqs(spark, *texts)
    trees = {rule: Tree(4, 4, tree, 0.5, rule, delta) for rule, delta in (("shortest_gain", 0.0), ("deepest_gain", 2.0), ("walk_gain", 0.0), ("min_total_gain", 2.0), ("deepest", 0.0), ("blend", 0.0), ("fixed", 0.0))}
    trees |= {"shorter": Tree(4, 2, tree, 0.5), "one": Tree(4, 1, tree, 0.5)}
    chunked = S.chunks(frame, 4, 33)
    rows = {name: P.predictions(frame, t).collect() for name, t in trees.items()}
    grid = [1, 40, 200, 500]
    letter = {(i, k + 1): k - t.rfind(" ", 0, k + 1) for i, t in enumerate(texts) for k in range(len(t))}
    own = {None: lambda r: 0, "letter": lambda r: letter[r.seq_id, r.pos], "grid": lambda r: next((g for g in grid if g >= r.pos), None)}
    for bins, place in own.items():
        for names in (list(trees), ["shortest_gain", "shorter"], ["blend"]):
            got = {(r.seq_id, r.bin): r for r in K.code_lengths(chunked, {n: trees[n] for n in names}, grid if bins == "grid" else bins).collect()}
            for name in names:
                want = {}
                for r in rows[name]:
                    if place(r) is not None:
                        n, last, nats = want.get((r.seq_id, place(r)), (0, 0, 0.0))
                        want[r.seq_id, place(r)] = (n + 1, max(last, r.pos), nats - math.log(r.p))
                assert {k: (r.n, r.last) for k, r in got.items()} == {k: v[:2] for k, v in want.items()}
                assert all(abs(got[k][name] - v[2]) < 1e-7 for k, v in want.items()), (bins, name)
    if tree == "incremental":
        t = Tree(4, 4, tree, 0.5)
        (nodes, cells), (nodes2, cells2) = P.trained_tree(P.corpus_levels(chunked, t, 2, 50), t), K.tree_of(chunked, t)
        seen = lambda f: {(r.depth, r.ctx, r.sym): r.cnt for r in f.collect()}
        gains = lambda f: {(r.depth, r.ctx): (r.n, r.gain) for r in f.collect()}
        assert seen(cells) == seen(cells2)
        a, b = gains(nodes), gains(nodes2)
        assert a.keys() == b.keys() and all(a[k][0] == b[k][0] and abs(a[k][1] - b[k][1]) < 1e-7 for k in a)


@pytest.mark.parametrize("tree", ["full", "incremental"])
def test_corpus_sums_of_parts(spark, tree, monkeypatch):
    """F1 to F4 and F6 to F8 of round 3: a pair's events come in many parts and rounds; the sums are the same."""
    for name, value in (("AT_ONCE", 20), ("ROUND", 400), ("HOP", 3)):
        monkeypatch.setattr(K, name, value)
    test_corpus_sums_are_the_kernels(spark, tree)


def test_corpus_tasks_hold_a_part(spark, monkeypatch):
    """F1 to F4 and F6 to F8 of round 3: no task has all events of a common pair of letters; the code is that of one kernel."""
    monkeypatch.setattr(K, "AT_ONCE", 100)
    text = "ab" * 2000 + "".join(random.Random(9).choices("ab", weights=[9, 1], k=4000))
    frame, t = seqs(spark, text), Tree(3, 5, "incremental", 0.5)
    kernel = K._unpacked

    def unpacked(rows, layout):
        if sum(n for _, n, *_ in rows) > 250:
            raise MemoryError("too many events at once")
        return kernel(rows, layout)

    monkeypatch.setattr(K, "_unpacked", unpacked)
    got = K.code_lengths(S.chunks(frame, 5, 64), {"nats": t}).first()
    want = P.predictions(frame, t).agg(F.sum(-F.ln("p")).alias("nats"), F.count("*").alias("n")).first()
    assert got.n == want.n == 8000 and abs(got.nats - want.nats) < 1e-7


def test_worked_parses_join_nothing(spark):
    """F5 of round 3: parses, lengths and trees come from rows: no join, and a shuffle by sequence for each part."""
    from seqentropy.plans import queries as Q

    rng = random.Random(11)
    texts = ["".join(rng.choices("ab", k=rng.randint(1, 30))) for _ in range(40)] + ["a", "aaaa", "abababab", "ça ça"]
    frame = seqs(spark, *texts)
    plan = Q.worked(frame)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "Generate" not in plan
    for k, t in enumerate(texts):
        nodes, starts = {}, range(1, min(5, len(t)) + 1)
        for i in starts:
            for p in range(1, len(t) - i + 2):
                nodes.setdefault(t[i - 1:i - 1 + p], []).append(i)
        want = {(w, len(w), len(x) == 1, x[0] if len(x) == 1 else None, len(x)) for w, x in nodes.items() if len(x) > 1 or len(w) == 1 or len(nodes[w[:-1]]) > 1}
        got = R.tree_nodes(t, 5)
        assert set(got) == want and len(got) == len(want)
    for kind, cut in (("dictionary", R.dictionary_phrases), ("substring", R.substring_phrases)):
        got = {}
        for r in R.parse(frame, kind, text=True).orderBy("seq_id", "k").collect():
            got.setdefault(r.seq_id, []).append((r.start, r.len, r.ref, r.new_sym, r.complete))
            assert r.w == texts[r.seq_id][r.start - 1:r.start - 1 + r.len]
        assert got == {k: cut(t) for k, t in enumerate(texts)}


def test_decoded_texts(spark):
    """both parses decoded in a row, without a shuffle; matches that reach into themselves, unfinished phrases."""
    rng = random.Random(8)
    texts = ["".join(rng.choices("ab ", k=500)), "a" * 400, "abc" * 90, "x", "ça ça"]
    got = R.decoded(seqs(spark, *texts))
    assert "Exchange" not in got._jdf.queryExecution().executedPlan().toString()
    assert {r.seq_id: (r.dictionary, r.substring) for r in got.collect()} == {k: (t, t) for k, t in enumerate(texts)}
    with pytest.raises(ValueError):
        R.phrases_text([(1, 3, 5, "a", True)], "substring")


def test_block_curve_counts_parts(spark):
    """chunks are cut where bins end; no row for a symbol."""
    rng = random.Random(9)
    texts = ["".join(rng.choices("abc", k=300)), "ab" * 70]
    grid, n_list = [1, 50, 96, 97, 300], [1, 2, 4]
    frame = B.block_curve(S.chunks(seqs(spark, *texts), 3, 32), n_list, grid, 3, methods=["plugin"], by=["seq_id"])
    assert "posexplode" not in frame._jdf.queryExecution().analyzed().toString() and "mapinarrow" in frame._jdf.queryExecution().analyzed().toString().lower()
    got = {(r.seq_id, r.length, r.n): (r.n_windows, r.n_words, r.h_block) for r in frame.collect()}
    from collections import Counter

    want = {}
    for i, t in enumerate(texts):
        for g in grid:
            for n in n_list:
                c = Counter(t[k:k + n] for k in range(min(g, len(t)) - n + 1))
                w = sum(c.values())
                if w:
                    want[i, g, n] = (w, len(c), math.log2(w) - sum(x * math.log2(x) for x in c.values()) / w)
    assert got.keys() == want.keys()
    assert all(got[k][:2] == want[k][:2] and abs(got[k][2] - want[k][2]) < 1e-9 for k in want)


@pytest.mark.parametrize("tree", ["full", "incremental"])
@pytest.mark.parametrize("order", [0, 1, 3])
def test_probabilities_of_all_levels(tree, order):
    texts = ["", "a", "abab", "ba", "the cat sat on the mat and the rat", "aaaaaaa", "", "mississippi", "b"]
    sym = np.array([ord(c) for c in "".join(texts)], np.int64)
    bound = np.concatenate([[0], np.cumsum([len(x) for x in texts])])
    t = Tree(27, order, tree, 1 / 27)
    want = np.full((order + 1, len(sym)), 1 / 27)
    for j, alive, n, _, p, *_ in C.levels(sym, bound, t):
        seen = alive[(n >= 1) | (j == 0)]
        want[j:, seen] = p[(n >= 1) | (j == 0)]
    assert (C.level_probabilities(sym, bound, t) == want).all()
    assert C.level_probabilities(sym[:0], np.array([0]), t).shape == (order + 1, 0)


@pytest.mark.parametrize("order", [0, 2, 3])
def test_static_weights_make_levels_once(spark, sf, order):
    """The weights, and the code length, are those of rounds over all symbols; only a few jobs read the texts."""
    docs = spark.read.parquet(f"{sf}/documents.parquet").selectExpr("doc_id AS seq_id", "lower(substr(text, 1, 300)) AS t").where("t <> ''").limit(60).cache()
    texts, t = [r.t for r in docs.collect()], Tree(300, order, beta=1 / 300, rule="blend")
    p = np.concatenate([C.level_probabilities(np.array([ord(c) for c in x], np.int64), np.array([0, len(x)]), t) for x in texts], axis=1)
    want = np.full(order + 1, 1 / (order + 1))
    for _ in range(20):
        part = want[:, None] * p
        new = (part / part.sum(0)).mean(1)
        if np.abs(new - want).max() < 1e-5:
            break
        want = new
    sc = spark.sparkContext
    sc.setJobGroup(f"static {order}", "")
    got = P.static_weights(docs, t)
    jobs = len(sc.statusTracker().getJobIdsForGroup(f"static {order}"))
    sc.setJobGroup("other", "")
    assert np.allclose(got, want, rtol=0, atol=1e-7) and jobs <= 4
    for fit in (P.static_fit, P._static_fit_by_rounds):
        c, n, nats = fit(docs, t, 20)
        assert np.allclose(c, want, rtol=0, atol=1e-7) and n == p.shape[1] and abs(nats + np.log(want @ p).sum()) < 1e-7 * n
    assert P.static_fit(docs.where("false"), t) == ([1 / (order + 1)] * (order + 1), 0, 0.0)
