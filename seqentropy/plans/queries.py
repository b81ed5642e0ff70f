"""Queries of the methods, variants, baselines, measures and workloads, each with SQL where SQL can express it."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import symbols as S
from ..operators import blocks as B
from ..operators import corpus as K
from ..operators import dynamics as D
from ..operators import gambling as G
from ..operators import language as L
from ..operators import predict as P
from ..operators import repeats as R
from ..operators.context_kernel import Tree
from ..sources.scratch import scratch, written
from ..sources.tables import table
from ..streaming import online as O
from . import oracles as Q

REGISTRY: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {}
DIGITS6 = 6


def query(name: str, sql: str | None = None):
    def add(f):
        REGISTRY[name] = (f, sql)
        return f

    return add


def r6(c) -> F.Column:
    return F.round(c if not isinstance(c, str) else F.col(c), DIGITS6)


# --- sources -----------------------------------------------------------------------------------------------------------


def docs27(spark, d) -> DataFrame:
    return S.sequences(table(spark, d, "documents"), "doc_id", S.normalise_27(F.col("text")))


def english(spark, d) -> DataFrame:
    return S.sequences(table(spark, d, "documents").where("lang = 'en'"), "doc_id", S.normalise_27(F.col("text")))


def bench27(spark, d) -> DataFrame:
    return S.sequences(table(spark, d, "benchmark"), "item_id", S.normalise_27(F.col("text")))


def turns27(spark, d) -> DataFrame:
    c = table(spark, d, "conversations")
    return S.sequences(c.select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "text"), "id", S.normalise_27(F.col("text")))


def user_symbols(spark, d) -> DataFrame:
    return S.symbols_from_events(table(spark, d, "events"), "user_id", ["ts", "event_id"], F.col("event_type"))


def users(spark, d) -> DataFrame:
    return S.gather(user_symbols(spark, d))


def customers(spark, d) -> DataFrame:
    return S.gather(S.symbols_from_events(table(spark, d, "orders"), "o_custkey", ["o_orderdate", "o_orderkey"], F.col("o_orderpriority")))


EN27 = Q.DOCS27.replace("WHERE text IS NOT NULL", "WHERE text IS NOT NULL AND lang = 'en'")
USERS = "SELECT user_id AS seq_id, string_agg(sym, '' ORDER BY ts, event_id) AS t FROM (SELECT user_id, ts, event_id, CAST(dense_rank() OVER (ORDER BY event_type) - 1 AS VARCHAR) AS sym FROM events WHERE user_id IS NOT NULL AND event_type IS NOT NULL) GROUP BY user_id"
CUSTOMERS = "SELECT o_custkey AS seq_id, string_agg(sym, '' ORDER BY o_orderdate, o_orderkey) AS t FROM (SELECT o_custkey, o_orderdate, o_orderkey, CAST(dense_rank() OVER (ORDER BY o_orderpriority) - 1 AS VARCHAR) AS sym FROM orders WHERE o_custkey IS NOT NULL AND o_orderpriority IS NOT NULL) GROUP BY o_custkey"


_BITS2 = CUSTOMERS.replace("SELECT o_custkey AS seq_id, string_agg(sym, '' ORDER BY o_orderdate, o_orderkey) AS t", "SELECT o_custkey AS seq_id, translate(string_agg(sym, '' ORDER BY o_orderdate, o_orderkey), '01234', '00111') AS t")


def customer_bits(spark, d) -> DataFrame:
    """Order histories as above or below the middle priority."""
    return customers(spark, d).select("seq_id", F.translate("t", "01234", "00111").alias("t"))


# --- symbols ---------------------------------------------------------------------------------------------------------


@query("s1_text27", f"SELECT seq_id, CAST(len(t) AS INTEGER) AS n, md5(t) AS digest FROM ({Q.DOCS27})")
def s1(spark, d):
    return docs27(spark, d).select("seq_id", F.length("t").alias("n"), F.md5("t").alias("digest"))


@query("s2_ascii7", r"SELECT doc_id, CAST(len(t) AS INTEGER) AS n, md5(t) AS digest FROM (SELECT doc_id, regexp_replace(text, '[^\x00-\x7F]', '', 'g') AS t FROM documents)")
def s2(spark, d):
    return table(spark, d, "documents").select("doc_id", S.ascii7(F.col("text")).alias("t")).select("doc_id", F.length("t").alias("n"), F.md5("t").alias("digest"))


@query("s3_symbol_counts", f"WITH seqs AS ({Q.DOCS27}) SELECT sym, count(*) AS cnt, CAST(max(pos) AS BIGINT) AS last_pos FROM (SELECT unnest(string_split(t, '')) AS sym, unnest(range(1, len(t) + 1)) AS pos FROM seqs) GROUP BY sym")
def s3(spark, d):
    return S.explode_symbols(docs27(spark, d)).groupBy("sym").agg(F.count("*").alias("cnt"), F.max("pos").alias("last_pos"))


@query("s4_event_symbols", f"SELECT seq_id, CAST(len(t) AS INTEGER) AS n, md5(t) AS digest FROM ({USERS})")
def s4(spark, d):
    return users(spark, d).select("seq_id", F.length("t").alias("n"), F.md5("t").alias("digest"))


@query("s5_value_cells", "SELECT CAST((value >= 10)::INT + (value >= 50)::INT + (value >= 100)::INT AS VARCHAR) AS cell, CAST(least(floor(value / 25), 61) AS INTEGER) AS width_cell, count(*) AS cnt FROM events GROUP BY ALL")
def s5(spark, d):
    e = table(spark, d, "events")
    return e.select(S.partition_series(F.col("value"), cuts=[10, 50, 100]).alias("cell"), F.least(F.floor(F.col("value") / 25), F.lit(61)).cast("int").alias("width_cell")).groupBy("cell", "width_cell").agg(F.count("*").alias("cnt"))


@query("s5_quantile_cut", "SELECT count(*) FILTER (value >= m) AS upper, count(*) FILTER (value < m) AS lower FROM events, (SELECT quantile_cont(value, 0.5) AS m FROM events)")
def s5b(spark, d):
    e = table(spark, d, "events")
    cuts = S.quantile_cuts(e, "value", 2)
    cell = S.partition_series(F.col("value"), cuts=cuts)
    return e.agg(F.sum(F.when(cell == "1", 1).otherwise(0)).alias("upper"), F.sum(F.when(cell == "0", 1).otherwise(0)).alias("lower"))


@query("s7_corpus_offsets", f"SELECT seq_id, CAST(coalesce(sum(len(t) + 1) OVER (ORDER BY seq_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS pos_before FROM ({EN27})")
def s7(spark, d):
    return S.offsets(english(spark, d)).select("seq_id", F.col("offset").alias("pos_before"))


@query("g7_scrambled_words", f"SELECT seq_id, md5(string_agg(w, ' ' ORDER BY md5(concat(i - 1, ':0')))) AS digest FROM (SELECT seq_id, unnest(string_split(t, ' ')) AS w, unnest(range(1, len(string_split(t, ' ')) + 1)) AS i FROM ({Q.DOCS27})) GROUP BY seq_id")
def g7(spark, d):
    return S.scramble_words(docs27(spark, d)).select("seq_id", F.md5("t").alias("digest"))


# --- block entropies -------------------------------------------------------------------------------------------------


def doc_counts(spark, d, n):
    return B.block_counts(S.chunks(docs27(spark, d), n - 1), n)


@query("b1_block_counts", f"WITH {Q.with_seqs(Q.DOCS27)}, {Q.words(3)} SELECT n, word, cnt FROM counts")
def b1(spark, d):
    return doc_counts(spark, d, 3)


@query("b1_block_counts_arrow", f"WITH {Q.with_seqs(Q.DOCS27)}, {Q.words(5)} SELECT n, word, cnt FROM counts")
def b1a(spark, d):
    return B.block_counts_arrow(docs27(spark, d), 5)


def _entropies(h: DataFrame, *by: str) -> DataFrame:
    return h.select(*by, "n", "method", F.col("n_windows").cast("long").alias("n_windows"), F.col("n_words").cast("long").alias("n_words"), r6("h_block").alias("h_block"), r6("h_diff").alias("h_diff"), r6("h_per_symbol").alias("h_per_symbol"))


_H = "n, method, CAST(w AS BIGINT) AS n_windows, CAST(m AS BIGINT) AS n_words, round(h_block, 6) AS h_block, round(h_block - coalesce(lag(h_block) OVER (PARTITION BY {p}method ORDER BY n), 0), 6) AS h_diff, round(h_block / n, 6) AS h_per_symbol FROM h"


@query("b2_b11_block_entropies", f"WITH {Q.with_seqs(Q.DOCS27)}, {Q.words(6)}, {Q.block_entropy(27)} SELECT {_H.format(p='')}")
def b2(spark, d):
    return _entropies(B.block_entropy(B.block_counts_arrow(docs27(spark, d), 6), 27))


_LANG27 = "SELECT * FROM (SELECT lang, trim(regexp_replace(lower(text), '[^a-z]+', ' ', 'g')) AS t FROM documents WHERE text IS NOT NULL) WHERE t <> ''"


@query("w2_entropies_by_language", f"WITH {Q.with_seqs(_LANG27)}, {Q.words(4, 'lang')}, {Q.block_entropy(27, by='lang')} SELECT lang, {_H.format(p='lang, ')}")
def w2lang(spark, d):
    docs = table(spark, d, "documents")
    chunked = S.chunks(docs27(spark, d), 3).join(docs.select(F.col("doc_id").alias("seq_id"), "lang"), "seq_id")
    return _entropies(B.block_entropy(B.block_counts(chunked, 4, ["lang"]), 27, by=["lang"]), "lang")


_CORPUS = "SELECT 0 AS seq_id, string_agg(t, ' ' ORDER BY seq_id) || ' ' AS t FROM ({})"


_LINE = f"line AS ({_CORPUS.format(EN27)}), big AS (SELECT s0 - greatest(s0 - 5, 1) AS k0, substr(t, greatest(s0 - 5, 1), 8192 + s0 - greatest(s0 - 5, 1)) AS t FROM (SELECT t, unnest(range(1, len(t) + 1, 8192)) AS s0 FROM line)), pieces AS (SELECT substr(t, greatest(s - 5, 1), s - greatest(s - 5, 1)) AS l, substr(t, s, 256) AS b FROM (SELECT t, unnest(range(k0 + 1, len(t) + 1, 256)) AS s FROM big)), ends AS (SELECT l || b AS t, unnest(range(len(l) + 1, len(l) + len(b) + 1)) AS e FROM pieces)"


@query("w2_english_corpus", f"WITH {_LINE}, words AS (SELECT t, e, unnest(range(1, least(6, e) + 1)) AS n FROM ends), counts AS (SELECT CAST(n AS INTEGER) AS n, substr(t, e - n + 1, n) AS word, count(*) AS cnt FROM words GROUP BY ALL), {Q.block_entropy(27)} SELECT {_H.format(p='')}")
def w2corpus(spark, d):
    """English texts as one sequence, blocks of 1 to 6 letters, all estimators."""
    return _entropies(B.block_entropy(B.block_counts(S.corpus_chunks(english(spark, d), 5), 6), 27))


_ASCII = r"SELECT * FROM (SELECT doc_id AS seq_id, regexp_replace(text, '[^\x00-\x7F]', '', 'g') AS t FROM documents WHERE text IS NOT NULL AND lang = 'en') WHERE t <> ''"


@query("w2_ascii_entropies", f"WITH {Q.with_seqs(_ASCII)}, {Q.words(4)}, {Q.block_entropy(128)} SELECT {_H.format(p='')}")
def w2ascii(spark, d):
    seqs = S.sequences(table(spark, d, "documents").where("lang = 'en'"), "doc_id", S.ascii7(F.col("text")))
    return _entropies(B.block_entropy(B.block_counts_arrow(seqs, 4), 128))


@query("b5_b10_conditional", f"WITH {Q.with_seqs(Q.DOCS27)}, {Q.words(4)}, c AS (SELECT n, cnt, sum(cnt) OVER (PARTITION BY n, substr(word, 1, n - 1)) AS ctx FROM counts) SELECT n, round(sum(-cnt * ln(cnt / ctx)) / sum(cnt) / {Q.LN2!r}, 6) AS h, round(sum(-cnt * ln((cnt + 1) / (ctx + 27))) / sum(cnt) / {Q.LN2!r}, 6) AS h_laplace FROM c GROUP BY n")
def b5(spark, d):
    counts = B.block_counts_arrow(docs27(spark, d), 4)
    return B.conditional_entropy(counts, 27).select("n", r6("h").alias("h")).join(B.conditional_entropy(counts, 27, laplace=True).select("n", r6("h").alias("h_laplace")), "n")


@query("b12_min_count", f"WITH {Q.with_seqs(Q.DOCS27)}, {Q.words(5)} SELECT n, round((coalesce(sum(cnt) FILTER (cnt >= 3), 0) * ln(sum(cnt)) - coalesce(sum(cnt * ln(cnt)) FILTER (cnt >= 3), 0)) / sum(cnt) / {Q.LN2!r}, 6) AS h_block FROM counts GROUP BY n")
def b12(spark, d):
    return B.min_count_entropy(B.block_counts_arrow(docs27(spark, d), 5), 3).select("n", r6("h_block").alias("h_block"))


_B13 = "(w_kept * ln(w) - coalesce(clogc, 0)) / w + CASE WHEN once > 0 THEN -(once / w) * ln((once / w) / greatest(exp(5 * ln(27.0)) - often, once, 1.0)) ELSE 0.0 END"


@query("b13_assumed_tail", f"WITH {Q.with_seqs(Q.DOCS27)}, {Q.words(5)}, g AS (SELECT n, CAST(sum(cnt) AS DOUBLE) AS w, coalesce(sum(cnt) FILTER (cnt > 1), 0) AS w_kept, sum(cnt * ln(cnt)) FILTER (cnt > 1) AS clogc, count(*) FILTER (cnt = 1) AS once, count(*) FILTER (cnt > 1) AS often FROM counts GROUP BY n) SELECT n, round(({_B13}) / {Q.LN2!r}, 6) AS h_block FROM g")
def b13(spark, d):
    return B.assumed_tail_entropy(B.block_counts_arrow(docs27(spark, d), 5), 27.0**5).select("n", r6("h_block").alias("h_block"))


@query("b14_description_bound", f"WITH {Q.with_seqs(Q.DOCS27)}, {Q.words(4)}, {Q.block_entropy(27)} SELECT n, method, round((w * h_block + exp(n * ln(27.0)) * ln(w) / {Q.LN2!r}) / w, 6) AS per_window FROM h WHERE method = 'plugin'")
def b14(spark, d):
    h = B.block_entropy(B.block_counts_arrow(docs27(spark, d), 4), 27, methods=["plugin"])
    return B.description_bound(h, 27).select("n", "method", r6("per_window").alias("per_window"))


@query("b15_block_rates", f"WITH {Q.with_seqs(Q.DOCS27)}, {Q.words(5)}, {Q.block_entropy(27)}, x AS (SELECT n, method, h_block - coalesce(lag(h_block) OVER (PARTITION BY method ORDER BY n), 0) AS h_diff, h_block / n AS per FROM h) SELECT method, round(max_by(h_diff, n), 6) AS last_rate, round(max_by(per, n), 6) AS per_symbol FROM x GROUP BY method")
def b15(spark, d):
    h = B.block_entropy(B.block_counts_arrow(docs27(spark, d), 5), 27)
    return B.block_rate(h).select("method", r6("rate").alias("last_rate")).join(B.block_rate(h, "per_symbol").select("method", r6("rate").alias("per_symbol")), "method")


GRID = [2000, 20000, 200000]


@query("b16_block_curve", f"WITH line AS ({_CORPUS.format(EN27)}), grid AS (SELECT unnest({GRID}) AS length), chopped AS (SELECT t, unnest(range(1, 200001, 2000)) AS s FROM line), pieces AS (SELECT s, substr(t, greatest(s - 3, 1), least(s - 1, 3)) AS l, substr(t, s, 2000) AS b FROM chopped), ends AS (SELECT s, l, l || b AS t, unnest(range(len(l) + 1, len(l) + len(b) + 1)) AS e FROM pieces), words AS (SELECT s + e - len(l) - 1 AS pos, t, e, unnest(range(1, least(4, e) + 1)) AS n FROM ends), counts AS (SELECT length, CAST(n AS INTEGER) AS n, substr(t, e - n + 1, n) AS word, count(*) AS cnt FROM words JOIN grid ON pos <= length GROUP BY ALL), {Q.block_entropy(27, by='length')} SELECT CAST(length AS INTEGER) AS length, n, method, round(h_block, 6) AS h_block FROM h WHERE method IN ('plugin', 'digamma_parity')")
def b16(spark, d):
    """Estimates over growing beginnings of the English corpus (the measure's own prefixes)."""
    h = B.block_curve(S.corpus_chunks(english(spark, d), 3), [1, 2, 3, 4], GRID, 27, methods=["plugin", "digamma_parity"])
    return h.select("length", "n", "method", r6("h_block").alias("h_block"))


@query("b17_monotone_violations", f"WITH {Q.with_seqs(Q.DOCS27)}, {Q.words(4)}, {Q.block_entropy(27)}, x AS (SELECT n, method, h_block - coalesce(lag(h_block) OVER (PARTITION BY method ORDER BY n), 0) AS h_diff FROM h), y AS (SELECT *, lag(h_diff) OVER (PARTITION BY method ORDER BY n) AS before FROM x) SELECT n, method FROM y WHERE h_diff > before + 1e-9 AND method IN ('plugin', 'digamma_parity')")
def b17(spark, d):
    h = B.block_entropy(B.block_counts_arrow(docs27(spark, d), 4), 27, methods=["plugin", "digamma_parity"])
    return B.check_monotone(h).select("n", "method")


# --- repeats and parsings --------------------------------------------------------------------------------------------


@query("p4_first_occurrences", f"WITH {Q.with_seqs(CUSTOMERS)}, e AS (SELECT seq_id, t, unnest(range(1, len(t) + 1)) AS i FROM seqs), w AS (SELECT seq_id, t, i, unnest(range(1, least(6, len(t) - i + 1) + 1)) AS p FROM e) SELECT seq_id, CAST(p AS INTEGER) AS p, substr(t, i, p) AS word, CAST(min(i) AS INTEGER) AS first, count(*) AS cnt FROM w GROUP BY ALL")
def p4a(spark, d):
    return R.first_occurrences(customers(spark, d), 6)


_LENGTHS = "e AS (SELECT seq_id, t, unnest(range(1, len(t) + 1)) AS i FROM seqs), w AS (SELECT seq_id, t, i, unnest(range(1, len(t) - i + 2)) AS p FROM e), g AS (SELECT seq_id, i, p, min(i) OVER (PARTITION BY seq_id, substr(t, i, p)) AS first, count(*) OVER (PARTITION BY seq_id, substr(t, i, p)) AS cnt FROM w)"


@query("p4_match_lengths", f"WITH {Q.with_seqs(CUSTOMERS)}, {_LENGTHS} SELECT seq_id, CAST(i AS BIGINT) AS pos, CAST(min(p) AS INTEGER) AS len FROM g WHERE first = i GROUP BY seq_id, i")
def p4(spark, d):
    return R.match_lengths(customers(spark, d))


@query("p5_unique_prefix_lengths", f"WITH {Q.with_seqs(CUSTOMERS)}, {_LENGTHS} SELECT seq_id, CAST(i AS BIGINT) AS pos, CAST(min(p) AS INTEGER) AS len FROM g WHERE cnt = 1 GROUP BY seq_id, i")
def p5(spark, d):
    return R.match_lengths(customers(spark, d), "both")


@query("p6_repeat_rate_histories", f"WITH {Q.with_seqs(CUSTOMERS)}, {_LENGTHS}, l AS (SELECT seq_id, i, min(p) AS len FROM g WHERE first = i GROUP BY seq_id, i) SELECT count(*) AS n, CAST(sum(len) AS BIGINT) AS sum_len, round(count(*) * ln(count(*)) / sum(len) / {Q.LN2!r}, 6) AS rate FROM l")
def p6(spark, d):
    return R.repeat_rate(R.match_lengths(customers(spark, d))).select("n", "sum_len", r6("rate").alias("rate"))


@query("p6_repeat_rate_documents")
def p6d(spark, d):
    """Repeat rate of each document (whole texts)."""
    return R.repeat_rate(R.match_lengths(docs27(spark, d)), by=["seq_id"]).select("seq_id", "n", "sum_len", r6("rate").alias("rate"))


@query("p7_prefix_tree", f"WITH {Q.with_seqs(CUSTOMERS)}, {_LENGTHS}, m AS (SELECT seq_id, i, min(p) AS p FROM g WHERE cnt = 1 GROUP BY seq_id, i), leaf AS (SELECT seq_id, substr(t, i, m.p) AS node FROM m JOIN seqs USING (seq_id)) SELECT seq_id, CAST(count(*) AS BIGINT) AS leaves, CAST(max(len(node)) AS INTEGER) AS height FROM leaf GROUP BY seq_id")
def p7(spark, d):
    tree = R.prefix_tree(customers(spark, d), 1 << 30).where("is_leaf")
    return tree.groupBy("seq_id").agg(F.count("*").alias("leaves"), F.max("depth").alias("height"))


def _parses(kind: str):
    def run(spark, d):
        phrases = R.parse(docs27(spark, d), kind)
        rates = R.parse_rate(phrases, by=["seq_id"])
        bits = R.parse_code_bits(phrases, 27, kind)
        return rates.join(bits, "seq_id").select("seq_id", "phrases", "n", r6("mean_len").alias("mean_len"), r6("rate").alias("rate"), F.round("bits", 4).alias("bits"))

    return run


query("p1_p3_p8_dictionary_parse")(_parses("dictionary"))
query("p2_p3_p8_substring_parse")(_parses("substring"))

_PARSED = f"SELECT seq_id, count(*) FILTER (complete) AS phrases, CAST(sum(len) FILTER (complete) AS BIGINT) AS n, round(sum(len) FILTER (complete) / count(*) FILTER (complete), 6) AS mean_len, round(ln(sum(len) FILTER (complete)) * count(*) FILTER (complete) / sum(len) FILTER (complete) / {Q.LN2!r}, 6) AS rate, round(sum({{}} + log2(5)), 4) AS bits FROM p GROUP BY seq_id"
_DICTIONARY = f"WITH RECURSIVE {Q.with_seqs(CUSTOMERS)}, s AS (SELECT seq_id, t, 0 AS k, 1 AS start, 0 AS len, false AS complete, CAST([] AS VARCHAR[]) AS known FROM seqs UNION ALL SELECT seq_id, t, k + 1, start + len, CASE WHEN start + len + m <= len(t) THEN m + 1 ELSE m END, start + len + m <= len(t), list_append(known, substr(t, start + len, m + 1)) FROM (SELECT *, coalesce(list_max(list_transform(known, lambda x: CASE WHEN starts_with(substr(t, start + len), x) THEN len(x) ELSE 0 END)), 0) AS m FROM s WHERE start + len <= len(t))), p AS (SELECT * FROM s WHERE k > 0)"
_SUBSTRING = f"WITH RECURSIVE {Q.with_seqs(CUSTOMERS)}, {_LENGTHS}, m AS (SELECT seq_id, i, min(p) AS len FROM g WHERE first = i GROUP BY seq_id, i), f AS (SELECT seq_id, len(t) AS size FROM seqs), s AS (SELECT seq_id, size, CAST(0 AS BIGINT) AS k, CAST(1 AS BIGINT) AS start, CAST(0 AS BIGINT) AS len, false AS complete FROM f UNION ALL SELECT s.seq_id, size, k + 1, s.start + s.len, coalesce(m.len, size - (s.start + s.len) + 1), m.len IS NOT NULL FROM s LEFT JOIN m ON m.seq_id = s.seq_id AND m.i = s.start + s.len WHERE s.start + s.len <= size), p AS (SELECT * FROM s WHERE k > 0)"


def _history_parses(kind: str):
    def run(spark, d):
        phrases = R.parse(customers(spark, d), kind)
        rates = R.parse_rate(phrases, by=["seq_id"]).join(R.parse_code_bits(phrases, 5, kind), "seq_id")
        return rates.select("seq_id", "phrases", "n", r6("mean_len").alias("mean_len"), r6("rate").alias("rate"), F.round("bits", 4).alias("bits"))

    return run


query("p1_p3_p8_dictionary_histories", f"{_DICTIONARY} {_PARSED.format('log2(k)')}")(_history_parses("dictionary"))
query("p2_p3_p8_substring_histories", f"{_SUBSTRING} {_PARSED.format('log2(greatest(start, 1)) + 2 * floor(log2(len)) + 1')}")(_history_parses("substring"))


@query("p9_decoded_parses", f"SELECT seq_id, md5(t) AS dictionary, md5(t) AS substrings FROM ({Q.DOCS27})")
def p9(spark, d):
    """Both parses decoded again: equal to the texts."""
    return R.decoded(docs27(spark, d)).select("seq_id", F.md5("dictionary").alias("dictionary"), F.md5("substring").alias("substrings"))


@query("p10_compressors")
def p10(spark, d):
    seqs = docs27(spark, d)
    rows = [R.compressor_bits(seqs, t).groupBy().agg(F.lit(t).alias("tool"), F.sum("n").alias("n"), r6(F.sum("bits") / F.sum("n")).alias("bits_per_symbol")) for t in ("zlib", "bz2", "lzma", "lzw")]
    out = rows[0]
    for r in rows[1:]:
        out = out.unionAll(r)
    return out


def _leaves_sql(n: int) -> str:
    """The leaves of the prefix trees of the first n starts."""
    return f"SELECT seq_id, 'tree{n}' AS what, string_agg(node, ',' ORDER BY node) AS answer FROM (SELECT seq_id, i, min_by(node, p) AS node FROM (SELECT seq_id, i, p, node, count(*) OVER (PARTITION BY seq_id, node) AS cnt FROM (SELECT seq_id, i, p, substr(t, i, p) AS node FROM (SELECT seq_id, t, i, unnest(range(1, len(t) - i + 2)) AS p FROM (SELECT seq_id, t, unnest(range(1, least(len(t), {n}) + 1)) AS i FROM ({CUSTOMERS}))))) WHERE cnt = 1 GROUP BY seq_id, i) GROUP BY seq_id"


_W5 = " UNION ALL ".join([
    f"SELECT * FROM ({_DICTIONARY} SELECT seq_id, 'dictionary' AS what, string_agg(substr(t, start, len), ',' ORDER BY k) AS answer FROM p GROUP BY seq_id)",
    f"SELECT * FROM ({_SUBSTRING} SELECT p.seq_id, 'substring' AS what, string_agg(substr(t, p.start, p.len), ',' ORDER BY k) AS answer FROM p JOIN seqs ON seqs.seq_id = p.seq_id GROUP BY p.seq_id)",
    f"SELECT seq_id, 'lengths' AS what, string_agg(len, ',' ORDER BY i) AS answer FROM (WITH {Q.with_seqs(CUSTOMERS)}, {_LENGTHS} SELECT seq_id, i, CAST(min(p) AS VARCHAR) AS len FROM g WHERE first = i GROUP BY seq_id, i) GROUP BY seq_id",
    _leaves_sql(4), _leaves_sql(5),
])


@query("w5_worked_parses", _W5)
def w5(spark, d):
    """Parses, repeat lengths and prefix trees of order histories, written out."""
    return worked(written(customers(spark, d), "histories"))


def worked(seqs: DataFrame) -> DataFrame:
    """seq_id, what, answer: phrases of both parses, repeat lengths, and the leaves of the prefix trees of the first 4 and 5 starts."""
    line = lambda what, key, value: [F.lit(what).alias("what"), F.array_join(F.transform(F.array_sort(F.collect_list(F.struct(F.col(key).alias("k"), value.alias("v")))), lambda r: r["v"].cast("string")), ",").alias("answer")]
    out = R.match_lengths(seqs).groupBy("seq_id").agg(*line("lengths", "pos", F.col("len")))
    for kind in ("dictionary", "substring"):
        out = out.unionAll(R.parse(seqs, kind, text=True).groupBy("seq_id").agg(*line(kind, "k", F.col("w"))))
    for n in (4, 5):
        out = out.unionAll(R.prefix_tree(seqs, n).where("is_leaf").groupBy("seq_id").agg(*line(f"tree{n}", "node", F.col("node"))))
    return out


# --- context trees and prediction ------------------------------------------------------------------------------------


@query("c2_context_counts", f"WITH e AS ({Q.places(Q.DOCS27, 3)}), r AS (SELECT t, e, unnest(range(0, least(3, e - 1) + 1)) AS depth FROM e) SELECT CAST(depth AS INTEGER) AS depth, substr(t, e - depth, depth) AS ctx, substr(t, e, 1) AS sym, count(*) AS cnt FROM r GROUP BY ALL")
def c2(spark, d):
    return P.context_counts(S.chunks(docs27(spark, d), 3), 3)


@query("c1_suffix_tree_counts", f"WITH e AS ({Q.places(_BITS2, 2)}), r AS (SELECT t, e, unnest(range(0, least(2, e - 1) + 1)) AS depth FROM e), c AS (SELECT substr(t, e - depth, depth) AS ctx, substr(t, e, 1) AS sym FROM r) SELECT ctx, sym, count(*) AS cnt FROM c WHERE ctx IN ('', '1', '11') GROUP BY ctx, sym")
def c1(spark, d):
    """Trees of binary order histories: what followed 1 and 11, and the symbols' own counts."""
    return P.context_counts(S.chunks(customer_bits(spark, d), 2), 2).where("ctx in ('', '1', '11')").select("ctx", "sym", "cnt")


def _tree_statistics(tree: str, order: int) -> str:
    alive = " UNION ALL ".join(f"SELECT {j} AS depth, seq_id, key FROM b{j} WHERE alive" for j in range(order + 1))
    least = "WHERE visits > 1" if tree == "full" else ""
    return f"SELECT '{tree}' AS tree, CAST(depth AS INTEGER) AS depth, count(*) AS nodes, CAST(sum(visits) AS BIGINT) AS visits FROM (WITH {Q.levels(order, 5, 0.5, 'fixed', tree=tree)} SELECT depth, seq_id, key, count(*) AS visits FROM ({alive}) GROUP BY ALL) {least.replace('visits', '(depth = 0 OR visits')}{')' if least else ''} GROUP BY depth"


@query("c3_c6_tree_statistics_users", f"WITH {Q.with_seqs(USERS)}, {Q.events(4)} {_tree_statistics('full', 4)} UNION ALL {_tree_statistics('incremental', 4)}")
def c6u(spark, d):
    """Nodes and visits by depth of the trees of user histories."""
    out = None
    for tree in ("full", "incremental"):
        s = P.tree_statistics(users(spark, d), Tree(5, 4, tree))
        row = s.groupBy(F.lit(tree).alias("tree"), "depth").agg(F.sum("nodes").alias("nodes"), F.sum("visits").alias("visits"))
        out = row if out is None else out.unionAll(row)
    return out


@query("c1_suffix_words", f"WITH {Q.with_seqs(_BITS2)}, k AS (SELECT seq_id, '01101' || t AS s, unnest(range(1, len(t) + 1)) AS k FROM seqs), w AS (SELECT seq_id, s, k, unnest(range(1, k + 6)) AS p FROM k), own AS (SELECT seq_id, substr(s, k + 6 - p, p) AS word, min(k) AS k, min(p) AS p FROM w GROUP BY seq_id, substr(s, k + 6 - p, p) HAVING count(*) = 1) SELECT seq_id, CAST(k AS INTEGER) AS k, min_by(word, p) AS word FROM own GROUP BY seq_id, k")
def c1w(spark, d):
    """Suffix trees of binary order histories after an aperiodic precursor: the leaf of every position."""
    return R.suffix_words(customer_bits(spark, d), "01101").select("seq_id", F.col("k").cast("int").alias("k"), "word")


_ROOT = S.root_half(24)


@query("s8_counts_after_a_precursor", f"WITH seqs AS (SELECT seq_id, '{_ROOT}' || translate(t, '01234', '00111') AS t FROM ({CUSTOMERS})), e AS ({Q.places('SELECT * FROM seqs', 3)}), r AS (SELECT t, e, unnest(range(0, least(3, e - 1) + 1)) AS depth FROM e) SELECT CAST(depth AS INTEGER) AS depth, substr(t, e - depth, depth) AS ctx, substr(t, e, 1) AS sym, count(*) AS cnt FROM r GROUP BY ALL")
def s8(spark, d):
    """Contexts of binary histories that begin after a fixed aperiodic precursor."""
    bits = customers(spark, d).select("seq_id", F.translate("t", "01234", "00111").alias("t"))
    return P.context_counts(S.chunks(S.with_precursor(bits, _ROOT), 3), 3)


@query("s6_sign_partition", "SELECT user_id AS seq_id, md5(string_agg(CASE WHEN value - 50 >= 0 THEN '1' ELSE '0' END, '' ORDER BY ts, event_id)) AS digest FROM events WHERE user_id IS NOT NULL AND value IS NOT NULL GROUP BY user_id")
def s6(spark, d):
    """Event values as above or below 50, a binary sequence for each user."""
    e = table(spark, d, "events")
    rows = S.symbols_from_events(e, "user_id", ["ts", "event_id"], S.sign_partition(F.col("value") - 50))
    both = S.gather(rows.join(F.broadcast(spark.createDataFrame([("0",), ("1",)], "sym string")), "sym"))
    return both.select("seq_id", F.md5("t").alias("digest"))


@query("c3_c6_tree_statistics")
def c6(spark, d):
    """Nodes and depth of the full and the incremental trees of whole documents."""
    out = None
    for tree in ("full", "incremental"):
        s = P.tree_statistics(docs27(spark, d), Tree(27, 24, tree))
        row = s.groupBy(F.lit(tree).alias("tree"), "depth").agg(F.sum("nodes").alias("nodes"), F.sum("visits").alias("visits"))
        out = row if out is None else out.unionAll(row)
    return out


def _rate(seqs: DataFrame, t: Tree) -> DataFrame:
    return P.gamble(seqs, {"r": t}).agg(F.sum("n").cast("long").alias("n"), r6(F.sum("nats") / F.sum("n") / math.log(2)).alias("bits"))


for _order in (0, 1, 2, 3):
    query(f"e6_fixed_order_{_order}", f"WITH {Q.with_seqs(Q.DOCS27)}, {Q.events(_order)}, {Q.levels(_order, 27, 1 / 27, 'fixed')} {Q.RATE}")(lambda spark, d, order=_order: _rate(docs27(spark, d), Tree(27, order, beta=1 / 27, rule="fixed")))

for _tree in ("full", "incremental"):
    for _rule, _delta in (("shortest_gain", 0.0), ("deepest_gain", 2.0), ("walk_gain", 2.0), ("min_total_gain", 2.0), ("deepest", 0.0), ("blend", 0.0)):
        _t = dict(order=3, beta=0.5, rule=_rule, delta=_delta, tree=_tree)
        query(f"e5_{_rule}_{_tree}_users", f"WITH {Q.with_seqs(USERS)}, {Q.events(3)}, {Q.levels(3, 5, 0.5, _rule, _delta, _tree)} {Q.RATE}")(lambda spark, d, t=_t: _rate(users(spark, d), Tree(5, **t)))

query("e5_shortest_gain_documents", f"WITH {Q.with_seqs(Q.DOCS27)}, {Q.events(3)}, {Q.levels(3, 27, 1 / 27, 'shortest_gain')} {Q.RATE}")(lambda spark, d: _rate(docs27(spark, d), Tree(27, 3, beta=1 / 27)))
query("e8_blend_documents", f"WITH {Q.with_seqs(Q.DOCS27)}, {Q.events(3)}, {Q.levels(3, 27, 1 / 27, 'blend')} {Q.RATE}")(lambda spark, d: _rate(docs27(spark, d), Tree(27, 3, beta=1 / 27, rule="blend")))


@query("e4_window_engine", f"WITH {Q.with_seqs(USERS)}, {Q.events(2)}, {Q.levels(2, 5, 0.5, 'min_total_gain', 2.0, 'incremental')} SELECT seq_id, count(*) AS n, round(sum(-ln(p)), 6) AS nats FROM pred GROUP BY seq_id")
def e4(spark, d):
    """The same by windows over rows of events, counts in blocks of positions."""
    ev = S.events(S.chunks(users(spark, d), 2), 2)
    pred = P.window_predictions(ev, Tree(5, 2, "incremental", 0.5, "min_total_gain", 2.0), block=512, crowded=0)
    return pred.groupBy("seq_id").agg(F.count("*").alias("n"), r6(F.sum(-F.ln("p"))).alias("nats"))


@query("e7_static_blend")
def e7(spark, d):
    seqs = docs27(spark, d)
    t = Tree(27, 3, beta=1 / 27, rule="blend")
    c, n, nats = P.static_fit(seqs, t)
    row = (n, nats / n / math.log(2)) if n else (None, None)
    rate = spark.createDataFrame([row], "n long, bits double").withColumn("bits", r6(F.col("bits")))
    return rate.withColumn("weights", F.lit(",".join(f"{x:.4f}" for x in c)))


_STATIC = [0.1, 0.2, 0.3, 0.4]


@query("e7_given_weights", f"WITH {Q.with_seqs(USERS)}, {Q.events(3)}, {Q.levels(3, 5, 0.5, 'blend', static=_STATIC)} {Q.RATE}")
def e7g(spark, d):
    """Blend with given weights of the levels, the same for all positions."""
    return _rate(users(spark, d), Tree(5, 3, rule="blend", static=_STATIC))


@query("e9_tree_mixture", f"WITH {Q.with_seqs(_BITS2)}, {Q.events(4)}, {Q.mixture(4, 2)} SELECT (SELECT count(*) FROM ev) AS n, round(-sum(w) / (SELECT count(*) FROM ev) / {Q.LN2!r}, 6) AS bits FROM w0")
def e9(spark, d):
    """Mixture over all binary trees of depth 4, of order histories as above or below the middle priority."""
    bits = customers(spark, d).select("seq_id", F.translate("t", "01234", "00111").alias("t"))
    return P.tree_mixture(bits, 4, 2).agg(F.sum("n").alias("n"), r6(F.sum("nats") / F.sum("n") / math.log(2)).alias("bits"))


_FORECAST = "WITH c AS ({s}), r AS (SELECT t, e, unnest(range(0, least(3, e - 1) + 1)) AS depth FROM c), k AS (SELECT depth, substr(t, e - depth, depth) AS ctx, substr(t, e, 1) AS sym, count(*) AS cnt FROM r GROUP BY ALL), own AS (SELECT * FROM k WHERE ends_with('{x}', ctx) QUALIFY depth = max(depth) OVER ()), l AS (SELECT substr('abcdefghijklmnopqrstuvwxyz ', unnest(range(1, 28)), 1) AS sym) SELECT l.sym, round((coalesce(cnt, 0) + 1.0 / 27) / ((SELECT sum(cnt) FROM own) + 1), 6) AS p FROM l LEFT JOIN own ON l.sym = own.sym"


@query("e11_next_letter", _FORECAST.format(s=Q.places(Q.DOCS27, 3), x="and th"))
def e11(spark, d):
    counts = P.context_counts(S.chunks(docs27(spark, d), 3), 3)
    return P.forecast(counts, "and th", 27, 1 / 27, list("abcdefghijklmnopqrstuvwxyz ")).select("sym", r6("p").alias("p"))


# --- measures --------------------------------------------------------------------------------------------------------


@query("a1_rate_by_language", f"WITH {Q.with_seqs(Q.DOCS27)}, {Q.events(2)}, {Q.levels(2, 27, 0.5, 'fixed')} SELECT lang, count(*) AS n, round(sum(-ln(p)) / count(*) / {Q.LN2!r}, 6) AS bits FROM pred JOIN documents ON doc_id = seq_id GROUP BY lang")
def a1(spark, d):
    g = P.gamble(docs27(spark, d), {"r": Tree(27, 2, rule="fixed")})
    lang = table(spark, d, "documents").select(F.col("doc_id").alias("seq_id"), "lang")
    return g.join(lang, "seq_id").groupBy("lang").agg(F.sum("n").cast("long").alias("n"), r6(F.sum("nats") / F.sum("n") / math.log(2)).alias("bits"))


@query("a2_final_capital", f"WITH {Q.with_seqs(USERS)}, {Q.events(1)}, {Q.levels(1, 5, 0.5, 'fixed')} SELECT seq_id, max(pos) AS n, round(sum(ln(5.0) + ln(p)), 6) AS log_capital FROM pred GROUP BY seq_id")
def a2(spark, d):
    pred = P.predictions(users(spark, d), Tree(5, 1, rule="fixed"))
    return G.capital_curve(pred, 5).groupBy("seq_id").agg(F.max("pos").alias("n"), r6(F.max_by("log_capital", "pos")).alias("log_capital"))


@query("a4_arithmetic_code", f"WITH {Q.with_seqs(USERS)}, {Q.events(1)}, {Q.levels(1, 5, 0.5, 'fixed')} SELECT seq_id, CAST(ceil(round(sum(-log2(p)), 6)) + 2 AS BIGINT) AS bits FROM pred GROUP BY seq_id")
def a4(spark, d):
    return G.arithmetic_code_bits(P.predictions(users(spark, d), Tree(5, 1, rule="fixed")))


@query("a5_convergence", f"WITH {Q.with_seqs(USERS)}, {Q.events(2)}, {Q.levels(2, 5, 0.5, 'deepest_gain', 2.0)}, g AS (SELECT unnest([50, 100, 200, 400]) AS n) SELECT CAST(n AS BIGINT) AS n, round(avg(h), 6) AS h, count(*) AS replicas FROM (SELECT seq_id, n, sum(-ln(p)) / n / {Q.LN2!r} AS h, count(*) AS k FROM pred JOIN g ON pos <= n GROUP BY seq_id, n HAVING count(*) = n) GROUP BY n")
def a5(spark, d):
    grid = [50, 100, 200, 400]
    g = P.gamble(users(spark, d), {"r": Tree(5, 2, rule="deepest_gain", delta=2.0)}, grid)
    return G.mean_curve(G.curve(g.where(F.col("n").isin(grid)), by=["seq_id"])).select("n", r6("h").alias("h"), "replicas")


# --- dynamical sources -----------------------------------------------------------------------------------------------

_ORBIT = "WITH RECURSIVE s AS (SELECT DISTINCT CAST(c_custkey AS DOUBLE) * CAST(0.6180339887 AS DOUBLE) AS turn, c_custkey AS seq_id FROM customer), o AS (SELECT seq_id, 0 AS pos, CAST(-0.9 AS DOUBLE) + CAST(1.8 AS DOUBLE) * (turn - floor(turn)) AS x FROM s UNION ALL SELECT seq_id, pos + 1, CAST(1 AS DOUBLE) - CAST(1.8 AS DOUBLE) * x * x FROM o WHERE pos < 40)"


@query("g1_map_orbits", f"{_ORBIT} SELECT seq_id, CAST(pos AS BIGINT) AS pos, round(x, 6) AS x FROM o WHERE pos > 0")
def g1(spark, d):
    return D.map_series(D.seeds(table(spark, d, "customer"), "c_custkey"), "quadratic", 40).select("seq_id", "pos", r6("x").alias("x"))


@query("y1_lyapunov_from_orbits", f"{_ORBIT} SELECT seq_id, round(avg(ln(abs(CAST(3.6 AS DOUBLE) * x))), 6) AS lyapunov FROM o WHERE pos > 0 GROUP BY seq_id")
def y1(spark, d):
    series = D.map_series(D.seeds(table(spark, d, "customer"), "c_custkey"), "quadratic", 40)
    return D.lyapunov_1d(series, 1.8).select("seq_id", r6("lyapunov").alias("lyapunov"))


@query("y1_y2_lyapunov_exponents")
def y2(spark, d):
    """All maps' exponents against their known entropies (nats)."""
    start = D.seeds(table(spark, d, "customer"), "c_custkey", 50)
    out = None
    for name, kind, a, known in (("quadratic 1.8", "quadratic", D.CHAOTIC, 0.40495), ("quadratic 1.7499", "quadratic", D.INTERMITTENT, 0.1884), ("plane", "plane", D.PLANE_A, 0.4199), ("laser", "laser", 0.0, 0.5076)):
        small = start.select("seq_id", (F.col("x0") * (0.1 if kind == "plane" else 1.0)).alias("x0"))
        row = D.lyapunov(small, kind, 20000, a=a).agg(F.lit(name).alias("workload"), F.avg("lyapunov").alias("estimate"), F.lit(known).alias("reference"))
        out = row if out is None else out.unionAll(row)
    return G.accuracy(out)


_BITS = "SELECT l_suppkey AS seq_id, string_agg(CASE WHEN CAST('0x' || substr(md5(concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey)), 1, 8) AS BIGINT) < 214748364 THEN '0' ELSE '1' END, '' ORDER BY l_orderkey, l_linenumber, l_partkey, l_shipdate) AS t FROM lineitem GROUP BY l_suppkey"


def supplier_bits(spark, d) -> DataFrame:
    return line_bits(spark, d)


def line_bits(spark, d, groups: int | None = None) -> DataFrame:
    """Biased bits from hashes of line items, a sequence for each supplier, or for each of some groups of suppliers."""
    from pyspark.sql import Window

    rows = table(spark, d, "lineitem").withColumn("group", F.pmod("l_suppkey", F.lit(groups)) if groups else F.col("l_suppkey"))
    pos = F.row_number().over(Window.partitionBy("group").orderBy("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate") if groups else Window.partitionBy("group").orderBy("l_orderkey", "l_linenumber", "l_partkey", "l_shipdate"))
    return S.gather(D.bernoulli_bits(rows.withColumn("pos", pos), "group", "pos", ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"], 0.05))


def _taps(steps: int) -> str:
    return " + ".join(f"CAST(substr(t, CAST(i AS INTEGER) + ({o}), 1) AS INTEGER)" for o in D.odd_offsets(steps))


@query("g4_g5_automaton", f"WITH {Q.with_seqs(_BITS)} " + " UNION ALL ".join(f"SELECT {s} AS steps, seq_id, md5(array_to_string(list_transform(range({s + 1}, len(t) - {s} + 1), lambda i: CAST(({_taps(s)}) % 2 AS VARCHAR)), '')) AS digest FROM seqs WHERE len(t) > {2 * s}" for s in (2, 4, 6)))
def g4(spark, d):
    bits = supplier_bits(spark, d)
    out = None
    for s in (2, 4, 6):
        row = D.automaton_150(bits, s).select(F.lit(s).alias("steps"), "seq_id", F.md5("t").alias("digest"))
        out = row if out is None else out.unionAll(row)
    return out


_H2 = "CASE WHEN {0} > 0 AND {0} < 1 THEN -({0} * log2({0}) + (1 - {0}) * log2(1 - {0})) ELSE 0.0 END"


@query("y3_exact_rates", f"WITH e AS ({Q.places(_BITS2, 1)}), c AS (SELECT avg(CASE WHEN substr(t, e, 1) = '1' THEN 1.0 ELSE 0.0 END) AS p, avg(CASE WHEN substr(t, e, 1) = '1' THEN 1.0 ELSE 0.0 END) FILTER (e > 1 AND substr(t, e - 1, 1) = '0') AS a, avg(CASE WHEN substr(t, e, 1) = '0' THEN 1.0 ELSE 0.0 END) FILTER (e > 1 AND substr(t, e - 1, 1) = '1') AS b FROM e) SELECT 'bits' AS source, round({_H2.format('p')}, 6) AS bits FROM c UNION ALL SELECT 'chain', round((b * {_H2.format('a')} + a * {_H2.format('b')}) / (a + b), 6) FROM c UNION ALL SELECT 'letters', round(log2(count(DISTINCT o_orderpriority)), 6) FROM orders")
def y3(spark, d):
    """Exact rates of biased bits and of a chain of order 1 that have the frequencies of binary order histories, and of as many equally likely letters as there are priorities."""
    c = {(r.ctx, r.sym): r.cnt for r in P.context_counts(S.chunks(customer_bits(spark, d), 1), 1).collect()}
    share = lambda ctx: [c.get((ctx, s), 0) / (c.get((ctx, "0"), 0) + c.get((ctx, "1"), 0)) for s in "01"]
    letters = table(spark, d, "orders").select(F.countDistinct("o_orderpriority")).first()[0]
    rows = [("bits", D.entropy_bernoulli(share("")[1])), ("chain", D.entropy_markov([share("0"), share("1")])), ("letters", math.log2(letters))]
    return spark.createDataFrame(rows, "source string, bits double").select("source", r6("bits").alias("bits"))


@query("y4_accuracy", f"WITH {Q.with_seqs(Q.DOCS27)}, {Q.words(4)}, {Q.block_entropy(27)}, x AS (SELECT n, max(h_block) FILTER (method = 'plugin') AS a, max(h_block) FILTER (method = 'digamma_parity') AS b FROM h GROUP BY n) SELECT n, round((a - b) / b, 6) AS rel_error, a >= b AS is_above, round(a / log2(27), 6) AS ratio FROM x")
def y4(spark, d):
    """How far the likelihood estimate is under the corrected one, and both against a plain code."""
    h = B.block_entropy(B.block_counts_arrow(docs27(spark, d), 4), 27, methods=["plugin", "digamma_parity"])
    both = h.groupBy("n").agg(F.max(F.when(F.col("method") == "plugin", F.col("h_block"))).alias("estimate"), F.max(F.when(F.col("method") != "plugin", F.col("h_block"))).alias("reference"))
    return G.accuracy(both, 27).select("n", r6("rel_error").alias("rel_error"), "is_above", r6("ratio").alias("ratio"))


_CHAINS = [[[0.9, 0.1], [0.3, 0.7]], [[0.9, 0.1], [0.2, 0.8], [0.5, 0.5], [0.7, 0.3], [0.1, 0.9], [0.6, 0.4], [0.3, 0.7], [0.8, 0.2]]]


@query("g6_y3_chains_with_known_rates")
def g6(spark, d):
    """Chains of order 1 and 3, driven by hashes of events, a replica for every 20,000 event ids: prediction against the exact rate."""
    e = table(spark, d, "events").where("event_id is not null").withColumn("replica", F.floor(F.col("event_id") / 20_000))
    seqs = None
    for k, p in enumerate(_CHAINS):
        own = D.hashed_chains(e, "replica", "event_id", ["event_id", "user_id", "event_type"], p).select((F.col("seq_id") * 2 + k).alias("seq_id"), "t")
        seqs = own if seqs is None else seqs.unionAll(own)
    rates = P.gamble(seqs, {"shortest_gain": Tree(2, 8), "min_total_gain": Tree(2, 8, rule="min_total_gain", delta=2.0), "blend": Tree(2, 8, rule="blend"), "fixed 3": Tree(2, 3, rule="fixed")})
    out = rates.groupBy(F.pmod("seq_id", F.lit(2)).alias("seq_id"), "method").agg((F.sum("nats") / F.sum("n") / math.log(2)).alias("estimate"))
    exact = F.when(F.col("seq_id") == 0, D.entropy_markov(_CHAINS[0])).otherwise(D.entropy_markov(_CHAINS[1]))
    return G.accuracy(out.withColumn("reference", exact))


# --- workloads -------------------------------------------------------------------------------------------------------


@query("w1_plane_map_blocks")
def w1(spark, d):
    """Block entropies of the plane map's bits against the length, with its Lyapunov exponent (nats)."""
    start = D.seeds(table(spark, d, "supplier"), "s_suppkey", 10).select("seq_id", (F.col("x0") * 0.1).alias("x0"))
    seqs = D.map_symbols(start, "plane", 20000, a=D.PLANE_A)
    h = B.block_curve(S.chunks(seqs, 24), [8, 12, 20, 22, 24, 25], [1000, 4000, 20000], 2, "nats", ["plugin", "digamma_parity"], by=["seq_id"])
    return h.groupBy("length", "n", "method").agg(F.avg("h_per_symbol").alias("h_per_symbol"), F.avg("h_diff").alias("h_diff"))


def _repeat_workload(a: float):
    def run(spark, d):
        seqs = D.map_symbols(D.seeds(table(spark, d, "customer"), "c_custkey", 50), "quadratic", 20000, a=a)
        curve = R.repeat_curve(R.match_lengths(seqs), G.geometric_grid(20000), "nats", by=["seq_id"])
        return G.mean_curve(curve)

    return run


query("w3_repeat_rate_chaotic")(_repeat_workload(D.CHAOTIC))
query("w4_repeat_rate_accumulation")(_repeat_workload(D.ACCUMULATION))


def _length(spark, d, most: int = 10**6) -> int:
    """Symbols of a replica: 20,000 on the smaller tables, then in proportion to them, to the experiments' million."""
    return min(most, max(20_000, 13 * table(spark, d, "customer").count()))


def _map_workload(kind: str, a: float, known: float, h0: float | None = None, replicas: int = 50, most: int = 10**6):
    """Gambling by full trees, as deep as contexts repeat."""

    def run(spark, d):
        n = _length(spark, d, most)
        start = D.seeds(table(spark, d, "customer"), "c_custkey", replicas).repartition(replicas)
        seqs = D.map_symbols(start, kind, n, a=a)
        trees = {"shortest_gain": Tree(2), "min_total_gain": Tree(2, rule="min_total_gain", delta=2.0), "deepest_gain": Tree(2, rule="deepest_gain", delta=2.0)}
        curve = G.mean_curve(G.curve(P.gamble(seqs, trees, G.geometric_grid(n)), "nats", by=["seq_id", "method"]), by=["method"])
        curve = written(curve, "curve")
        last = curve.groupBy("method").agg(F.max_by("h", "n").alias("h_last"), F.max("n").alias("n"))
        return G.fit_tail(curve, by=["method"], h0=h0).join(last, "method").withColumn("reference", F.lit(known))

    return run


query("w7_gambling_chaotic")(_map_workload("quadratic", D.CHAOTIC, 0.405))
query("w7_gambling_intermittent")(_map_workload("quadratic", D.INTERMITTENT, 0.184))
query("w8_gambling_accumulation")(_map_workload("quadratic", D.ACCUMULATION, 0.0, h0=0.0, replicas=8, most=10_000))
query("w9_gambling_laser")(_map_workload("laser", 0.0, 0.508))


@query("w10_gambling_automaton")
def w10(spark, d):
    """Rule 150 after 0, 2, 4 and 6 steps, by full trees: last rates and fitted limits against that of the bits (0.286 bits)."""
    bits = written(line_bits(spark, d, 10), "bits").repartition(10)  # a task for each sequence
    out = None
    for s in (0, 2, 4, 6):
        seqs = bits if not s else D.automaton_150(bits, s)
        g = P.gamble(seqs, {"min_total_gain": Tree(2, rule="min_total_gain", delta=2.0), "shortest_gain": Tree(2)}, G.geometric_grid(100_000))
        row = G.curve(g, by=["seq_id", "method"]).select("seq_id", F.concat_ws(" ", F.lit(s).cast("string"), "method").alias("method"), "n", "h")
        out = row if out is None else out.unionAll(row)
    curve = G.mean_curve(out, by=["method"]).where("replicas >= 5")
    curve = written(curve, "curve")
    fit = G.fit_tail(curve, by=["method"], least_n=500).select("method", F.col("h").alias("estimate"), "gamma", "ok")
    both = fit.join(curve.groupBy("method").agg(F.max_by("h", "n").alias("h_last"), F.max("n").alias("n")), "method").withColumn("reference", F.lit(D.entropy_bernoulli(0.05)))
    return G.accuracy(both)


# --- corpora as one sequence -----------------------------------------------------------------------------------------

CORPORA = ["en", "de", "fr", "es", "conversations", "benchmark"]


def one_line(seqs: DataFrame, left: int, size: int = K.BLOCK, number: int = 0) -> DataFrame:
    """Sequences as one; they are written first, else their texts are made anew for each pass over their lengths."""
    return S.corpus_chunks(written(seqs, "texts"), left, size, number)


def corpora(spark, d, left: int, names: list[str], size: int = K.BLOCK) -> DataFrame:
    """Each corpus as one sequence (seq_id its place in CORPORA), its texts in the order of their ids."""
    out = None
    for name in names:
        seqs = turns27(spark, d) if name == "conversations" else bench27(spark, d) if name == "benchmark" else S.sequences(table(spark, d, "documents").where(F.col("lang") == name), "doc_id", S.normalise_27(F.col("text")))
        part = one_line(seqs, left, size, CORPORA.index(name))
        out = part if out is None else out.unionAll(part)
    return written(out, "corpora")


def corpus_bits(chunked: DataFrame, trees: dict[str, Tree]) -> DataFrame:
    """n, and the bits a symbol of each tree (trees differ in rule and order alone)."""
    sums = K.code_lengths(chunked, trees)
    return sums.agg(F.sum("n").alias("n"), *((F.sum(c) / F.sum("n") / math.log(2)).alias(c) for c in trees))


def corpus_information(chunked: DataFrame, t: Tree) -> DataFrame:
    """letter_no, n, bits: mean information of the letters by their place in the word, as ``language.info_by_letter``."""
    sums = K.code_lengths(chunked, {"p": t}, "letter")
    return sums.groupBy(F.col("bin").cast("int").alias("letter_no")).agg(F.sum("n").alias("n"), (F.sum("p") / F.sum("n") / math.log(2)).alias("bits"))


def _corpus_sql(names: list[str], source: str = "{}") -> str:
    lang = "SELECT * FROM (SELECT doc_id AS seq_id, trim(regexp_replace(lower(text), '[^a-z]+', ' ', 'g')) AS t FROM documents WHERE text IS NOT NULL AND lang = '{}') WHERE t <> ''"
    return " UNION ALL ".join(f"SELECT {CORPORA.index(n)} AS seq_id, string_agg(t, ' ' ORDER BY seq_id) || ' ' AS t FROM ({lang.format(n)})" for n in names)


@query("w11_corpora")
def w11(spark, d):
    """Six corpora, each bet on as one sequence: incremental tree of up to 8 letters, beta 1/27; last rate and the limit of the curve."""
    sums = K.code_lengths(corpora(spark, d, 8, CORPORA), {"nats": Tree(27, 8, "incremental", 1 / 27)}, G.geometric_grid(10**8, 1000)[:-1])
    curve = written(G.curve_of_bins(sums.select("seq_id", F.col("bin").alias("n"), "last", "nats"), ["seq_id"]), "curve")
    fit = G.fit_tail(curve, by=["seq_id"])
    last = curve.groupBy("seq_id").agg(F.max_by("h", "n").alias("h_last"), F.max("n").alias("n"))
    name = F.element_at(F.array(*(F.lit(c) for c in CORPORA)), (F.col("seq_id") + 1).cast("int"))
    return fit.join(last, "seq_id").select(name.alias("corpus"), "n", "h_last", "h", "c", "gamma", "sse", "n_points", "ok")


_GRID11 = [1000, 3000, 10000, 30000, 100000]


@query("w11_corpus_curves", f"WITH seqs AS ({_corpus_sql(['de', 'fr', 'es'])}), {Q.line_events(4)}, {Q.levels(4, 27, 1 / 27, 'shortest_gain', tree='incremental')}, g AS (SELECT unnest({_GRID11}) AS n) SELECT seq_id, CAST(n AS BIGINT) AS n, round(sum(-ln(p)) / n / {Q.LN2!r}, 6) AS h FROM pred JOIN g ON pos <= n GROUP BY seq_id, n HAVING count(*) = n")
def w11c(spark, d):
    """Convergence of the incremental tree's code on whole corpora."""
    sums = K.code_lengths(corpora(spark, d, 4, ["de", "fr", "es"]), {"nats": Tree(27, 4, "incremental", 1 / 27)}, _GRID11)
    return G.curve_of_bins(sums.select("seq_id", F.col("bin").alias("n"), "last", "nats"), ["seq_id"]).select(F.col("seq_id").cast("int").alias("seq_id"), "n", r6("h").alias("h"))


@query("w12_ascii_against_compressors")
def w12(spark, d):
    """7-bit English as one sequence: gambling and blending against general compressors (on stretches of a million characters), bits a character."""
    seqs = S.sequences(table(spark, d, "documents").where("lang = 'en'"), "doc_id", S.ascii7(F.col("text")))
    seqs = written(seqs, "texts")
    chunked = written(S.corpus_chunks(seqs, 6, K.BLOCK), "ascii")
    out = None
    for name, t in (("shortest_gain", Tree(128, 6, "incremental", 1 / 128)), ("blend", Tree(128, 6, "full", 1 / 128, "blend"))):
        row = corpus_bits(chunked, {"bits": t}).select(F.lit(name).alias("method"), "bits")
        out = row if out is None else out.unionAll(row)
    whole = written(S.corpus_chunks(seqs, 0, 1 << 20).select(F.col("start").alias("seq_id"), F.col("body").alias("t")), "stretches")
    for tool in ("zlib", "bz2", "lzma", "lzw"):
        out = out.unionAll(R.compressor_bits(whole, tool).agg(F.lit(tool).alias("method"), (F.sum("bits") / F.sum("n")).alias("bits")))
    return out


_W13 = " UNION ALL ".join(f"SELECT {n} AS n, bits FROM (WITH {Q.levels(n - 1, 27, 1 / 27, 'shortest_gain', tree='incremental')} {Q.RATE})" for n in (4, 5, 6))


@query("w13_truncated_trees", f"WITH seqs AS ({_corpus_sql(['en'])}), {Q.line_events(5)}, words AS (SELECT past || sym AS w, unnest(range(1, len(past) + 2)) AS n FROM events), counts AS (SELECT CAST(n AS INTEGER) AS n, right(w, n) AS word, count(*) AS cnt FROM words GROUP BY ALL), {Q.block_entropy(27)}, r AS (SELECT n, h_block - lag(h_block) OVER (ORDER BY n) AS reference FROM h WHERE method = 'digamma_parity'), x AS ({_W13}) SELECT CAST(x.n AS INTEGER) AS n, bits AS estimate, round(reference, 6) AS reference, bits >= reference AS is_above FROM x JOIN r ON r.n = x.n")
def w13(spark, d):
    """English as one sequence: trees cut at depth 3, 4, 5 against block entropies of 4, 5, 6 letters of the same text."""
    chunked = corpora(spark, d, 5, ["en"])
    trees = {f"p{n}": Tree(27, n - 1, "incremental", 1 / 27) for n in (4, 5, 6)}
    rates = corpus_bits(chunked, trees)
    g = rates.select(F.explode(F.array(*(F.struct(F.lit(n).alias("n"), F.col(f"p{n}").alias("estimate")) for n in (4, 5, 6)))).alias("x")).select("x.*")
    h = B.block_entropy(B.block_counts(chunked, 6), 27, methods=["digamma_parity"]).select("n", F.col("h_diff").alias("reference"))
    return G.accuracy(g.join(h, "n")).select("n", r6("estimate").alias("estimate"), r6("reference").alias("reference"), "is_above")


def english_tree(spark, d, order: int, letters: int | None = None) -> tuple[DataFrame, DataFrame]:
    """The incremental tree that the first letters of the English corpus leave (all of it without a number)."""
    chunked = corpora(spark, d, order, ["en"])
    if letters:
        whole = -(-letters // S.CHUNK) * S.CHUNK
        chunked = chunked.where(F.col("start") <= whole).withColumn("body", F.left("body", (F.lit(whole + 1) - F.col("start")).cast("int")))
    t = Tree(27, order, "incremental", 1 / 27)
    nodes, cells = K.tree_of(chunked, t)
    return nodes, written(cells, "cells")


@query("w14_greedy_continuation")
def w14(spark, d):
    """Most probable continuations of the benchmark's texts by trees trained on growing parts of the English corpus, and the share of words the training text doesn't have."""
    prompts = bench27(spark, d).select("seq_id", F.right("t", F.lit(12)).alias("t"))
    seqs = english(spark, d)
    placed = written(seqs.join(S.offsets(seqs), "seq_id"), "placed")
    out = None
    for size in (100_000, 1_000_000, 5_500_000):  # the experiment's training sizes
        nodes, cells = english_tree(spark, d, 5, size)
        new = L.generate_greedy(prompts, nodes, cells, 60, 5)
        share = L.unknown_word_share(new.select("seq_id", F.col("continuation").alias("t")), placed.where(F.col("offset") < size).select("seq_id", "t"))
        row = share.select(F.lit(size).alias("letters"), "words", "unknown", "share")
        out = row if out is None else out.unionAll(row)
    return out


_TEST = f"tseqs AS ({Q.BENCH27}), {Q.line_events(3, 'tseqs', 'tests')}"
_PATH = "asked AS (SELECT t.*, g1.gain AS g1, g2.gain AS g2, g3.gain AS g3 FROM tests t LEFT JOIN nodes g1 ON g1.depth = 1 AND len(past) >= 1 AND g1.ctx = right(past, 1) LEFT JOIN nodes g2 ON g2.depth = 2 AND len(past) >= 2 AND g2.ctx = right(past, 2) LEFT JOIN nodes g3 ON g3.depth = 3 AND len(past) >= 3 AND g3.ctx = right(past, 3)), chosen AS (SELECT *, CASE WHEN g1 IS NULL OR g1 >= 0 THEN 0 WHEN g2 IS NULL OR g2 >= 0 THEN 1 WHEN g3 IS NULL OR g3 >= 0 THEN 2 ELSE 3 END AS depth FROM asked)"


@query("w15_forecast_table", f"WITH seqs AS ({_corpus_sql(['en'])}), {Q.line_events(3)}, {Q.levels(3, 27, 1 / 27, 'fixed', tree='incremental')}, {Q.trained(3)}, {_TEST}, {_PATH}, o AS (SELECT seq_id, pos, c.sym AS actual, k.sym AS letter, (cnt + {1 / 27!r}) / (sum(cnt) OVER (PARTITION BY seq_id, pos) + 1) AS p FROM chosen c JOIN cells k ON k.depth = c.depth AND k.ctx = CASE WHEN c.depth > 0 THEN right(past, c.depth) ELSE '' END) SELECT seq_id, pos, actual, CAST(row_number() OVER (PARTITION BY seq_id, pos ORDER BY p DESC, letter) AS INTEGER) AS rank, letter, round(p, 6) AS p, CASE WHEN p >= 0.6 THEN '0.6' WHEN p >= 0.25 THEN '0.25' ELSE '0.1' END AS band FROM o WHERE p >= 0.1")
def w15(spark, d):
    """Letters forecast at every place of the benchmark's texts by the English corpus's tree: contexts chosen by the gains they have reached."""
    nodes, cells = english_tree(spark, d, 3)
    ev = S.events(S.chunks(bench27(spark, d), 3), 3)
    return L.forecast_table(ev, written(nodes, "nodes"), cells, 3, 27, 1 / 27).withColumn("p", r6("p"))


@query("w16_scramble_gap")
def w16(spark, d):
    """English as one sequence and with every text's words scrambled: incremental tree of up to 6 letters."""
    seqs = english(spark, d)
    rates = []
    for number, s in enumerate((seqs, S.scramble_words(seqs))):
        rates.append(corpus_bits(written(one_line(s, 6), "corpora"), {"bits": Tree(27, 6, "incremental", 1 / 27)}).select(F.lit(number).alias("scrambled"), "n", "bits"))
    both = rates[0].unionAll(rates[1])
    return both.agg(F.max("n").alias("n"), F.max(F.when(F.col("scrambled") == 0, F.col("bits"))).alias("bits"), F.max(F.when(F.col("scrambled") == 1, F.col("bits"))).alias("bits_scrambled")).withColumn("gap", F.col("bits_scrambled") - F.col("bits"))


_MIXED = f"SELECT seq_id, string_agg(w, ' ' ORDER BY md5(concat(i - 1, ':0'))) AS t FROM (SELECT seq_id, unnest(string_split(t, ' ')) AS w, unnest(range(1, len(string_split(t, ' ')) + 1)) AS i FROM ({Q.BENCH27} UNION ALL SELECT seq_id + 1000000, t FROM ({Q.TURNS27}))) GROUP BY seq_id"
_UNMIXED = f"{Q.BENCH27} UNION ALL SELECT seq_id + 1000000, t FROM ({Q.TURNS27})"


def _v4(source: str) -> str:
    return f"(WITH {Q.with_seqs(source)}, {Q.events(3)}, {Q.levels(3, 27, 1 / 27, 'shortest_gain', tree='incremental')} {Q.RATE})"


@query("v4_scramble_gap_sequences", f"SELECT a.n, a.bits, b.bits AS bits_scrambled, round(b.bits - a.bits, 5) AS gap FROM {_v4(_UNMIXED)} a, {_v4(_MIXED)} b")
def v4(spark, d):
    """The scramble gap of the benchmark's texts and the conversations' turns, a tree for each."""
    seqs = bench27(spark, d).unionAll(turns27(spark, d).select((F.col("seq_id") + 1000000).alias("seq_id"), "t"))
    g = L.scramble_gap(seqs, Tree(27, 3, "incremental", 1 / 27))
    return g.select(F.col("n").cast("long").alias("n"), r6("bits").alias("bits"), r6("bits_scrambled").alias("bits_scrambled"), F.round(r6("bits_scrambled") - r6("bits"), 5).alias("gap"))


@query("w17_corpus_information", f"WITH seqs AS ({_corpus_sql(['en'])}), {Q.line_events(3)}, {Q.levels(3, 27, 1 / 27, 'shortest_gain', tree='incremental')}, w AS (SELECT *, pos - coalesce(last_value(CASE WHEN sym = ' ' THEN pos END IGNORE NULLS) OVER (PARTITION BY seq_id ORDER BY pos), 0) AS letter_no FROM pred) SELECT CAST(letter_no AS INTEGER) AS letter_no, count(*) AS n, round(avg(-log2(p)), 6) AS bits FROM w GROUP BY letter_no")
def w17c(spark, d):
    """Information by place in the word, English as one sequence."""
    return corpus_information(corpora(spark, d, 3, ["en"]), Tree(27, 3, "incremental", 1 / 27)).select("letter_no", "n", r6("bits").alias("bits"))


@query("w17_information_by_letter", f"WITH {Q.with_seqs(EN27)}, {Q.events(2)}, {Q.levels(2, 27, 0.5, 'fixed')}, w AS (SELECT *, pos - coalesce(last_value(CASE WHEN sym = ' ' THEN pos END IGNORE NULLS) OVER (PARTITION BY seq_id ORDER BY pos), 0) AS letter_no FROM pred) SELECT CAST(letter_no AS INTEGER) AS letter_no, count(*) AS n, round(avg(-log2(p)), 6) AS bits FROM w GROUP BY letter_no")
def w17(spark, d):
    return L.info_by_letter(P.predictions(english(spark, d), Tree(27, 2, rule="fixed"))).select("letter_no", "n", r6("bits").alias("bits"))


@query("w17_information_by_letter_scrambled")
def w17b(spark, d):
    """The same with 6 letters of context, plain and with every text's words scrambled."""
    seqs = english(spark, d)
    out = None
    for mixed, s in ((False, seqs), (True, S.scramble_words(seqs))):
        row = corpus_information(written(one_line(s, 6), "corpora"), Tree(27, 6, "incremental", 1 / 27)).withColumn("scrambled", F.lit(mixed))
        out = row if out is None else out.unionAll(row)
    return out


@query("w18_ablations")
def w18(spark, d):
    """Tree kind, rule, beta, delta, least count and q on the benchmark's and conversations' text and on the chaotic map's replicas."""
    text = turns27(spark, d).unionAll(bench27(spark, d))
    bits = D.map_symbols(D.seeds(table(spark, d, "customer"), "c_custkey", 50).repartition(25), "quadratic", 20000)
    out = None
    for name, seqs, size in (("text", text, 27), ("map", bits, 2)):
        trees = {}
        for tree in ("full", "incremental"):
            for beta in (1.0, 0.5, 1 / size):
                for delta in (0.0, 2.0):
                    for rule in ("shortest_gain", "deepest_gain", "walk_gain", "min_total_gain"):
                        trees[f"{tree} {rule} beta={beta:.3f} delta={delta:g}"] = Tree(size, 8, tree, beta, rule, delta)
            for q in (0.25, 1.0, 4.0):
                trees[f"{tree} blend q={q:g}"] = Tree(size, 8, tree, 1 / size, "blend", q=q)
            trees[f"{tree} deepest_gain n_min=4"] = Tree(size, 8, tree, 0.5, "deepest_gain", 0.0, 4)
        row = P.gamble(seqs, trees).groupBy(F.lit(name).alias("workload"), "method").agg((F.sum("nats") / F.sum("n") / math.log(2)).alias("bits"))
        out = row if out is None else out.unionAll(row)
    return out


@query("w19_entropy_as_quality", f"WITH {Q.with_seqs(Q.DOCS27)}, {Q.events(2)}, {Q.levels(2, 27, 0.5, 'deepest')}, r AS (SELECT seq_id, sum(-ln(p)) / count(*) / {Q.LN2!r} AS bits FROM pred GROUP BY seq_id) SELECT quality, toxic, count(*) AS docs, round(avg(bits), 6) AS bits FROM r JOIN labels ON doc_id = seq_id GROUP BY ALL")
def w19(spark, d):
    g = P.gamble(docs27(spark, d), {"r": Tree(27, 2, rule="deepest")}).select(F.col("seq_id").alias("doc_id"), (F.col("nats") / F.col("n") / math.log(2)).alias("bits"))
    return g.join(table(spark, d, "labels"), "doc_id").groupBy("quality", "toxic").agg(F.count("*").alias("docs"), r6(F.avg("bits")).alias("bits"))


_PAGES27 = "SELECT * FROM (SELECT page_id AS seq_id, trim(regexp_replace(lower(regexp_replace(html, '<[^>]*>', ' ', 'g')), '[^a-z]+', ' ', 'g')) AS t FROM pages WHERE html IS NOT NULL) WHERE t <> ''"


@query("w19_pages", f"WITH {Q.with_seqs(_PAGES27)}, {Q.events(1)}, {Q.levels(1, 27, 0.5, 'fixed')} SELECT seq_id, count(*) AS n, round(sum(-ln(p)) / count(*) / {Q.LN2!r}, 6) AS bits FROM pred GROUP BY seq_id")
def w19p(spark, d):
    pages = table(spark, d, "pages")
    seqs = S.sequences(pages, "page_id", S.normalise_27(F.regexp_replace("html", "<[^>]*>", " ")))
    return P.gamble(seqs, {"r": Tree(27, 1, rule="fixed")}).select("seq_id", "n", r6(F.col("nats") / F.col("n") / math.log(2)).alias("bits"))


_LINES = "SELECT l_suppkey AS seq_id, string_agg(sym, '' ORDER BY l_shipdate, l_orderkey, l_linenumber, l_partkey, l_extendedprice) AS t FROM (SELECT *, CAST(dense_rank() OVER (ORDER BY l_returnflag || l_linestatus) - 1 AS VARCHAR) AS sym FROM lineitem) GROUP BY l_suppkey"


@query("w20_supplier_histories", f"WITH {Q.with_seqs(_LINES)}, {Q.events(2)}, {Q.levels(2, 6, 0.5, 'shortest_gain')} {Q.RATE}")
def w20(spark, d):
    rows = table(spark, d, "lineitem")
    s = S.symbols_from_events(rows, "l_suppkey", ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice"], F.concat("l_returnflag", "l_linestatus"))
    return _rate(S.gather(s), Tree(6, 2))


@query("w20_embedding_signs", f"WITH {Q.with_seqs('SELECT vec_id AS seq_id, array_to_string(list_transform(embedding, lambda x: CASE WHEN x >= 0 THEN 1 ELSE 0 END), CAST(chr(0) AS VARCHAR)) AS t FROM embeddings').replace('CAST(chr(0) AS VARCHAR)', chr(39) * 2)}, {Q.events(2)}, {Q.levels(2, 2, 0.5, 'deepest')} {Q.RATE}")
def w20e(spark, d):
    e = table(spark, d, "embeddings")
    seqs = e.select(F.col("vec_id").alias("seq_id"), F.array_join(F.transform("embedding", lambda x: F.when(x >= 0, "1").otherwise("0")), "").alias("t"))
    return _rate(seqs, Tree(2, 2, rule="deepest"))


@query("v6_local_rates", f"WITH {Q.with_seqs(Q.DOCS27)}, {Q.events(1)}, {Q.levels(1, 27, 0.5, 'fixed')} SELECT seq_id, CAST(floor((pos - 1) / 2000) AS INTEGER) AS bin, count(*) AS n, round(avg(-log2(p)), 6) AS bits FROM pred GROUP BY ALL")
def v6(spark, d):
    return L.local_rate(P.predictions(docs27(spark, d), Tree(27, 1, rule="fixed")), 2000).select("seq_id", "bin", "n", r6("bits").alias("bits"))


@query("v3_unknown_words", f"WITH k AS (SELECT DISTINCT unnest(string_split(t, ' ')) AS word FROM ({EN27})), w AS (SELECT unnest(string_split(t, ' ')) AS word FROM ({Q.BENCH27})) SELECT count(*) AS words, count(*) FILTER (k.word IS NULL) AS unknown, round(count(*) FILTER (k.word IS NULL) / count(*), 6) AS share FROM w LEFT JOIN k ON k.word = w.word")
def v3(spark, d):
    return L.unknown_word_share(bench27(spark, d), english(spark, d)).withColumn("share", r6("share"))


# --- streams ---------------------------------------------------------------------------------------------------------


@query("w21_windowed_entropy", "WITH c AS (SELECT date_trunc('day', ts) AS start, event_type, count(*) AS c FROM events GROUP BY ALL), n AS (SELECT start, sum(c) AS n FROM c GROUP BY start) SELECT CAST(n.n AS BIGINT) AS n, round(sum(-(c / n.n) * log2(c / n.n)), 6) AS bits, strftime(n.start, '%Y-%m-%d') AS day FROM c JOIN n USING (start) GROUP BY n.n, n.start")
def w21(spark, d):
    """Daily entropy of event types by a stream over the event file, all windows."""
    stream = O.windowed_entropy(O.event_stream(spark, d), O.TYPES, "1 day")
    got = O.run_available(stream, scratch(spark, "windows"), "complete")
    last = got.agg(F.max("batch").alias("batch"))
    return got.join(F.broadcast(last), "batch").select("n", r6("bits").alias("bits"), F.date_format("start", "yyyy-MM-dd").alias("day"))


@query("w21_online_gamblers", f"WITH {Q.with_seqs(USERS)}, {Q.events(1)}, {Q.levels(1, 5, 0.5, 'fixed')} SELECT seq_id AS user_id, count(*) AS n FROM pred GROUP BY seq_id")
def w21b(spark, d):
    """Every user's events are bet on as they come; state is one user's counts."""
    got = O.run_available(O.online_gamble(O.event_stream(spark, d), O.TYPES), scratch(spark, "gamblers"), "update")
    return got.groupBy("user_id").agg(F.max("n").alias("n"))


@query("w21_online_code_lengths", "WITH e AS (SELECT user_id, ts, event_id, event_type, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS past FROM events WHERE user_id IS NOT NULL), c AS (SELECT *, count(*) OVER (PARTITION BY user_id, past ORDER BY ts, event_id) - 1 AS n, count(*) OVER (PARTITION BY user_id, past, event_type ORDER BY ts, event_id) - 1 AS na FROM e) SELECT user_id, count(*) AS n, round(sum(-ln((na + 0.5) / (n + 2.5))), 6) AS nats FROM c GROUP BY user_id")
def w21c(spark, d):
    got = O.run_available(O.online_gamble(O.event_stream(spark, d), O.TYPES), scratch(spark, "gamblers"), "update")
    return got.groupBy("user_id").agg(F.max("n").alias("n"), r6(F.max_by("nats", "n")).alias("nats"))


@query("w21_sliding_entropy", "WITH e AS (SELECT date_trunc('day', ts) - unnest([INTERVAL 0 DAY, INTERVAL 1 DAY]) AS start, event_type FROM events), c AS (SELECT start, event_type, count(*) AS c FROM e GROUP BY ALL), n AS (SELECT start, sum(c) AS n FROM c GROUP BY start) SELECT CAST(n.n AS BIGINT) AS n, round(sum(-(c / n.n) * log2(c / n.n)), 6) AS bits, strftime(n.start, '%Y-%m-%d') AS day FROM c JOIN n USING (start) GROUP BY n.n, n.start")
def w21s(spark, d):
    stream = O.windowed_entropy(O.event_stream(spark, d), O.TYPES, "2 days", "1 day")
    got = O.run_available(stream, scratch(spark, "windows"), "complete")
    last = got.agg(F.max("batch").alias("batch"))
    return got.join(F.broadcast(last), "batch").select("n", r6("bits").alias("bits"), F.date_format("start", "yyyy-MM-dd").alias("day"))


@query("w21_sessions", "WITH s AS (SELECT user_id, ts, sum(CASE WHEN ts < before + INTERVAL 30 MINUTE THEN 0 ELSE 1 END) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS before FROM events)) SELECT user_id, count(*) AS sessions, CAST(sum(n) AS BIGINT) AS events FROM (SELECT user_id, k, count(*) AS n FROM s GROUP BY ALL) GROUP BY user_id")
def w21ses(spark, d):
    """The sessions' function on the whole table (a stream closes its last sessions only with later events)."""
    e = table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return O.session_counts(e).groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"))


@query("w21_deduplicated", "SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY event_type")
def w21d(spark, d):
    twice = O.event_stream(spark, d)
    got = O.run_available(O.deduplicated(twice.unionAll(O.event_stream(spark, d)), "60 days"), scratch(spark, "deduplicated"))
    return got.groupBy("event_type").agg(F.count("*").alias("n"))


@query("w21_stream_static_join", "SELECT c_mktsegment, count(*) AS n FROM events LEFT JOIN customer ON user_id = c_custkey GROUP BY c_mktsegment")
def w21j(spark, d):
    got = O.run_available(O.enriched(O.event_stream(spark, d), table(spark, d, "customer")), scratch(spark, "enriched"))
    return got.groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("w21_stream_stream_join", "SELECT a.user_id, count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR GROUP BY a.user_id")
def w21ss(spark, d):
    got = O.run_available(O.followed_by(O.event_stream(spark, d), "click", "purchase", "6 hours"), scratch(spark, "followed"))
    return got.groupBy("user_id").agg(F.count("*").alias("pairs"))


@query("b7_expected_bias", f"WITH {Q.with_seqs(USERS)}, {Q.words(4)}, g AS (SELECT n, cnt / sum(cnt) OVER (PARTITION BY n) AS p FROM counts) SELECT n, round(-(count(*) - 1) / 2000 + (1 - sum(1 / p)) / 12000000, 9) AS bias FROM g GROUP BY n")
def b7(spark, d):
    """Bias of the likelihood estimate for 1000 symbols of a source that has the word probabilities of all user histories."""
    counts = B.block_counts(S.chunks(users(spark, d), 3), 4)
    total = counts.groupBy("n").agg(F.sum("cnt").alias("total"))
    return B.bias_expected(counts.join(total, "n").select("n", (F.col("cnt") / F.col("total")).alias("p")), 1000).select("n", F.round("bias", 9).alias("bias"))


@query("a3_ideal_growth", "WITH c AS (SELECT user_id, count(*) AS c FROM events WHERE user_id IS NOT NULL AND event_type IS NOT NULL GROUP BY user_id, event_type), g AS (SELECT user_id, ln(sum(c)) - sum(c * ln(c)) / sum(c) AS h FROM c GROUP BY user_id) SELECT user_id, round(ln(5.0) - h, 6) AS log_growth, round(5.0 / exp(h), 6) AS factor FROM g")
def a3(spark, d):
    """What a gambler gains at fair odds on five types who knows how often each user has them."""
    c = table(spark, d, "events").where("user_id is not null and event_type is not null").groupBy("user_id", "event_type").agg(F.count("*").alias("c"))
    g, f = G.ideal_growth(F.col("h"), 5)
    return c.groupBy("user_id").agg((F.ln(F.sum("c")) - F.sum(F.col("c") * F.ln("c")) / F.sum("c")).alias("h")).select("user_id", r6(g).alias("log_growth"), r6(f).alias("factor"))


@query("p4_repeat_lengths_in_levels", f"WITH {Q.with_seqs(Q.TURNS27)}, e AS (SELECT seq_id, t, unnest(range(1, len(t) + 1)) AS i FROM seqs), w AS (SELECT seq_id, i, unnest(range(1, least(4, len(t) - i + 1) + 1)) AS p, t FROM e), g AS (SELECT seq_id, i, p, min(i) OVER (PARTITION BY seq_id, p, substr(t, i, p)) AS first FROM w), l AS (SELECT seq_id, i, min(p) FILTER (first = i) AS len FROM g GROUP BY seq_id, i) SELECT CAST(len AS INTEGER) AS len, count(*) AS n FROM l GROUP BY len")
def p4l(spark, d):
    """Positions by repeat length up to 4 (null: longer), by joins: the way for sequences that fit no task."""
    return R.match_lengths_levels(S.chunks(turns27(spark, d), 3), 4).groupBy("len").agg(F.count("*").alias("n"))


# --- limits ----------------------------------------------------------------------------------------------------------


_POINTS = [1000, 1250, 1600, 2000, 2500, 3150, 4000, 5000, 6300]
_REPLICA = 32_000  # order keys


def _fit_sql(h0: float | None) -> str:
    """The search for gamma, each grid around the last one's best."""
    u = "ln(x) / pow(x, gamma)"
    if h0 is None:
        parts = "regr_intercept(y, u) AS h, regr_slope(y, u) AS c, greatest(regr_syy(y, u) - regr_slope(y, u) * regr_slope(y, u) * regr_sxx(y, u), 0.0) AS sse, min(y) AS low"
        fair = "c > 0 AND h >= 0 AND h <= low"
    else:
        parts = f"{h0} AS h, sum(u * (y - {h0})) / sum(u * u) AS c, greatest(sum((y - {h0}) * (y - {h0})) - sum(u * (y - {h0})) / sum(u * u) * sum(u * (y - {h0})), 0.0) AS sse, min(y) AS low"
        fair = "c > 0 AND h >= 0"
    out, at = [], "SELECT DISTINCT curve, g * 0.05 AS gamma FROM points, (SELECT unnest(range(1, 31)) AS g)"
    for k, step in enumerate((0.05, 0.01, 0.002)):
        if k:
            at = f"SELECT curve, gamma FROM (SELECT curve, round(gamma + i * {step}, 6) AS gamma FROM b{k - 1}, (SELECT unnest(range(-5, 6)) AS i)) WHERE gamma >= 0.05 AND gamma <= 1.5"
        out.append(f"f{k} AS (SELECT curve, gamma, {parts} FROM (SELECT p.curve, gamma, y, {u} AS u FROM points p JOIN ({at}) a ON a.curve = p.curve) GROUP BY curve, gamma), b{k} AS (SELECT * FROM f{k} WHERE {fair} QUALIFY row_number() OVER (PARTITION BY curve ORDER BY sse, gamma) = 1)")
    return ", ".join(out) + " SELECT curve, round(h, 5) AS h, round(c, 4) AS c, round(gamma, 4) AS gamma FROM b2"


_ORDER_BIT = "CASE WHEN CAST('0x' || substr(md5(concat_ws('|', o_orderkey, o_custkey)), 1, 8) AS BIGINT) < 214748364 THEN '0' ELSE '1' END"
_PRIORITY = "CAST(dense_rank() OVER (ORDER BY o_orderpriority) - 1 AS VARCHAR)"
_ENOUGH = "QUALIFY count(*) OVER (PARTITION BY curve) > 3"


def _rates_sql(symbol: str, order: int, size: int, curve: int) -> str:
    """Mean code length of the first orders of each stretch of keys, over the stretches that have so many."""
    seqs = f"SELECT seq_id, string_agg(sym, '' ORDER BY o_orderkey, o_custkey) AS t FROM (SELECT CAST(floor(o_orderkey / {_REPLICA}) AS BIGINT) AS seq_id, o_orderkey, o_custkey, {symbol} AS sym FROM orders WHERE o_orderkey IS NOT NULL AND o_custkey IS NOT NULL AND o_orderpriority IS NOT NULL) GROUP BY seq_id"
    return f"SELECT {curve} AS curve, CAST(n AS DOUBLE) AS x, avg(h) AS y FROM (WITH {Q.with_seqs(seqs)}, {Q.events(order)}, {Q.levels(order, size, 0.5, 'fixed')}, g AS (SELECT unnest({_POINTS}) AS n) SELECT seq_id, n, sum(-ln(p)) / n / {Q.LN2!r} AS h FROM pred JOIN g ON pos <= n GROUP BY seq_id, n HAVING count(*) = n) GROUP BY n"


def _order_rates(seqs: DataFrame, order: int, size: int, curve: int) -> DataFrame:
    g = P.gamble(seqs, {"r": Tree(size, order, rule="fixed")}, _POINTS).where(F.col("n").isin(_POINTS))
    return G.mean_curve(G.curve(g, by=["seq_id"])).select(F.lit(curve).alias("curve"), "n", "h")


def _stretches(spark, d) -> DataFrame:
    o = table(spark, d, "orders").where("o_orderkey is not null and o_custkey is not null and o_orderpriority is not null")
    return o.withColumn("stretch", F.floor(F.col("o_orderkey") / _REPLICA))


def _fitted(curves: DataFrame, h0: float | None) -> DataFrame:
    """Fits of at least four points: fewer leave gamma open."""
    fit = G.fit_tail(curves, by=["curve"], h0=h0).where("ok and n_points > 3")
    return fit.select("curve", F.round("h", 5).alias("h"), F.round("c", 4).alias("c"), F.round("gamma", 4).alias("gamma"))


@query("x1_tail_fits", f"WITH points AS (SELECT * FROM ({_rates_sql(_PRIORITY, 1, 5, 1)} UNION ALL {_rates_sql(_PRIORITY, 2, 5, 2)}) {_ENOUGH}), {_fit_sql(None)}")
def x1(spark, d):
    """Limits of the code lengths of order priorities, by contexts of one and of two orders, over stretches of 32,000 order keys."""
    seqs = S.gather(S.symbols_from_events(_stretches(spark, d), "stretch", ["o_orderkey", "o_custkey"], F.col("o_orderpriority")))
    return _fitted(written(_order_rates(seqs, 1, 5, 1).unionAll(_order_rates(seqs, 2, 5, 2)), "curve"), None)


_KNOWN = D.entropy_bernoulli(0.05)


@query("x2_tail_fit_of_known_limit", f"WITH points AS (SELECT * FROM ({_rates_sql(_ORDER_BIT, 3, 2, 3)}) {_ENOUGH}), {_fit_sql(_KNOWN)}")
def x2(spark, d):
    """The same of biased bits from hashes of orders, by contexts of three bits; their limit is known."""
    from pyspark.sql import Window

    o = _stretches(spark, d)
    rows = o.withColumn("pos", F.row_number().over(Window.partitionBy("stretch").orderBy("o_orderkey", "o_custkey")))
    seqs = S.gather(D.bernoulli_bits(rows, "stretch", "pos", ["o_orderkey", "o_custkey"], 0.05))
    return _fitted(written(_order_rates(seqs, 3, 2, 3), "curve"), _KNOWN)


@query("x3_block_extrapolation")
def x3(spark, d):
    """Limits of the block estimates over the whole length of the English corpus."""
    chunked = corpora(spark, d, 5, ["en"])
    length = chunked.agg(F.max(F.col("start") + F.length("body") - 1)).first()[0] or 1
    grid = sorted({max(1, length >> k) for k in range(8)})
    h = written(B.block_curve(chunked, [1, 2, 3, 4, 5, 6], grid, 27, methods=["plugin", "digamma_parity"]), "curve")
    # block estimates rise to their limit: the fit is of what is missing, mirrored at the largest estimate
    top = h.groupBy("n", "method").agg(F.max("h_diff").alias("top"))
    mirrored = h.join(top, ["n", "method"]).select(F.concat_ws(" ", "method", F.col("n")).alias("estimate"), F.col("length").alias("n"), (2 * F.col("top") - F.col("h_diff")).alias("h"), "top")
    fit = G.fit_tail(mirrored, by=["estimate", "top"])
    return fit.select("estimate", (2 * F.col("top") - F.col("h")).alias("limit"), "gamma", "sse", "ok")
