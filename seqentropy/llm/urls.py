"""URL filter: allow and block rules, and a ratio of two character language models for the urls that no rule decides.

A rule is a host and the beginning of a path; it fits the host and its subdomains, the longest fitting rule decides.
Urls that rules allow and block are the training data of two smoothed variable-order Markov models over bytes: the
probability of a byte after its last n bytes is interpolated with that after n - 1, down to a uniform one (the shorter
context weighs as much as ``PRIOR`` bytes seen).  A url's score is the difference of its
log-likelihoods a byte.  One in ``HELD_OUT`` of the decided urls, by their hash, is left out of the models; the cut is
the one that separates those best (balanced accuracy over a histogram of all of them).

A key is a byte with the ``ORDERS - 1`` before it, packed without loss in a long; shorter contexts are its low bits.
Keys are counted exactly in a distributed aggregate; shorter ones are sums of longer ones, so all further steps work on
distinct keys.  The probabilities of each order are joined to the keys of the next one; a url's score is the
sum of its keys' log ratios, a byte.  Log ratios are summed as whole numbers, so the order of the sums doesn't matter.

Bounds: all decided urls are counted or calibrate (all of them do both where a class has none held out); the model
grows with the table and never comes to the driver, which gathers ``2 * BINS`` bins of the histogram.
Rows are numbered once, in a written table.

Defined cases: null urls and urls without ``://`` have an empty host and path, fit no rule and are judged by the models
on what there is; where a class has no decided url, the models allow all; repeated rows are each judged; other columns
are ignored.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels as K
from .common import cut, read

# The task's rules.
RULES = [("allow", "com/"), ("block", "example.com/en/"), ("allow", "www.example.com/en/"), ("block", "net/es/"), ("block", "net/fr/")]
ORDERS, BINS, SPAN, PRIOR = 6, 2000, 10.0, 4.0
HELD_OUT = 10
BITS, MARK, UNIT = 9, 256, 1e12
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def url_parts(url: Column) -> tuple[Column, Column]:
    """Host and path."""
    rest = F.when(F.instr(url, "://") > 0, F.substring(url, F.instr(url, "://") + 3, F.length(url))).otherwise("")
    raw = F.regexp_extract(rest, "^[^/?#]*", 0)
    path = F.regexp_extract(F.substring(rest, F.length(raw) + 1, F.length(rest)), "^[^?#]*", 0)
    return F.coalesce(F.translate(raw, UPPER, LOWER), F.lit("")), F.coalesce(path, F.lit(""))


def rule_of(host: Column, path: Column, rules=RULES) -> Column:
    """The longest fitting rule, or null."""
    out = F.lit(None).cast("string")
    for _, rule in sorted(rules, key=lambda r: len(r[1])):
        own, _, begin = rule.partition("/")
        fits = ((host == own) | host.endswith(f".{own}")) & path.startswith(f"/{begin}")
        out = F.when(fits, F.lit(rule)).otherwise(out)
    return out


def by_rule(rule: Column, rules=RULES) -> Column:
    out = F.lit(None).cast("string")
    for verdict, name in rules:
        out = F.when(rule == name, F.lit(verdict)).otherwise(out)
    return out


def ruled(pages: DataFrame, rules=RULES) -> DataFrame:
    """page_id, url, host, path, rule and the rule's verdict."""
    host, path = url_parts(F.col("url"))
    parts = pages.select("page_id", "url", host.alias("host"), path.alias("path"))
    return parts.withColumn("rule", rule_of(F.col("host"), F.col("path"), rules)).withColumn("ruled", by_rule(F.col("rule"), rules))


def _column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def keys(piece: K.Piece) -> np.ndarray:
    """For each byte, the byte and those before it, the byte lowest; before the beginning: marks."""
    data = K.table("lower")[piece.data].astype(np.int64)
    n = len(data)
    at = np.arange(n) - np.repeat(piece.off[:-1], np.diff(piece.off))
    out = data.copy()
    for order in range(1, ORDERS):
        older = np.full(n, MARK, np.int64)
        older[order:] = data[:max(0, n - order)]
        out |= np.where(at >= order, older, MARK) << (BITS * order)
    return out


def _keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows, label = _column(batch, "row").to_numpy(), np.array([{"allow": 0, "block": 1}.get(x, 2) for x in _column(batch, "ruled").to_pylist()], np.int32)
        for piece in K.pieces(_column(batch, "url"), 1 << 18):
            of = np.repeat(np.arange(piece.first, piece.first + piece.n), np.diff(piece.off))
            yield pa.RecordBatch.from_arrays([pa.array(rows[of]), pa.array(label[of]), pa.array(keys(piece))], ["row", "label", "key"])


def ratios(keyed: DataFrame) -> DataFrame:
    """key, gain (log of the byte's probability among allowed urls less that among blocked ones, in UNITs) for all keys; no rows if a class has no urls."""
    low = lambda c, n: F.col(c).bitwiseAND(F.lit((1 << (BITS * n)) - 1))
    counts = {ORDERS: keyed.groupBy("key").agg(*(F.sum((F.col("label") == k).cast("long")).alias(f"n{k}") for k in (0, 1)))}
    for n in range(ORDERS - 1, 0, -1):
        counts[n] = counts[n + 1].groupBy(low("key", n).alias("key")).agg(*(F.sum(f"n{k}").alias(f"n{k}") for k in (0, 1)))
    total = counts[1].agg(*(F.sum(f"n{k}").alias(f"t{k}") for k in (0, 1))).where("t0 > 0 and t1 > 0")
    known = counts[1].crossJoin(F.broadcast(total)).select("key", *(((F.col(f"n{k}") + PRIOR / 256) / (F.col(f"t{k}") + PRIOR)).alias(f"p{k}") for k in (0, 1)))
    for n in range(2, ORDERS + 1):
        context = counts[n].groupBy(F.shiftright("key", BITS).alias("context")).agg(*(F.sum(f"n{k}").alias(f"t{k}") for k in (0, 1)))
        known = known.withColumnRenamed("key", "shorter")
        joined = counts[n].withColumn("context", F.shiftright("key", BITS)).withColumn("shorter", low("key", n - 1)).join(context, "context").join(known, "shorter")
        known = joined.select("key", *(((F.col(f"n{k}") + PRIOR * F.col(f"p{k}")) / (F.col(f"t{k}") + PRIOR)).alias(f"p{k}") for k in (0, 1)))
    return known.select("key", F.round((F.log("p0") - F.log("p1")) * UNIT).cast("long").alias("gain"))


def scores(pages: DataFrame) -> DataFrame:
    """pages (row, url, ruled): row, score (log-likelihood difference a byte, allow less block); no rows for empty urls."""
    keyed = pages.mapInArrow(_keyed, "row long, label int, key long")
    return keyed.select("row", "key").join(cut(ratios(keyed), "url-model"), "key").groupBy("row").agg(F.round(F.sum("gain") / UNIT / F.count("*"), 9).alias("score"))


def best_cut(allow: np.ndarray, block: np.ndarray) -> float:
    """The score from which urls are allowed: the middle of the bins' borders with the best balanced accuracy."""
    good = np.concatenate([[0], np.cumsum(allow)]) / allow.sum()  # allowed ones below a border
    bad = np.concatenate([[0], np.cumsum(block)]) / block.sum()
    gain = np.round(bad - good, 12)
    best = np.flatnonzero(gain == gain.max())
    return float((best[0] + best[-1]) / 2 / BINS * 2 * SPAN - SPAN)


def judged(pages: DataFrame, rules=RULES) -> DataFrame:
    """page_id, host, path, rule, verdict, score."""
    apart = F.pmod(F.xxhash64(F.lit("held"), "url"), F.lit(HELD_OUT)) == 0
    known = cut(ruled(pages, rules).select(F.monotonically_increasing_id().alias("row"), "*", apart.alias("apart")), "url-rows")
    per_class = {(r.ruled, r.apart): r.n for r in known.where("ruled is not null").groupBy("ruled", "apart").agg(F.count("*").alias("n")).collect()}
    able = all(per_class.get((c, a)) for c in ("allow", "block") for a in (True, False))
    counted = F.when(~F.col("apart") | F.lit(not able), F.col("ruled"))
    scored = cut(known.drop("url").join(scores(known.select("row", "url", counted.alias("ruled"))), "row", "left").withColumn("score", F.coalesce("score", F.lit(0.0))), "url-scores")
    at = F.greatest(F.lit(0), F.least(F.lit(BINS - 1), F.floor((F.col("score") + SPAN) / (2 * SPAN) * BINS))).cast("int")
    hist = np.zeros((2, BINS))
    for r in scored.where("ruled is not null").where(F.col("apart") | F.lit(not able)).groupBy((F.col("ruled") == "block").alias("bad"), at.alias("bin")).agg(F.count("*").alias("n")).collect():
        hist[int(r.bad), r.bin] = r.n
    both = hist[0].any() and hist[1].any()
    by_score = F.when(F.col("score") >= best_cut(hist[0], hist[1]), "allow").otherwise("block") if both else F.lit("allow")
    return scored.select(F.col("page_id").cast("long").alias("page_id"), "host", "path", "rule", F.coalesce("ruled", by_score).alias("verdict"), "score")


def op4_url_markov_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``pages``."""
    return judged(read(spark, sf_dir, "pages"))


register_pickle_by_value(sys.modules[__name__])
