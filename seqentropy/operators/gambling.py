"""What predictions are worth: code lengths, capital, convergence curves, and their limit."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.mathx import unit


def gambling_rate(pred: DataFrame, units: str = "bits", by: list[str] | None = None) -> DataFrame:
    """n, rate: the mean of -log p: an upper bound on the entropy on average."""
    return pred.groupBy(*(by or [])).agg(F.count("*").alias("n"), (F.sum(-F.ln("p")) / F.count("*") / unit(units)).alias("rate"))


def capital_curve(pred: DataFrame, d: int, block: int = 4096) -> DataFrame:
    """seq_id, pos, log_capital: log of a gambler's capital who stakes by the predictions at fair odds d (nats), summed in blocks of positions."""
    rows = pred.withColumn("gain", F.lit(math.log(d)) + F.ln("p")).withColumn("b", F.floor(F.col("pos") / block))
    sums = rows.groupBy("seq_id", "b").agg(F.sum("gain").alias("s"))
    sums = sums.select("seq_id", "b", F.coalesce(F.sum("s").over(Window.partitionBy("seq_id").orderBy("b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)).alias("before"))
    local = F.sum("gain").over(Window.partitionBy("seq_id", "b").orderBy("pos"))
    return rows.join(sums, ["seq_id", "b"]).select("seq_id", "pos", (F.col("before") + local).alias("log_capital"))


def ideal_growth(h: float | Column, d: int) -> tuple:
    """Log growth a step, and the factor, of a gambler who knows the source of entropy h (nats)."""
    return math.log(d) - h, d / (F.exp(h) if isinstance(h, Column) else math.exp(h))


def arithmetic_code_bits(pred: DataFrame) -> DataFrame:
    """seq_id, bits: an arithmetic coder needs the ideal length, rounded up, and two bits."""
    return pred.groupBy("seq_id").agg((F.ceil(F.round(F.sum(-F.log2("p")), 6)) + 2).cast("long").alias("bits"))


def arithmetic_round_trip(sym: list[int], p_of) -> tuple[str, list[int]]:
    """Codes symbols with exact rational intervals and decodes them again.  p_of(past) gives the distribution as fractions."""
    from fractions import Fraction

    low, width = Fraction(0), Fraction(1)
    for k, s in enumerate(sym):
        p = p_of(sym[:k])
        low += width * sum(p[:s], Fraction(0))
        width *= p[s]
    bits = ""
    a, w = Fraction(0), Fraction(1)
    while not (low <= a and a + w <= low + width):
        w /= 2
        if a + w <= low + width / 2:
            a += w
            bits += "1"
        else:
            bits += "0"
    value, out, low, width = a, [], Fraction(0), Fraction(1)
    for _ in sym:
        p, at = p_of(out), low
        for s, x in enumerate(p):
            if at <= value < at + width * x:
                out.append(s)
                low, width = at, width * x
                break
            at += width * x
    return bits, out


def rate_curve(pred: DataFrame, grid: list[int], p: str = "p", by: list[str] | None = None, units: str = "bits") -> DataFrame:
    """[by,] n, h: the mean code length of the first n symbols for every n of grid that a sequence has, from sums of bins."""
    by = by or ["seq_id"]
    points = F.array(*(F.lit(g).cast("long") for g in sorted(grid)))
    binned = pred.select(*by, "pos", F.array_min(F.filter(points, lambda g: g >= F.col("pos"))).alias("n"), (-F.ln(p)).alias("nats")).where("n is not null").groupBy(*by, "n").agg(F.sum("nats").alias("nats"), F.max("pos").alias("last"))
    return curve_of_bins(binned, by, units)


def curve_of_bins(binned: DataFrame, by: list[str], units: str = "bits") -> DataFrame:
    """[by,] n, h from the code lengths (nats) of bins that end at n, where their last position is n."""
    run = F.sum("nats").over(Window.partitionBy(*by).orderBy("n"))
    return binned.withColumn("nats", run).where("last = n").select(*by, "n", (F.col("nats") / F.col("n") / unit(units)).alias("h"))


def geometric_grid(n: int, first: int = 200, ratio: float = 1.3) -> list[int]:
    out, x = [], float(first)
    while x < n:
        out.append(round(x))
        x *= ratio
    return [*out, n]


def curve(sums: DataFrame, units: str = "bits", by: list[str] | None = None) -> DataFrame:
    """[by,] n, h from code lengths (n, nats)."""
    return sums.select(*(by or []), "n", (F.col("nats") / F.col("n") / unit(units)).alias("h"))


def mean_curve(curves: DataFrame, by: list[str] | None = None) -> DataFrame:
    """[by,] n, h, spread, replicas: averaged over replicas before any fit."""
    return curves.groupBy(*(by or []), "n").agg(F.avg("h").alias("h"), F.stddev("h").alias("spread"), F.count("*").alias("replicas"))


def fit_tail(curves: DataFrame, by: list[str] | None = None, h0: float | None = None, refine: int = 2, least_n: int = 1000) -> DataFrame:
    """[by,] h, c, gamma, sse, n_points, ok: least squares of h + c ln n / n^gamma over the points with n >= least_n.

    For a given gamma the rest is linear; gamma is searched on a grid that is narrowed around the best twice (all in one
    plan: each group's grid is its own).  h stays within 0 and the smallest observation, c above 0; ``ok`` is false where
    no gamma allows that, and the smallest observation stands in for h.  With h0 the limit is given.
    """
    by = by or []
    points = curves.where(F.col("n") >= least_n).select(*by, F.col("n").cast("double").alias("x"), F.col("h").alias("y"))
    spark = curves.sparkSession
    key = by or ["_all"]
    points = points if by else points.withColumn("_all", F.lit(0))
    step, grid = 0.05, spark.range(1, 31).select((F.col("id") * 0.05).alias("gamma"))
    at = points.select(*key).distinct().crossJoin(F.broadcast(grid))
    best = None
    for k in range(refine + 1):
        u = F.ln("x") / F.pow("x", "gamma")
        rows = points.join(at, key).select(*key, "gamma", "y", u.alias("u"))
        if h0 is None:
            fits = rows.groupBy(*key, "gamma").agg(F.regr_intercept("y", "u").alias("h"), F.regr_slope("y", "u").alias("c"), F.regr_sxx("y", "u").alias("sxx"), F.regr_syy("y", "u").alias("syy"), F.count("*").alias("n_points"), F.min("y").alias("low"))
            fits = fits.withColumn("sse", F.greatest(F.col("syy") - F.col("c") * F.col("c") * F.col("sxx"), F.lit(0.0)))
        else:
            fits = rows.groupBy(*key, "gamma").agg(F.lit(float(h0)).alias("h"), (F.sum(F.col("u") * (F.col("y") - h0)) / F.sum(F.col("u") * F.col("u"))).alias("c"), F.sum((F.col("y") - h0) * (F.col("y") - h0)).alias("yy"), F.sum(F.col("u") * (F.col("y") - h0)).alias("uy"), F.count("*").alias("n_points"), F.min("y").alias("low"))
            fits = fits.withColumn("sse", F.greatest(F.col("yy") - F.col("c") * F.col("uy"), F.lit(0.0)))
        fair = F.coalesce((F.col("c") > 0) & (F.col("h") >= 0) & ((F.col("h") <= F.col("low")) | F.lit(h0 is not None)), F.lit(False))
        ranked = F.struct((~fair).alias("bad"), F.coalesce("sse", F.lit(float("inf"))).alias("sse"), "gamma", "h", "c", "n_points", "low")
        best = fits.groupBy(*key).agg(F.min(ranked).alias("b"))
        step /= 5
        around = F.explode(F.filter(F.transform(F.sequence(F.lit(-5), F.lit(5)), lambda i: F.round(F.col("b.gamma") + i * step, 6)), lambda g: (g >= 0.05) & (g <= 1.5)))
        if k < refine:
            at = best.select(*key, around.alias("gamma"))
    ok = ~F.col("b.bad")
    return best.select(*by, F.when(ok, F.col("b.h")).otherwise(F.col("b.low")).alias("h"), F.when(ok, F.col("b.c")).alias("c"), F.when(ok, F.col("b.gamma")).alias("gamma"), F.col("b.sse").alias("sse"), F.col("b.n_points").cast("int").alias("n_points"), ok.alias("ok"))


def accuracy(estimates: DataFrame, units_d: int | None = None) -> DataFrame:
    """Adds rel_error, is_above (an upper bound should be) and, with an alphabet's size, ratio (of the plain code) to estimate and reference."""
    out = estimates.withColumn("rel_error", (F.col("estimate") - F.col("reference")) / F.col("reference")).withColumn("is_above", F.col("estimate") >= F.col("reference"))
    return out.withColumn("ratio", F.col("estimate") / math.log2(units_d)) if units_d else out
