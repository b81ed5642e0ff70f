"""Experiments with written language: continuation, forecasts, word surrogates, information by letter, local rates."""

from __future__ import annotations

import sys

import pyarrow as pa
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.symbols import scramble_words
from . import predict as P
from .context_kernel import Tree

BANDS = (0.6, 0.25, 0.1)
MAX_NODES = 2_000_000


def model_table(nodes: DataFrame, counts: DataFrame, max_nodes: int = MAX_NODES) -> dict[str, tuple[float, dict[str, int]]]:
    """Contexts with their gain and what followed them, for generators.  Its size is checked: counts of more rows are refused (lower the order or raise the least count)."""
    rows = counts.select("ctx", "sym", "cnt").limit(max_nodes + 1).toArrow()
    if rows.num_rows > max_nodes:
        raise ValueError(f"the model has more than {max_nodes} rows")
    gains = nodes.join(counts.select("depth", "ctx").distinct(), ["depth", "ctx"], "left_semi").select("ctx", "gain").toArrow()
    gain = dict(zip(gains["ctx"].to_pylist(), gains["gain"].to_pylist(), strict=True))
    out: dict[str, tuple[float, dict[str, int]]] = {}
    for ctx, sym, cnt in zip(*(rows[c].to_pylist() for c in ("ctx", "sym", "cnt")), strict=True):
        out.setdefault(ctx, (gain.get(ctx, 0.0), {}))[1][sym] = cnt
    return out


def chosen_context(table: dict, past: str, order: int, delta: float = 0.0) -> str:
    """The shortest context that has gained and whose child on the path has not, or is not there; else the empty one."""
    candidate = None
    for j in range(min(order, len(past)) + 1):
        ctx = past[len(past) - j:] if j else ""
        node = table.get(ctx)
        if j and (node is None or node[0] >= 0):
            if candidate is not None:
                return candidate
            if node is None:
                return ""
        gained = (-1.0 if not j else node[0]) < -delta if node else False
        candidate = ctx if gained else None
    return candidate if candidate is not None else ""


def continue_text(table: dict, prime: str, n: int, order: int, delta: float = 0.0, seed: int | None = None) -> str:
    """Appends the most probable letter (ties: the smallest) after the chosen context, n times; or draws it, with a seed."""
    import random

    rng, out = random.Random(seed), prime
    for _ in range(n):
        own = table.get(chosen_context(table, out, order, delta), (0.0, {}))[1]
        if not own:
            break
        out += min(own, key=lambda a: (-own[a], a)) if seed is None else rng.choices(sorted(own), [own[a] for a in sorted(own)])[0]
    return out[len(prime):]


def generate_greedy(prompts: DataFrame, nodes: DataFrame, counts: DataFrame, n: int, order: int, delta: float = 0.0, seed: int | None = None) -> DataFrame:
    """seq_id, continuation for prompts (seq_id, t) by a trained tree."""
    table = prompts.sparkSession.sparkContext.broadcast(model_table(nodes, counts))

    def run(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([continue_text(table.value, t or "", n, order, delta, None if seed is None else seed + k) for k, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)], pa.string())], ["seq_id", "continuation"])

    return prompts.select("seq_id", "t").mapInArrow(run, "seq_id long, continuation string")


def choose_contexts(test_events: DataFrame, nodes: DataFrame, order: int, delta: float = 0.0) -> DataFrame:
    """seq_id, pos, actual, depth, ctx: the context that a trained tree predicts each position of new text by (the default rule on its final gains).

    Each position asks for its contexts in one join; what comes back is one small row a context.
    """
    asked = test_events.select("seq_id", "pos", F.col("sym").alias("actual"), "past", F.explode(F.sequence(F.lit(0), F.least(F.length("past"), F.lit(order)))).alias("depth"))
    asked = asked.select("seq_id", "pos", "actual", "past", "depth", F.when(F.col("depth") > 0, F.right("past", F.col("depth"))).otherwise("").alias("ctx"))
    path = asked.join(nodes.select("depth", "ctx", "gain"), ["depth", "ctx"]).groupBy("seq_id", "pos", "actual", "past").agg(F.array_sort(F.collect_list(F.struct("depth", "gain"))).alias("path"))
    none = F.struct(F.lit(-1).alias("found"), F.lit(-1).alias("candidate"), F.lit(0).alias("next"))

    def step(a, node):
        here = node["depth"] == a["next"]  # a gap ends the path
        stop = here & (node["depth"] > 0) & (node["gain"] >= 0) & (a["candidate"] >= 0)
        gained = F.when(node["depth"] == 0, F.lit(-1.0)).otherwise(node["gain"]) < -delta
        found = F.when((a["found"] < 0) & (stop | (~here & (a["candidate"] >= 0))), a["candidate"]).otherwise(a["found"])
        return F.struct(found.alias("found"), F.when(here & gained, node["depth"]).otherwise(F.lit(-1)).alias("candidate"), F.when(here, a["next"] + 1).otherwise(F.lit(-1)).alias("next"))

    last = F.aggregate("path", none, step)
    depth = F.when(last["found"] >= 0, last["found"]).when(last["candidate"] >= 0, last["candidate"]).otherwise(0)
    chosen = path.select("seq_id", "pos", "actual", "past", depth.cast("int").alias("depth"))
    return chosen.select("seq_id", "pos", "actual", "depth", F.when(F.col("depth") > 0, F.right("past", F.col("depth"))).otherwise("").alias("ctx"))


def forecast_table(test_events: DataFrame, nodes: DataFrame, counts: DataFrame, order: int, d: int, beta: float, bands=BANDS, delta: float = 0.0) -> DataFrame:
    """seq_id, pos, actual, rank, letter, p, band: letters that the chosen context of each position gives at least the lowest band.

    test_events: seq_id, pos, sym, past; nodes and counts: a trained tree.  Probabilities and ranks are made once for each
    context, and joined to the positions that chose it.
    """
    total = F.sum("cnt").over(Window.partitionBy("depth", "ctx"))
    p = counts.withColumn("p", P.additive(F.col("cnt"), total, d, beta)).where(F.col("p") >= min(bands))
    rank = F.row_number().over(Window.partitionBy("depth", "ctx").orderBy(F.desc("p"), "sym"))
    band = F.lit(None).cast("string")
    for b in sorted(bands):
        band = F.when(F.col("p") >= b, F.lit(f"{b:g}")).otherwise(band)
    letters = p.select("depth", "ctx", F.col("sym").alias("letter"), rank.alias("rank"), "p", band.alias("band"))
    return choose_contexts(test_events, nodes, order, delta).join(letters, ["depth", "ctx"]).select("seq_id", "pos", "actual", "rank", "letter", "p", "band")


def words(seqs: DataFrame) -> DataFrame:
    """seq_id, word_idx, word, start_pos."""
    none = F.struct(F.lit(1).alias("next"), F.array().cast("array<struct<w:string,s:int>>").alias("out"))
    add = lambda a, w: F.struct((a["next"] + F.length(w) + 1).alias("next"), F.concat(a["out"], F.array(F.struct(w.alias("w"), a["next"].alias("s")))).alias("out"))
    cut = seqs.select("seq_id", F.aggregate(F.split("t", " "), none, add, lambda a: a["out"]).alias("z"))
    return cut.select("seq_id", F.posexplode("z").alias("word_idx", "z")).select("seq_id", "word_idx", F.col("z.w").alias("word"), F.col("z.s").alias("start_pos"))


def word_list(seqs: DataFrame) -> DataFrame:
    """seq_id, word."""
    return seqs.select("seq_id", F.explode(F.split("t", " ")).alias("word")).where("word <> ''")


def unknown_word_share(text: DataFrame, training: DataFrame) -> DataFrame:
    """words, unknown, share: words of a text that the training text doesn't have."""
    own = word_list(text)
    known = word_list(training).select("word").distinct().withColumn("known", F.lit(1))
    return own.join(known, "word", "left").agg(F.count("*").alias("words"), F.sum(F.when(F.col("known").isNull(), 1).otherwise(0)).alias("unknown")).withColumn("share", F.col("unknown") / F.col("words"))


def scramble_gap(seqs: DataFrame, t: Tree, seed: int = 0) -> DataFrame:
    """n, bits, bits_scrambled, gap: how much the order of words is worth (bits a letter)."""
    rate = lambda s, name: P.gamble(s, {"r": t}).agg(F.sum("n").alias("n"), (F.sum("nats") / F.sum("n") / F.ln(F.lit(2.0))).alias(name))
    both = rate(seqs, "bits").crossJoin(F.broadcast(rate(scramble_words(seqs, seed), "bits_scrambled").drop("n")))
    return both.withColumn("gap", F.col("bits_scrambled") - F.col("bits"))


def info_by_letter(pred: DataFrame, block: int = 65_536) -> DataFrame:
    """letter_no, n, bits: mean information of the letters by their place in the word; the blank itself is 0.

    The last blank before a position is looked for in its block of positions, and before that in the blocks' last blanks.
    """
    rows = pred.withColumn("_block", F.floor(F.col("pos") / block))
    blanks = F.when(F.col("sym") == " ", F.col("pos"))
    ends = rows.groupBy("seq_id", "_block").agg(F.max(blanks).alias("_last"))
    earlier = F.max("_last").over(Window.partitionBy("seq_id").orderBy("_block").rowsBetween(Window.unboundedPreceding, -1))
    ends = ends.select("seq_id", "_block", F.coalesce(earlier, F.lit(0)).alias("_before"))
    blank = F.last(blanks, ignorenulls=True).over(Window.partitionBy("seq_id", "_block").orderBy("pos"))
    numbered = rows.withColumn("_own", blank).join(ends, ["seq_id", "_block"]).withColumn("letter_no", (F.col("pos") - F.coalesce("_own", "_before")).cast("int"))
    return numbered.groupBy("letter_no").agg(F.count("*").alias("n"), F.avg(-F.log2("p")).alias("bits"))


def local_rate(pred: DataFrame, size: int) -> DataFrame:
    """seq_id, bin, n, bits: the rate in stretches of a sequence."""
    return pred.groupBy("seq_id", F.floor((F.col("pos") - 1) / size).cast("int").alias("bin")).agg(F.count("*").alias("n"), F.avg(-F.log2("p")).alias("bits"))


register_pickle_by_value(sys.modules[__name__])
