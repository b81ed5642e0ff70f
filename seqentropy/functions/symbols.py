"""Sequences of symbols from text, events and series.

A *sequence frame* has ``seq_id`` and ``t``: a string with one character for each symbol.  A *chunk frame* is the same
cut up: ``seq_id``, ``start`` (the position of the body's first symbol, from 1), ``left`` (the symbols just before it,
as many as asked for) and ``body``.  Long sequences, or a whole corpus as one sequence, are chunks; nothing ever holds
a long sequence in one row or task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Symbols of alphabets that aren't letters, in order.
DIGITS = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"
ACCENTS = ("àáâãäåçèéêëìíîïñòóôõöùúûüýÿ", "aaaaaaceeeeiiiinooooouuuuyy")
CHUNK = 256


def normalise_27(text: Column, fold_accents: bool = False) -> Column:
    """26 letters and the blank: lower case, everything else a blank, one blank for several, none at the ends."""
    low = F.lower(text)
    if fold_accents:
        low = F.translate(low, *ACCENTS)
    return F.trim(F.regexp_replace(low, "[^a-z]+", " "))


def ascii7(text: Column) -> Column:
    return F.regexp_replace(text, r"[^\x00-\x7F]", "")


def sequences(df: DataFrame, key: str, text: Column) -> DataFrame:
    """seq_id, t; null and empty texts are left out."""
    return df.select(F.col(key).cast("long").alias("seq_id"), text.alias("t")).where("t is not null and t <> ''")


def explode_symbols(seqs: DataFrame) -> DataFrame:
    """seq_id, pos (from 1), sym (a one-character string)."""
    return seqs.select("seq_id", F.posexplode(F.split("t", "")).alias("pos", "sym")).select("seq_id", (F.col("pos") + 1).cast("long").alias("pos"), "sym")


def gather(symbols: DataFrame) -> DataFrame:
    """Rows of symbols (seq_id, pos, sym) as sequences; for sequences that fit a row."""
    rows = F.array_sort(F.collect_list(F.struct("pos", "sym")))
    return symbols.groupBy("seq_id").agg(rows.alias("rows")).select("seq_id", F.array_join(F.transform("rows", lambda r: r["sym"].cast("string")), "").alias("t"))


def symbols_from_events(df: DataFrame, key: str, order_by: list[str], value: Column) -> DataFrame:
    """A categorical history for each key: seq_id, pos, sym (the value's place in the sorted alphabet, as a character)."""
    rows = df.select(F.col(key).cast("long").alias("seq_id"), *order_by, value.alias("value")).where("seq_id is not null and value is not null")
    names = rows.select("value").distinct()
    alphabet = names.select("value", F.substring(F.lit(DIGITS), F.row_number().over(Window.orderBy("value")), F.lit(1)).alias("sym"))  # an alphabet has at most 62 symbols
    place = F.row_number().over(Window.partitionBy("seq_id").orderBy(*order_by)).cast("long")
    return rows.join(F.broadcast(alphabet), "value").select("seq_id", place.alias("pos"), "sym")


def partition_series(x: Column, cuts: list[float] | None = None, eps: float | None = None, low: float = 0.0) -> Column:
    """Cells of a real value: between cuts, or of width eps from low on."""
    if cuts is not None:
        cell = sum((F.when(x >= c, 1).otherwise(0) for c in cuts), F.lit(0))
    else:
        cell = F.floor((x - low) / eps)
    return F.substring(F.lit(DIGITS), cell.cast("int") + 1, F.lit(1))


def quantile_cuts(df: DataFrame, x: str, cells: int) -> list[float]:
    """Cuts that share the values out evenly (exact order statistics by a distributed aggregate)."""
    return list(df.agg(F.percentile(x, F.array(*(F.lit(k / cells) for k in range(1, cells)))).alias("q")).first().q or [])


def sign_partition(x: Column) -> Column:
    """The two laps of a one-humped map; zero belongs to the right one."""
    return F.when(x >= 0, "1").otherwise("0")


def chunks(seqs: DataFrame, left: int, size: int = CHUNK) -> DataFrame:
    """Cuts sequences in chunks."""
    starts = F.sequence(F.lit(1).cast("long"), F.length("t").cast("long"), F.lit(size).cast("long"))
    cut = seqs.select("seq_id", "t", F.explode(starts).alias("start"))
    begin = F.greatest(F.col("start") - left, F.lit(1).cast("long"))
    return cut.select("seq_id", "start", F.substring(F.col("t"), begin.cast("int"), (F.col("start") - begin).cast("int")).alias("left"), F.substring(F.col("t"), F.col("start").cast("int"), F.lit(size)).alias("body"))


def offsets(seqs: DataFrame, gap: int = 1) -> DataFrame:
    """Where each sequence begins if all stand in one line in the order of seq_id: seq_id, offset.

    Range partitions are summed on their own, then the partitions' sums (one row each); no task sees all rows.
    """
    sizes = seqs.select("seq_id", (F.length("t") + gap).cast("long").alias("size")).repartitionByRange("seq_id").select("*", F.spark_partition_id().alias("part"))
    within = F.sum("size").over(Window.partitionBy("part").orderBy("seq_id").rowsBetween(Window.unboundedPreceding, -1))
    totals = sizes.groupBy("part").agg(F.sum("size").alias("total"))
    before = totals.select("part", F.coalesce(F.sum("total").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    return sizes.select("seq_id", "part", F.coalesce(within, F.lit(0)).alias("within")).join(before, "part").select("seq_id", (F.col("before") + F.col("within")).alias("offset"))


def corpus_chunks(seqs: DataFrame, left: int, size: int = CHUNK, number: int = 0) -> DataFrame:
    """All sequences in one line, a blank between them, as chunks of the sequence ``number``."""
    placed = seqs.join(offsets(seqs), "seq_id").select("offset", F.concat("t", F.lit(" ")).alias("t"))
    length = F.length("t")
    first, last = F.floor(F.col("offset") / size), F.floor((F.col("offset") + length - 1) / size)
    parts = placed.select("offset", "t", F.explode(F.sequence(first, last)).alias("chunk"))
    begin = F.greatest(F.col("chunk") * size, F.col("offset"))
    end = F.least((F.col("chunk") + 1) * size, F.col("offset") + F.length("t"))
    part = parts.select("chunk", begin.alias("at"), F.substring("t", (begin - F.col("offset") + 1).cast("int"), (end - begin).cast("int")).alias("s"))
    whole = part.groupBy("chunk").agg(F.array_sort(F.collect_list(F.struct("at", "s"))).alias("rows")).select("chunk", F.array_join(F.transform("rows", lambda r: r["s"]), "").alias("body"))
    hops = -(-left // size) if left else 0
    tail = whole.select("chunk", "body", F.explode(F.array(*(F.lit(k) for k in range(hops + 1)))).alias("hop")).select((F.col("chunk") + F.col("hop")).alias("chunk"), F.col("hop"), F.when(F.col("hop") > 0, F.right("body", F.lit(left))).otherwise(F.col("body")).alias("body"))
    joined = tail.groupBy("chunk").agg(F.array_sort(F.collect_list(F.struct((-F.col("hop")).alias("k"), "body"))).alias("rows"))
    text = joined.select("chunk", F.array_join(F.transform(F.filter("rows", lambda r: r["k"] < 0), lambda r: r["body"]), "").alias("before"), F.try_element_at(F.filter("rows", lambda r: r["k"] == 0), F.lit(1))["body"].alias("body"))
    return text.where("body is not null").select(F.lit(number).cast("long").alias("seq_id"), (F.col("chunk") * size + 1).cast("long").alias("start"), (F.substring(F.col("before"), F.greatest(F.length("before") - left + 1, F.lit(1)), F.lit(left)) if left else F.lit("")).alias("left"), "body")


def events(chunked: DataFrame, order: int) -> DataFrame:
    """A row for every symbol: seq_id, pos, sym, past (the up to ``order`` symbols before it)."""
    both = chunked.select("seq_id", "start", F.length("left").alias("l"), F.concat("left", "body").alias("s"), F.posexplode(F.split("body", "")).alias("i", "sym"))
    have = F.least(F.col("l") + F.col("i"), F.lit(order))
    return both.select("seq_id", (F.col("start") + F.col("i")).cast("long").alias("pos"), "sym", (F.substring(F.col("s"), F.col("l") + F.col("i") - have + 1, have) if order else F.lit("")).alias("past"))


def with_precursor(seqs: DataFrame, precursor: str) -> DataFrame:
    """A fixed beginning before each sequence (contexts reach into it)."""
    return seqs.select("seq_id", F.concat(F.lit(precursor), "t").alias("t"))


def root_half(n: int) -> str:
    """The first n binary digits of 1/sqrt 2, in reversed order: an aperiodic precursor for two symbols."""
    from math import isqrt

    return format(isqrt(1 << (2 * n - 1)), "b").zfill(n)[::-1]


def scramble_words(seqs: DataFrame, seed: int = 0) -> DataFrame:
    """The words of each sequence in the order of hashes of their places: same words, no long correlations."""
    mixed = F.array_sort(F.transform(F.split("t", " "), lambda w, i: F.struct(F.md5(F.concat_ws(":", i.cast("string"), F.lit(str(seed)))).alias("h"), w.alias("w"))))
    return seqs.select("seq_id", F.array_join(F.transform(mixed, lambda r: r["w"]), " ").alias("t"))
