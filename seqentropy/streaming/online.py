"""Streams of events: entropies over event-time windows, and gamblers who bet before each event."""

from __future__ import annotations

import json
import sys
from collections.abc import Iterator

from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
TYPES = ["click", "error", "purchase", "signup", "view"]


def event_stream(spark: SparkSession, folder: str, name: str = "events.parquet", files: int = 1) -> DataFrame:
    """A file stream of a folder's event files."""
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", name).option("maxFilesPerTrigger", files).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def windowed_entropy(events: DataFrame, types: list[str], width: str = "1 hour", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """start, n, bits: the entropy of event types over tumbling or sliding windows.  State is one count a type and window."""
    span = F.window("ts", width, slide) if slide else F.window("ts", width)
    counts = [F.sum(F.when(F.col("event_type") == t, 1).otherwise(0)).alias(f"c{k}") for k, t in enumerate(types)]
    g = events.withWatermark("ts", late).groupBy(span.alias("w")).agg(F.count("*").alias("n"), *counts)
    h = sum((F.when(F.col(f"c{k}") > 0, -(F.col(f"c{k}") / F.col("n")) * F.log2(F.col(f"c{k}") / F.col("n"))).otherwise(0.0) for k in range(len(types))), F.lit(0.0))
    return g.select(F.col("w.start").alias("start"), "n", h.alias("bits"))


def session_counts(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """user_id, start, n of sessions."""
    g = events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return g.select("user_id", F.col("w.start").alias("start"), "n")


def deduplicated(events: DataFrame, late: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def online_gamble(events: DataFrame, types: list[str], order: int = 1, beta: float = 0.5, max_nodes: int = 4096) -> DataFrame:
    """user_id, n, nats (for each batch, the running totals of every user that had events): each event is bet on with the counts after the user's last ``order`` events.

    State is one user's counts.  It is bounded: beyond ``max_nodes`` contexts the oldest ones go.
    """
    d = len(types)

    def bet(key, frames: Iterator, state: GroupState):
        import math

        import pandas as pd

        past, n, nats, table = state.get if state.exists else ("", 0, 0.0, "{}")
        counts: dict[str, list[int]] = json.loads(table)
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        for kind in rows["event_type"]:
            if kind not in types:
                continue
            s = types.index(kind)
            own = counts.setdefault(past, [0] * d)
            nats -= math.log((own[s] + beta) / (sum(own) + beta * d))
            own[s] += 1
            n += 1
            past = (past + chr(97 + s))[-order:] if order else ""
            if len(counts) > max_nodes:
                counts.pop(next(iter(counts)))
        state.update((past, n, nats, json.dumps(counts)))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "nats": [nats]})

    return events.where("user_id is not null").groupBy("user_id").applyInPandasWithState(bet, "user_id long, n long, nats double", "past string, n long, nats double, counts string", "update", GroupStateTimeout.NoTimeout)


def enriched(events: DataFrame, customers: DataFrame) -> DataFrame:
    """Stream-static join: each event with its user's segment."""
    return events.join(customers.select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id", "left")


def followed_by(events: DataFrame, first: str, second: str, within: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Stream-stream join: pairs of a user's events of two types in a time span."""
    a = events.where(F.col("event_type") == first).select(F.col("user_id").alias("user_a"), F.col("ts").alias("ts_a"), F.col("event_id").alias("id_a")).withWatermark("ts_a", late)
    b = events.where(F.col("event_type") == second).select(F.col("user_id").alias("user_b"), F.col("ts").alias("ts_b"), F.col("event_id").alias("id_b")).withWatermark("ts_b", late)
    return a.join(b, F.expr(f"user_a = user_b and ts_b > ts_a and ts_b <= ts_a + interval {within}")).select(F.col("user_a").alias("user_id"), "id_a", "id_b")


def run_available(stream: DataFrame, path: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there and returns what it has written: files for append, the last table of each batch for update and complete."""
    spark = stream.sparkSession
    writer = stream.writeStream.option("checkpointLocation", f"{path}-state").trigger(availableNow=True)
    if mode == "append":
        writer.outputMode("append").format("parquet").option("path", path).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(path)
    schema = stream.schema

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("append").parquet(path)

    writer.outputMode(mode).foreachBatch(keep).start().awaitTermination()
    return spark.read.schema(StructType([*schema.fields, StructField("batch", IntegerType())])).parquet(path)


register_pickle_by_value(sys.modules[__name__])
