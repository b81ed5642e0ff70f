"""Readers with fixed schemas, and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

REQUIRED = {
    "documents": {"doc_id": "bigint", "text": "string", "lang": "string", "source": "string"},
    "benchmark": {"item_id": "bigint", "text": "string"},
    "conversations": {"conv_id": "bigint", "turn": "bigint", "role": "string", "text": "string"},
    "pages": {"page_id": "bigint", "url": "string", "html": "string"},
    "events": {"event_id": "bigint", "user_id": "bigint", "event_type": "string", "value": "double"},
    "orders": {"o_orderkey": "bigint", "o_custkey": "bigint", "o_orderstatus": "string", "o_orderpriority": "string"},
    "lineitem": {"l_orderkey": "bigint", "l_suppkey": "bigint", "l_returnflag": "string", "l_linestatus": "string"},
    "labels": {"doc_id": "bigint"},
}


def require_columns(df: DataFrame, needed: dict[str, str]) -> DataFrame:
    """The frame, or an error that names missing columns and wrong types."""
    have = dict(df.dtypes)
    wrong = {c: (t, have.get(c)) for c, t in needed.items() if have.get(c) != t}
    if wrong:
        raise ValueError(f"columns (needed, found): {wrong}")
    return df


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return require_columns(spark.read.parquet(f"{sf_dir}/{name}.parquet"), REQUIRED.get(name, {}))


def text_files(spark: SparkSession, path: str) -> DataFrame:
    """path, text: one row a file (files that fit a row)."""
    return spark.read.text(path, wholetext=True).selectExpr("_metadata.file_path as path", "value as text")


def read(spark: SparkSession, path: str, kind: str, schema: str) -> DataFrame:
    """parquet, orc, json or csv with a stated schema: nothing is inferred."""
    reader = spark.read.schema(schema)
    return reader.option("header", True).csv(path) if kind == "csv" else reader.format(kind).load(path)


def write(df: DataFrame, path: str, by: list[str] | None = None, kind: str = "parquet", mode: str = "overwrite") -> None:
    writer = df.write.mode(mode)
    (writer.partitionBy(*by) if by else writer).format(kind).save(path)
