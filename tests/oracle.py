"""Runs a query and its SQL and compares them."""

import duckdb
import pandas as pd

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def rows(frame: pd.DataFrame) -> list[tuple]:
    def text(v) -> str:
        if pd.isna(v):
            return "NULL"
        if isinstance(v, float):
            return str(int(v)) if v == int(v) else repr(round(v, 6))
        return str(v)

    return sorted(tuple(text(v) for v in r) for r in frame[sorted(frame.columns)].itertuples(index=False))


def same(spark, sf: str, query, sql: str) -> None:
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from read_parquet('{sf}/{t}.parquet')")
    ours, theirs = query(spark, sf).toPandas(), con.execute(sql).df()
    assert sorted(ours.columns) == sorted(theirs.columns)
    assert rows(ours) == rows(theirs)
