"""SQL names for the methods, and how plans are chosen."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.context_kernel import Tree


def register_all(spark: SparkSession) -> None:
    """text27(t), ascii7(t): SQL functions; seq_entropy(t): an aggregate (plug-in bits a symbol of all texts of a group); phrases(t), block_words(t, n): table functions."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION text27(t STRING) RETURNS STRING RETURN trim(regexp_replace(lower(t), '[^a-z]+', ' '))")
    spark.sql(r"CREATE OR REPLACE TEMPORARY FUNCTION ascii7(t STRING) RETURNS STRING RETURN regexp_replace(t, '[^\\x00-\\x7F]', '')")
    spark.udf.register("seq_entropy", seq_entropy_udf())
    spark.udtf.register("phrases", phrases_udtf())
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION block_words(t STRING, n INT) RETURNS TABLE (word STRING) RETURN SELECT substring(t, i, n) FROM (SELECT explode(sequence(1, length(t) - n + 1)) AS i WHERE length(t) >= n)")


def seq_entropy_udf():
    def entropy(texts: pd.Series) -> float:
        import math
        from collections import Counter

        c: Counter = Counter()
        for t in texts:
            c.update(t or "")
        n = sum(c.values())
        return -sum(v / n * math.log2(v / n) for v in c.values()) if n else 0.0

    return F.pandas_udf(entropy, "double")


def phrases_udtf():
    @F.udtf(returnType="k int, start int, len int")
    class Phrases:
        def eval(self, t: str):
            known: set[str] = set()
            at, k = 0, 0
            while at < len(t or ""):
                size = 1
                while at + size <= len(t) and t[at:at + size] in known:
                    size += 1
                word = t[at:at + size]
                known.add(word)
                k += 1
                yield k, at + 1, len(word)
                at += len(word)

    return Phrases


def choose_engine(longest: int, total: int, tree: Tree, row_limit: int = 5_000_000) -> dict[str, object]:
    """kernel for sequences that fit a row; windows beyond, with counts in blocks where a context may hold a large part of all positions."""
    if longest <= row_limit:
        return {"engine": "kernel", "block": None, "order": tree.order}
    order = tree.order if tree.order is not None else 8
    crowded = 0
    while crowded < order and tree.d ** (crowded + 1) < 10_000:
        crowded += 1
    return {"engine": "windows", "block": max(65_536, total // 100_000), "crowded": crowded, "order": order}


def explain_plan(seqs: DataFrame, tree: Tree) -> dict[str, object]:
    """The choice for a frame of sequences, from one aggregate over their lengths."""
    row = seqs.agg(F.max(F.length("t")).alias("longest"), F.sum(F.length("t")).alias("total")).first()
    return choose_engine(row.longest or 0, row.total or 0, tree) | {"longest": row.longest, "total": row.total}
