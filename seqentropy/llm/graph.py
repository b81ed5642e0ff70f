"""Connected components in DataFrame joins, with edges reduced to forests inside each task first."""

from __future__ import annotations

import sys
from collections.abc import Iterator

import pyarrow as pa
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut


class Forest:
    """Disjoint sets whose names are their smallest members."""

    def __init__(self):
        self.up: dict[int, int] = {}

    def top(self, k: int) -> int:
        up = self.up
        root = k
        while up.get(root, root) != root:
            root = up[root]
        while up.get(k, k) != root:
            up[k], k = root, up[k]
        return root

    def join(self, a: int, b: int) -> bool:
        """Whether the two were apart."""
        a, b = self.top(a), self.top(b)
        if a != b:
            self.up[max(a, b)] = min(a, b)
        return a != b


def _forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of a task's edges: each node but the smallest of its component, with the smallest."""
    forest = Forest()
    for batch in batches:
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            forest.join(a, b)
    nodes = list(forest.up)
    for k in range(0, len(nodes), 100_000):
        own = nodes[k:k + 100_000]
        yield pa.RecordBatch.from_arrays([pa.array(own, pa.int64()), pa.array([forest.top(x) for x in own], pa.int64())], ["u", "v"])


def _mark(edges: DataFrame) -> tuple:
    r = edges.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
    return r.n, r.h


def _jump(home: DataFrame) -> DataFrame:
    """Of rows u, v: each with v's smallest parent in v's place, if it has one; one row for a row, however many parents there are.

    What was connected stays so: each node's smallest parents lead to a root whose children keep it, and a row joins
    u's line to v's.
    """
    parents = home.groupBy(F.col("u").alias("v")).agg(F.min("v").alias("w"))
    return home.join(parents, "v", "left").select("u", F.coalesce("w", "v").alias("v"))


def components(edges: DataFrame, most: int = 40) -> DataFrame:
    """edges: u, v (any direction).  Returns node, root: the smallest node that is reachable, for nodes other than roots.

    A task's edges become a forest of at most as many rows as it has nodes, so a node with very many edges shrinks to
    one row a task before anything is shuffled.  Rounds then bring a node's rows together, replace them by a forest
    again, and let every node point to the smallest node that its parent points to, until nothing changes: each node then
    has one parent, and no parent has one.  What a task holds is bounded by its partition of the edges.
    """
    now = cut(edges.select("u", "v").where("u <> v").mapInArrow(_forest, "u long, v long"), "edges")
    mark = _mark(now)
    for _ in range(most):
        if not mark[0]:
            break
        home = now.repartition("u").mapInArrow(_forest, "u long, v long")
        now = cut(_jump(home).distinct(), "edges")
        last, mark = mark, _mark(now)
        if mark == last:
            break
    else:
        raise RuntimeError("components didn't settle")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root"))


register_pickle_by_value(sys.modules[__name__])
