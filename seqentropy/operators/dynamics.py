"""Test sources with known entropy: chaotic maps, a cellular automaton, chains and biased bits; Lyapunov exponents.

One row of seeds is one replica; replicas run apart from each other in a kernel that iterates all replicas of a batch
together.
"""

from __future__ import annotations

import math
import sys

import numpy as np
import pyarrow as pa
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# The parameters of the experiments.
CHAOTIC, INTERMITTENT, ACCUMULATION = 1.8, 1.7499, 1.401155189092
PLANE_A, PLANE_B = 1.4, 0.3
LASER = {"p": 1.0, "b": 0.9, "kappa": 0.4, "alpha": 6.0}


def seeds(df: DataFrame, key: str, replicas: int | None = None) -> DataFrame:
    """seq_id, x0 between -0.9 and 0.9 from a key's golden-ratio multiples; the first replicas by key if a number is given (the experiment's number of runs)."""
    rows = df.select(F.col(key).cast("long").alias("seq_id")).where("seq_id is not null").distinct()
    if replicas:
        rows = rows.orderBy("seq_id").limit(replicas)
    turn = F.col("seq_id") * 0.6180339887
    return rows.select("seq_id", (-0.9 + 1.8 * (turn - F.floor(turn))).alias("x0"))


def _step(kind: str, a: float, x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    if kind == "quadratic":
        return 1 - a * x * x, y
    if kind == "plane":
        return 1 + PLANE_B * y - a * x * x, x
    z = x + 1j * y
    z = LASER["p"] + LASER["b"] * z * np.exp(1j * LASER["kappa"] - 1j * LASER["alpha"] / (1 + np.abs(z) ** 2))
    return z.real, z.imag


def orbits(kind: str, x0: np.ndarray, n: int, burn: int, a: float) -> np.ndarray:
    """x of n steps after the burn-in, a row for each replica."""
    x, y = x0.astype(float), np.zeros(len(x0))
    out = np.empty((len(x0), n))
    for k in range(burn + n):
        x, y = _step(kind, a, x, y)
        if k >= burn:
            out[:, k - burn] = x
    return out


def map_symbols(start: DataFrame, kind: str, n: int, burn: int = 1000, a: float = CHAOTIC) -> DataFrame:
    """seq_id, t: binary sequences of a map (quadratic, plane or laser) cut at x = 0.

    For the two-dimensional maps this cut is not known to be generating: their rates are only bounds to look at.
    """

    def run(batches):
        for batch in batches:
            x = orbits(kind, batch.column(1).to_numpy(), n, burn, a)
            bits = (x >= (0 if kind != "laser" else 0.5)).astype(np.uint8) + 48
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([r.tobytes().decode() for r in bits], pa.string())], ["seq_id", "t"])

    return start.select("seq_id", "x0").mapInArrow(run, "seq_id long, t string")


def map_series(start: DataFrame, kind: str, n: int, burn: int = 0, a: float = CHAOTIC) -> DataFrame:
    """seq_id, pos, x."""

    def run(batches):
        for batch in batches:
            x = orbits(kind, batch.column(1).to_numpy(), n, burn, a)
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(batch.column(0).to_numpy(), n)), pa.array(np.tile(np.arange(1, n + 1), len(x))), pa.array(x.ravel())], ["seq_id", "pos", "x"])

    return start.select("seq_id", "x0").mapInArrow(run, "seq_id long, pos long, x double")


def _slopes(kind: str, x0: np.ndarray, n: int, burn: int, a: float) -> np.ndarray:
    x, y = x0.astype(float), np.zeros(len(x0))
    u, v, total = np.ones(len(x0)), np.zeros(len(x0)), np.zeros(len(x0))
    for k in range(burn + n):
        if kind == "quadratic":
            u, v = -2 * a * x * u, v * 0
        elif kind == "plane":
            u, v = -2 * a * x * u + PLANE_B * v, u
        else:
            eps = 1e-7
            fx, fy = _step(kind, a, x, y)
            gx, gy = _step(kind, a, x + eps * u, y + eps * v)
            u, v = (gx - fx) / eps, (gy - fy) / eps
        x, y = _step(kind, a, x, y)
        size = np.hypot(u, v)
        size[size == 0] = 1e-300
        if k >= burn:
            total += np.log(size)
        u, v = u / size, v / size
    return total / n


def lyapunov(start: DataFrame, kind: str, n: int, burn: int = 1000, a: float = CHAOTIC) -> DataFrame:
    """seq_id, lyapunov (nats a step): mean logarithm of how a tangent vector grows.  Positive ones equal the entropy."""

    def run(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(_slopes(kind, batch.column(1).to_numpy(), n, burn, a))], ["seq_id", "lyapunov"])

    return start.select("seq_id", "x0").mapInArrow(run, "seq_id long, lyapunov double")


def lyapunov_1d(series: DataFrame, a: float) -> DataFrame:
    """seq_id, lyapunov of the quadratic map from its orbit, by an aggregate."""
    return series.groupBy("seq_id").agg(F.avg(F.ln(F.abs(2 * a * F.col("x")))).alias("lyapunov"))


def bernoulli_bits(df: DataFrame, key: str, pos: str, row: list[str], p: float) -> DataFrame:
    """seq_id, pos, sym: independent biased bits from hashes of rows (the same in any engine): 0 with probability p."""
    h = F.conv(F.substring(F.md5(F.concat_ws("|", *(F.col(c).cast("string") for c in row))), 1, 8), 16, 10).cast("long")
    return df.select(F.col(key).cast("long").alias("seq_id"), F.col(pos).cast("long").alias("pos"), F.when(h < int(p * 2**32), "0").otherwise("1").alias("sym"))


def odd_offsets(steps: int) -> list[int]:
    """Offsets of the cells whose sum modulo 2 is a cell after some steps of rule 150: odd coefficients of (1 + x + 1/x)^steps."""
    row = {0: 1}
    for _ in range(steps):
        new: dict[int, int] = {}
        for k, c in row.items():
            for o in (-1, 0, 1):
                new[k + o] = new.get(k + o, 0) ^ c
        row = {k: c for k, c in new.items() if c}
    return sorted(row)


def automaton_150(seqs: DataFrame, steps: int) -> DataFrame:
    """seq_id, t after some steps of rule 150 with open ends: each side loses ``steps`` cells."""
    taps = odd_offsets(steps)

    def run(batches):
        for batch in batches:
            out = []
            for t in batch.column(1).to_pylist():
                bits = np.frombuffer(t.encode(), np.uint8) & 1
                cells = np.zeros(len(bits) - 2 * steps, np.uint8)
                for o in taps:
                    cells ^= bits[steps + o:len(bits) - steps + o]
                out.append((cells + 48).tobytes().decode())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.string())], ["seq_id", "t"])

    return seqs.where(F.length("t") > 2 * steps).select("seq_id", "t").mapInArrow(run, "seq_id long, t string")


def markov_sequence(p: list[list[float]], n: int, seed: int) -> str:
    """A chain whose order is the base-d logarithm of the number of rows of p."""
    rng, d = np.random.default_rng(seed), len(p[0])
    edges, state, out = np.cumsum(np.array(p), 1), 0, []
    for u in rng.random(n).tolist():
        s = min(d - 1, int(np.searchsorted(edges[state], u, "right")))
        out.append("0123456789"[s])
        state = (state * d + s) % len(p)
    return "".join(out)


def hashed_chains(rows: DataFrame, key: str, pos: str, row: list[str], p: list[list[float]]) -> DataFrame:
    """seq_id, t: a chain for each key, as ``markov_sequence``'s, its random numbers from hashes of rows in the order of pos."""
    edges, d, m = np.cumsum(np.array(p), 1), len(p[0]), len(p)
    h = F.conv(F.substring(F.md5(F.concat_ws("|", *(F.col(c).cast("string") for c in row))), 1, 8), 16, 10).cast("long") / float(2**32)
    numbers = F.transform(F.array_sort(F.collect_list(F.struct(F.col(pos).alias("pos"), h.alias("u")))), lambda r: r["u"])

    def run(batches):
        for batch in batches:
            out = []
            for us in batch.column(1).to_pylist():
                state, t = 0, []
                for u in us:
                    s = min(d - 1, int(np.searchsorted(edges[state], u, "right")))
                    t.append("0123456789"[s])
                    state = (state * d + s) % m
                out.append("".join(t))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.string())], ["seq_id", "t"])

    return rows.groupBy(F.col(key).cast("long").alias("seq_id")).agg(numbers.alias("us")).mapInArrow(run, "seq_id long, t string")


def entropy_bernoulli(p: float) -> float:
    """Bits."""
    return -p * math.log2(p) - (1 - p) * math.log2(1 - p)


def entropy_markov(p: list[list[float]]) -> float:
    """Bits a symbol of a stationary chain (rows are the states of the last symbols)."""
    d, m = len(p[0]), len(p)
    move = np.zeros((m, m))
    for s in range(m):
        for a in range(d):
            move[s, (s * d + a) % m] += p[s][a]
    pi = np.full(m, 1 / m)
    for _ in range(5000):
        pi = pi @ move
    return float(-sum(pi[s] * x * math.log2(x) for s in range(m) for x in p[s] if x > 0))


register_pickle_by_value(sys.modules[__name__])
