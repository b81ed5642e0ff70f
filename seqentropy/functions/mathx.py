"""Special functions as Column expressions: no Python at run time.

Each takes and returns Columns; ``sql_*`` give the same formulas as SQL text, term by term, for oracles.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

SHIFT = 10
HALF_LOG_TWO_PI = 0.5 * math.log(2 * math.pi)


def digamma(x: Column) -> Column:
    """Logarithmic derivative of the gamma function for x > 0: asymptotic series at x + 10, shifted back."""
    y = x.cast("double") + SHIFT
    series = F.ln(y) - 1 / (2 * y) - 1 / (12 * y * y) + 1 / (120 * y * y * y * y) - 1 / (252 * y * y * y * y * y * y)
    for k in range(SHIFT):
        series = series - 1 / (x + k)
    return series


def sql_digamma(x: str) -> str:
    y = f"(({x}) + {SHIFT}.0)"
    return f"(ln({y}) - 1/(2*{y}) - 1/(12*{y}*{y}) + 1/(120*{y}*{y}*{y}*{y}) - 1/(252*{y}*{y}*{y}*{y}*{y}*{y})" + "".join(f" - 1.0/(({x}) + {k})" for k in range(SHIFT)) + ")"


def lgamma(x: Column) -> Column:
    """Logarithm of the gamma function for x > 0."""
    y = x.cast("double") + SHIFT
    series = (y - 0.5) * F.ln(y) - y + HALF_LOG_TWO_PI + 1 / (12 * y) - 1 / (360 * y * y * y) + 1 / (1260 * y * y * y * y * y)
    for k in range(SHIFT):
        series = series - F.ln(x + k)
    return series


def sql_lgamma(x: str) -> str:
    y = f"(({x}) + {SHIFT}.0)"
    return f"(({y} - 0.5)*ln({y}) - {y} + {HALF_LOG_TWO_PI!r} + 1/(12*{y}) - 1/(360*{y}*{y}*{y}) + 1/(1260*{y}*{y}*{y}*{y}*{y})" + "".join(f" - ln(({x}) + {k})" for k in range(SHIFT)) + ")"


def xlogx(x: Column) -> Column:
    return F.when(x > 0, x * F.ln(x)).otherwise(0.0)


def log_add(a: Column, b: Column) -> Column:
    """ln(exp a + exp b)."""
    top = F.greatest(a, b)
    return top + F.ln(F.exp(a - top) + F.exp(b - top))


def unit(units: str, d: float | None = None) -> float:
    """What nats are divided by."""
    if units == "base_d":
        return math.log(d)
    return {"nats": 1.0, "bits": math.log(2)}[units]
