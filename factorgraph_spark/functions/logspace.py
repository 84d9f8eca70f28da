"""Arrays of log values as column expressions, all within the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Log of what stands for zero; its exponential is still above 0.
LOG_ZERO = -700.0


def lse(values: Column) -> Column:
    """log(sum(exp(values))), shifted by the largest. The fold carries the largest so far and the sum in its terms: one pass over values."""

    def merge(acc: Column, x: Column) -> Column:
        top = F.greatest(acc["top"], x)
        return F.struct(top.alias("top"), (acc["sum"] * F.exp(acc["top"] - top) + F.exp(x - top)).alias("sum"))

    start = F.struct(F.lit(-1e300).alias("top"), F.lit(0.0).alias("sum"))
    return F.aggregate(values, start, merge, lambda acc: acc["top"] + F.ln(acc["sum"]))


def lnorm(values: Column) -> Column:
    """values minus their lse, floored."""
    # The one-element array binds values and total, so neither is computed once per element.
    bound = F.transform(F.array(values), lambda v: F.struct(v.alias("v"), lse(v).alias("t")))
    return F.get(F.transform(bound, lambda b: F.transform(b["v"], lambda x: F.greatest(x - b["t"], F.lit(LOG_ZERO)))), F.lit(0))


def l1(a: Column, b: Column) -> Column:
    """L1 distance of two log distributions, in probability space."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.abs(F.exp(x) - F.exp(y))), F.lit(0.0), lambda s, x: s + x)


def damp(new: Column, old: Column, weight: float, space: str = "prob") -> Column:
    """Mix of a new and an old log message; weight is the share of the old one."""
    if not weight:
        return new
    if space == "log":
        return lnorm(F.zip_with(new, old, lambda n, o: (1 - weight) * n + weight * o))
    return lnorm(F.zip_with(new, old, lambda n, o: F.ln((1 - weight) * F.exp(n) + weight * F.exp(o))))


def add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def minus(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x - y)


def md5_uniform(text: Column) -> Column:
    """A number in [0, 1) from text: the first eight hex digits of its md5. Other engines repeat it."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def binary_message(weight: Column, odds: Column) -> Column:
    """Log-odds that an equality factor of that log-weight passes on."""
    return 2 * F.atanh(F.tanh(weight / 2) * F.tanh(odds / 2))
