"""Vector expressions that stay in the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a, b) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def unit(v: Column) -> Column:
    """v over its length; a zero vector stays as it is."""
    return F.transform(F.array(v), lambda x: F.transform(x, lambda c: c / F.coalesce(F.nullif(F.sqrt(dot(x, x)), F.lit(0.0)), F.lit(1.0))))[0]


def add(a, b, scale: float = 1.0) -> Column:
    return F.zip_with(a, b, lambda x, y: x + F.lit(scale) * y)


def binomial_two_sided(a: Column, b: Column) -> Column:
    """Exact two-sided sign test on a and b discordant cases."""
    n, k = a + b, F.least(a, b)
    log_fact = lambda x: F.aggregate(F.sequence(F.lit(1).cast("long"), F.greatest(x, F.lit(1).cast("long"))), F.lit(0.0), lambda s, i: s + F.ln(i.cast("double")))
    tail = F.aggregate(F.transform(F.sequence(F.lit(0).cast("long"), k), lambda i: F.exp(log_fact(n) - log_fact(i) - log_fact(n - i) - n * F.ln(F.lit(2.0)))), F.lit(0.0), lambda s, x: s + x)
    return F.when(n == 0, F.lit(1.0)).otherwise(F.least(F.lit(1.0), F.lit(2.0) * tail))
