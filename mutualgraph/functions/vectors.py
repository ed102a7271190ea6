"""Functions on array columns."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def dot(a: Column | str, b: Column | str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda acc, v: acc + v)


def power_sum(a: Column | str, p: float = 1.0) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda acc, x: acc + F.pow(F.abs(x.cast("double")), F.lit(p)))


def total(a: Column | str) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda acc, x: acc + x.cast("double"))


def axpy(alpha: float, x: Column | str, y: Column | str) -> Column:
    return F.zip_with(x, y, lambda p, q: alpha * p + q)


def norms(rows: DataFrame) -> DataFrame:
    """l1, l2 and signed (entries summed without absolute values) of all rows (vec)."""
    return rows.agg(F.sum(power_sum("vec", 1.0)).alias("l1"), F.sqrt(F.sum(power_sum("vec", 2.0))).alias("l2"), F.sum(total("vec")).alias("signed"))
