"""Error bounds and the linear-scaling quantiser, as expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fieldloom.model import ErrorBound


def quantise(value: Column | str, eps: Column) -> Column:
    """The nearest multiple of twice the bound; ties go up, for negative values too."""
    v = F.col(value) if isinstance(value, str) else value
    return F.floor(v.cast("double") / (2 * eps) + F.lit(0.5)).cast("bigint")


def dequantise(q: Column | str, eps: Column) -> Column:
    v = F.col(q) if isinstance(q, str) else q
    return v.cast("double") * (2 * eps)


def floor_div(a: Column, b) -> Column:
    """Division that rounds down for either sign."""
    return ((a - F.pmod(a, b)) / b).cast("bigint")


def half_down_mean(total: Column, n: Column) -> Column:
    """The mean of integers, rounded to the nearest with ties down, in whole numbers."""
    a = n - 2 * total
    b = 2 * n
    return -F.expr("0").cast("bigint") - ((a - F.pmod(a, b)) / b).cast("bigint")


def grid_facts(points: DataFrame, bound: ErrorBound) -> DataFrame:
    """One row a field: eps, extents d0, d1, d2, and the number of points."""
    size = F.lit(float(bound.size))
    span = F.max("value") - F.min("value")
    # a constant field has no range; its bound is relative to its magnitude
    fallback = size * F.greatest(F.max(F.abs("value")), F.lit(1.0))
    eps = F.when(span > 0, size * span).otherwise(fallback) if bound.relative else F.max(size)
    ends = [(F.max(c) + 1).cast("bigint").alias(f"d{a}") for a, c in enumerate("ijk")]
    return points.groupBy("field").agg(eps.alias("eps"), *ends, F.count("*").alias("n_points"))


def quantised(points: DataFrame, bound: ErrorBound) -> DataFrame:
    """``points`` (field, i, j, k, value) with q and the grid facts; there is one facts row a field."""
    return points.join(F.broadcast(grid_facts(points, bound)), "field").withColumn("q", quantise("value", F.col("eps")))


def checked(points: DataFrame, on_invalid: str = "error", fill: float = 0.0) -> DataFrame:
    """``points`` without null, NaN or infinite values: they raise, are filled, or are dropped ('mask')."""
    v = F.col("value")
    bad = v.isNull() | F.isnan(v) | (F.abs(v) == float("inf"))
    if on_invalid == "mask":
        return points.where(~bad)
    other = F.lit(fill) if on_invalid == "fill" else F.raise_error(F.lit("a field value is null, NaN or infinite")).cast("double")
    return points.withColumn("value", F.when(bad, other).otherwise(v))
