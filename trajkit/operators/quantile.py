"""Exact quantiles of a column without sorting it or bringing it to one task."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BINS = 4096
KEPT = 10_000  # values that the driver sorts at the end


def order_statistic(values: DataFrame, rank: int, low: float, high: float) -> float:
    """The value of ``rank`` (from 0) in column v.  Each pass counts equal-width bins between the bounds
    (at most ``BINS`` rows reach the driver) and goes on inside the bin that holds the rank."""
    while low < high:
        inside = values.filter((F.col("v") >= low) & (F.col("v") <= high))
        width = (high - low) / BINS
        place = F.least(F.lit(BINS - 1), F.floor((F.col("v") - low) / width)).cast("int") if width > 0 else F.lit(0)
        bins = sorted(inside.groupBy(place.alias("bin")).agg(F.count("*").alias("n"), F.min("v").alias("a"), F.max("v").alias("b")).collect())
        for _, n, a, b in bins:
            if rank < n:
                break
            rank -= n
        if a == b:
            return a
        if n <= KEPT:
            rows = values.filter((F.col("v") >= a) & (F.col("v") <= b)).collect()
            return sorted(r[0] for r in rows)[rank]
        low, high = a, b
    return low


def exact_quantile(df: DataFrame, value: Column, q: float) -> float | None:
    """Quantile with linear interpolation between neighbours; nulls and NaN take no part."""
    v = df.select(value.cast("double").alias("v")).filter("v IS NOT NULL AND NOT isnan(v)")
    n, low, high = v.agg(F.count("*"), F.min("v"), F.max("v")).first()
    if not n:
        return None
    at = q * (n - 1)
    a = order_statistic(v, math.floor(at), low, high)
    b = order_statistic(v, math.ceil(at), low, high) if at > math.floor(at) else a
    return a + (b - a) * (at - math.floor(at))
