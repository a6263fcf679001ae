"""Feature scaling: fit on one pass of column statistics, then a projection."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

Scaler = dict[str, tuple[float, float]]


def fit_zscore(df: DataFrame, cols: list[str], ddof: int = 0) -> Scaler:
    """Mean and standard deviation of each column, rounded so that the order of summation does
    not show; one row goes to the driver."""
    sd = F.stddev_pop if ddof == 0 else F.stddev_samp
    aggs = [a for c in cols for a in (F.round(F.avg(c), 9).alias(f"m_{c}"), F.round(sd(c), 9).alias(f"s_{c}"))]
    r = df.agg(*aggs).first()
    return {c: (float(r[f"m_{c}"] or 0.0), float(r[f"s_{c}"] or 0.0)) for c in cols}


def fit_robust(df: DataFrame, cols: list[str]) -> Scaler:
    """Median and interquartile range."""
    r = df.agg(*[F.percentile(c, F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75))).alias(c) for c in cols]).first()
    return {c: (r[c][1], r[c][2] - r[c][0]) for c in cols}


def scaled(df: DataFrame, scaler: Scaler, keep: tuple[str, ...] = ("item_id",), suffix: str = "") -> DataFrame:
    """A column without spread becomes 0."""
    z = [(F.round((F.col(c) - F.lit(m)) / F.lit(s), 9) if s > 0 else F.lit(0.0)).alias(f"{c}{suffix}") for c, (m, s) in scaler.items()]
    return df.select(*keep, *z)
