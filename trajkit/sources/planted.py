"""Planted panels: a deterministic thinning of given rows that gives every item a known shape.

A row is kept if a number in [0, 1) made from the md5 of its key lies below the shape of its item's
class at its period, so any engine makes the same panel.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from trajkit.operators import panel as P
from trajkit.sources.tables import read_table

LINE_KEY = "concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey, {date})"
_D = lambda v: f"CAST({v} AS DOUBLE)"
SHAPES = ("exp(-8 * {x})", f"greatest({_D(0.12)}, exp(-pow(({{x}} - {_D(0.18)}) / {_D(0.12)}, 2)))", f"pow({{x}}, {_D(1.5)})", f"exp(-pow(({{x}} - {_D(0.62)}) / {_D(0.12)}, 2))")


def shape_sql(cls: str, t: str, w: int) -> str:
    x = f"((CAST({t} AS DOUBLE) + CAST(0.5 AS DOUBLE)) / CAST({w} AS DOUBLE))"
    return "CASE " + cls + " " + " ".join(f"WHEN {g} THEN " + s.format(x=x) for g, s in enumerate(SHAPES)) + " END"


def unit(key: Column) -> Column:
    return F.conv(F.substring(F.md5(key.cast("binary")), 1, 8), 16, 10).cast("double") / 4294967296.0


def class_sql(item: str, imbalanced: bool = False) -> str:
    if imbalanced:
        return f"(CASE WHEN {item} % 100 < 2 THEN 0 WHEN {item} % 100 < 47 THEN 1 WHEN {item} % 100 < 99 THEN 2 ELSE 3 END)"
    return f"({item} % 4)"


def planted_panel(spark: SparkSession, sf_dir: str, kind: str = "supp", imbalanced: bool = False) -> tuple[DataFrame, int]:
    """(panel, W) of suppliers by month in 28 quarters (easy), users by day (medium), parts by quarter (hard)."""
    if kind == "user":
        log = read_table(spark, sf_dir, "events", "event_id", "user_id", "ts")
        item, w, t, key = "user_id", 30, P.day_index(F.col("ts")), F.col("event_id").cast("string")
    else:
        item, w = ("l_suppkey" if kind == "supp" else "l_partkey"), 28
        log = read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate")
        t, key = P.quarter_index(F.col("l_shipdate")), F.expr(LINE_KEY.format(date="date_format(l_shipdate, 'yyyy-MM-dd')"))
    log = log.withColumn("__t", t).filter((F.col("__t") >= 0) & (F.col("__t") < w))
    kept = log.filter(unit(key) < F.expr(shape_sql(class_sql(item, imbalanced), "__t", w)))
    return P.build_panel(kept, item, F.col("__t")), w


def planted_sql(kind: str = "supp", imbalanced: bool = False) -> str:
    if kind == "user":
        item, w, t, key, table = "user_id", 30, "date_diff('day', DATE '2024-01-01', ts::DATE)", "event_id::VARCHAR", "events"
    else:
        item, w, table = ("l_suppkey" if kind == "supp" else "l_partkey"), 28, "lineitem"
        t, key = "((year(l_shipdate) - 1995) * 4 + quarter(l_shipdate) - 1)", LINE_KEY.format(date="strftime(l_shipdate, '%Y-%m-%d')")
    u = f"(('0x' || substr(md5({key}), 1, 8))::BIGINT / 4294967296.0)"
    return f"SELECT {item} AS item_id, t::INTEGER AS t, count(*)::BIGINT AS n FROM (SELECT *, {t} AS t FROM {table}) WHERE t >= 0 AND t < {w} AND {u} < {shape_sql(class_sql(item, imbalanced), 't', w)} GROUP BY 1, 2"


def truth(panel: DataFrame, imbalanced: bool = False) -> DataFrame:
    return panel.select("item_id").distinct().select("item_id", F.expr(class_sql("item_id", imbalanced)).cast("int").alias("class"))
