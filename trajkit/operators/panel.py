"""Activity logs to per-item count series.

A panel is long, ``(item_id, t, n)`` with active periods only, or dense, ``(item_id, series)`` with
one number for each of W periods.  The long form is what the operators work on: absent periods
are zeros by definition and need no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def day_index(at: Column, origin: str = "2024-01-01") -> Column:
    return F.datediff(at, F.lit(origin).cast("date"))


def month_index(at: Column, year: int = 1995) -> Column:
    return (F.year(at) - year) * 12 + F.month(at) - 1


def quarter_index(at: Column, year: int = 1995) -> Column:
    return (F.year(at) - year) * 4 + F.quarter(at) - 1


def half_year_age(at: Column, birth: Column) -> Column:
    """Whole half-years since birth."""
    months = (F.year(at) - F.year(birth)) * 12 + F.month(at) - F.month(birth) - F.when(F.dayofmonth(at) < F.dayofmonth(birth), 1).otherwise(0)
    return F.floor(months / 6)


def build_panel(log: DataFrame, item: str, t: Column, weight: Column | None = None) -> DataFrame:
    """One shuffle of partial counts; a hot item sends one row a task and period at most."""
    n = F.count("*") if weight is None else F.sum(weight)
    return log.groupBy(F.col(item).alias("item_id"), t.cast("int").alias("t")).agg(n.cast("long").alias("n"))


def build_panel_from_birth(log: DataFrame, item: str, at: str) -> DataFrame:
    """Half-years since each item's own first record."""
    birth = log.groupBy(F.col(item).alias("__item")).agg(F.min(at).alias("__birth"))
    joined = log.join(birth, F.col(item) == F.col("__item"))
    return build_panel(joined, item, half_year_age(F.col(at), F.col("__birth")))


def clip_window(panel: DataFrame, w: int, inclusive_end: bool = False) -> DataFrame:
    return panel.filter((F.col("t") >= 0) & (F.col("t") < w + int(inclusive_end)))


def cohort(items: DataFrame, birth: Column, period) -> DataFrame:
    return items.filter(birth == period)


def densify_long(panel: DataFrame, w: int) -> DataFrame:
    """A row for each of the w periods; absent ones are 0."""
    grid = panel.select("item_id").distinct().select("item_id", F.explode(F.sequence(F.lit(0), F.lit(w - 1))).alias("t"))
    return grid.join(panel, ["item_id", "t"], "left").select("item_id", "t", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


def densify(panel: DataFrame, w: int) -> DataFrame:
    """One array of w numbers an item; no join, and a group never has more than w entries."""
    inside = clip_window(panel, w)
    m = F.map_from_entries(F.collect_list(F.struct("t", "n")))
    one = inside.groupBy("item_id").agg(m.alias("m"))
    series = F.transform(F.sequence(F.lit(0), F.lit(w - 1)), lambda t: F.coalesce(F.try_element_at("m", t), F.lit(0)).cast("long"))
    return one.select("item_id", series.alias("series"))


def totals(panel: DataFrame, w: int) -> DataFrame:
    """Sum over the window and mean rate a period."""
    c = F.sum("n").cast("long")
    return clip_window(panel, w).groupBy("item_id").agg(c.alias("total")).withColumn("rate", F.col("total") / F.lit(w))


def success_ratio(totals_: DataFrame, floor: float = 5.0, mu: str = "own", field: str | None = None) -> DataFrame:
    """total / max(mean, floor).  ``mu``: the item's own rate, its cohort's mean total, or the mean
    total of its ``field``."""
    if mu == "own":
        mean = F.col("rate")
        out = totals_
    else:
        keys = [field] if mu == "field" else []
        means = totals_.groupBy(*keys).agg(F.avg("total").alias("group_mean"))
        out = totals_.join(means, keys) if keys else totals_.crossJoin(F.broadcast(means))  # one row
        mean = F.col("group_mean")
    return out.withColumn("ratio", F.col("total") / F.greatest(mean, F.lit(floor)))


def eligible(panel: DataFrame, w: int, least: int = 5) -> DataFrame:
    """Items whose own-rate ratio is 1 or more.  With w >= 1 that is the case exactly if the total
    reaches ``least``, so the filter is applied to the sum."""
    return clip_window(panel, w).groupBy("item_id").agg(F.sum("n").cast("long").alias("total")).filter(F.col("total") >= least)


def keep_items(panel: DataFrame, items: DataFrame) -> DataFrame:
    return panel.join(items.select("item_id"), "item_id", "left_semi")


def eligible_panel(panel: DataFrame, w: int, least: int = 5) -> DataFrame:
    """The clipped panel of eligible items, by a window sum on the item's partition: no join."""
    part = W.partitionBy("item_id")
    return clip_window(panel, w).withColumn("__c", F.sum("n").over(part)).filter(F.col("__c") >= least).drop("__c")


def drop_self_mentions(log: DataFrame, source: Column, target: Column) -> DataFrame:
    return log.filter(source != target)


def window_impact(panel: DataFrame, windows: tuple[int, ...] = (2, 5)) -> DataFrame:
    """Totals and averages within the first periods: the traditional indicators."""
    cols = []
    for k in windows:
        s = F.coalesce(F.sum(F.when(F.col("t") < k, F.col("n"))), F.lit(0)).cast("long")
        cols += [s.alias(f"total_{k}"), (s / F.lit(k)).alias(f"mean_{k}")]
    return panel.groupBy("item_id").agg(*cols)


def cumulate(panel: DataFrame) -> DataFrame:
    """Running total and its share of the item's total."""
    part = W.partitionBy("item_id")
    run = F.sum("n").over(part.orderBy("t").rowsBetween(W.unboundedPreceding, 0)).cast("long")
    return panel.select("item_id", "t", "n", run.alias("cum"), (run / F.sum("n").over(part)).alias("share"))
