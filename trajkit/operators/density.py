"""Density clustering on a few columns: a grid of cells with the radius as their side, so a point's
neighbours lie in its own and the adjoining cells; no pair outside them is formed."""

from __future__ import annotations

from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trajkit.sources.shared import materialised


def _pairs(z: DataFrame, cols: list[str], eps: float) -> DataFrame:
    """a, b of points within eps (each with itself too).  Equal points are one row with a weight
    beforehand, so a crowded value does not multiply."""
    cell = [F.floor(F.col(c) / eps).cast("long").alias(f"k_{c}") for c in cols]
    left = z.select("point", *cols, *cell)
    shift = F.array(*[F.struct(*[F.lit(v).cast("long").alias(f"s_{c}") for c, v in zip(cols, s)]) for s in product((-1, 0, 1), repeat=len(cols))])
    near = left.withColumn("s", F.explode(shift)).select("point", *cols, *[(F.col(f"k_{c}") + F.col(f"s.s_{c}")).alias(f"k_{c}") for c in cols])
    a, b = near.alias("a"), left.alias("b")
    on = [F.col(f"a.k_{c}") == F.col(f"b.k_{c}") for c in cols]
    d2 = F.lit(0.0)
    for c in cols:
        d2 = d2 + (F.col(f"a.{c}") - F.col(f"b.{c}")) * (F.col(f"a.{c}") - F.col(f"b.{c}"))
    return a.join(b, on).filter(d2 <= eps * eps).select(F.col("a.point").alias("a"), F.col("b.point").alias("b"))


def _points(z: DataFrame, cols: list[str]) -> DataFrame:
    return z.groupBy(*cols).agg(F.count("*").alias("weight"), F.min("item_id").alias("point"))


def neighbour_counts(z: DataFrame, cols: list[str], eps: float) -> DataFrame:
    """Items within eps of each item, itself included."""
    points = materialised(_points(z, cols))
    n = _pairs(points, cols, eps).join(points.select(F.col("point").alias("b"), "weight"), "b").groupBy("a").agg(F.sum("weight").alias("neighbours"))
    per_point = points.join(n, F.col("point") == F.col("a")).select(*cols, "neighbours")
    return z.select("item_id", *cols).join(per_point, cols)


def dbscan(z: DataFrame, cols: list[str], eps: float, min_pts: int) -> DataFrame:
    """item_id, cluster (least id of its core component; null: noise)."""
    points = materialised(_points(z, cols))
    pairs = materialised(_pairs(points, cols, eps))
    n = pairs.join(points.select(F.col("point").alias("b"), "weight"), "b").groupBy("a").agg(F.sum("weight").alias("n"))
    core = materialised(n.filter(F.col("n") >= min_pts).select(F.col("a").alias("point")))
    links = materialised(pairs.join(core.withColumnRenamed("point", "a"), "a").join(core.withColumnRenamed("point", "b"), "b"))
    label = core.withColumn("label", F.col("point"))
    while True:  # labels jump to their own label's label, so steps grow with the logarithm of a cluster's width
        got = links.join(label.select(F.col("point").alias("b"), "label"), "b").groupBy(F.col("a").alias("point")).agg(F.min("label").alias("low"))
        step = label.join(got, "point", "left").select("point", "label", F.least("label", F.coalesce("low", "label")).alias("new"))
        jump = step.select(F.col("point").alias("__p"), F.col("new").alias("__n"))
        step = materialised(step.join(jump, F.col("new") == F.col("__p"), "left").select("point", "label", F.least("new", F.coalesce("__n", "new")).alias("new")))
        label = step.select("point", F.col("new").alias("label"))
        if not step.filter("new < label").limit(1).count():
            break
    # A border point joins the least cluster among its core neighbours.
    border = pairs.join(label.select(F.col("point").alias("b"), "label"), "b").groupBy(F.col("a").alias("point")).agg(F.min("label").alias("near"))
    named = points.join(label, "point", "left").join(border, "point", "left").select(*cols, F.coalesce("label", "near").alias("cluster"))
    return z.select("item_id", *cols).join(named, cols).select("item_id", "cluster")
