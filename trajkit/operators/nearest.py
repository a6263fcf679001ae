"""Exact nearest items in feature space, without forming all pairs.

Items with equal vectors are one point that keeps its ``k + 1`` smallest ids, so a crowded vector does
not multiply.  A k-d tree, cut on the driver from a bounded hash sample, deals the points into leaves.
Each point's distance to the ``k``-th other point of its own leaf bounds its answer from above, and it
then visits exactly the leaves whose bounding box is no farther than that.  Leaves meet points on an
equi-join key, so Spark can split crowded ones; the driver holds the cuts and boxes of ``most`` leaves
at most.  Beyond ``per_leaf * most`` points leaves grow and with them the work of a point.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from trajkit.sources.shared import materialised

SLACK = 1e-6  # distances are rounded, bounds of boxes are not
SAMPLE = 16  # sampled points a leaf
ROWS = 256  # rows whose distances to all boxes are held at once


def cuts(sample: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """Column and value of each inner node of a complete tree, parents first; points above the value go
    right.  A node of equal points keeps all of them left."""
    column, value = np.zeros(2**depth - 1, int), np.full(2**depth - 1, np.inf)
    held = {0: sample}
    for node in range(2**depth - 1):
        x = held.pop(node)
        if len(x) and (spread := np.ptp(x, axis=0)).max() > 0:
            column[node] = spread.argmax()
            v = np.sort(x[:, column[node]])
            middle = v[len(v) // 2]
            value[node] = middle if middle < v[-1] else v[v < v[-1]][-1]
        right = x[:, column[node]] > value[node]
        held[2 * node + 1], held[2 * node + 2] = x[~right], x[right]
    return column, value


def leaves_of(points: DataFrame, cols: list[str], column: np.ndarray, value: np.ndarray) -> DataFrame:
    """point, cols -> the same with the leaf of each point."""
    depth = (len(column) + 1).bit_length() - 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.stack([batch.column(c).to_numpy(zero_copy_only=False) for c in cols], 1)
            node, row = np.zeros(len(x), int), np.arange(len(x))
            for _ in range(depth):
                node = 2 * node + 1 + (x[row, column[node]] > value[node])
            yield batch.append_column("leaf", pa.array(node - len(column)))

    return points.select("point", *cols).mapInArrow(run, ", ".join(["point long", *[f"{c} double" for c in cols], "leaf long"]))


def visits(bounded: DataFrame, cols: list[str], leaf: np.ndarray, low: np.ndarray, high: np.ndarray) -> DataFrame:
    """point, cols, reach (null: none) -> the same once for each leaf whose box is within reach."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for i in range(0, whole.num_rows, ROWS):
                batch = whole.slice(i, ROWS)
                x = np.stack([batch.column(c).to_numpy(zero_copy_only=False) for c in cols], 1)
                away = np.zeros((len(x), len(leaf)))
                for j in range(len(cols)):
                    y = x[:, j : j + 1]
                    away += np.maximum(np.maximum(low[:, j] - y, y - high[:, j]), 0) ** 2
                reach = batch.column("reach").to_numpy(zero_copy_only=False)
                row, at = np.nonzero(np.sqrt(away) <= reach[:, None] + SLACK)
                yield batch.take(pa.array(row)).append_column("leaf", pa.array(leaf[at]))

    return bounded.select("point", *cols, "reach").mapInArrow(run, ", ".join(["point long", *[f"{c} double" for c in cols], "reach double", "leaf long"]))


def nearest(z: DataFrame, cols: list[str], k: int = 3, per_leaf: int = 64, most: int = 16_384) -> DataFrame:
    """item_id, cols -> item_id, similar, dist: the ``k`` nearest other items of each (all, if fewer) by
    Euclidean distance rounded to nine places, ties to smaller ids.  Rows with a null, NaN or
    infinite value in ``cols`` take no part."""
    known = reduce(lambda a, b: a & b, [F.abs(F.col(c).cast("double")) < float("inf") for c in cols])
    items = materialised(z.filter(known).select(F.col("item_id").cast("long"), *[F.col(c).cast("double").alias(c) for c in cols]))
    points = materialised(items.groupBy(*cols).agg(F.min("item_id").alias("point")))
    n = points.count()
    depth = min(max(math.ceil(math.log2(max(n, 1) / per_leaf)), 0), int(math.log2(most)))
    part = min(1.0, SAMPLE * 2**depth / max(n, 1))
    sample = points.filter(F.pmod(F.xxhash64(F.lit(5), *cols), F.lit(1 << 20)) < int(part * (1 << 20))).select(*cols).toPandas().to_numpy(float)
    # Pairs cost far more than rows, so adaptive execution must not merge these partitions by their bytes.
    parts = int(z.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    placed = materialised(leaves_of(points, cols, *cuts(sample, depth)).repartition(parts, "leaf"))

    other = placed.select("leaf", F.col("point").alias("near"), *[F.col(c).alias(f"o_{c}") for c in cols])
    square = reduce(lambda a, b: a + b, [(F.col(c) - F.col(f"o_{c}")) * (F.col(c) - F.col(f"o_{c}")) for c in cols])
    own = placed.join(other, "leaf").select("leaf", "point", "near", square.alias("square"))
    rank = F.row_number().over(W.partitionBy("leaf", "point").orderBy("square", "near"))
    reach = own.withColumn("rank", rank).filter(f"rank <= {k + 1}").filter(f"rank = {k + 1}").select("point", F.sqrt("square").alias("reach"))
    bounded = placed.drop("leaf").join(reach, "point", "left").fillna(float("inf"), ["reach"]).repartition(parts, "point")

    boxes = placed.groupBy("leaf").agg(*[F.min(c).alias(f"low_{c}") for c in cols], *[F.max(c).alias(f"high_{c}") for c in cols]).toPandas()
    low, high = (boxes[[f"{side}_{c}" for c in cols]].to_numpy(float) for side in ("low", "high"))
    met = visits(bounded, cols, boxes["leaf"].to_numpy(np.int64), low, high).join(other, "leaf")
    met = met.select("point", "near", F.sqrt(square).alias("dist"), "reach").filter(F.col("dist") <= F.col("reach") + SLACK)
    met = met.select("point", "near", F.round("dist", 9).alias("dist"))
    # The k + 1 nearest ids are among those of the k + 1 nearest points, each of which has one at least.
    first = met.withColumn("rank", F.row_number().over(W.partitionBy("point").orderBy("dist", "near"))).filter(f"rank <= {k + 1}")

    named = items.join(points, cols).select("item_id", "point")
    ids = named.withColumn("rank", F.row_number().over(W.partitionBy("point").orderBy("item_id"))).filter(f"rank <= {k + 1}")
    ids = ids.select(F.col("point").alias("near"), F.col("item_id").alias("similar"))
    found = first.select("point", "near", "dist").join(ids, "near").groupBy("point").agg(F.array_sort(F.collect_list(F.struct("dist", "similar"))).alias("found"))
    others = F.slice(F.filter("found", lambda x: x["similar"] != F.col("item_id")), 1, k)
    got = named.join(found, "point").select("item_id", F.explode(others).alias("x"))
    return got.select("item_id", "x.similar", "x.dist")
