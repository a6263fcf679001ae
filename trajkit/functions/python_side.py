"""Python functions for what columns cannot say: Arrow UDF, grouped aggregate, table function, and
the SQL surface."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from trajkit.operators.features import extract_features


@F.pandas_udf(T.DoubleType())
def geometric_mean(n: pd.Series) -> float:
    """Grouped aggregate: a group is one item's active periods, so it is small."""
    x = n[n > 0]
    return float(np.exp(np.log(x).mean())) if len(x) else float("nan")


def nearest_label(vectors: DataFrame, most: int = 1000) -> DataFrame:
    """vec_id, label of the nearest of the labels' mean vectors, by an Arrow-batched kernel.  The means are
    held by every task, so more than ``most`` labels are refused."""
    means = {r["label"]: np.array(r["m"]) for r in vectors.groupBy("label").agg(F.array(*[F.avg(F.col("embedding")[i]) for i in range(64)]).alias("m")).orderBy("label").limit(most + 1).collect()}
    if len(means) > most:
        raise ValueError(f"more than {most} labels")
    names, centers = np.array(list(means)), np.array(list(means.values()))

    @F.pandas_udf(T.IntegerType())
    def nearest(v: pd.Series) -> pd.Series:
        x = np.stack(v.to_numpy()).astype(float)
        return pd.Series(names[((x[:, None] - centers[None]) ** 2).sum(2).argmin(1)])

    return vectors.select("vec_id", nearest("embedding").alias("nearest"))


def partial_sums(panel: DataFrame) -> DataFrame:
    """Partial sums by mapInArrow, merged by an aggregate."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = total = 0
        for b in batches:
            rows += b.num_rows
            total += int(b.column(0).to_numpy(zero_copy_only=False).sum())
        yield pa.RecordBatch.from_arrays([pa.array([rows]), pa.array([total])], ["rows", "total"])

    part = panel.select("n").mapInArrow(run, "rows long, total long")
    return part.agg(F.sum("rows").alias("active_rows"), F.sum("total").alias("total"))


@F.udtf(returnType=T.StructType([T.StructField("t", T.IntegerType()), T.StructField("n", T.LongType()), T.StructField("cum", T.LongType()), T.StructField("phase", T.StringType())]))
class ExplodeTrajectory:
    def eval(self, series: list):
        top, cum = max(range(len(series)), key=lambda i: (series[i], -i)), 0
        for t, n in enumerate(series):
            cum += n
            yield t, n, cum, "growth" if t <= top else "decay"


def explode_trajectories(spark: SparkSession, dense: DataFrame) -> DataFrame:
    spark.udtf.register("explode_trajectory", ExplodeTrajectory)
    return spark.sql("SELECT d.item_id, x.t, x.n, x.cum, x.phase FROM {dense} AS d, LATERAL explode_trajectory(d.series) AS x", dense=dense)


def register_sql(spark: SparkSession) -> None:
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION traj_gain(part DOUBLE, total DOUBLE) RETURNS DOUBLE RETURN part / nullif(total, 0)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION traj_z(x DOUBLE, mean DOUBLE, sd DOUBLE) RETURNS DOUBLE RETURN (x - mean) / nullif(sd, 0)")


def sql_surface(spark: SparkSession, panel: DataFrame, w: int) -> DataFrame:
    """The feature table as a view, with the SQL functions on top of it."""
    register_sql(spark)
    f = extract_features(panel, w)
    return spark.sql(
        """SELECT item_id, t_peak, round(traj_gain(g_init * total, total), 9) AS gain, round(traj_z(total, m, s), 6) AS z
           FROM {f} CROSS JOIN (SELECT avg(total) AS m, stddev_pop(total) AS s FROM {f})""",
        f=f,
    )
