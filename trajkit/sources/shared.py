"""Lineage is cut by writing Parquet to the folder that the cluster shares."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Callable
from typing import Any

from pyspark.sql import DataFrame, SparkSession

_written: list[tuple[SparkSession, str]] = []
_shared: dict[tuple, Any] = {}


def shared_dir(spark: SparkSession) -> str:
    sc = spark.sparkContext
    named = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if named:
        return named.rstrip("/")
    if not sc.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    sc.setCheckpointDir(tempfile.mkdtemp(prefix="trajkit-"))  # tests only
    return sc.getCheckpointDir().rstrip("/")


def materialised(df: DataFrame, row_group: int | None = None) -> DataFrame:
    """The same rows, read back from the shared folder; the files go when the driver ends.  ``row_group``
    bounds the bytes that a reader takes at once, for rows that are large."""
    path = f"{shared_dir(df.sparkSession)}/table-{uuid.uuid4().hex}"
    (df.write.option("parquet.block.size", row_group) if row_group else df.write).parquet(path)
    if not _written:
        atexit.register(_clean)
    _written.append((df.sparkSession, path))
    return df.sparkSession.read.schema(df.schema).parquet(path)


def once(spark: SparkSession, key: tuple, build: Callable[[], Any]) -> Any:
    """What ``build`` returns, built once a session and key: queries that start from one fit share it.
    Tables of a directory are taken as fixed while a session lasts."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _shared:
        _shared[key] = build()
    return _shared[key]


def _clean() -> None:
    for spark, path in _written:
        try:
            where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
        except Exception:  # the session may be gone already
            pass
