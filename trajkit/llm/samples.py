"""Bounded training samples that do not depend on partitioning."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def id_mod(n: int) -> Column:
    """crc32 of the id as text, modulo n; a null id counts as the empty text."""
    return F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")), F.lit(n))


def bounded(rows: DataFrame, label: str, per_class: int, seed: int = 17) -> DataFrame:
    """About ``per_class`` rows of each value of ``label`` at most, picked by a hash of doc_id;
    rows whose label is null are left out."""
    counts = {r[label]: r["count"] for r in rows.filter(F.col(label).isNotNull()).groupBy(label).count().collect()}
    if not counts:
        return rows.limit(0)
    u = F.pmod(F.xxhash64(F.lit(seed), "doc_id"), F.lit(1 << 20)) / float(1 << 20)
    keep = F.lit(False)
    for value, n in counts.items():
        keep = keep | ((F.col(label) == F.lit(value)) & (u < min(1.0, per_class / n)))
    return rows.filter(keep)
