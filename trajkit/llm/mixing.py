"""Mixing sources to target weights along a time-varying curriculum (DataFrame functions only).

Every source has a weight schedule: a weight at each of several knots of curriculum time, linear in
between.  Its integral over the whole time is what the source weighs in all: it sets the source's
share of all words, where a target stops at ``max_repeat`` times the source's own words and the excess
flows to the others (water filling, solved in closed form by one ordered pass over the sources).  The
running integral, brought to the target, is the source's cumulative demand.  Within a source, documents
are laid end to end in hash order, pass after pass; a copy is taken if and only if demand reaches the
middle of its place before the curriculum ends, and the time at which it does is its training position.
The mixed corpus is every taken copy as a whole row, in order of training positions.

Edge cases: a null text has size 0; a null source is a source of its own, ordered last; sources
without words get target 0; repeated rows are taken as separate rows; an empty table gives an
empty result.  Columns of the input other than the named ones pass through ``mix`` untouched.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .scratch import stored

WORD = r"[^\x20\x09-\x0D]+"


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def id_hash() -> Column:
    return F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary"))


def source_targets(per_source: DataFrame, weights: Sequence[int] = (5, 2, 1), max_repeat: int = 3) -> DataFrame:
    """(src_null, src, source_size) -> adds rank, weight, target.  One row per source.  A column
    ``weight`` (the integral of a schedule) is used where there is one, else ``weights`` by rank."""
    ranked = per_source if "weight" in per_source.columns else scheduled(per_source, weights, ())
    big = "decimal(38,0)"
    cap = (F.lit(max_repeat) * F.col("source_size")).cast("decimal(24,0)")
    by_level = W.partitionBy().orderBy(F.col("cap") / F.col("weight"), "rank")
    before = by_level.rowsBetween(W.unboundedPreceding, -1)
    every = W.partitionBy()
    out = (
        ranked.withColumn("cap", cap)
        .withColumn("left", F.sum("source_size").over(every) - F.coalesce(F.sum("cap").over(before), F.lit(0)).cast(big))
        .withColumn("w_left", F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0)))
        .withColumn("capped", F.col("cap") * F.col("w_left") <= F.col("left").cast("decimal(24,0)") * F.col("weight"))
        .withColumn("level", F.max(F.when(~F.col("capped"), F.col("left").cast("double") / F.col("w_left").cast("double"))).over(every))
    )
    target = F.when(F.col("capped"), F.col("cap").cast("double")).otherwise(F.col("weight").cast("double") * F.col("level"))
    return out.select("src_null", "src", "source_size", "rank", "weight", F.round(target, 6).alias("target"))


def scheduled(per_source: DataFrame, weights: Sequence[int], slopes: Sequence[float], knots: int = 2) -> DataFrame:
    """Adds rank, ``pieces`` (the weight schedule as linear pieces: from, to, the weights at both ends and
    the integral before them) and ``weight``, the integral over all of curriculum time.

    A source's schedule runs from weight * (1 - slope) to weight * (1 + slope) through ``knots`` knots.
    The integral is kept to three digits, as a decimal, so that the comparison with caps stays exact.
    """
    rank = F.row_number().over(W.partitionBy().orderBy("src_null", "src")) - 1
    pick = lambda values: F.element_at(F.array(*[F.lit(float(v)) for v in values]), (F.col("rank") % len(values) + 1).cast("int"))
    slope = pick(slopes) if slopes else F.lit(0.0)
    at = [i / (knots - 1) for i in range(knots)]
    weight_at = [F.col("__w") * (1 + F.col("__slope") * (2 * t - 1)) for t in at]
    pieces, before = [], F.lit(0.0)
    for a, b, wa, wb in zip(at, at[1:], weight_at, weight_at[1:]):
        pieces.append(F.struct(F.lit(a).alias("from"), F.lit(b).alias("to"), wa.alias("w_from"), wb.alias("w_to"), before.alias("before")))
        before = before + (wa + wb) / 2 * (b - a)
    out = per_source.withColumn("rank", rank).withColumn("__w", pick(weights)).withColumn("__slope", slope)
    return out.withColumns({"pieces": F.array(*pieces), "weight": before.cast("decimal(12,3)")}).drop("__w", "__slope")


def plan_mix(
    docs: DataFrame,
    weights: Sequence[int] = (5, 2, 1),
    max_repeat: int = 3,
    slopes: Sequence[float] = (-0.5, 0.0, 0.5),
    rows_per_bucket: int = 20_000,
) -> DataFrame:
    """doc_id, source, text -> one row per document: a number of its own, sizes, target, copies, taken,
    its place in hash order, where in the source's stream it starts and its source's schedule.

    ``slopes`` tilt the sources' weight schedules by rank (``scheduled``).  Running sums use two levels (hash buckets, then
    inside a bucket), so a source that holds a third of all rows is never one task.
    """
    base = docs.select(
        "doc_id",
        "source",
        F.col("source").isNull().alias("src_null"),
        F.coalesce("source", F.lit("")).alias("src"),
        word_count(F.col("text")).alias("size"),
        id_hash().alias("place"),
        F.monotonically_increasing_id().alias("row"),
    )
    base = stored(base)
    digits, rows = 1, base.count()
    while rows / 16**digits > rows_per_bucket and digits < 6:
        digits += 1
    base = base.withColumn("bucket", F.substring("place", 1, digits))
    key = ["src_null", "src"]
    buckets = base.groupBy(*key, "bucket").agg(F.sum("size").alias("bucket_size"))
    offsets = buckets.withColumn(
        "offset", F.sum("bucket_size").over(W.partitionBy(*key).orderBy("bucket")) - F.col("bucket_size")
    ).drop("bucket_size")
    per_source = scheduled(buckets.groupBy(*key).agg(F.sum("bucket_size").alias("source_size")), weights, slopes)
    targets = source_targets(per_source, max_repeat=max_repeat).join(per_source.select(*key, "pieces"), key)
    inside = W.partitionBy(*key, "bucket").orderBy("place", "doc_id", "size", "row")
    reached = F.size(F.filter(F.sequence(F.lit(0), F.lit(max_repeat)), lambda c: place(c) < demand(F.lit(1.0))))
    return (
        base.withColumn("inner", F.sum("size").over(inside.rowsBetween(W.unboundedPreceding, 0)) - F.col("size"))
        .join(offsets.join(targets, key), [*key, "bucket"])
        .withColumn("start", F.col("offset") + F.col("inner"))
        .withColumn("copies", F.when(F.col("source_size") > 0, F.least(F.lit(max_repeat), reached)).otherwise(0).cast("long"))
        .select("row", "place", "doc_id", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"), "start", "weight", "pieces")
    )


def place(copy: Column) -> Column:
    """Where the middle of a copy (from 0) lies in its source's stream."""
    return copy * F.col("source_size") + F.col("start") + F.col("size") / 2


def demand(t: Column) -> Column:
    """Words of the source that the mix has asked for by time t: the schedule's integral up to t over
    its whole integral, times the target."""
    def upto(p: Column) -> Column:
        dt = F.least(t, p["to"]) - p["from"]
        rise = (p["w_to"] - p["w_from"]) / (p["to"] - p["from"])
        return F.when(dt > 0, p["w_from"] * dt + rise * dt * dt / 2).otherwise(0.0)

    area = F.aggregate("pieces", F.lit(0.0), lambda a, p: a + upto(p))
    return area / F.col("weight").cast("double") * F.col("target")


def position(copy: Column) -> Column:
    """Curriculum time at which demand reaches the given copy (from 0): the quadratic of the piece
    that holds its place, solved."""
    y = F.when(F.col("target") > 0, F.least(F.lit(1.0), place(copy) / F.col("target"))).otherwise(0.0) * F.col("weight").cast("double")
    piece = F.element_at(F.filter("pieces", lambda p: (p["before"] <= y) | (p["from"] == 0)), -1)

    def solved(p: Column) -> Column:
        a = (p["w_to"] - p["w_from"]) / (p["to"] - p["from"])
        left = y - p["before"]
        root = (F.sqrt(F.greatest(p["w_from"] * p["w_from"] + 2 * a * left, F.lit(0.0))) - p["w_from"]) / a
        return F.least(p["to"], p["from"] + F.when(F.abs(a) < 1e-9, left / p["w_from"]).otherwise(root))

    return F.element_at(F.transform(F.array(piece), solved), 1)


def in_order(docs: DataFrame, plan: DataFrame) -> DataFrame:
    """Each row of ``docs`` as often as the plan takes it, with its number in the plan (``__row``) and the
    copy's training position (``__position``), range-sorted by the latter.

    Rows are found again by id; only where ids repeat are rows of one id told apart by source,
    size and a running number.
    """
    rest = plan.groupBy("source").agg(F.max(F.when(F.col("copies") > 0, F.col("place"))).alias("__last"), F.sum(F.when(F.col("copies") == 0, F.col("size"))).alias("__idle"))
    # what comes after the last taken row of its source need not be shuffled to the join, which would drop it:
    # the sources that leave most are enough, so that the broadcast stays small
    rest = rest.filter("__idle > 0").orderBy(F.desc("__idle")).limit(1000).select(F.col("source").alias("__source"), "__last")
    after = F.col("source").eqNullSafe(F.col("__source")) & (F.col("__last").isNull() | (id_hash() > F.col("__last")))
    near = docs.join(F.broadcast(rest), after, "left_anti")
    plan = plan.filter("copies > 0").select(
        F.col("row").alias("__row"), F.col("doc_id").alias("__id"), F.col("source").alias("__source"), F.col("size").alias("__n"), F.col("start").alias("__start"),
        F.transform(F.sequence(F.lit(0), (F.col("copies") - 1).cast("int")), position).alias("__at"),
    )
    left, on = near, F.col("doc_id").eqNullSafe(F.col("__id"))
    if docs.groupBy("doc_id").count().filter("count > 1").limit(1).count():
        plan = plan.withColumn("__k", F.row_number().over(W.partitionBy("__id", "__source", "__n").orderBy("__start", "__row")))
        left = near.withColumn("__size", word_count(F.col("text")))
        left = left.withColumn("__nth", F.row_number().over(W.partitionBy("doc_id", "source", "__size").orderBy(F.xxhash64("text"))))
        on = on & F.col("source").eqNullSafe(F.col("__source")) & (F.col("__size") == F.col("__n")) & (F.col("__nth") == F.col("__k"))
    joined = left.join(plan.hint("merge"), on).select(*[F.col(f"`{c}`") for c in docs.columns], "__row", F.explode("__at").alias("__position"))
    return joined.orderBy("__position")


def mix(docs: DataFrame, **options) -> DataFrame:
    """The mixed corpus: each row as often as the plan takes it, range-sorted by training position."""
    return in_order(docs, stored(plan_mix(docs, **options))).drop("__row", "__position")


def op9_mix_curriculum(spark, sf_dir: str) -> DataFrame:
    """Writes the mixed corpus, whole rows in training order, and counts in it what was taken of each document."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    plan = stored(plan_mix(docs))
    mixed = stored(in_order(docs, plan), compression="zstd")
    found = mixed.groupBy("__row").agg(
        F.sum(word_count(F.col("text"))).alias("__taken"), F.count(F.lit(1)).alias("__copies"), F.round(F.min("__position"), 9).alias("first_position")
    )
    return plan.join(found, F.col("row") == F.col("__row"), "left").select(
        "doc_id", "size", "source_size", "target", F.coalesce("__taken", F.lit(0)).alias("taken"), F.coalesce("__copies", F.lit(0)).cast("int").alias("copies"), "first_position"
    )


ORACLE = r"""
WITH d AS (
  SELECT doc_id, source, source IS NULL AS src_null, coalesce(source, '') AS src, md5(doc_id::VARCHAR) AS place,
         coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size
  FROM documents),
s AS (SELECT src_null, src, sum(size)::BIGINT AS source_size FROM d GROUP BY ALL),
r AS (SELECT *, row_number() OVER (ORDER BY src_null, src) - 1 AS rank FROM s),
w AS (SELECT *, CASE rank % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS weight, 3 * source_size AS cap FROM r),
l AS (SELECT *, sum(source_size) OVER () - coalesce(sum(cap) OVER b, 0) AS lft,
             sum(weight) OVER () - coalesce(sum(weight) OVER b, 0) AS w_left
      FROM w WINDOW b AS (ORDER BY cap / weight, rank ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
c AS (SELECT *, cap * w_left <= lft * weight AS capped FROM l),
v AS (SELECT *, max(CASE WHEN NOT capped THEN lft::DOUBLE / w_left::DOUBLE END) OVER () AS level FROM c),
t AS (SELECT src_null, src, rank, source_size, round(CASE WHEN capped THEN cap::DOUBLE ELSE weight::DOUBLE * level END, 6) AS target FROM v),
p AS (SELECT d.*, t.rank, t.source_size, t.target,
             sum(size) OVER (PARTITION BY d.src_null, d.src ORDER BY place, doc_id, size ROWS UNBOUNDED PRECEDING) - size AS start,
             CASE WHEN t.source_size > 0 THEN least(3, floor(t.target / t.source_size)) ELSE 0 END::BIGINT AS whole
      FROM d JOIN t ON d.src_null = t.src_null AND d.src = t.src),
k AS (SELECT *, (whole + CASE WHEN start + size / 2 < target - whole * source_size THEN 1 ELSE 0 END)::INTEGER AS copies,
             CASE rank % 3 WHEN 0 THEN -0.5::DOUBLE WHEN 1 THEN 0.0::DOUBLE ELSE 0.5::DOUBLE END AS a,
             CASE WHEN target > 0 THEN least(1.0, (start + size / 2)::DOUBLE / target) ELSE 0.0 END AS y FROM p)
SELECT doc_id, size, source_size, target, (copies * size)::BIGINT AS taken, copies,
       CASE WHEN copies > 0 THEN round(CASE WHEN a = 0 THEN y ELSE (sqrt((1 - a) * (1 - a) + 4 * a * y) - (1 - a)) / (2 * a) END, 9) END AS first_position
FROM k
"""
