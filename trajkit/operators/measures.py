"""Measures of a labelling.  Each takes DataFrames with ``item_id`` and ``class`` (and features) and
returns a few rows; contingency tables are aggregates, so cost follows the items, not their pairs."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def class_sizes(final: DataFrame) -> DataFrame:
    n = final.groupBy("class").agg(F.count("*").alias("items"))
    return n.withColumn("share", F.round(F.col("items") / F.sum("items").over(W.partitionBy()), 9))


def time_profile(rows: DataFrame, cols: tuple[str, ...] = ("t_init", "t_grow", "t_decay")) -> DataFrame:
    q = F.array(*[F.lit(x) for x in (0.25, 0.5, 0.75)])
    aggs = []
    for c in cols:
        p = F.percentile(c, q)
        aggs += [F.round(F.avg(c), 6).alias(f"{c}_mean"), F.round(F.stddev_samp(c), 6).alias(f"{c}_sd"), p[0].alias(f"{c}_q1"), p[1].alias(f"{c}_q2"), p[2].alias(f"{c}_q3")]
    return rows.groupBy("class").agg(*aggs)


def gain_histogram(rows: DataFrame, width: float = 0.1, cols: tuple[str, ...] = ("g_init", "g_grow", "g_decay")) -> DataFrame:
    phase = F.explode(F.array(*[F.struct(F.lit(c).alias("phase"), F.floor(F.col(c) / width + 1e-9).cast("int").alias("bin")) for c in cols])).alias("x")
    return rows.select("class", phase).groupBy("class", "x.phase", "x.bin").agg(F.count("*").alias("items"))


def peak_box(rows: DataFrame, cols: tuple[str, ...]) -> DataFrame:
    """Quartiles, extremes and whiskers at 1.5 interquartile ranges, by class and feature."""
    long = rows.select("class", F.explode(F.array(*[F.struct(F.lit(c).alias("feature"), F.col(c).cast("double").alias("x")) for c in cols])).alias("v")).select("class", "v.*")
    q = F.percentile("x", F.array(*[F.lit(p) for p in (0.25, 0.5, 0.75)]))
    box = long.groupBy("class", "feature").agg(q.alias("q"), F.min("x").alias("lo"), F.max("x").alias("hi"))
    iqr = F.col("q")[2] - F.col("q")[0]
    return box.select("class", "feature", "lo", "hi", F.col("q")[0].alias("q1"), F.col("q")[1].alias("q2"), F.col("q")[2].alias("q3"),
                      F.greatest(F.col("lo"), F.col("q")[0] - 1.5 * iqr).alias("whisker_lo"), F.least(F.col("hi"), F.col("q")[2] + 1.5 * iqr).alias("whisker_hi"))


def anova(rows: DataFrame, cols: list[str]) -> DataFrame:
    """One-way analysis of variance by feature: F, degrees of freedom, eta squared, p."""
    long = rows.select("class", F.explode(F.array(*[F.struct(F.lit(c).alias("feature"), F.col(c).cast("double").alias("x")) for c in cols])).alias("v")).select("class", "v.*")
    by = long.groupBy("feature", "class").agg(F.count("*").alias("n"), F.sum("x").alias("s"), F.sum(F.col("x") * F.col("x")).alias("q"))
    one = by.groupBy("feature").agg(
        F.count("*").alias("k"), F.sum("n").alias("n"), F.sum(F.col("s") * F.col("s") / F.col("n")).alias("between"), F.sum("s").alias("s"), F.sum("q").alias("q")
    )
    ssb = F.col("between") - F.col("s") * F.col("s") / F.col("n")
    ssw = F.col("q") - F.col("between")
    f = (ssb / (F.col("k") - 1)) / F.nullif(ssw / (F.col("n") - F.col("k")), F.lit(0.0))
    out = one.select("feature", (F.col("k") - 1).alias("df1"), (F.col("n") - F.col("k")).alias("df2"), F.round(f, 4).alias("f"), F.round(ssb / F.nullif(ssb + ssw, F.lit(0.0)), 6).alias("eta2"))
    return out


def f_tail(f: float | None, d1: int, d2: int) -> float | None:
    """P(F >= f): the regularised incomplete beta function by its continued fraction."""
    if f is None or f <= 0:
        return None if f is None else 1.0
    a, b, x = d2 / 2, d1 / 2, d2 / (d2 + d1 * f)
    if x > (a + 1) / (a + b + 2):
        return 1 - _beta(b, a, 1 - x)
    return _beta(a, b, x)


def _beta(a: float, b: float, x: float) -> float:
    if x <= 0:
        return 0.0
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x)) / a
    c, d, tiny = 1.0, 1 - (a + b) * x / (a + 1), 1e-300
    d = 1 / (d if abs(d) > tiny else tiny)
    h = d
    for m in range(1, 300):
        for num in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 + num * d
            d = 1 / (d if abs(d) > tiny else tiny)
            c = 1 + num / c if abs(c) > tiny else tiny
            h *= c * d
        if abs(c * d - 1) < 1e-14:
            break
    return front * h


def tail_counts(totals: DataFrame, levels: tuple[int, ...]) -> DataFrame:
    total = F.count("*")
    return totals.agg(total.alias("items"), *[F.sum((F.col("total") > x).cast("long")).alias(f"over_{x}") for x in levels],
                      F.round(F.sum((F.col("total") < levels[-1]).cast("long")) / total, 9).alias("share_below"))


def crosswalk(a: DataFrame, b: DataFrame) -> DataFrame:
    """Contingency of two labellings with the share of each row."""
    n = a.select("item_id", F.col("class").alias("a")).join(b.select("item_id", F.col("class").alias("b")), "item_id").groupBy("a", "b").agg(F.count("*").alias("items"))
    return n.withColumn("row_share", F.round(F.col("items") / F.sum("items").over(W.partitionBy("a")), 9))


def unclassified_share(schemes: DataFrame) -> DataFrame:
    """(item_id, scheme, class, unclassified) -> share by scheme."""
    return schemes.groupBy("scheme").agg(F.round(F.avg(F.col("unclassified").cast("int")), 9).alias("share"))


def _contingency(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("item_id", F.col("class").alias("a")).join(b.select("item_id", F.col("class").alias("b")), "item_id").groupBy("a", "b").agg(F.count("*").alias("n"))


def agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: adjusted Rand index, normalised mutual information, purity of a's classes."""
    n = _contingency(a, b)
    rows, cols = n.groupBy("a").agg(F.sum("n").alias("ra")), n.groupBy("b").agg(F.sum("n").alias("rb"))
    pairs = lambda c: F.sum(F.col(c) * (F.col(c) - 1) / 2.0)
    full = n.join(rows, "a").join(cols, "b").crossJoin(F.broadcast(n.agg(F.sum("n").alias("all"))))  # one row
    info = F.sum(F.col("n") / F.col("all") * F.ln(F.col("n") * F.col("all") / (F.col("ra") * F.col("rb"))))
    one = full.agg(info.alias("mi"), pairs("n").alias("sum_n"), F.max("all").alias("all"))
    entropy = lambda df, c, name: df.crossJoin(F.broadcast(n.agg(F.sum("n").alias("all")))).agg(F.sum(-F.col(c) / F.col("all") * F.ln(F.col(c) / F.col("all"))).alias(f"h_{name}"), pairs(c).alias(f"sum_{name}"))
    top = n.groupBy("a").agg(F.max("n").alias("n")).agg(F.sum("n").alias("top"))
    j = one.crossJoin(entropy(rows, "ra", "a")).crossJoin(entropy(cols, "rb", "b")).crossJoin(top)  # one row each
    expected = F.col("sum_a") * F.col("sum_b") / (F.col("all") * (F.col("all") - 1) / 2.0)
    ari = (F.col("sum_n") - expected) / F.nullif((F.col("sum_a") + F.col("sum_b")) / 2 - expected, F.lit(0.0))
    nmi = F.col("mi") / F.nullif((F.col("h_a") + F.col("h_b")) / 2, F.lit(0.0))
    return j.select(F.round(ari, 6).alias("ari"), F.round(nmi, 6).alias("nmi"), F.round(F.col("top") / F.col("all"), 6).alias("purity"))


def agreement_of(a: DataFrame, b: DataFrame) -> tuple[float | None, float | None, float | None]:
    """The numbers of ``agreement`` from one job: the table of class pairs comes to the driver."""
    cells = [tuple(r) for r in _contingency(a, b).collect()]
    rows, cols, top = {}, {}, {}
    for x, y, n in cells:
        rows[x], cols[y], top[x] = rows.get(x, 0) + n, cols.get(y, 0) + n, max(top.get(x, 0), n)
    total, pairs = sum(rows.values()), lambda v: sum(n * (n - 1) / 2 for n in v)
    if not total:
        return None, None, None
    over, under = pairs(rows.values()) * pairs(cols.values()), total * (total - 1) / 2
    half, expected = (pairs(rows.values()) + pairs(cols.values())) / 2, over / under if under else 0.0
    info = sum(n / total * math.log(n * total / (rows[x] * cols[y])) for x, y, n in cells)
    spread = sum(-n / total * math.log(n / total) for v in (rows, cols) for n in v.values()) / 2
    return (
        round((pairs(n for _, _, n in cells) - expected) / (half - expected), 6) if half != expected else None,
        round(info / spread, 6) if spread else None,
        round(sum(top.values()) / total, 6),
    )


def simplified_silhouette(assigned: DataFrame, d_own: Column, d_other: Column) -> DataFrame:
    """Mean of (other - own) / max over items, with distances to own and nearest other centre."""
    return assigned.agg(F.round(F.avg((d_other - d_own) / F.nullif(F.greatest(d_other, d_own), F.lit(0.0))), 6).alias("silhouette"))


def name_classes(profile: DataFrame, w: int, early: float = 0.4, rapid: float = 0.25) -> DataFrame:
    """A place on the rise and decline grid from the mean times of each class."""
    rise = F.when(F.col("t_init_mean") + F.col("t_grow_mean") <= early * w, "early").otherwise("delayed")
    decline = F.when(F.col("t_decay_mean") < 0.05 * w, "none").when(F.col("t_decay_mean") <= rapid * w, "rapid").otherwise("slow")
    name = F.concat_ws("_", "rise", "decline")
    names = {"early_rapid": "FLASH", "early_slow": "EARLY_TAIL", "delayed_none": "CLIMBER", "delayed_slow": "LATE_WAVE"}
    label = F.coalesce(*[F.when(name == k, v) for k, v in names.items()], F.upper(name))
    return profile.withColumn("rise", rise).withColumn("decline", decline).select("class", "rise", "decline", label.alias("name"))
