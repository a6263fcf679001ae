"""Timing, gain and peak-count features of a count series.

``extract_features`` reads the long panel: window functions over each item's active periods, then
one aggregate, all on one shuffle and one sort by item, inside generated code.  Peak levels are
compared in whole numbers, so no rounding decides an exact tie.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

TIMES = ["t_init", "t_grow", "t_decay"]
GAINS = ["g_init", "g_grow", "g_decay"]
PEAKS = ["hi_grow", "hi_decay", "md_grow", "md_decay", "lo_grow", "lo_decay"]
FEATURES = TIMES + GAINS + PEAKS
TOL = 1e-9


@dataclass(frozen=True)
class FeatureOptions:
    """The readings of the feature table; the first of each comment is the default."""

    init_rule: str = "cum_vs_gm"  # cum_vs_gm, annual_vs_gm, log_time_mean, sqrt_total
    gm_zero: str = "positive_only"  # positive_only, log1p (over all periods)
    peak_tie: str = "first"  # first, last
    end_rule: str = "last_mention"  # last_mention, window_end
    gain_mode: str = "prefix"  # prefix, phase
    mu: str = "mean"  # mean, geo
    cmp: str = "ge"  # ge, gt
    sd: str = "pop"  # pop, samp
    band: str = "nested"  # nested, exclusive
    growth_start: str = "birth"  # birth, after_init
    flat: str = "zero_peaks"  # zero_peaks, literal


def geometric_log(o: FeatureOptions, w: int, n: Column, over) -> Column:
    """Log of the geometric mean (log1p: of the counts plus one, less one)."""
    if o.gm_zero == "positive_only":
        return F.avg(F.when(n > 0, F.ln(n))).over(over)
    return F.ln(F.exp(F.sum(F.log1p(n)).over(over) / F.lit(w)) - 1 + F.lit(1e-300))


def _reached(o: FeatureOptions) -> Column:
    if o.init_rule == "annual_vs_gm":
        return F.ln("n") >= F.col("gm") - TOL
    if o.init_rule == "sqrt_total":
        return F.col("cum") * F.col("cum") >= F.col("c")
    return F.ln("cum") >= F.col("gm") - TOL


def above(o: FeatureOptions, w: int, j: int) -> Column:
    """Whether a period's count lies j standard deviations above the mean."""
    n, c, q = F.col("n"), F.col("c"), F.col("q")
    var = F.lit(w) * q - c * c
    if o.mu == "geo":
        sd = F.sqrt(var.cast("double")) / F.lit(float(w)) if o.sd == "pop" else F.sqrt(var.cast("double") / (w * max(w - 1, 1)))
        level = F.exp("gm") + j * sd
        hit = n >= level - TOL if o.cmp == "ge" else n > level + TOL
    else:
        dev = F.lit(w) * n - c
        left, right = dev * dev, F.lit(j * j) * var
        if o.sd == "samp":
            left, right = left * (w - 1), right * w
        hit = (dev >= 0) & (left >= right) if o.cmp == "ge" else (dev > 0) & (left > right)
    return hit & (var > 0) if o.flat == "zero_peaks" else hit


def timed(panel: DataFrame, w: int, o: FeatureOptions = FeatureOptions()) -> DataFrame:
    """The clipped panel's active periods with their item's sums and times."""
    p = panel.filter((F.col("t") >= 0) & (F.col("t") < w) & (F.col("n") > 0))
    part = W.partitionBy("item_id")
    run = part.orderBy("t").rowsBetween(W.unboundedPreceding, 0)
    tie = F.struct("n", -F.col("t")) if o.peak_tie == "first" else F.struct("n", "t")
    p = (
        p.withColumn("cum", F.sum("n").over(run))
        .withColumn("c", F.sum("n").over(part))
        .withColumn("q", F.sum(F.col("n") * F.col("n")).over(part))
        .withColumn("gm", geometric_log(o, w, F.col("n"), part))
        .withColumn("t_peak", F.max_by("t", tie).over(part))
        .withColumn("t_last", F.max("t").over(part) if o.end_rule == "last_mention" else F.lit(w - 1))
    )
    if o.init_rule == "log_time_mean":
        mean = F.sum(F.col("n") * F.ln(F.col("t") + 1)).over(part) / F.col("c")
        return p.withColumn("t_init", F.floor(F.exp(mean) - 1 + TOL).cast("int"))
    return p.withColumn("t_init", F.min(F.when(_reached(o), F.col("t"))).over(part))


def extract_features(panel: DataFrame, w: int, o: FeatureOptions = FeatureOptions()) -> DataFrame:
    """(item_id, t, n) -> item_id, total, t_init, t_peak, t_last, the times, gains and peak counts."""
    p = timed(panel, w, o).withColumn("t_grow", F.col("t_peak") - F.col("t_init")).withColumn("t_decay", F.col("t_last") - F.col("t_peak"))
    n, t = F.col("n"), F.col("t")
    share = lambda cond: F.coalesce(F.sum(F.when(cond, n)), F.lit(0)) / F.first("c")
    if o.gain_mode == "prefix":
        gains = [share(t <= F.col("t_init")), share(t <= F.col("t_grow")), share(t <= F.col("t_decay"))]
    else:
        gains = [share(t <= F.col("t_init")), share((t > F.col("t_init")) & (t <= F.col("t_peak"))), share((t > F.greatest("t_init", "t_peak")) & (t <= F.col("t_last")))]
    start = t >= 0 if o.growth_start == "birth" else t > F.col("t_init")
    hit = {j: above(o, w, j) for j in (1, 2, 3)}
    if o.band == "exclusive":
        hit = {3: hit[3], 2: hit[2] & ~hit[3], 1: hit[1] & ~hit[2]}
    count = lambda cond: F.sum(F.when(cond, 1).otherwise(0)).cast("long")
    peaks = []
    for name, j in (("hi", 3), ("md", 2), ("lo", 1)):
        peaks += [count(hit[j] & start & (t <= F.col("t_peak"))).alias(f"{name}_grow"), count(hit[j] & (t > F.col("t_peak"))).alias(f"{name}_decay")]
    first = lambda c: F.first(c).alias(c)
    return p.groupBy("item_id").agg(
        F.first("c").cast("long").alias("total"), *[first(c) for c in ("t_init", "t_peak", "t_last", "t_grow", "t_decay")],
        *[g.alias(name) for g, name in zip(gains, GAINS)], *peaks,
    ).select("item_id", "total", "t_init", "t_peak", "t_last", *FEATURES[1:3], *GAINS, *PEAKS)


def features_of_series(dense: DataFrame, w: int) -> DataFrame:
    """The default features from a dense array by folds, without any shuffle."""
    s = F.col("series")
    fold = F.aggregate(
        s,
        F.struct(F.lit(0).cast("long").alias("c"), F.lit(0).cast("long").alias("q"), F.lit(0).alias("k"), F.lit(0.0).alias("ln"), F.lit(0).alias("i"), F.lit(-1).cast("long").alias("top"), F.lit(0).alias("peak"), F.lit(-1).alias("last")),
        lambda a, x: F.struct(
            (a["c"] + x).alias("c"), (a["q"] + x * x).alias("q"), (a["k"] + (x > 0).cast("int")).alias("k"), (a["ln"] + F.when(x > 0, F.ln(x)).otherwise(0.0)).alias("ln"),
            (a["i"] + 1).alias("i"), F.greatest(a["top"], x).alias("top"), F.when(x > a["top"], a["i"]).otherwise(a["peak"]).alias("peak"), F.when(x > 0, a["i"]).otherwise(a["last"]).alias("last"),
        ),
    )
    d = dense.withColumn("f", fold).filter("f.c > 0")
    gm = F.col("f.ln") / F.col("f.k")
    start = F.aggregate(
        s, F.struct(F.lit(0).alias("i"), F.lit(0).cast("long").alias("cum"), F.lit(-1).alias("t")),
        lambda a, x: F.struct((a["i"] + 1).alias("i"), (a["cum"] + x).alias("cum"), F.when((a["t"] < 0) & (a["cum"] + x > 0) & (F.ln(F.greatest(a["cum"] + x, F.lit(1))) >= gm - TOL), a["i"]).otherwise(a["t"]).alias("t")),
    )["t"]
    d = d.withColumn("t_init", start)
    d = d.select("item_id", "series", F.col("f.c").alias("total"), "t_init", F.col("f.peak").alias("t_peak"), F.col("f.last").alias("t_last"), F.col("f.q").alias("q"))
    d = d.withColumn("t_grow", F.col("t_peak") - F.col("t_init")).withColumn("t_decay", F.col("t_last") - F.col("t_peak"))
    prefix = lambda k: F.aggregate(F.slice("series", 1, k + 1), F.lit(0).cast("long"), lambda a, x: a + x) / F.col("total")
    d = d.withColumn("g_init", prefix(F.col("t_init"))).withColumn("g_grow", prefix(F.col("t_grow"))).withColumn("g_decay", prefix(F.col("t_decay")))
    var = F.lit(w) * F.col("q") - F.col("total") * F.col("total")
    for name, j in (("hi", 3), ("md", 2), ("lo", 1)):
        hit = lambda x: (F.lit(w) * x - F.col("total") >= 0) & ((F.lit(w) * x - F.col("total")) * (F.lit(w) * x - F.col("total")) >= j * j * var) & (var > 0)  # noqa: B023, E731
        d = d.withColumn(f"{name}_grow", F.size(F.filter(F.slice("series", 1, F.col("t_peak") + 1), hit)).cast("long"))
        d = d.withColumn(f"{name}_decay", F.size(F.filter(F.slice("series", F.col("t_peak") + 2, F.lit(w)), hit)).cast("long"))
    return d.select("item_id", "total", "t_init", "t_peak", "t_last", "t_grow", "t_decay", *GAINS, *PEAKS)
