"""Rule-based and model-based schemes over one array of counts an item.

Each function reads ``series`` (item_id, series array<bigint> with a number for every period, as
``panel.densify`` makes them) and returns a row an item, as a projection: no scheme shuffles items.
Those that compare an item with its cohort first take a few numbers from an aggregate.  Thresholds
are parameters with the values printed in the literature; lengths of time scale with the window
unless told not to.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from trajkit.operators.quantile import exact_quantile
from trajkit.sources.shared import materialised

def series_() -> Column:
    return F.col("series")


def total(x: Column, kind: str = "bigint") -> Column:
    return F.aggregate(x, F.lit(0).cast(kind), lambda a, v: a + v)


def head(k: int) -> Column:
    return F.slice(series_(), 1, k)


def weighted(f: Callable[[Column, Column], Column], kind: str = "double") -> Column:
    """Sum over periods of f(count, period)."""
    return total(F.transform(series_(), lambda n, t: f(n, t).cast(kind)), kind)


def first_where(x: Column, f: Callable[[Column], Column]) -> Column:
    """The first place (from 0) at which f holds, or null."""
    at = F.array_position(F.transform(x, f), F.lit(True))
    return F.when(at > 0, at - 1).cast("int")


def periods(w: int) -> Column:
    return F.array(*[F.lit(t) for t in range(w)])


def running(inclusive: bool = True) -> Column:
    """Running totals; without ``inclusive`` those before each period."""
    return F.transform(series_(), lambda _, t: total(F.slice(series_(), F.lit(1), t + int(inclusive))))


def peak() -> Column:
    return first_where(series_(), lambda n: n == F.array_max(series_()))


def delayed_recognition(series: DataFrame, w: int, total_min: int = 30, early_max: float = 0.25, w_ref: int | None = 25, years: int = 10) -> DataFrame:
    """Much mentioned in all, with few mentions in the first years."""
    k = max(1, round(years * w / (w_ref or w)))
    x = series.select("item_id", total(head(k)).alias("early"), total(series_()).alias("c"))
    return x.withColumn("class", F.when((F.col("c") >= total_min) & (F.col("early") <= early_max * F.col("c")), "delayed").otherwise("other"))


def rise_decline(series: DataFrame, w: int, w_ref: int = 16, scaled: bool = True) -> DataFrame:
    """Share gained in the first 3 of 16 periods against the share in periods 7 to 12: a 3 x 3 grid."""
    f = w / w_ref if scaled else 1.0
    a, lo, hi = max(1, round(3 * f)), round(6 * f), round(12 * f)
    x = series.select("item_id", (total(head(a)) / total(series_())).alias("rise_share"), (total(F.slice(series_(), lo + 1, hi - lo)) / total(series_())).alias("late_share"))
    rise, late = F.col("rise_share"), F.col("late_share")
    return x.withColumns({
        "rise": F.when(rise > 0.30, "early").when(rise >= 0.15, "medium").otherwise("delayed"),
        "decline": F.when(late < 0.30, "rapid").when(late <= 0.50, "slow").otherwise("none"),
    })


def age_ratio(series: DataFrame, w: int, scale: float = 1.0, order: tuple[str, ...] = ("sleeping", "discovery", "hot")) -> DataFrame:
    """Mean mention age over item age with thresholds on the total (250, 500 and 350 times ``scale``);
    the rules overlap, and of those that hold the first in ``order`` wins."""
    r = F.round(weighted(lambda n, t: n * t, "bigint") / total(series_()) / float(w - 1), 9)
    x = series.select("item_id", total(series_()).alias("c"), r.alias("r"))
    c, r = F.col("c"), F.col("r")
    holds = {"sleeping": (c > 250 * scale) & (r > 0.7), "discovery": (c > 500 * scale) & (r < 0.4), "hot": (c > 350 * scale) & (r > 2 / 3)}
    return x.withColumn("class", F.coalesce(*[F.when(holds[k], F.lit(k)) for k in order], F.lit("other")))


def half_life(series: DataFrame, mode: str = "cohort") -> DataFrame:
    """Periods to a quarter, half and three quarters of the total; against the cohort's quartiles of
    the half-life (counts of few different integers), or against the item's own spread."""
    reach = lambda part: first_where(F.col("run"), lambda x: 4 * x >= part * F.col("c"))
    x = series.select("item_id", running().alias("run"), total(series_()).alias("c")).select("item_id", reach(1).alias("t25"), reach(2).alias("t50"), reach(3).alias("t75"))
    if mode == "own":
        up, down = F.col("t50") - F.col("t25"), F.col("t75") - F.col("t50")
        return x.withColumn("class", F.when(up > down, "delayed").when(up < down, "flash").otherwise("normal"))
    q = x.agg(F.percentile("t50", 0.25).alias("p25"), F.percentile("t50", 0.75).alias("p75"))  # one row
    cls = F.when(F.col("t50") < F.col("p25"), "flash").when(F.col("t50") > F.col("p75"), "delayed").otherwise("normal")
    return x.crossJoin(F.broadcast(q)).select("item_id", "t25", "t50", "t75", cls.alias("class"))


def peak_shape(series: DataFrame, w: int, frac: float = 0.75, early: int = 5, w_ref: int | None = 20, decline: float = 0.5, few: float = 0.5) -> DataFrame:
    """Number and place of local maxima of at least ``frac`` of the highest.  An initial peak must be
    followed by a decline (mean of the later periods at most ``decline`` of the peak), a late one
    have few initial mentions (mean of the early periods at most ``few`` of it)."""
    k, m = max(1, round(early * w / (w_ref or w))), F.array_max(series_())
    near = lambda t: F.coalesce(F.get(series_(), t), F.lit(-1))
    top = F.filter(periods(w), lambda t: (F.get(series_(), t) > F.when(t > 0, near(t - 1)).otherwise(-1)) & (F.get(series_(), t) >= near(t + 1)) & (F.get(series_(), t) >= frac * m))
    rest = F.filter(periods(w), lambda t: t > 0)
    ups = F.size(F.filter(rest, lambda t: F.get(series_(), t) >= F.get(series_(), t - 1)))
    downs = F.size(F.filter(rest, lambda t: (t > 1) & (F.get(series_(), t) <= F.get(series_(), t - 1))))
    x = series.select("item_id", "series", top.alias("top"), m.alias("m"), ups.alias("ups"), downs.alias("downs"))
    x = x.withColumns({"peaks": F.size("top").cast("long"), "first_peak": F.get("top", F.lit(0))})
    p, after = F.col("first_peak"), F.slice(series_(), F.col("first_peak") + 2, F.lit(w))
    falls = F.when(p < w - 1, total(after) / F.size(after) <= decline * F.col("m")).otherwise(False)
    quiet = total(head(k)) / k <= few * F.col("m")
    one = F.col("peaks") == 1
    cls = (
        F.when(F.col("ups") == w - 1, "monotone_up").when((F.col("downs") == w - 2) & (p <= 1), "monotone_down").when(F.col("peaks") > 1, "several")
        .when(one & (p <= k) & falls, "initial").when(one & (p > k) & (p < w - 1) & quiet, "late").otherwise("other")
    )
    return x.select("item_id", "peaks", "first_peak", cls.alias("class"))


def diffusion_moments(series: DataFrame) -> DataFrame:
    """Sums that the regression of a period's count on the total before it needs."""
    x = series.select("item_id", "series", F.transform(running(False), lambda v: v.cast("double")).alias("p"))
    power = lambda j: total(F.transform("p", lambda v: F.pow(v, F.lit(float(j))) if j != 1 else v), "double")
    mixed = lambda j: total(F.zip_with(series_(), "p", lambda n, v: n * F.pow(v, F.lit(float(j)))), "double")
    return x.select("item_id", *[power(j).alias(f"s{j}") for j in range(5)], *[mixed(j).alias(f"y{j}") for j in range(3)])


def diffusion(series: DataFrame) -> DataFrame:
    """Least squares of n on N and N squared (centred), then the diffusion model's market size and its
    innovation and imitation coefficients, null where the fit has no such solution; classes by the
    exact medians of both."""
    c = F.col
    x = diffusion_moments(series)
    # Centred sums, times s0, keep the normal equations to two.
    x = x.select(
        "item_id", "s0", "s1", "s2", "y0", (c("s0") * c("s2") - c("s1") * c("s1")).alias("vv"), (c("s0") * c("s3") - c("s1") * c("s2")).alias("vw"), (c("s0") * c("s4") - c("s2") * c("s2")).alias("ww"),
        (c("s0") * c("y1") - c("s1") * c("y0")).alias("vy"), (c("s0") * c("y2") - c("s2") * c("y0")).alias("wy"),
    ).withColumn("det", c("vv") * c("ww") - c("vw") * c("vw"))
    div = lambda a, b: F.when(b != 0, a / b)
    x = x.withColumns({"b": div(c("vy") * c("ww") - c("wy") * c("vw"), c("det")), "k": div(c("wy") * c("vv") - c("vy") * c("vw"), c("det"))})
    x = x.withColumn("a", (c("y0") - c("b") * c("s1") - c("k") * c("s2")) / c("s0"))
    root = c("b") * c("b") - 4 * c("a") * c("k")
    x = x.withColumn("m", F.when((c("k") < 0) & (root >= 0), (-c("b") - F.sqrt(F.greatest(root, F.lit(0.0)))) / (2 * c("k"))))
    x = x.select("item_id", "m", F.when(c("m") > 0, c("a") / c("m")).alias("p"), F.when(c("m") > 0, -c("k") * c("m")).alias("q"))
    x = materialised(x)  # the medians and the classes read it several times
    mp, mq = exact_quantile(x, c("p"), 0.5), exact_quantile(x, c("q"), 0.5)
    size = lambda v, mid, name: F.concat(F.when(v > F.lit(mid), "large_").otherwise("small_"), F.lit(name))
    cls = F.when(c("p").isNull(), "none").otherwise(F.concat_ws("_", size(c("p"), mp, "p"), size(c("q"), mq, "q")))
    return x.select("item_id", F.round("m", 4).alias("m"), F.round("p", 6).alias("p"), F.round("q", 6).alias("q"), cls.alias("class"))


def _to_peak(series: DataFrame) -> DataFrame:
    """Birth, peak, and the series from birth to peak."""
    x = series.select("item_id", "series", F.get(series_(), F.lit(0)).alias("n0"), peak().alias("t_peak"), F.array_max(series_()).alias("n_peak"))
    return x.withColumn("rise", F.slice(series_(), F.lit(1), F.col("t_peak") + 1))


def beauty(series: DataFrame) -> DataFrame:
    """Sum of the gaps between the line from birth to peak and the series, over the series."""
    up = (F.col("n_peak") - F.col("n0")) / F.greatest(F.col("t_peak"), F.lit(1)).cast("double")
    gaps = F.transform("rise", lambda n, t: F.when(F.col("t_peak") > 0, (up * t + F.col("n0") - n) / F.greatest(n, F.lit(1))).otherwise(0.0))
    return _to_peak(series).select("item_id", F.round(total(gaps, "double"), 9).alias("beauty"))


def awakening(series: DataFrame) -> DataFrame:
    """The period farthest from that line; the first of equals."""
    up, across = F.col("n_peak") - F.col("n0"), F.col("t_peak")
    far = F.transform("rise", lambda n, t: F.round(F.abs(up * t - across * n + across * F.col("n0")) / F.sqrt((up * up + across * across).cast("double") + 1e-12), 6))
    x = _to_peak(series).select("item_id", far.alias("far"))
    return x.select("item_id", first_where(F.col("far"), lambda v: v == F.array_max("far")).alias("t_awake"), F.array_max("far").alias("distance"))


def angle(series: DataFrame, hi: float = 60, lo: float = 30, x_scale: float = 1.0, y_scale: float = 1.0) -> DataFrame:
    """Angle of the line from birth to peak above the zero line."""
    deg = F.round(F.degrees(F.atan2(F.array_max(series_()) / y_scale, F.greatest(peak().cast("double"), F.lit(0.5)) / x_scale)), 6)
    x = series.select("item_id", deg.alias("angle"))
    return x.withColumn("class", F.when(F.col("angle") > hi, "smart").when(F.col("angle") < lo, "sleeping").otherwise("between"))


def second_act(series: DataFrame, w: int, fall: float = 0.5, again: float = 0.75, sleep: float = 0.25) -> DataFrame:
    """After the first high period, a fall to ``fall`` of it and a later return to ``again`` of it;
    sleepers have few mentions in the first third."""
    # One fold finds the three periods.  Expressions that build on one another through lambdas would be
    # put into each other by the optimiser and evaluated anew for every period of every period.
    none = F.lit(None).cast("int")

    def move(a: Column, n: Column) -> Column:
        first = F.when(a["first"].isNull() & (n >= again * a["m"]), a["i"]).otherwise(a["first"])
        low = F.when(a["low"].isNull() & (a["first"] < a["i"]) & (n <= fall * a["m"]), a["i"]).otherwise(a["low"])
        back = F.when(a["back"].isNull() & (a["low"] < a["i"]) & (n >= again * a["m"]), a["i"]).otherwise(a["back"])
        return F.struct(a["m"].alias("m"), (a["i"] + 1).alias("i"), first.alias("first"), low.alias("low"), back.alias("back"))

    start = F.struct(F.array_max(series_()).alias("m"), F.lit(0).alias("i"), none.alias("first"), none.alias("low"), none.alias("back"))
    x = series.select("item_id", "series", F.aggregate(series_(), start, move).alias("x"))
    x = x.select("item_id", "series", F.col("x.first").alias("first_high"), "x.low", "x.back")
    asleep, back = total(head(w // 3)) <= sleep * total(series_()), F.col("back").isNotNull()
    cls = F.when(~back & asleep, "single_peak_sleeper").when(back & asleep, "second_act_sleeper").when(back, "second_act").otherwise("other")
    return x.select("item_id", "first_high", "low", "back", cls.alias("class"))


def revival(series: DataFrame, w: int, **options) -> DataFrame:
    """Whether a high period comes again after a fall."""
    return second_act(series, w, **options).select("item_id", F.col("back").isNotNull().alias("revived"), (F.col("back") - F.col("low")).alias("quiet"))


def half_peak(series: DataFrame, w: int) -> DataFrame:
    """Peak of the series over each period's mean (one row of w numbers): first half hot, second half delayed."""
    means = series.agg(F.array(*[F.avg(F.get(series_(), F.lit(t))) for t in range(w)]).alias("means"))
    ratio = F.zip_with(series_(), "means", lambda n, v: F.when(v > 0, n / v))
    x = series.crossJoin(F.broadcast(means)).select("item_id", ratio.alias("r"))
    at = first_where(F.col("r"), lambda v: v == F.array_max("r"))
    return x.select("item_id", at.alias("t_norm_peak"), F.when(at < w / 2, "hot").otherwise("delayed").alias("class"))


def sleepers(series: DataFrame, w: int, length: int = 5, depth: float = 1.0, wake: int = 4) -> DataFrame:
    """Depth of the sleep of the first periods, the share of it in each (heartbeat) and the
    mentions in as many periods after it."""
    first = total(head(length))
    x = series.select(
        "item_id", (first / float(length)).alias("asleep"), total(F.slice(series_(), length + 1, length)).alias("intensity"),
        *[F.when(first > 0, F.get(series_(), F.lit(k)) / first).alias(f"beat_{k}") for k in range(length)],
    )
    sleeps = (F.col("asleep") <= depth) & (F.col("intensity") >= wake)
    return x.withColumn("class", F.when(sleeps & F.col("beat_0").isNull(), "all_elements").when(sleeps, "sleeper").otherwise("other"))


def poly_basis(w: int, degree: int = 5) -> np.ndarray:
    """Orthonormal polynomials on the window's periods; all items share them."""
    q, r = np.linalg.qr(np.vander(np.linspace(-1, 1, w), degree + 1, increasing=True))
    return np.round(q * np.sign(np.diag(r)), 12)


def poly_fit(series: DataFrame, w: int, degree: int = 5) -> DataFrame:
    """Coefficients on the shared basis (a projection, no solve per item) and R squared."""
    basis = poly_basis(w, degree)
    dot = lambda j: total(F.zip_with(series_(), F.array(*[F.lit(float(v)) for v in basis[:, j]]), lambda n, v: n * v), "double")
    squares = total(F.transform(series_(), lambda n: n * n)).cast("double")
    x = series.select("item_id", total(series_()).cast("double").alias("c"), squares.alias("nn"), *[dot(j).alias(f"c{j}") for j in range(degree + 1)])
    spread, fit = F.col("nn") - F.col("c") * F.col("c") / float(w), sum((F.col(f"c{j}") * F.col(f"c{j}") for j in range(1, degree + 1)), F.col("c0") * F.col("c0"))
    r2 = F.when(spread != 0, F.round(1 - (F.col("nn") - fit) / spread, 6))
    return x.select("item_id", *[(F.round(f"c{j}", 6) + 0.0).alias(f"c{j}") for j in range(degree + 1)], r2.alias("r2"))


def transient_sticky(series: DataFrame, w: int, early: float = 0.2, tail: float = 0.2) -> DataFrame:
    """An early peak and a steep fall, or still mentioned in the second half."""
    x = series.select("item_id", peak().alias("t_peak"), (total(F.slice(series_(), w // 2 + 1, w)) / total(series_())).alias("tail_share"))
    sticky = F.col("tail_share") >= tail
    return x.withColumn("class", F.when((F.col("t_peak") <= early * w) & ~sticky, "transient").when(sticky, "sticky").otherwise("other"))


def spread_exponent(series: DataFrame, w: int) -> DataFrame:
    """Half the slope of log variance of the running totals on log time: one aggregate of w variances."""
    var = series.select(running().alias("run")).agg(F.array(*[F.var_pop(F.get("run", F.lit(t))) for t in range(w)]).alias("v"))
    each = var.select(F.posexplode("v").alias("t", "v")).filter("v > 0")
    return each.agg(F.round(F.regr_slope(F.log("v"), F.log(F.col("t") + 1.0)) / 2, 6).alias("h"), F.count("*").alias("periods"))
