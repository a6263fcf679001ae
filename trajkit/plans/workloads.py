"""The experiments, re-expressed on the given tables.

Those that only aggregate have SQL; those that fit the ensemble are checked by their invariants and,
on planted panels, by agreement with the planted classes.
"""

from __future__ import annotations

import math
import time
from concurrent.futures import ThreadPoolExecutor
from itertools import combinations

from pyspark.sql import functions as F

from trajkit.operators import density, ensemble as E, features as FT, lloyd as L, measures as M, panel as P, rules as R, scaling, spectral
from trajkit.operators.blocks import copies, packed
from trajkit.operators.features import FEATURES, PEAKS, FeatureOptions
from trajkit.operators.nearest import nearest
from trajkit.plans import sqltext as Q
from trajkit.plans.base_queries import PART, ORACLES, QUERIES, Z_PART, features_of, panel_of, register, scaled_features, without_self
from trajkit.plans.cluster_queries import CLASSED, EMB, POLY, anova_sql, classed, diffusion_vector, embedding_columns, unioned
from trajkit.plans.rule_queries import SCHEMES, scheme_of, series_part
from trajkit.sources import planted as PL
from trajkit.sources.shared import materialised, once
from trajkit.sources.tables import read_table

#: Ten rounds at most, as in the experiments; the stop rules end a fit earlier where little is left.
FIT = E.RoundOptions(k=8, eps=2.0, t_max=10, max_iter=10, stop="both")
SEEDS = ("0", "1", "2", "3", "4")
WINDOWS = {"short": 10, "long": 28}


def fitted(z, classes: int | None = 3, o: E.RoundOptions = FIT, q: float | None = None, cols=FEATURES):
    """(model, labels) of an ensemble on scaled columns; ``q`` sets the radius by a quantile."""
    if q is not None:
        o = E.RoundOptions(**{**o.__dict__, "eps": max(E.eps_from_quantile(z, cols, q), 1e-3)})
    z = packed(z, list(cols))
    model = E.EnsembleModel.fit(z, list(cols), o, classes)
    return model, model.transform(z)


# W1: two items of one field with the same total and very different curves.
_W1 = """SELECT item_id, field, sum(n)::BIGINT AS total, sum(n * t) / sum(n) AS mean_t, sum(CASE WHEN t < 7 THEN n ELSE 0 END)::BIGINT AS early FROM (SELECT p.*, p_type AS field FROM ({p}) AS p JOIN part ON p_partkey = item_id) GROUP BY 1, 2"""


@register("w01_equal_totals", f"""WITH x AS ({_W1.format(p=PART)}), g AS (SELECT field, total, min(CASE WHEN mean_t = lo THEN item_id END) AS a, max(CASE WHEN mean_t = hi THEN item_id END) AS b, round(max(hi) - min(lo), 6) AS gap FROM (SELECT *, min(mean_t) OVER f AS lo, max(mean_t) OVER f AS hi FROM x WINDOW f AS (PARTITION BY field, total)) GROUP BY 1, 2 HAVING count(*) > 1)
  SELECT g.field, g.total, a, b, gap, xa.early AS early_a, xb.early AS early_b FROM g JOIN x AS xa ON xa.item_id = a JOIN x AS xb ON xb.item_id = b QUALIFY row_number() OVER (PARTITION BY g.field ORDER BY gap DESC, g.total) = 1""")
def _(s, d):
    from pyspark.sql import Window as W

    field = read_table(s, d, "part", F.col("p_partkey").alias("item_id"), F.col("p_type").alias("field"))
    n, t = F.col("n"), F.col("t")
    x = panel_of(s, d, "part_quarter").join(field, "item_id").groupBy("item_id", "field").agg(F.sum("n").cast("long").alias("total"), (F.sum(n * t) / F.sum("n")).alias("mean_t"), F.sum(F.when(t < 7, n).otherwise(0)).cast("long").alias("early"))
    order = F.struct("mean_t", "item_id")
    # The earliest and the latest of each (field, total): extremes instead of all pairs.
    one = F.struct("item_id", "early")
    g = x.groupBy("field", "total").agg(F.min_by(one, order).alias("a"), F.max_by(one, order).alias("b"), F.round(F.max("mean_t") - F.min("mean_t"), 6).alias("gap"), F.count("*").alias("k")).filter("k > 1")
    top = g.withColumn("r", F.row_number().over(W.partitionBy("field").orderBy(F.desc("gap"), "total"))).filter("r = 1")
    return top.select("field", "total", F.col("a.item_id").alias("a"), F.col("b.item_id").alias("b"), "gap", F.col("a.early").alias("early_a"), F.col("b.early").alias("early_b"))


# W2: a worked example, every quantity of one series: the part with most shipments in the first eight quarters.
_W2 = f"SELECT * FROM ({PART}) WHERE t >= 0 AND t < 8"


@register("w02_worked_example", f"""WITH p AS MATERIALIZED ({_W2}), x AS MATERIALIZED (SELECT p.item_id, p.t, p.n::DOUBLE AS n FROM p JOIN (SELECT item_id FROM p GROUP BY item_id ORDER BY sum(n) DESC, item_id LIMIT 1) USING (item_id)),
    m AS (SELECT min(item_id) AS item_id, sum(n) AS total, avg(ln(n)) AS gm, arg_max(t, n * 100 - t) AS t_peak, max(t) AS t_last, sum(n) / 8 AS mean, sqrt(greatest(sum(n * n) / 8 - (sum(n) / 8) * (sum(n) / 8), 0)) AS sd FROM x),
    i AS (SELECT min(t) AS t_init FROM (SELECT t, sum(n) OVER (ORDER BY t) AS cum FROM x) AS r, m WHERE ln(cum) >= gm - 1e-9),
    h AS (SELECT x.t, x.t <= t_peak AS grow, CASE WHEN sd <= 1e-12 THEN 0 ELSE (n - mean) / sd + 1e-9 END AS z FROM x, m),
    k AS (SELECT {', '.join(f"count(*) FILTER (WHERE z >= {j} AND {'' if g == 'grow' else 'NOT '}grow) AS {v}_{g}" for v, j in (("hi", 3), ("md", 2), ("lo", 1)) for g in ("grow", "decay"))} FROM h)
  SELECT item_id, total::BIGINT AS total, t_init, t_peak, t_last, t_peak - t_init AS t_grow, t_last - t_peak AS t_decay,
    {', '.join(f"round((SELECT coalesce(sum(n), 0) FROM x WHERE t <= {k}) / total, 9) AS {g}" for g, k in (("g_init", "t_init"), ("g_grow", "t_peak - t_init"), ("g_decay", "t_last - t_peak")))}, k.* FROM m, i, k""")
def _(s, d):
    p = materialised(P.clip_window(panel_of(s, d, "part_quarter"), 8))
    top = p.groupBy("item_id").agg(F.sum("n").alias("c")).orderBy(F.desc("c"), "item_id").limit(1)
    f = FT.extract_features(p.join(F.broadcast(top.select("item_id")), "item_id"), 8)  # one item
    return f.withColumns({g: F.round(g, 9) for g in FT.GAINS})


# W3: eligibility by cohort under the three readings of the mean.
_FIRST = "SELECT o_custkey AS item_id, year(min(o_orderdate))::INTEGER AS birth FROM orders GROUP BY 1"
_C10 = f"SELECT item_id, sum(n)::BIGINT AS total FROM ({Q.CUST_HALF}) WHERE t >= 0 AND t < 10 GROUP BY 1"


@register("w03_eligibility", f"SELECT birth, count(*) AS items, count(CASE WHEN total / greatest(total / 10, 5) >= 1 THEN 1 END) AS own, count(CASE WHEN total / greatest(m, 5) >= 1 THEN 1 END) AS cohort FROM (SELECT birth, total, avg(total) OVER (PARTITION BY birth) AS m FROM ({_C10}) JOIN ({_FIRST}) USING (item_id)) GROUP BY 1")
def _(s, d):
    born = read_table(s, d, "orders", "o_custkey", "o_orderdate").groupBy(F.col("o_custkey").alias("item_id")).agg(F.year(F.min("o_orderdate")).alias("birth"))
    tot = P.totals(panel_of(s, d, "cust_half"), 10).join(born, "item_id")
    own = P.success_ratio(tot).withColumnRenamed("ratio", "own")
    both = P.success_ratio(own, mu="field", field="birth")
    return both.groupBy("birth").agg(F.count("*").alias("items"), F.count(F.when(F.col("own") >= 1, 1)).alias("own"), F.count(F.when(F.col("ratio") >= 1, 1)).alias("cohort"))


# W4: skew of totals on every panel.
_LEVELS = {"user_day": (80, 70, 60), "part_quarter": (40, 35, 30), "supp_month": (640, 620, 600), "cust_half": (20, 15, 10)}


@register("w04_tails", " UNION ALL ".join(f"SELECT '{k}' AS panel, count(*) AS items, " + ", ".join(f"count(CASE WHEN total > {x} THEN 1 END) AS over_{i}" for i, x in enumerate(v)) + f" FROM (SELECT sum(n) AS total FROM ({Q.PANELS[k]}) WHERE t >= 0 AND t < {Q.WIDTH[k]} GROUP BY item_id)" for k, v in _LEVELS.items()))
def _(s, d):
    return unioned([P.totals(panel_of(s, d, k), Q.WIDTH[k]).agg(F.lit(k).alias("panel"), F.count("*").alias("items"), *[F.count(F.when(F.col("total") > x, 1)).alias(f"over_{i}") for i, x in enumerate(v)]) for k, v in _LEVELS.items()])


# W5-W8: the three windows through the whole pipeline, and the flow of sizes.
def window_pipeline(s, d, kind: str, w: int, classes: int = 3):
    def build():
        f = materialised(FT.extract_features(P.eligible_panel(panel_of(s, d, kind), w), w))
        z = scaling.scaled(f, scaling.fit_zscore(f, FEATURES))
        model, final = fitted(z, classes, q=0.05)
        return f, model, materialised(final)

    return once(s, ("window", d, kind, w, classes), build)


for _no, _runs in (("05_short", {"part_quarter": 10, "user_day": 10}), ("06_mid", {"part_quarter": 20}), ("07_long", {"part_quarter": 28, "user_day": 30, "supp_month": 83})):
    register(f"w{_no}")(lambda s, d, runs=_runs: unioned([M.class_sizes(window_pipeline(s, d, k, w)[2]).withColumn("panel", F.lit(k)) for k, w in runs.items()]))


@register("w08_flow")
def _(s, d):
    _, model, final = window_pipeline(s, d, "part_quarter", 28)
    rounds = s.createDataFrame([("round", h, p, c) for h, (p, c) in enumerate(model.rounds.sizes)], "step string, no int, pool long, items long")
    last = final.groupBy("class").agg(F.count("*").alias("items"))
    return rounds.unionByName(last.select(F.lit("final").alias("step"), F.col("class").cast("int").alias("no"), F.lit(None).cast("long").alias("pool"), "items"))


def window_classes(s, d, window: str = "long"):
    """Features of the part panel in a window, with the ensemble's classes."""
    f, _, final = window_pipeline(s, d, "part_quarter", WINDOWS[window])
    return materialised(f.join(final.select("item_id", "class"), "item_id"))


def both_windows(measure):
    """A measure of the ensemble's classes in the short and in the long window."""

    def run(s, d):
        return unioned([measure(window_classes(s, d, name)).withColumn("window", F.lit(name)) for name in WINDOWS])

    return run


register("w09_time_profile")(both_windows(M.time_profile))
register("w10_phase_histograms_ensemble")(both_windows(M.gain_histogram))


@register("w10_phase_histograms", " UNION ALL ".join(f"SELECT class, '{c}' AS phase, floor({c} / 0.1 + 1e-9)::INTEGER AS bin, count(*) AS items FROM (SELECT *, CASE WHEN t_peak < 10 THEN 0 WHEN t_peak < 19 THEN 1 ELSE 2 END AS class FROM ({Q.features_sql(PART, 28, FeatureOptions(gain_mode='phase'))})) GROUP BY 1, 2, 3" for c in FT.GAINS))
def _(s, d):
    return M.gain_histogram(features_of(s, d, gain_mode="phase").withColumn("class", F.expr("CASE WHEN t_peak < 10 THEN 0 WHEN t_peak < 19 THEN 1 ELSE 2 END")))


register("w11_peak_boxes")(both_windows(lambda x: M.peak_box(x, tuple(PEAKS))))


# W12: analysis of variance of document measures by quality label.
_DOC = "SELECT quality AS class, n_chars, len(string_split(text, ' ')) AS words, len(string_split(text, chr(10))) AS lines FROM documents JOIN labels USING (doc_id) WHERE quality IS NOT NULL"


@register("w12_anova_documents", anova_sql(["n_chars", "words", "lines"], f"({_DOC})"))
def _(s, d):
    docs = read_table(s, d, "documents", "doc_id", "text", "n_chars").join(read_table(s, d, "labels", "doc_id", F.col("quality").alias("class")), "doc_id").filter("class IS NOT NULL")
    return M.anova(docs.select("class", "n_chars", F.size(F.split("text", " ")).alias("words"), F.size(F.split("text", "\n")).alias("lines")), ["n_chars", "words", "lines"])


register("w12_anova_ensemble")(both_windows(lambda x: M.anova(x, FEATURES)))


@register("w13_grid")
def _(s, d):
    return unioned([M.name_classes(M.time_profile(window_classes(s, d, name)), w).withColumn("window", F.lit(name)) for name, w in WINDOWS.items()])


@register("w14_alignment")
def _(s, d):
    """Classes of the ensemble in both windows against every scheme: the rules, spectral clustering of
    the series' shapes and k-means on features, polynomials and diffusion parameters."""
    out = []
    for name, w in WINDOWS.items():
        mine = window_classes(s, d, name)
        z = materialised(scaling.scaled(mine, scaling.fit_zscore(mine, FEATURES)))
        series = materialised(series_part(s, d, w).join(mine.select("item_id"), "item_id", "left_semi"))
        others = {n: scheme_of(series, n, w) for n in SCHEMES}
        others["spectral"] = spectral.landmark_spectral(z, FEATURES, 3, 200)
        for source, x, cols in (("features", z, FEATURES), ("poly", R.poly_fit(series, w).select("item_id", *POLY), POLY), ("diffusion", diffusion_vector(series), ["p", "q"])):
            x = materialised(x)
            others[f"kmeans_{source}"] = L.assign(x, cols, L.lloyd(x, cols, 4)).select("item_id", F.col("label").alias("class"))
        for scheme_name, classes in others.items():
            cross = M.crosswalk(mine.select("item_id", "class"), classes)
            out.append(cross.withColumns({"b": F.col("b").cast("string"), "scheme": F.lit(scheme_name), "window": F.lit(name)}))
    return unioned(out)


# W15, W16: one learner against the ensemble, raw series against features, on planted panels.
def share_series(panel, w: int, how: str):
    dense = P.densify(panel, w)
    total = F.aggregate("series", F.lit(0).cast("long"), lambda a, v: a + v)
    if how == "z":  # each item's own mean and deviation
        mean = total / float(w)
        sd = F.sqrt(F.aggregate("series", F.lit(0.0), lambda a, v: a + (v - mean) * (v - mean)) / float(w))
        return dense.select("item_id", *[F.when(sd > 0, F.round((F.col("series")[t] - mean) / sd, 9)).otherwise(0.0).alias(f"n_{t}") for t in range(w)])
    div = total if how == "share" else F.lit(1)
    return dense.select("item_id", *[F.round(F.col("series")[t] / div, 9).alias(f"n_{t}") for t in range(w)])


def planted_table(s, d, kind: str, imbalanced: bool = False):
    """Panel, width, truth and scaled features of a planted panel."""

    def build():
        panel, w = PL.planted_panel(s, d, kind, imbalanced)
        panel = materialised(P.eligible_panel(panel, w))
        f = FT.extract_features(panel, w)
        return panel, w, materialised(PL.truth(panel, imbalanced)), materialised(scaling.scaled(f, scaling.fit_zscore(f, FEATURES)))

    return once(s, ("planted", d, kind, imbalanced), build)


def planted_classes(s, d, kind: str, method: str, seed: str, imbalanced: bool, k: int):
    panel, w, _, z = planted_table(s, d, kind, imbalanced)
    if method == "ensemble":
        return fitted(z, k, E.RoundOptions(k=12, t_max=10, max_iter=10, stop="remaining", seed=seed), q=0.02)[1]
    if method == "spectral":
        return spectral.landmark_spectral(z, FEATURES, k, 200, seed=seed)
    if method == "density":
        return density.dbscan(z, ["t_init", "t_grow", "t_decay"], 0.4, 10).select("item_id", F.coalesce("cluster", F.lit(-1)).alias("class"))
    if method == "features":
        x, cols = z, FEATURES
    else:
        x, cols = once(s, ("raw", d, kind, imbalanced, method), lambda: materialised(share_series(panel, w, method[4:]))), [f"n_{t}" for t in range(w)]
    return L.assign(x, cols, L.lloyd(x, cols, k, "hash_sample", 10, seed=seed)).select("item_id", F.col("label").alias("class"))


def planted_scores(s, d, kind: str, methods: tuple[str, ...], seeds: tuple[str, ...], imbalanced: bool = False, k: int = 4):
    """panel, method, seed, ari, nmi, purity, seconds: all methods on one panel with one number of classes."""

    def score(m: str, seed: str):
        true, start = planted_table(s, d, kind, imbalanced)[2], time.time()
        a = M.agreement_of(planted_classes(s, d, kind, m, seed, imbalanced, k), true)
        return kind + "_imbalanced" * imbalanced, m, seed, *a, round(time.time() - start, 2)

    # Density clustering draws nothing, so it has one run.
    return [once(s, ("score", d, kind, imbalanced, k, m, x), lambda m=m, x=x: score(m, x)) for m in methods for x in (seeds if m != "density" else seeds[:1])]


_SCORES = "panel string, method string, seed string, ari double, nmi double, purity double, seconds double"


def over_seeds(scores):
    """Mean and range over the seeds, one row a panel and method."""
    stat = lambda c: [F.round(f(c), 6).alias(f"{c}_{n}") for n, f in (("mean", F.avg), ("least", F.min), ("most", F.max))]
    return scores.groupBy("panel", "method").agg(F.count("*").alias("seeds"), *stat("ari"), *stat("nmi"), *stat("purity"), F.round(F.avg("seconds"), 2).alias("seconds"))


@register("w15_learner_vs_ensemble")
def _(s, d):
    """One k-means against the ensemble: five seeds on the planted panel, two on its imbalanced variant (W26 has embeddings)."""
    rows = planted_scores(s, d, "supp", ("features", "ensemble"), SEEDS)
    rows += planted_scores(s, d, "supp", ("features", "ensemble"), SEEDS[:2], imbalanced=True)
    return over_seeds(s.createDataFrame(rows, _SCORES))


@register("w16_raw_vs_features")
def _(s, d):
    """Raw series (counts, shares, z-scores), features and the ensemble, with their seconds; the same
    number of classes and iterations for all."""
    return over_seeds(s.createDataFrame(planted_scores(s, d, "supp", ("raw_counts", "raw_share", "raw_z", "features", "ensemble", "spectral", "density"), SEEDS), _SCORES))


@register("w17_sweep")
def _(s, d):
    panel, w = PL.planted_panel(s, d, "supp")
    panel = materialised(P.eligible_panel(panel, w))
    f = FT.extract_features(panel, w)
    z, true, rows = materialised(scaling.scaled(f, scaling.fit_zscore(f, FEATURES))), PL.truth(panel), []
    for t_max, k, q in ((2, 6, 0.05), (4, 6, 0.05), (10, 6, 0.05), (100, 6, 0.05), (10, 12, 0.05), (10, 6, 0.02), (10, 6, 0.2)):
        model, got = fitted(z, 4, E.RoundOptions(k=k, t_max=t_max, max_iter=10, stop="captured"), q=q)
        a = M.agreement(got, true).first()
        rows.append((t_max, k, q, len(model.rounds.sizes), sum(c for _, c in model.rounds.sizes), a["ari"]))
    return s.createDataFrame(rows, "t_max int, k int, quantile double, rounds int, captured long, ari double")


def scaling_run(s, d, times: tuple[int, ...] = (1, 4, 16, 64), rounds: int = 2):
    """(times, items, seconds of one k-means iteration, of a whole ensemble fit and its labels) on copies of
    the items; the number of rounds is fixed so that the work an item is the same.  The copies are
    stored in blocks before either clock starts."""
    z = materialised(scaled_features(s, d))
    items, centers, rows = packed(z, FEATURES), L.seeds(z, FEATURES, 6, "0"), []
    fitted(items, 3, E.RoundOptions(k=6, eps=2.0, t_max=1, max_iter=1, stop="remaining"))  # warms up
    for n in times:
        big = copies(items, n)
        start = time.time()
        L.step(big, FEATURES, centers)
        one, start = time.time() - start, time.time()
        fitted(big, 3, E.RoundOptions(k=6, eps=2.0, t_max=rounds, max_iter=3, stop="remaining"))[1].groupBy("class").count().collect()
        rows.append((n, big.count(), round(one, 3), round(time.time() - start, 3)))
    return rows


@register("w18_run_time")
def _(s, d):
    """Seconds of one k-means iteration and of the whole method at 1 to 64 times the items, and the slope
    of log seconds on log items up to there (1: linear)."""
    rows, out = scaling_run(s, d), []
    for k, (n, items, one, whole) in enumerate(rows):
        so_far = rows[: k + 1]
        slopes = [slope([(r[1], r[c]) for r in so_far]) if k else None for c in (2, 3)]
        out.append((n, items, one, whole, *slopes))
    return s.createDataFrame(out, "times int, items long, iteration_seconds double, fit_seconds double, iteration_slope double, fit_slope double")


@register("w19_nonlinear")
def _(s, d):
    """Rings and moons: the ensemble against spectral, density and plain k-means."""
    import numpy as np

    rows = []
    for name in ("rings", "moons"):
        i = np.arange(400)
        a, r = 2 * np.pi * ((i * 0.61803398875) % 1), 1 + 0.06 * np.sin(i * 7.3)
        cls = i % 2
        if name == "rings":
            x, y = np.cos(a) * r * (1 + 2 * cls), np.sin(a) * r * (1 + 2 * cls)
        else:
            x, y = np.cos(a / 2) * r * (1 - 2 * cls) + cls, np.sin(a / 2) * r * (1 - 2 * cls) + 0.3 * cls
        z = materialised(s.createDataFrame([(int(k), float(p), float(q)) for k, p, q in zip(i, x, y)], "item_id long, x double, y double"))
        true = s.createDataFrame([(int(k), int(c)) for k, c in zip(i, cls)], "item_id long, class int")
        cols = ["x", "y"]
        got = {
            "kmeans": L.assign(z, cols, L.lloyd(z, cols, 2)).select("item_id", F.col("label").alias("class")),
            "ensemble": fitted(z, 2, E.RoundOptions(k=16, eps=0.8 if name == "rings" else 0.3, t_max=6, max_iter=4, stop="remaining"), cols=cols)[1],
            "spectral": spectral.landmark_spectral(z, cols, 2, 200, sigma=0.2),
            "density": density.dbscan(z, cols, 0.35, 4).select("item_id", F.coalesce("cluster", F.lit(-1)).alias("class")),
        }
        rows += [(name, m, M.agreement(g, true).first()["ari"]) for m, g in got.items()]
    return s.createDataFrame(rows, "shape string, method string, ari double")


QUERIES["w20_unclassified"], ORACLES["w20_unclassified"] = QUERIES["unclassified_share"], ORACLES["unclassified_share"]


# W21: the three most similar items of each by all scaled features; the SQL forms all pairs.
_APART = "round(sqrt(" + " + ".join(f"(a.{c} - b.{c}) * (a.{c} - b.{c})" for c in FEATURES) + "), 9)"


@register(
    "w21_similar",
    f"""WITH z AS MATERIALIZED ({Z_PART}) SELECT a.item_id, b.item_id AS similar, {_APART} AS dist FROM z AS a JOIN z AS b ON a.item_id <> b.item_id
      QUALIFY row_number() OVER (PARTITION BY a.item_id ORDER BY {_APART}, b.item_id) <= 3""",
)
def _(s, d):
    return nearest(scaled_features(s, d), FEATURES, 3)


@register("w22_fields", f"SELECT p_brand AS brand, count(*) AS items, round(avg(t_init), 6) AS t_init, round(avg(t_grow), 6) AS t_grow, round(avg(t_decay), 6) AS t_decay, round(avg(CASE WHEN class = 0 THEN 1 ELSE 0 END), 6) AS early_share FROM {CLASSED} AS c JOIN part ON p_partkey = c.item_id GROUP BY 1")
def _(s, d):
    x = classed(s, d).join(read_table(s, d, "part", F.col("p_partkey").alias("item_id"), F.col("p_brand").alias("brand")), "item_id")
    return x.groupBy("brand").agg(F.count("*").alias("items"), *[F.round(F.avg(c), 6).alias(c) for c in ("t_init", "t_grow", "t_decay")], F.round(F.avg((F.col("class") == 0).cast("int")), 6).alias("early_share"))


QUERIES["w23_fixed_window"], ORACLES["w23_fixed_window"] = QUERIES["impact_vs_class"], ORACLES["impact_vs_class"]
QUERIES["w24_spread"], ORACLES["w24_spread"] = QUERIES["spread_exponent"], ORACLES["spread_exponent"]
QUERIES["w24_poly"], ORACLES["w24_poly"] = QUERIES["poly_fit_r2"], ORACLES["poly_fit_r2"]

_SELF = ORACLES["panel_without_self"]
_CLS = "CASE WHEN t_peak < 10 THEN 0 WHEN t_peak < 19 THEN 1 ELSE 2 END"


@register("w25_self_mentions", f"SELECT a, b, count(*) AS items FROM (SELECT item_id, {_CLS} AS a FROM ({Q.features_sql(PART, 28)})) JOIN (SELECT item_id, {_CLS} AS b FROM ({Q.features_sql(_SELF, 28)})) USING (item_id) GROUP BY 1, 2")
def _(s, d):
    a = features_of(s, d).select("item_id", F.expr(_CLS).alias("a"))
    b = FT.extract_features(without_self(s, d), 28).select("item_id", F.expr(_CLS).alias("b"))
    return a.join(b, "item_id").groupBy("a", "b").agg(F.count("*").alias("items"))


@register("w26_conversations", f"SELECT item_id, total, t_init, t_peak, t_last FROM ({Q.features_sql(Q.CONV_TURN, 10)})")
def _(s, d):
    return features_of(s, d, "conv_turn", 10).select("item_id", "total", "t_init", "t_peak", "t_last")


def embedding_scores(s, d, seeds: tuple[str, ...]):
    """Rows as of ``planted_scores`` on the embeddings, whose labels are the truth."""
    z = materialised(embedding_columns(s, d))
    true = read_table(s, d, "embeddings", F.col("vec_id").alias("item_id"), F.col("label").alias("class"))
    rows = []
    for m in ("kmeans", "ensemble"):
        for seed in seeds:
            start = time.time()
            if m == "kmeans":
                got = L.assign(z, EMB, L.lloyd(z, EMB, 10, seed=seed)).select("item_id", F.col("label").alias("class"))
            else:
                got = fitted(z, 10, E.RoundOptions(k=20, t_max=10, max_iter=10, stop="remaining", seed=seed), q=0.1, cols=EMB)[1]
            a = M.agreement(got, true).first()
            rows.append(("embeddings", m, seed, a["ari"], a["nmi"], a["purity"], round(time.time() - start, 2)))
    return rows


register("w26_embeddings")(lambda s, d: over_seeds(s.createDataFrame(embedding_scores(s, d, SEEDS[:2]), _SCORES)))


@register("w25_self_mentions_ensemble")
def _(s, d):
    """How classes move when self mentions go: the ensemble fitted on both panels."""
    sides = []
    for p in (panel_of(s, d, "part_quarter"), without_self(s, d)):
        f = materialised(FT.extract_features(P.eligible_panel(p, 28), 28))
        sides.append(materialised(fitted(scaling.scaled(f, scaling.fit_zscore(f, FEATURES)), 3, q=0.05)[1].select("item_id", "class")))
    return M.crosswalk(*sides)


@register("stability_over_seeds")
def _(s, d):
    """Pairwise agreement of fits that differ in their seed only, by method."""
    z, rows = materialised(scaled_features(s, d)), []

    def run(m: str, seed: str):
        if m == "kmeans":
            got = L.assign(z, FEATURES, L.lloyd(z, FEATURES, 4, seed=seed)).select("item_id", F.col("label").alias("class"))
        else:
            got = fitted(z, 4, E.RoundOptions(**{**FIT.__dict__, "seed": seed}))[1].select("item_id", "class")
        return materialised(got)

    # Fits do not depend on one another, and a small one does not fill the cores.
    with ThreadPoolExecutor(len(SEEDS)) as pool:
        for m in ("kmeans", "ensemble"):
            runs = list(pool.map(lambda seed: run(m, seed), SEEDS))  # noqa: B023
            pairs = list(combinations(range(len(SEEDS)), 2))
            rows += [(m, i, j, a[0]) for (i, j), a in zip(pairs, pool.map(lambda p: M.agreement_of(runs[p[0]], runs[p[1]]), pairs))]  # noqa: B023
    return s.createDataFrame(rows, "method string, a int, b int, ari double")


def slope(points: list[tuple[float, float]]) -> float:
    """Slope of log seconds on log items."""
    xs, ys = [math.log(a) for a, _ in points], [math.log(max(b, 1e-9)) for _, b in points]
    mx, my = sum(xs) / len(xs), sum(ys) / len(ys)
    return sum((x - mx) * (y - my) for x, y in zip(xs, ys)) / sum((x - mx) ** 2 for x in xs)

