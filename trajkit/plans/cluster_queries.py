"""Queries of k-means, the ensemble's steps and the measures, each with its SQL."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import functions as F

from trajkit.operators import density, ensemble as E, features as FT, graphcut, lloyd as L, measures as M, panel as P, rules as R, spectral
from trajkit.operators.features import FEATURES, PEAKS
from trajkit.plans import sqltext as Q
from trajkit.plans.base_queries import PART, Z_PART, features_of, panel_of, register, scaled_features
from trajkit.plans import rule_sql as RS
from trajkit.plans.rule_queries import DENSE, RULES, SCHEMES, scheme_of, series_part
from trajkit.sources import planted as PL
from trajkit.sources.shared import materialised, once
from trajkit.sources.tables import read_table

K, EPS, SEED = 6, 2.0, "0"


# ---- SQL of the iterations -------------------------------------------------------------------


def _dist(a: str, b: str, cols: list[str]) -> str:
    return "0.0::DOUBLE + " + " + ".join(f"({a}.{c} - {b}.{c}) * ({a}.{c} - {b}.{c})" for c in cols)


def _seed_cte(name: str, pool: str, cols: list[str], k: int, seed: str) -> str:
    c = ", ".join(cols)
    return f"{name} AS (SELECT (row_number() OVER (ORDER BY h) - 1)::INTEGER AS l, {c} FROM (SELECT min(md5('{seed}|' || item_id)) AS h, {c} FROM {pool} GROUP BY {c}) ORDER BY h LIMIT {k})"


def _assign_cte(name: str, pool: str, centers: str, cols: list[str]) -> str:
    return f"{name} AS (SELECT * FROM (SELECT p.item_id, {', '.join('p.' + c for c in cols)}, c.l AS label, round({_dist('p', 'c', cols)}, 9) AS d2 FROM {pool} AS p CROSS JOIN {centers} AS c) QUALIFY row_number() OVER (PARTITION BY item_id ORDER BY d2, label) = 1)"


def _update_cte(name: str, assigned: str, old: str, cols: list[str]) -> str:
    avg = ", ".join(f"round(avg({c}), 9) AS {c}" for c in cols)
    return f"{name} AS (SELECT o.l, {', '.join(f'coalesce(u.{c}, o.{c}) AS {c}' for c in cols)} FROM {old} AS o LEFT JOIN (SELECT label, {avg} FROM {assigned} GROUP BY label) AS u ON u.label = o.l)"


def lloyd_sql(prefix: str, pool: str, cols: list[str], k: int, iters: int, seed: str) -> tuple[list[str], str]:
    """CTEs and the name of the last centres."""
    out, now = [_seed_cte(f"{prefix}c0", pool, cols, k, seed)], f"{prefix}c0"
    for i in range(iters):
        out += [_assign_cte(f"{prefix}a{i}", pool, now, cols), _update_cte(f"{prefix}c{i + 1}", f"{prefix}a{i}", now, cols)]
        now = f"{prefix}c{i + 1}"
    return out, now


def kmeans_sql(source: str, cols: list[str], k: int, iters: int, seed: str = SEED, select: str = "item_id, label, d2 FROM done") -> str:
    ctes, last = lloyd_sql("r", "z", cols, k, iters, seed)
    return "WITH z AS MATERIALIZED (" + source + "), " + ", ".join(c.replace(" AS (", " AS MATERIALIZED (", 1) for c in [*ctes, _assign_cte("done", "z", last, cols)]) + f" SELECT {select}"


def _register_kmeans(name: str, source: str, frame, cols: list[str], k: int, iters: int) -> None:
    def run(s, d):
        z = materialised(frame(s, d))
        centers = L.seeds(z, cols, k, SEED)
        if iters:
            centers = L.lloyd(z, cols, k, centers, iters, tol=-1.0)
        return L.assign(z, cols, centers).select("item_id", "label", "d2")

    register(name, kmeans_sql(source, cols, k, iters))(run)


_register_kmeans("kmeans_assign_iter0", Z_PART, scaled_features, FEATURES, K, 0)
_register_kmeans("kmeans_iter3", Z_PART, scaled_features, FEATURES, K, 3)
_register_kmeans("base_feat_iter3", Z_PART, scaled_features, FEATURES, 4, 3)


# Raw series: counts, shares of the total, z-scores of each item's own series.
RAW = [f"n_{t}" for t in range(28)]


def raw_series(s, d, how: str = "counts"):
    x = P.densify(panel_of(s, d, "part_quarter"), 28)
    x = x.withColumn("total", F.aggregate("series", F.lit(0).cast("long"), lambda a, v: a + v))
    x = x.withColumn("sq", F.aggregate("series", F.lit(0).cast("long"), lambda a, v: a + v * v))
    x = x.withColumn("sd", F.sqrt((28 * F.col("sq") - F.col("total") * F.col("total")).cast("double")) / 28.0)
    if how == "counts":
        col = lambda t: F.col("series")[t].cast("double")
    elif how == "share":
        col = lambda t: F.round(F.col("series")[t] / F.col("total"), 9)
    else:
        col = lambda t: F.when(F.col("sd") > 0, F.round((F.col("series")[t] - F.col("total") / 28.0) / F.col("sd"), 9)).otherwise(0.0)
    return x.select("item_id", *[col(t).alias(f"n_{t}") for t in range(28)])


def _raw_sql(how: str) -> str:
    v = {"counts": "n::DOUBLE", "share": "round(n / c, 9)", "z": "CASE WHEN 28 * q - c * c > 0 THEN round((n - c / 28.0::DOUBLE) / (sqrt((28 * q - c * c)::DOUBLE) / 28.0::DOUBLE), 9) ELSE 0.0::DOUBLE END"}[how]
    inner = f"SELECT item_id, t, n, sum(n) OVER (PARTITION BY item_id)::BIGINT AS c, sum(n * n) OVER (PARTITION BY item_id)::BIGINT AS q FROM ({DENSE})"
    return f"SELECT item_id, {', '.join(f'max(CASE WHEN t = {t} THEN {v} END) AS n_{t}' for t in range(28))} FROM ({inner}) GROUP BY item_id"


for _how, _name in (("counts", "base_raw_iter3"), ("share", "base_raw_share_iter3"), ("z", "base_raw_z_iter3")):
    _register_kmeans(_name, _raw_sql(_how), lambda s, d, h=_how: raw_series(s, d, h), RAW, 2, 3)

POLY = [f"c{j}" for j in range(6)]
_register_kmeans("base_poly_iter3", f"SELECT item_id, {', '.join(POLY)} FROM ({RS.text(RS.poly_fit(28), DENSE)})", lambda s, d: R.poly_fit(series_part(s, d), 28).select("item_id", *POLY), POLY, 4, 3)
#: Items without a fit count as (0, 0); outliers are drawn in to the edge instead of left out.
_DIFF = "SELECT item_id, least(greatest(coalesce(p, 0), -1), 1) AS p, least(greatest(coalesce(q, 0), -2), 2) AS q FROM ({x}) AS y"


def diffusion_vector(series):
    held = lambda c, edge: F.least(F.greatest(F.coalesce(c, F.lit(0.0)), F.lit(-edge)), F.lit(edge)).alias(c)
    return R.diffusion(series).select("item_id", held("p", 1.0), held("q", 2.0))


_register_kmeans("base_diffusion_iter3", _DIFF.format(x=RS.text(RS.diffusion(), DENSE)), lambda s, d: diffusion_vector(series_part(s, d)), ["p", "q"], 4, 3)

EMB = [f"e{i}" for i in range(64)]


def embedding_columns(s, d):
    return read_table(s, d, "embeddings", "vec_id", "embedding").select(F.col("vec_id").alias("item_id"), *[F.round(F.col("embedding")[i].cast("double"), 9).alias(f"e{i}") for i in range(64)])


_EMB_SQL = "SELECT vec_id AS item_id, " + ", ".join(f"round(embedding[{i + 1}]::DOUBLE, 9) AS e{i}" for i in range(64)) + " FROM embeddings"
_register_kmeans("base_embeddings_iter2", _EMB_SQL, embedding_columns, EMB, 10, 2)


@register("kmeans_objective", kmeans_sql(Z_PART, FEATURES, K, 3, select="round(sum(d2), 6) AS objective, count(*) AS items FROM done"))
def _(s, d):
    z = scaled_features(s, d)
    return L.objective(L.assign(z, FEATURES, L.lloyd(z, FEATURES, K, L.seeds(z, FEATURES, K, SEED), 3, tol=-1.0)))


@register("credibility_flags", kmeans_sql(Z_PART, FEATURES, K, 3, select=f"item_id, label, d2 <= {EPS * EPS} AS credible FROM done"))
def _(s, d):
    z = scaled_features(s, d)
    done = L.assign(z, FEATURES, L.lloyd(z, FEATURES, K, L.seeds(z, FEATURES, K, SEED), 3, tol=-1.0))
    return done.select("item_id", "label", (F.col("d2") <= EPS * EPS).alias("credible"))


# ---- two fixed rounds ------------------------------------------------------------------------

OPTIONS = E.RoundOptions(k=K, eps=EPS, t_max=2, max_iter=3, stop="remaining", seed=SEED)


def _rounds_ctes() -> list[str]:
    out = [f"z AS ({Z_PART})"]
    a, c0 = lloyd_sql("p", "z", FEATURES, K, 3, f"{SEED}|0")
    out += [*a, _assign_cte("done0", "z", c0, FEATURES), f"pool1 AS (SELECT * FROM done0 WHERE d2 > {EPS * EPS})"]
    b, c1 = lloyd_sql("q", "pool1", FEATURES, K, 3, f"{SEED}|1")
    out += [*b, _assign_cte("all1", "z", c1, FEATURES)]
    f = ", ".join(FEATURES)
    out += [
        f"centers AS (SELECT l AS cid, 0 AS h, l, {f} FROM {c0} UNION ALL SELECT l + {K}, 1, l, {f} FROM {c1})",
        "labels AS (SELECT item_id, 0 AS h, label, sqrt(d2) AS dist FROM done0 UNION ALL SELECT item_id, 1, label, sqrt(d2) FROM all1)",
        f"capture AS (SELECT a.item_id, CASE WHEN a.d2 <= {EPS * EPS} THEN 0 WHEN b.d2 <= {EPS * EPS} THEN 1 END AS captured_at FROM done0 AS a JOIN all1 AS b USING (item_id))",
        f"pairs AS (SELECT a.cid AS a, b.cid AS b, sqrt({_dist('a', 'b', FEATURES)}) AS dist, {', '.join(f'(a.{c} + b.{c}) / 2 AS {c}' for c in FEATURES)} FROM centers AS a JOIN centers AS b ON a.cid < b.cid)",
        f"gated AS (SELECT * FROM pairs WHERE dist <= {4 * EPS})",
        f"edges AS (SELECT a, b, round(dist, 6) AS dist, coalesce(pop, 0)::BIGINT AS pop, round(coalesce(pop, 0) / dist, 6) AS w FROM gated LEFT JOIN (SELECT g.a AS pa, g.b AS pb, count(*) AS pop FROM z JOIN gated AS g ON round({_dist('z', 'g', FEATURES)}, 9) <= {EPS * EPS} GROUP BY 1, 2) ON pa = a AND pb = b)",
    ]
    return [c.replace(" AS (", " AS MATERIALIZED (", 1) for c in out]


def rounds_sql(select: str) -> str:
    return "WITH " + ", ".join(_rounds_ctes()) + f" SELECT {select}"


def two_rounds(s, d):
    def build():
        z = materialised(scaled_features(s, d))
        r = E.run_rounds(z, FEATURES, OPTIONS)
        return z, r, materialised(E.scan(z, FEATURES, r, EPS))

    return once(s, ("two_rounds", d), build)


def fixed_long(s, d):
    """Labels of both rounds over all items, without the credible flag's rounding."""
    _, r, sc = two_rounds(s, d)
    return r, sc, E.labels_long(sc, EPS)


register("rounds_labels", rounds_sql("item_id, h, label, round(dist, 6) AS dist FROM labels"))(lambda s, d: fixed_long(s, d)[2].select("item_id", "h", "label", F.round("dist", 6).alias("dist")))
register("rounds_captured", rounds_sql("* FROM capture"))(lambda s, d: two_rounds(s, d)[2].select("item_id", "captured_at"))
register("participation", rounds_sql("item_id, h, captured_at IS NULL OR captured_at >= h AS takes_part FROM capture CROSS JOIN (VALUES (0), (1)) AS r(h)"))(
    lambda s, d: two_rounds(s, d)[2].select("item_id", "captured_at", F.explode(F.array(F.lit(0), F.lit(1))).alias("h")).select("item_id", "h", (F.col("captured_at").isNull() | (F.col("captured_at") >= F.col("h"))).alias("takes_part"))
)


@register("objective_u", rounds_sql(f"round(sum(dist), 6) AS u, count(*) AS terms FROM labels JOIN capture USING (item_id) WHERE (captured_at IS NULL OR captured_at >= h) AND dist <= {EPS}"))
def _(s, d):
    _, sc, long = fixed_long(s, d)
    x = long.join(sc.select("item_id", "captured_at"), "item_id").filter((F.col("captured_at").isNull() | (F.col("captured_at") >= F.col("h"))) & F.col("credible"))
    return x.agg(F.round(F.sum("dist"), 6).alias("u"), F.count("*").alias("terms"))


register("coverage", rounds_sql("count(captured_at) AS covered, count(*) - count(captured_at) AS uncovered, round(1 - count(captured_at) / count(*), 9) AS uncovered_share FROM capture"))(
    lambda s, d: two_rounds(s, d)[2].agg(F.count("captured_at").alias("covered"), (F.count("*") - F.count("captured_at")).alias("uncovered"), F.round(1 - F.count("captured_at") / F.count("*"), 9).alias("uncovered_share"))
)


@register("rounds_sizes")
def _(s, d):
    r = E.run_rounds(scaled_features(s, d), FEATURES, E.RoundOptions(k=K, eps=EPS, t_max=4, max_iter=4))
    return s.createDataFrame([(h, p, c) for h, (p, c) in enumerate(r.sizes)], "h int, pool long, captured long")


@register("stop_rule_trace")
def _(s, d):
    z, rows = scaled_features(s, d), []
    for stop in ("captured", "remaining", "both"):
        r = E.run_rounds(z, FEATURES, E.RoundOptions(k=K, eps=EPS, t_max=3, max_iter=2, stop=stop))
        rows += [(stop, h, p, c, c < K * K, p - c < K * K) for h, (p, c) in enumerate(r.sizes)]
    return s.createDataFrame(rows, "stop string, h int, pool long, captured long, few_captured boolean, few_left boolean")


@register("rounds_scopes")
def _(s, d):
    z, rows = scaled_features(s, d), []
    for scope in ("final_center", "initial_center", "trimmed"):
        r = E.run_rounds(z, FEATURES, E.RoundOptions(k=K, eps=EPS, t_max=2, max_iter=2, scope=scope))
        rows += [(scope, h, p, c) for h, (p, c) in enumerate(r.sizes)]
    return s.createDataFrame(rows, "scope string, h int, pool long, captured long")


_SAMPLE = f"(SELECT * FROM ({Z_PART}) ORDER BY md5('0|' || item_id) LIMIT 200)"
register("eps_quantile", f"SELECT round(quantile_cont(d, 0.02), 6) AS eps, count(*) AS pairs FROM (SELECT sqrt({_dist('a', 'b', FEATURES)}) AS d FROM {_SAMPLE} AS a JOIN {_SAMPLE} AS b ON a.item_id < b.item_id)")(
    lambda s, d: s.createDataFrame([(round(E.eps_from_quantile(scaled_features(s, d), FEATURES, sample=200), 6), 199 * 100)], "eps double, pairs long")
)


@register("direct_overlap", rounds_sql(f"a.label AS a, b.label AS b, count(*) AS items FROM labels AS a JOIN labels AS b ON a.item_id = b.item_id AND a.h = 0 AND b.h = 1 WHERE a.dist <= {EPS} AND b.dist <= {EPS} GROUP BY 1, 2"))
def _(s, d):
    sc = two_rounds(s, d)[2]
    return sc.filter((F.col("dists")[0] <= EPS) & (F.col("dists")[1] <= EPS)).groupBy(F.col("labels")[0].alias("a"), F.col("labels")[1].alias("b")).agg(F.count("*").alias("items"))


@register("latent_midpoints", rounds_sql("a, b, round(dist, 6) AS dist, " + ", ".join(f"round({c}, 6) AS {c}" for c in FEATURES) + " FROM gated"))
def _(s, d):
    _, r, _ = two_rounds(s, d)
    c = np.concatenate(r.centers)
    a, b, dist = E.gated_pairs(c, EPS)
    rows = [(int(x), int(y), round(float(v), 6), *[round(float(m), 6) + 0.0 for m in (c[x] + c[y]) / 2]) for x, y, v in zip(a, b, dist)]
    return s.createDataFrame(rows, "a int, b int, dist double, " + ", ".join(f"{f} double" for f in FEATURES))


def edges_of(s, d):
    z, r, _ = two_rounds(s, d)
    return E.affinity(z, FEATURES, np.concatenate(r.centers), EPS).select("a", "b", F.round("dist", 6).alias("dist"), "pop", F.round("w", 6).alias("w"))


register("affinity_edges", rounds_sql("* FROM edges"))(edges_of)
_BOTH_WAYS = "(SELECT a AS node, b AS other, w FROM edges UNION ALL SELECT b, a, w FROM edges)"


def both_ways(e):
    return e.select(F.col("a").alias("node"), F.col("b").alias("other"), "w").unionByName(e.select(F.col("b").alias("node"), F.col("a").alias("other"), "w"))


register("graph_degree", rounds_sql(f"node, round(sum(w), 5) AS degree, count(*) AS edges FROM {_BOTH_WAYS} GROUP BY 1"))(
    lambda s, d: both_ways(edges_of(s, d)).groupBy("node").agg(F.round(F.sum("w"), 5).alias("degree"), F.count("*").alias("edges"))
)
register("ncut_value", rounds_sql(f"round(sum(cut / nullif(vol, 0)), 5) AS ncut FROM (SELECT node % 3 AS g, sum(w) AS vol, sum(CASE WHEN node % 3 <> other % 3 THEN w ELSE 0 END) AS cut FROM {_BOTH_WAYS} GROUP BY 1)"))(
    lambda s, d: s.createDataFrame([(round(graphcut.ncut_value(E.weight_matrix([tuple(r) for r in edges_of(s, d).collect()], 2 * K)[0], np.arange(2 * K) % 3), 5),)], "ncut double")
)


@register("node_groups")
def _(s, d):
    z, r, _ = two_rounds(s, d)
    c = np.concatenate(r.centers)
    edges = [tuple(x) for x in E.affinity(z, FEATURES, c, EPS).collect()]
    w, same = E.weight_matrix(edges, len(c))
    rows = []
    for method in ("spectral", "recursive", "components"):
        g = E.group_nodes(c, w, same, 3, method)
        rows += [(method, i, int(x), round(graphcut.ncut_value(w, g), 6)) for i, x in enumerate(g)]
    return s.createDataFrame(rows, "method string, cid int, grp int, ncut double")


GIVEN_GROUPS = np.arange(2 * K) % 3


def relabelled(s, d):
    r, sc, long = fixed_long(s, d)
    return E.relabel(long, [0, K, 2 * K], GIVEN_GROUPS), sc


_RELABEL = f"(SELECT item_id, h, (label + h * {K}) % 3 AS grp, dist FROM labels)"
register("relabelled", rounds_sql(f"item_id, h, grp FROM {_RELABEL}"))(lambda s, d: relabelled(s, d)[0].select("item_id", "h", "grp"))
_MAJ = f"(SELECT item_id, arg_max(grp, v * 10 - grp) AS class FROM (SELECT item_id, grp, count(*) AS v FROM {_RELABEL} GROUP BY 1, 2) GROUP BY 1)"
register("consensus_majority", rounds_sql(f"item_id, class FROM {_MAJ}"))(lambda s, d: E.consensus(*relabelled(s, d), how="majority"))
register("consensus_credible", rounds_sql(f"m.item_id, coalesce(r.grp, m.class) AS class FROM {_MAJ} AS m JOIN capture AS c USING (item_id) LEFT JOIN {_RELABEL} AS r ON r.item_id = m.item_id AND r.h = c.captured_at"))(lambda s, d: E.consensus(*relabelled(s, d)))
register("consensus_distance", rounds_sql(f"item_id, grp AS class FROM (SELECT item_id, grp, round(sum(1 / (dist + 1e-6)), 6) AS v FROM {_RELABEL} GROUP BY 1, 2) QUALIFY row_number() OVER (PARTITION BY item_id ORDER BY v DESC, grp) = 1"))(
    lambda s, d: E.consensus(*relabelled(s, d), how="distance_weighted")
)


@register("ensemble_fit")
def ensemble_fit(s, d):
    z = scaled_features(s, d)
    return E.EnsembleModel.fit(z, FEATURES, E.RoundOptions(k=12, eps=EPS, t_max=4, max_iter=4), classes=3).transform(z)


@register("ensemble_model_roundtrip")
def _(s, d):
    from trajkit.sources.shared import shared_dir

    z = scaled_features(s, d)
    m = E.EnsembleModel.fit(z, FEATURES, E.RoundOptions(k=K, eps=EPS, t_max=2, max_iter=2), classes=3)
    path = f"{shared_dir(s)}/model-{uuid.uuid4().hex}"
    m.save(s, path)
    same = m.transform(z).withColumnRenamed("class", "before").join(E.EnsembleModel.load(s, path).transform(z), "item_id")
    return same.agg(F.count("*").alias("items"), F.sum((F.col("before") == F.col("class")).cast("long")).alias("equal"))


# ---- density and spectral baselines ----------------------------------------------------------

TIMES_Z = ["t_init", "t_grow", "t_decay"]
register("dbscan_core_points", f"WITH z AS MATERIALIZED ({Z_PART}) SELECT a.item_id, count(*) AS neighbours, count(*) >= 10 AS core FROM z AS a JOIN z AS b ON {_dist('a', 'b', TIMES_Z)} <= 0.16 GROUP BY 1")(
    lambda s, d: density.neighbour_counts(scaled_features(s, d), TIMES_Z, 0.4).select("item_id", "neighbours", (F.col("neighbours") >= 10).alias("core"))
)
register("dbscan_clusters")(lambda s, d: density.dbscan(scaled_features(s, d), TIMES_Z, 0.4, 10))
register("base_spectral")(lambda s, d: spectral.landmark_spectral(scaled_features(s, d), FEATURES, 3, 200))


# ---- measures ---------------------------------------------------------------------------------

_GIVEN = "CASE WHEN t_peak < 10 THEN 0 WHEN t_peak < 19 THEN 1 ELSE 2 END"
FEAT = Q.features_sql(PART, 28)
CLASSED = f"(SELECT *, {_GIVEN} AS class FROM ({FEAT}))"


def classed(s, d):
    return features_of(s, d).withColumn("class", F.expr(_GIVEN))


register("class_sizes", f"SELECT class, count(*) AS items, round(count(*) / sum(count(*)) OVER (), 9) AS share FROM {CLASSED} GROUP BY 1")(lambda s, d: M.class_sizes(classed(s, d)))
_PROFILE = ", ".join(f"round(avg({c}), 6) AS {c}_mean, round(stddev_samp({c}), 6) AS {c}_sd, " + ", ".join(f"quantile_cont({c}, {p}) AS {c}_q{i}" for i, p in ((1, 0.25), (2, 0.5), (3, 0.75))) for c in ("t_init", "t_grow", "t_decay"))
PROFILE = f"SELECT class, {_PROFILE} FROM {CLASSED} GROUP BY 1"
register("class_time_profile", PROFILE)(lambda s, d: M.time_profile(classed(s, d)))
register("class_gain_hist", " UNION ALL ".join(f"SELECT class, '{c}' AS phase, floor({c} / 0.1 + 1e-9)::INTEGER AS bin, count(*) AS items FROM {CLASSED} GROUP BY 1, 2, 3" for c in ("g_init", "g_grow", "g_decay")))(lambda s, d: M.gain_histogram(classed(s, d)))
register("class_peak_box", " UNION ALL ".join(
    f"SELECT class, '{c}' AS feature, lo, hi, q1, q2, q3, greatest(lo, q1 - 1.5 * (q3 - q1)) AS whisker_lo, least(hi, q3 + 1.5 * (q3 - q1)) AS whisker_hi FROM (SELECT class, min({c})::DOUBLE AS lo, max({c})::DOUBLE AS hi, quantile_cont({c}, 0.25) AS q1, quantile_cont({c}, 0.5) AS q2, quantile_cont({c}, 0.75) AS q3 FROM {CLASSED} GROUP BY 1)"
    for c in PEAKS
))(lambda s, d: M.peak_box(classed(s, d), tuple(PEAKS)))


def anova_sql(cols: list[str], source: str) -> str:
    one = "SELECT '{c}' AS feature, count(*) AS k, sum(n)::BIGINT AS n, sum(s * s / n) AS between_, sum(s) AS s, sum(q) AS q FROM (SELECT class, count(*) AS n, sum({c})::DOUBLE AS s, sum({c}::DOUBLE * {c}) AS q FROM " + source + " GROUP BY class)"
    union = " UNION ALL ".join(one.replace("{c}", c) for c in cols)
    return f"SELECT feature, k - 1 AS df1, n - k AS df2, round(((between_ - s * s / n) / (k - 1)) / nullif((q - between_) / (n - k), 0), 4) AS f, round((between_ - s * s / n) / nullif(q - s * s / n, 0), 6) AS eta2 FROM ({union})"


ANOVA_COLS = ["t_init", "t_grow", "t_decay", *FT.GAINS, "lo_grow", "lo_decay", "md_grow", "md_decay"]
register("anova_f", anova_sql(ANOVA_COLS, CLASSED))(lambda s, d: M.anova(classed(s, d), ANOVA_COLS))


@register("anova_rank", f"SELECT feature, f, row_number() OVER (ORDER BY f DESC, feature)::INTEGER AS rank FROM ({anova_sql(ANOVA_COLS, CLASSED)})")
def _(s, d):
    from pyspark.sql import Window as W

    return M.anova(classed(s, d), ANOVA_COLS).select("feature", "f", F.row_number().over(W.orderBy(F.desc("f"), "feature")).alias("rank"))  # one row a feature


@register("anova_p")
def _(s, d):
    rows = [(r["feature"], r["f"], M.f_tail(r["f"], r["df1"], r["df2"])) for r in M.anova(classed(s, d), ANOVA_COLS).collect()]  # one row a feature
    return s.createDataFrame(rows, "feature string, f double, p double")


_LEVELS = (45, 40, 35, 20)
register("tail_counts", "SELECT count(*) AS items, " + ", ".join(f"count(CASE WHEN total > {x} THEN 1 END) AS over_{x}" for x in _LEVELS) + f", round(count(CASE WHEN total < 20 THEN 1 END) / count(*), 9) AS share_below FROM ({FEAT})")(
    lambda s, d: M.tail_counts(features_of(s, d), _LEVELS)
)


def scheme(s, d, name: str):
    return scheme_of(series_part(s, d), name)


def scheme_sql(name: str) -> str:
    q, col, _ = SCHEMES[name]
    return f"(SELECT item_id, {col} AS class FROM ({RS.text(RULES[q][1], DENSE)}) AS s)"


def crosswalk_sql(a: str, b: str) -> str:
    return f"SELECT *, round(items / sum(items) OVER (PARTITION BY a), 9) AS row_share FROM (SELECT x.class AS a, y.class AS b, count(*) AS items FROM {a} AS x JOIN {b} AS y ON x.item_id = y.item_id GROUP BY 1, 2)"


for _name in SCHEMES:
    register(f"crosswalk_{_name}", crosswalk_sql(CLASSED, scheme_sql(_name)))(lambda s, d, n=_name: M.crosswalk(classed(s, d), scheme(s, d, n)))

_OTHERS = [n for n, (_, _, other) in SCHEMES.items() if other]
register("unclassified_share", " UNION ALL ".join(f"SELECT '{n}' AS scheme, round(avg(CASE WHEN class = '{SCHEMES[n][2]}' THEN 1 ELSE 0 END), 9) AS share FROM {scheme_sql(n)}" for n in _OTHERS))(
    lambda s, d: M.unclassified_share(unioned([x.select("item_id", F.lit(n).alias("scheme"), "class", (F.col("class") == SCHEMES[n][2]).alias("unclassified")) for n, x in schemes_of(s, d, _OTHERS)]))
)


def schemes_of(s, d, names):
    """(name, classes) of schemes on one panel, which is built once for all of them."""
    series = materialised(series_part(s, d))
    return [(n, scheme_of(series, n)) for n in names]


def unioned(frames):
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def agreement_sql(a: str, b: str, cols: str = "ari, nmi, purity") -> str:
    return f"""WITH n AS MATERIALIZED (SELECT x.class AS a, y.class AS b, count(*) AS n FROM {a} AS x JOIN {b} AS y ON x.item_id = y.item_id GROUP BY 1, 2),
      t AS (SELECT sum(n)::DOUBLE AS t FROM n), ra AS (SELECT a, sum(n)::DOUBLE AS r FROM n GROUP BY 1), rb AS (SELECT b, sum(n)::DOUBLE AS r FROM n GROUP BY 1),
      x AS (SELECT sum(n * (n - 1) / 2) AS sn, sum(n / t * ln(n * t / (ra.r * rb.r))) AS mi FROM n JOIN ra ON ra.a = n.a JOIN rb ON rb.b = n.b CROSS JOIN t),
      y AS (SELECT sum(r * (r - 1) / 2) AS sa, sum(-r / t * ln(r / t)) AS ha FROM ra CROSS JOIN t), w AS (SELECT sum(r * (r - 1) / 2) AS sb, sum(-r / t * ln(r / t)) AS hb FROM rb CROSS JOIN t),
      m AS (SELECT sum(top) AS top FROM (SELECT max(n) AS top FROM n GROUP BY a))
      SELECT {cols} FROM (SELECT round((sn - sa * sb / (t * (t - 1) / 2)) / nullif((sa + sb) / 2 - sa * sb / (t * (t - 1) / 2), 0), 6) AS ari, round(mi / nullif((ha + hb) / 2, 0), 6) AS nmi, round(top / t, 6) AS purity FROM x, y, w, m, t)"""


def windowed_class(s, d, w: int):
    return FT.extract_features(panel_of(s, d, "part_quarter"), w).select("item_id", F.expr(f"CASE WHEN t_peak < {w / 3} THEN 0 WHEN t_peak < {2 * w / 3} THEN 1 ELSE 2 END").alias("class"))


def windowed_sql(w: int) -> str:
    return f"(SELECT item_id, CASE WHEN t_peak < {w / 3} THEN 0 WHEN t_peak < {2 * w / 3} THEN 1 ELSE 2 END AS class FROM ({Q.features_sql(PART, w)}))"


register("window_agreement", agreement_sql(windowed_sql(10), windowed_sql(20)))(lambda s, d: M.agreement(windowed_class(s, d, 10), windowed_class(s, d, 20)))
for _m in ("ari", "nmi", "purity"):
    register(_m, agreement_sql(CLASSED, scheme_sql("half_life"), _m))(lambda s, d, m=_m: M.agreement(classed(s, d), scheme(s, d, "half_life")).select(m))


@register("impact_vs_class", f"SELECT class, count(*) AS items, round(avg(total_2), 6) AS total_2, round(avg(total_5), 6) AS total_5, round(avg(total), 6) AS total, round(corr(total_5, total), 6) AS corr_5 FROM {CLASSED} JOIN (SELECT item_id, coalesce(sum(CASE WHEN t < 2 THEN n END), 0) AS total_2, coalesce(sum(CASE WHEN t < 5 THEN n END), 0) AS total_5 FROM ({PART}) GROUP BY 1) USING (item_id) GROUP BY 1")
def _(s, d):
    x = classed(s, d).join(P.window_impact(panel_of(s, d, "part_quarter")), "item_id")
    return x.groupBy("class").agg(F.count("*").alias("items"), *[F.round(F.avg(c), 6).alias(c) for c in ("total_2", "total_5", "total")], F.round(F.corr("total_5", "total"), 6).alias("corr_5"))


register("class_grid", f"SELECT class, rise, decline, CASE rise || '_' || decline WHEN 'early_rapid' THEN 'FLASH' WHEN 'early_slow' THEN 'EARLY_TAIL' WHEN 'delayed_none' THEN 'CLIMBER' WHEN 'delayed_slow' THEN 'LATE_WAVE' ELSE upper(rise || '_' || decline) END AS name FROM (SELECT class, CASE WHEN t_init_mean + t_grow_mean <= 0.4 * 28 THEN 'early' ELSE 'delayed' END AS rise, CASE WHEN t_decay_mean < 0.05 * 28 THEN 'none' WHEN t_decay_mean <= 0.25 * 28 THEN 'rapid' ELSE 'slow' END AS decline FROM ({PROFILE}))")(
    lambda s, d: M.name_classes(M.time_profile(classed(s, d)), 28)
)


@register("silhouette_simplified", kmeans_sql(Z_PART, FEATURES, K, 3, select=f"round(avg((o - w) / nullif(greatest(o, w), 0)), 6) AS silhouette FROM (SELECT item_id, sqrt(min(d2)) AS w, sqrt(max(CASE WHEN r = 2 THEN d2 END)) AS o FROM (SELECT p.item_id, round({_dist('p', 'c', FEATURES)}, 9) AS d2, row_number() OVER (PARTITION BY p.item_id ORDER BY round({_dist('p', 'c', FEATURES)}, 9)) AS r FROM z AS p CROSS JOIN rc3 AS c) GROUP BY 1)"))
def _(s, d):
    z = scaled_features(s, d)
    c = L.lloyd(z, FEATURES, K, L.seeds(z, FEATURES, K, SEED), 3, tol=-1.0)
    ds = F.array_sort(F.array(*[F.round(L.sq_dist(FEATURES, x), L.DIGITS) for x in c]))
    return M.simplified_silhouette(z.select(ds.alias("ds")), F.sqrt(F.col("ds")[0]), F.sqrt(F.col("ds")[1]))


for _kind in ("supp", "user", "part"):
    register(f"planted_{_kind}", PL.planted_sql(_kind))(lambda s, d, k=_kind: PL.planted_panel(s, d, k)[0])
register("planted_imbalanced", PL.planted_sql("supp", True))(lambda s, d: PL.planted_panel(s, d, "supp", True)[0])
