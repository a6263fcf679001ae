"""Queries on series, eligibility and features, each with its SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trajkit.operators import features as FT
from trajkit.operators import panel as P
from trajkit.operators import scaling
from trajkit.operators.features import FEATURES, FeatureOptions
from trajkit.plans import sqltext as Q
from trajkit.sources.shared import materialised
from trajkit.sources.tables import read_table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def register(name: str, sql: str | None = None):
    def put(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


def panel_of(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    if kind == "user_day":
        return P.build_panel(read_table(spark, sf_dir, "events", "user_id", "ts"), "user_id", P.day_index(F.col("ts")))
    if kind == "part_quarter":
        return P.build_panel(read_table(spark, sf_dir, "lineitem", "l_partkey", "l_shipdate"), "l_partkey", P.quarter_index(F.col("l_shipdate")))
    if kind == "supp_month":
        return P.build_panel(read_table(spark, sf_dir, "lineitem", "l_suppkey", "l_shipdate"), "l_suppkey", P.month_index(F.col("l_shipdate")))
    if kind == "cust_half":
        return P.build_panel_from_birth(read_table(spark, sf_dir, "orders", "o_custkey", "o_orderdate"), "o_custkey", "o_orderdate")
    return P.build_panel(read_table(spark, sf_dir, "conversations", "conv_id", "turn", "text"), "conv_id", F.col("turn"), F.length("text"))


for _kind, _sql in Q.PANELS.items():
    register(f"panel_{_kind}", _sql)(lambda s, d, k=_kind: panel_of(s, d, k))

PART = Q.PART_QUARTER
register("panel_dense_long", Q.dense_sql(PART, 28))(lambda s, d: P.densify_long(panel_of(s, d, "part_quarter"), 28))
register("panel_dense_array", f"SELECT item_id, list(n ORDER BY t) AS series FROM ({Q.dense_sql(PART, 28)}) GROUP BY 1")(lambda s, d: P.densify(panel_of(s, d, "part_quarter"), 28))
for _w in (10, 20, 30):
    register(f"panel_window_{_w}", f"SELECT * FROM ({Q.USER_DAY}) WHERE t >= 0 AND t < {_w}")(lambda s, d, w=_w: P.clip_window(panel_of(s, d, "user_day"), w))


@register("cohort_first_order_year", "SELECT o_custkey AS item_id, year(min(o_orderdate))::INTEGER AS birth FROM orders GROUP BY 1 HAVING year(min(o_orderdate)) = 1996")
def _(s, d):
    born = read_table(s, d, "orders", "o_custkey", "o_orderdate").groupBy(F.col("o_custkey").alias("item_id")).agg(F.year(F.min("o_orderdate")).alias("birth"))
    return P.cohort(born, F.col("birth"), 1996)


_TOT = f"SELECT item_id, sum(n)::BIGINT AS total, sum(n) / 28 AS rate FROM ({PART}) WHERE t >= 0 AND t < 28 GROUP BY 1"
register("totals_and_rate", _TOT)(lambda s, d: P.totals(panel_of(s, d, "part_quarter"), 28))
register("success_ratio_own", f"SELECT *, total / greatest(rate, 5.0) AS ratio FROM ({_TOT})")(lambda s, d: P.success_ratio(P.totals(panel_of(s, d, "part_quarter"), 28)))
register("success_ratio_cohort", f"SELECT item_id, total, rate, round(avg(total) OVER (), 9) AS group_mean, round(total / greatest(avg(total) OVER (), 5.0), 9) AS ratio FROM ({_TOT})")(
    lambda s, d: P.success_ratio(P.totals(panel_of(s, d, "part_quarter"), 28), mu="cohort").withColumns({c: F.round(c, 9) for c in ("group_mean", "ratio")})
)


@register("success_ratio_field", f"SELECT item_id, total, p_type AS field, round(total / greatest(avg(total) OVER (PARTITION BY p_type), 5.0), 9) AS ratio FROM ({_TOT}) JOIN part ON p_partkey = item_id")
def _(s, d):
    field = read_table(s, d, "part", F.col("p_partkey").alias("item_id"), F.col("p_type").alias("field"))
    tot = P.totals(panel_of(s, d, "part_quarter"), 28).join(field, "item_id")
    return P.success_ratio(tot, mu="field", field="field").select("item_id", "total", "field", F.round("ratio", 9).alias("ratio"))


register("eligible_items", f"SELECT item_id, total FROM (SELECT item_id, sum(n)::BIGINT AS total FROM ({Q.CUST_HALF}) WHERE t >= 0 AND t < 10 GROUP BY 1) WHERE total / greatest(total / 10, 5) >= 1")(
    lambda s, d: P.eligible(panel_of(s, d, "cust_half"), 10)
)


@register("panel_without_self", """SELECT l_partkey AS item_id, ((year(l_shipdate) - 1995) * 4 + quarter(l_shipdate) - 1)::INTEGER AS t, count(*)::BIGINT AS n
  FROM lineitem JOIN supplier ON s_suppkey = l_suppkey JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey WHERE c_nationkey <> s_nationkey GROUP BY 1, 2""")
def without_self(s, d):
    log = (
        read_table(s, d, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_shipdate")
        .join(read_table(s, d, "orders", F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey")
        .join(read_table(s, d, "customer", F.col("c_custkey").alias("o_custkey"), "c_nationkey"), "o_custkey")
        .join(read_table(s, d, "supplier", F.col("s_suppkey").alias("l_suppkey"), "s_nationkey"), "l_suppkey")
    )
    return P.build_panel(P.drop_self_mentions(log, F.col("c_nationkey"), F.col("s_nationkey")), "l_partkey", P.quarter_index(F.col("l_shipdate")))


_IMPACT = ", ".join(f"coalesce(sum(CASE WHEN t < {k} THEN n END), 0)::BIGINT AS total_{k}, coalesce(sum(CASE WHEN t < {k} THEN n END), 0) / {k} AS mean_{k}" for k in (2, 5))
register("window_impact", f"SELECT item_id, {_IMPACT} FROM ({PART}) GROUP BY 1")(lambda s, d: P.window_impact(panel_of(s, d, "part_quarter")))
register("cumulative_series", f"SELECT item_id, t, n, sum(n) OVER (PARTITION BY item_id ORDER BY t)::BIGINT AS cum, sum(n) OVER (PARTITION BY item_id ORDER BY t) / sum(n) OVER (PARTITION BY item_id) AS share FROM ({PART})")(
    lambda s, d: P.cumulate(panel_of(s, d, "part_quarter"))
)


def features_of(s: SparkSession, d: str, kind: str = "part_quarter", w: int = 28, **options) -> DataFrame:
    return FT.extract_features(panel_of(s, d, kind), w, FeatureOptions(**options))


def _feature(name: str, cols: str, kind: str = "part_quarter", w: int = 28, **options) -> None:
    sql = f"SELECT item_id, {cols} FROM ({Q.features_sql(Q.PANELS[kind], w, FeatureOptions(**options))})"
    register(name, sql)(lambda s, d: features_of(s, d, kind, w, **options).select("item_id", *cols.split(", ")))


for _name, _cols, _opt in (
    ("feat_t_init", "t_init", {}), ("feat_t_init_annual", "t_init", {"init_rule": "annual_vs_gm"}), ("feat_t_init_logtime", "t_init", {"init_rule": "log_time_mean"}),
    ("feat_t_init_sqrt", "t_init", {"init_rule": "sqrt_total"}), ("feat_t_init_log1p", "t_init", {"gm_zero": "log1p"}),
    ("feat_t_grow", "t_grow, t_peak", {}), ("feat_t_grow_last_peak", "t_grow, t_peak", {"peak_tie": "last"}),
    ("feat_t_decay", "t_decay, t_last", {}), ("feat_t_decay_window_end", "t_decay, t_last", {"end_rule": "window_end"}),
    ("feat_gain_prefix", "g_init, g_grow, g_decay", {}), ("feat_gain_phase", "g_init, g_grow, g_decay", {"gain_mode": "phase"}),
    ("feat_peaks", ", ".join(FT.PEAKS), {}), ("feat_peaks_geo", ", ".join(FT.PEAKS), {"mu": "geo"}), ("feat_peaks_gt", ", ".join(FT.PEAKS), {"cmp": "gt"}),
    ("feat_peaks_samp", ", ".join(FT.PEAKS), {"sd": "samp"}), ("feat_peaks_exclusive", ", ".join(FT.PEAKS), {"band": "exclusive"}),
    ("feat_peaks_after_init", ", ".join(FT.PEAKS), {"growth_start": "after_init"}), ("feat_peaks_flat_literal", ", ".join(FT.PEAKS), {"flat": "literal"}),
):
    _feature(_name, _cols, **_opt)

_ALL = ", ".join(["total", "t_init", "t_peak", "t_last", *FEATURES[1:]])
for _name, _kind, _w in (("features_long", "user_day", 30), ("features_mid", "user_day", 20), ("features_short", "user_day", 10), ("features_part_long", "part_quarter", 28), ("features_part_mid", "part_quarter", 20), ("features_part_short", "part_quarter", 10), ("features_supp", "supp_month", 83), ("features_cust", "cust_half", 10)):
    _feature(_name, _ALL, _kind, _w)

register("features_array", Q.features_sql(PART, 28))(lambda s, d: FT.features_of_series(P.densify(panel_of(s, d, "part_quarter"), 28), 28))


def scaled_features(s: SparkSession, d: str, kind: str = "part_quarter", w: int = 28, least: int = 5, **options) -> DataFrame:
    """Eligible items' features, z-scored: item_id and one column a feature."""
    # Later passes are many and read this table of a few numbers an item, not the log.
    f = materialised(FT.extract_features(P.eligible_panel(panel_of(s, d, kind), w, least), w, FeatureOptions(**options)))
    return scaling.scaled(f, scaling.fit_zscore(f, FEATURES))


Z_PART = Q.z_sql(Q.features_sql(PART, 28, least=5))
register("features_z", Z_PART)(scaled_features)


@register("features_z_robust", "SELECT item_id, " + ", ".join(f"CASE WHEN s_{c} > 0 THEN round(({c} - m_{c}) / s_{c}, 9) ELSE 0.0::DOUBLE END AS {c}" for c in FEATURES) + f" FROM ({Q.features_sql(PART, 28)}), (SELECT " + ", ".join(f"quantile_cont({c}, 0.5) AS m_{c}, quantile_cont({c}, 0.75) - quantile_cont({c}, 0.25) AS s_{c}" for c in FEATURES) + f" FROM ({Q.features_sql(PART, 28)}))")
def _(s, d):
    f = features_of(s, d)
    return scaling.scaled(f, scaling.fit_robust(f, FEATURES))
