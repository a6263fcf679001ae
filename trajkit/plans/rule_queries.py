"""Queries of the rule- and model-based schemes: (function on arrays, SQL on long rows)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame

from trajkit.operators import panel as P
from trajkit.operators import rules as R
from trajkit.plans import rule_sql as RS
from trajkit.plans import sqltext as Q
from trajkit.plans.base_queries import PART, panel_of, register

W = 28
DENSE = Q.dense_sql(PART, W)
SCALE = 0.1  # the given panels have totals of tens where the thresholds speak of hundreds
HOT_FIRST = ("hot", "sleeping", "discovery")
#: name: (function of series and window, SQL for the window ``W``)
RULES: dict[str, tuple[Callable[[DataFrame, int], DataFrame], str]] = {
    "rule_delayed": (lambda x, w: R.delayed_recognition(x, w), RS.delayed_recognition(W)),
    "rule_delayed_unscaled": (lambda x, w: R.delayed_recognition(x, w, w_ref=None), RS.delayed_recognition(W, w_ref=None)),
    "rule_rise_decline": (lambda x, w: R.rise_decline(x, w), RS.rise_decline(W)),
    "rule_rise_decline_unscaled": (lambda x, w: R.rise_decline(x, w, scaled=False), RS.rise_decline(W, scaled=False)),
    "rule_age_ratio": (lambda x, w: R.age_ratio(x, w, SCALE), RS.age_ratio(W, SCALE)),
    "rule_age_ratio_printed": (lambda x, w: R.age_ratio(x, w), RS.age_ratio(W)),
    "rule_age_ratio_hot_first": (lambda x, w: R.age_ratio(x, w, SCALE, HOT_FIRST), RS.age_ratio(W, SCALE, HOT_FIRST)),
    "rule_half_life": (lambda x, w: R.half_life(x), RS.half_life()),
    "rule_half_life_own": (lambda x, w: R.half_life(x, "own"), RS.half_life("own")),
    "rule_peak_shape": (lambda x, w: R.peak_shape(x, w), RS.peak_shape(W)),
    "rule_peak_shape_unscaled": (lambda x, w: R.peak_shape(x, w, w_ref=None), RS.peak_shape(W, w_ref=None)),
    "model_diffusion_moments": (lambda x, w: R.diffusion_moments(x), RS.diffusion_moments()),
    "model_diffusion_pq": (lambda x, w: R.diffusion(x), RS.diffusion()),
    "beauty_coefficient": (lambda x, w: R.beauty(x), RS.beauty()),
    "awakening_time": (lambda x, w: R.awakening(x), RS.awakening()),
    "rule_angle": (lambda x, w: R.angle(x), RS.angle()),
    "rule_second_act": (lambda x, w: R.second_act(x, w), RS.second_act(W)),
    "rule_revival": (lambda x, w: R.revival(x, w), RS.revival(W)),
    "rule_half_peak": (lambda x, w: R.half_peak(x, w), RS.half_peak(W)),
    "rule_sleepers": (lambda x, w: R.sleepers(x, w), RS.sleepers(W)),
    "poly_fit_r2": (lambda x, w: R.poly_fit(x, w), RS.poly_fit(W)),
    "rule_transient": (lambda x, w: R.transient_sticky(x, w), RS.transient_sticky(W)),
    "spread_exponent": (lambda x, w: R.spread_exponent(x, w), RS.spread_exponent()),
}
#: Schemes that give each item one class: query, column, the class that means "none of them".
SCHEMES = {
    "delayed": ("rule_delayed", "class", "other"),
    "age_ratio": ("rule_age_ratio", "class", "other"),
    "half_life": ("rule_half_life", "class", None),
    "peak_shape": ("rule_peak_shape", "class", "other"),
    "diffusion": ("model_diffusion_pq", "class", "none"),
    "angle": ("rule_angle", "class", "between"),
    "second_act": ("rule_second_act", "class", "other"),
    "half_peak": ("rule_half_peak", "class", None),
    "sleepers": ("rule_sleepers", "class", "other"),
    "transient": ("rule_transient", "class", "other"),
    "rise": ("rule_rise_decline", "rise", None),
    "decline": ("rule_rise_decline", "decline", None),
}


def series_part(s, d, w: int = W) -> DataFrame:
    return P.densify(panel_of(s, d, "part_quarter"), w)


def scheme_of(series: DataFrame, name: str, w: int = W) -> DataFrame:
    """item_id, class of one scheme on the given series."""
    query, col, _ = SCHEMES[name]
    return RULES[query][0](series, w).selectExpr("item_id", f"{col} AS class")


for _name, (_rule, _text) in RULES.items():
    register(_name, RS.text(_text, DENSE))(lambda s, d, f=_rule: f(series_part(s, d), W))
