"""SQL for DuckDB that states the batch operators independently of the DataFrame code."""

from __future__ import annotations

from trajkit.operators.features import FEATURES, FeatureOptions

USER_DAY = "SELECT user_id AS item_id, date_diff('day', DATE '2024-01-01', ts::DATE)::INTEGER AS t, count(*)::BIGINT AS n FROM events GROUP BY 1, 2"
PART_QUARTER = "SELECT l_partkey AS item_id, ((year(l_shipdate) - 1995) * 4 + quarter(l_shipdate) - 1)::INTEGER AS t, count(*)::BIGINT AS n FROM lineitem GROUP BY 1, 2"
SUPP_MONTH = "SELECT l_suppkey AS item_id, ((year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1)::INTEGER AS t, count(*)::BIGINT AS n FROM lineitem GROUP BY 1, 2"
CUST_HALF = """SELECT o_custkey AS item_id, floor(((year(o_orderdate) - year(b)) * 12 + month(o_orderdate) - month(b) - CASE WHEN day(o_orderdate) < day(b) THEN 1 ELSE 0 END) / 6)::INTEGER AS t, count(*)::BIGINT AS n
  FROM (SELECT o_custkey, o_orderdate, min(o_orderdate) OVER (PARTITION BY o_custkey) AS b FROM orders) GROUP BY 1, 2"""
CONV_TURN = "SELECT conv_id AS item_id, turn::INTEGER AS t, sum(length(text))::BIGINT AS n FROM conversations GROUP BY 1, 2"
PANELS = {"user_day": USER_DAY, "part_quarter": PART_QUARTER, "supp_month": SUPP_MONTH, "cust_half": CUST_HALF, "conv_turn": CONV_TURN}
WIDTH = {"user_day": 30, "part_quarter": 28, "supp_month": 83, "cust_half": 10, "conv_turn": 10}


def timed_sql(panel: str, w: int, o: FeatureOptions = FeatureOptions()) -> str:
    gm = "avg(ln(n)) OVER i" if o.gm_zero == "positive_only" else f"ln(exp(sum(ln(1 + n)) OVER i / {w}) - 1 + 1e-300)"
    peak = "arg_max(t, n * 1000 - t) OVER i" if o.peak_tie == "first" else "arg_max(t, n * 1000 + t) OVER i"
    last = "max(t) OVER i" if o.end_rule == "last_mention" else f"{w - 1}"
    hit = {"annual_vs_gm": "ln(n) >= gm - 1e-9", "sqrt_total": "cum * cum >= c"}.get(o.init_rule, "ln(cum) >= gm - 1e-9")
    init = "floor(exp(sum(n * ln(t + 1)) OVER i / c) - 1 + 1e-9)::INTEGER" if o.init_rule == "log_time_mean" else f"min(CASE WHEN {hit} THEN t END) OVER i"
    return f"""SELECT *, {init} AS t_init FROM (
      SELECT item_id, t, n, sum(n) OVER (PARTITION BY item_id ORDER BY t)::BIGINT AS cum, sum(n) OVER i::BIGINT AS c, sum(n * n) OVER i::BIGINT AS q,
             {gm} AS gm, {peak} AS t_peak, {last} AS t_last
      FROM ({panel}) WHERE t >= 0 AND t < {w} AND n > 0 WINDOW i AS (PARTITION BY item_id)) WINDOW i AS (PARTITION BY item_id)"""


def _above(o: FeatureOptions, w: int, j: int) -> str:
    var = f"({w} * q - c * c)"
    if o.mu == "geo":
        sd = f"sqrt({var}::DOUBLE) / {float(w)}" if o.sd == "pop" else f"sqrt({var}::DOUBLE / {w * max(w - 1, 1)})"
        hit = f"n >= exp(gm) + {j} * {sd} - 1e-9" if o.cmp == "ge" else f"n > exp(gm) + {j} * {sd} + 1e-9"
    else:
        dev, a, b = f"({w} * n - c)", (f" * {w - 1}" if o.sd == "samp" else ""), (f" * {w}" if o.sd == "samp" else "")
        op = ">=" if o.cmp == "ge" else ">"
        hit = f"{dev} {op} 0 AND {dev} * {dev}{a} {op} {j * j} * {var}{b}"
    return f"({hit} AND {var} > 0)" if o.flat == "zero_peaks" else f"({hit})"


def features_sql(panel: str, w: int, o: FeatureOptions = FeatureOptions(), least: int = 0) -> str:
    if o.gain_mode == "prefix":
        conds = ["t <= t_init", "t <= t_peak - t_init", "t <= t_last - t_peak"]
    else:
        conds = ["t <= t_init", "t > t_init AND t <= t_peak", "t > greatest(t_init, t_peak) AND t <= t_last"]
    gains = ", ".join(f"coalesce(sum(CASE WHEN {k} THEN n END), 0) / any_value(c) AS {g}" for k, g in zip(conds, ("g_init", "g_grow", "g_decay")))
    hit = {j: _above(o, w, j) for j in (1, 2, 3)}
    if o.band == "exclusive":
        hit = {3: hit[3], 2: f"{hit[2]} AND NOT {hit[3]}", 1: f"{hit[1]} AND NOT {hit[2]}"}
    start = "t >= 0" if o.growth_start == "birth" else "t > t_init"
    peaks = ", ".join(f"count(CASE WHEN {hit[j]} AND {start} AND t <= t_peak THEN 1 END) AS {m}_grow, count(CASE WHEN {hit[j]} AND t > t_peak THEN 1 END) AS {m}_decay" for m, j in (("hi", 3), ("md", 2), ("lo", 1)))
    having = f" HAVING sum(n) >= {least}" if least else ""
    return f"""SELECT item_id, any_value(c) AS total, any_value(t_init) AS t_init, any_value(t_peak) AS t_peak, any_value(t_last) AS t_last,
      any_value(t_peak - t_init) AS t_grow, any_value(t_last - t_peak) AS t_decay, {gains}, {peaks} FROM ({timed_sql(panel, w, o)}) GROUP BY item_id{having}"""


def dense_sql(panel: str, w: int) -> str:
    return f"""SELECT i.item_id, g.t::INTEGER AS t, coalesce(p.n, 0)::BIGINT AS n FROM (SELECT DISTINCT item_id FROM ({panel}) WHERE t >= 0 AND t < {w}) AS i
      CROSS JOIN (SELECT unnest(range({w})) AS t) AS g LEFT JOIN ({panel}) AS p ON p.item_id = i.item_id AND p.t = g.t"""


def z_sql(features: str, cols: list[str] = FEATURES, keep: str = "item_id") -> str:
    stats = ", ".join(f"round(avg({c}), 9) AS m_{c}, round(stddev_pop({c}), 9) AS s_{c}" for c in cols)
    z = ", ".join(f"CASE WHEN s_{c} > 0 THEN round(({c} - m_{c}) / s_{c}, 9) ELSE 0.0::DOUBLE END AS {c}" for c in cols)
    return f"SELECT {keep}, {z} FROM ({features}) AS f, (SELECT {stats} FROM ({features}))"
