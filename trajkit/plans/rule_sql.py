"""The schemes once more, as SQL statements for another engine: they state each definition over long
rows with windows and joins, where ``operators.rules`` works on one array an item, and so check it.

Every statement reads ``{dense}`` (item_id, t, n with zeros).
"""

from __future__ import annotations

from trajkit.operators.rules import poly_basis

_TOTALS = """SELECT item_id, sum(n) AS c, min(CASE WHEN n = top THEN t END) AS t_peak, max(n) AS n_peak, max(CASE WHEN n > 0 THEN t END) AS t_last
      FROM (SELECT item_id, t, n, max(n) OVER (PARTITION BY item_id) AS top FROM {dense}) AS y GROUP BY item_id"""
_CUM = "SELECT item_id, t, n, sum(n) OVER (PARTITION BY item_id ORDER BY t) AS cum, sum(n) OVER (PARTITION BY item_id) AS c FROM {dense}"


def delayed_recognition(w: int, total_min: int = 30, early_max: float = 0.25, w_ref: int | None = 25, years: int = 10) -> str:
    """Much mentioned in all, with few mentions in the first years."""
    k = max(1, round(years * w / (w_ref or w)))
    return f"""SELECT item_id, early, c, CASE WHEN c >= {total_min} AND early <= {early_max} * c THEN 'delayed' ELSE 'other' END AS class
      FROM (SELECT item_id, CAST(sum(CASE WHEN t < {k} THEN n ELSE 0 END) AS BIGINT) AS early, CAST(sum(n) AS BIGINT) AS c FROM {{dense}} GROUP BY item_id) AS x"""


def rise_decline(w: int, w_ref: int = 16, scaled: bool = True) -> str:
    """Share gained in the first 3 of 16 periods against the share in periods 7 to 12: a 3 x 3 grid."""
    f = w / w_ref if scaled else 1.0
    a, lo, hi = max(1, round(3 * f)), round(6 * f), round(12 * f)
    return f"""SELECT item_id, rise_share, late_share,
        CASE WHEN rise_share > 0.30 THEN 'early' WHEN rise_share >= 0.15 THEN 'medium' ELSE 'delayed' END AS rise,
        CASE WHEN late_share < 0.30 THEN 'rapid' WHEN late_share <= 0.50 THEN 'slow' ELSE 'none' END AS decline
      FROM (SELECT item_id, sum(CASE WHEN t < {a} THEN n ELSE 0 END) / CAST(sum(n) AS DOUBLE) AS rise_share,
                   sum(CASE WHEN t >= {lo} AND t < {hi} THEN n ELSE 0 END) / CAST(sum(n) AS DOUBLE) AS late_share FROM {{dense}} GROUP BY item_id) AS x"""


def age_ratio(w: int, scale: float = 1.0, order: tuple[str, ...] = ("sleeping", "discovery", "hot")) -> str:
    tests = {"sleeping": f"c > {250 * scale} AND r > 0.7", "discovery": f"c > {500 * scale} AND r < 0.4", "hot": f"c > {350 * scale} AND r > 2.0 / 3"}
    cases = " ".join(f"WHEN {tests[x]} THEN '{x}'" for x in order)
    return f"""SELECT item_id, c, r, CASE {cases} ELSE 'other' END AS class
      FROM (SELECT item_id, CAST(sum(n) AS BIGINT) AS c, round(sum(n * t) / CAST(sum(n) AS DOUBLE) / {w - 1}, 9) AS r FROM {{dense}} GROUP BY item_id) AS x"""


def half_life(mode: str = "cohort") -> str:
    """Periods to a quarter, half and three quarters of the total; against the cohort's quartiles of
    the half-life, or against the item's own spread."""
    times = f"""SELECT item_id, min(CASE WHEN 4 * cum >= c THEN t END) AS t25, min(CASE WHEN 2 * cum >= c THEN t END) AS t50, min(CASE WHEN 4 * cum >= 3 * c THEN t END) AS t75 FROM ({_CUM}) AS x GROUP BY item_id"""
    if mode == "own":
        return f"SELECT item_id, t25, t50, t75, CASE WHEN t50 - t25 > t75 - t50 THEN 'delayed' WHEN t50 - t25 < t75 - t50 THEN 'flash' ELSE 'normal' END AS class FROM ({times}) AS y"
    q = f"SELECT percentile_cont(0.25) WITHIN GROUP (ORDER BY t50) AS p25, percentile_cont(0.75) WITHIN GROUP (ORDER BY t50) AS p75 FROM ({times}) AS z"
    return f"SELECT item_id, t25, t50, t75, CASE WHEN t50 < p25 THEN 'flash' WHEN t50 > p75 THEN 'delayed' ELSE 'normal' END AS class FROM ({times}) AS y CROSS JOIN ({q}) AS q"


def peak_shape(w: int, frac: float = 0.75, early: int = 5, w_ref: int | None = 20, decline: float = 0.5, few: float = 0.5) -> str:
    k = max(1, round(early * w / (w_ref or w)))
    near = "SELECT item_id, t, n, lag(n) OVER i AS before, lead(n) OVER i AS after, max(n) OVER (PARTITION BY item_id) AS m FROM {dense} WINDOW i AS (PARTITION BY item_id ORDER BY t)"
    marked = f"SELECT *, n > coalesce(before, -1) AND n >= coalesce(after, -1) AND n >= {frac} * m AS top FROM ({near}) AS a"
    firsts = f"SELECT *, min(CASE WHEN top THEN t END) OVER (PARTITION BY item_id) AS first_peak FROM ({marked}) AS b"
    return f"""SELECT item_id, peaks, first_peak, CASE
          WHEN ups = {w - 1} THEN 'monotone_up' WHEN downs = {w - 2} AND first_peak <= 1 THEN 'monotone_down' WHEN peaks > 1 THEN 'several'
          WHEN peaks = 1 AND first_peak <= {k} AND tail <= {decline} * m THEN 'initial'
          WHEN peaks = 1 AND first_peak > {k} AND first_peak < {w - 1} AND head <= {few} * m THEN 'late' ELSE 'other' END AS class
      FROM (SELECT item_id, CAST(sum(CASE WHEN top THEN 1 ELSE 0 END) AS BIGINT) AS peaks, first_peak, max(n) AS m, avg(CASE WHEN t > first_peak THEN n END) AS tail, avg(CASE WHEN t < {k} THEN n END) AS head,
                   sum(CASE WHEN n >= before THEN 1 ELSE 0 END) AS ups, sum(CASE WHEN t > 1 AND n <= before THEN 1 ELSE 0 END) AS downs
            FROM ({firsts}) AS c GROUP BY item_id, first_peak) AS x"""


_MOMENTS = """SELECT item_id, CAST(count(*) AS DOUBLE) AS s0, CAST(sum(p) AS DOUBLE) AS s1, sum(CAST(p AS DOUBLE) * p) AS s2, sum(CAST(p AS DOUBLE) * p * p) AS s3, sum(CAST(p AS DOUBLE) * p * p * p) AS s4,
        CAST(sum(n) AS DOUBLE) AS y0, sum(CAST(n AS DOUBLE) * p) AS y1, sum(CAST(n AS DOUBLE) * p * p) AS y2
      FROM (SELECT item_id, t, n, coalesce(sum(n) OVER (PARTITION BY item_id ORDER BY t ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS p FROM {dense}) AS x GROUP BY item_id"""


def diffusion_moments() -> str:
    """Sums that the regression of a period's count on the total before it needs."""
    return _MOMENTS


def diffusion() -> str:
    """n = a + b N + c N^2 by the normal equations, then the diffusion model's market size and its
    innovation and imitation coefficients; null where the fit has no such solution."""
    det = "s0 * (s2 * s4 - s3 * s3) - s1 * (s1 * s4 - s2 * s3) + s2 * (s1 * s3 - s2 * s2)"
    a = "(y0 * (s2 * s4 - s3 * s3) - s1 * (y1 * s4 - s3 * y2) + s2 * (y1 * s3 - s2 * y2)) / nullif(d, 0)"
    b = "(s0 * (y1 * s4 - y2 * s3) - y0 * (s1 * s4 - s2 * s3) + s2 * (s1 * y2 - s2 * y1)) / nullif(d, 0)"
    c = "(s0 * (s2 * y2 - s3 * y1) - s1 * (s1 * y2 - s2 * y1) + y0 * (s1 * s3 - s2 * s2)) / nullif(d, 0)"
    fit = f"SELECT item_id, {a} AS a, {b} AS b, {c} AS c FROM (SELECT *, {det} AS d FROM ({_MOMENTS}) AS m) AS n"
    m = "CASE WHEN c < 0 AND b * b - 4 * a * c >= 0 THEN (-b - sqrt(greatest(b * b - 4 * a * c, 0.0))) / (2 * c) END"
    pq = f"SELECT item_id, a, m, CASE WHEN m > 0 THEN a / m END AS p, CASE WHEN m > 0 THEN -c * m END AS q FROM (SELECT *, {m} AS m FROM ({fit}) AS f) AS g"
    mid = "SELECT percentile_cont(0.5) WITHIN GROUP (ORDER BY p) AS mp, percentile_cont(0.5) WITHIN GROUP (ORDER BY q) AS mq FROM (" + pq + ") AS h"
    cls = "CASE WHEN p IS NULL THEN 'none' ELSE concat(CASE WHEN p > mp THEN 'large_p' ELSE 'small_p' END, '_', CASE WHEN q > mq THEN 'large_q' ELSE 'small_q' END) END"
    return f"SELECT item_id, round(m, 4) AS m, round(p, 6) AS p, round(q, 6) AS q, {cls} AS class FROM ({pq}) AS k CROSS JOIN ({mid}) AS mid"


_LINE = f"""SELECT d.item_id, d.t, d.n, x.t_peak, x.n_peak, f.n0 FROM {{dense}} AS d JOIN ({_TOTALS}) AS x ON x.item_id = d.item_id
      JOIN (SELECT item_id, n AS n0 FROM {{dense}} WHERE t = 0) AS f ON f.item_id = d.item_id WHERE d.t <= x.t_peak"""


def beauty() -> str:
    """Sum of the gaps between the line from birth to peak and the series, over the series."""
    return f"""SELECT item_id, round(sum(CASE WHEN t_peak = 0 THEN 0.0 ELSE ((n_peak - n0) / CAST(t_peak AS DOUBLE) * t + n0 - n) / greatest(1, n) END), 9) AS beauty FROM ({_LINE}) AS l GROUP BY item_id"""


def awakening() -> str:
    """The period farthest from that line; the first of equals."""
    dist = "round(abs((n_peak - n0) * t - t_peak * n + t_peak * n0) / sqrt(CAST((n_peak - n0) * (n_peak - n0) + t_peak * t_peak AS DOUBLE) + 1e-12), 6)"
    return f"SELECT item_id, min(t) AS t_awake, distance FROM (SELECT *, max(d) OVER (PARTITION BY item_id) AS distance FROM (SELECT *, {dist} AS d FROM ({_LINE}) AS l) AS m) AS k WHERE d = distance GROUP BY item_id, distance"


def angle(hi: float = 60, lo: float = 30, x_scale: float = 1.0, y_scale: float = 1.0) -> str:
    """Angle of the line from birth to peak above the zero line."""
    deg = f"round(degrees(atan2(n_peak / {y_scale}, greatest(t_peak, 0.5) / {x_scale})), 6)"
    return f"SELECT item_id, angle, CASE WHEN angle > {hi} THEN 'smart' WHEN angle < {lo} THEN 'sleeping' ELSE 'between' END AS class FROM (SELECT item_id, {deg} AS angle FROM ({_TOTALS}) AS x) AS y"


def second_act(w: int, fall: float = 0.5, again: float = 0.75, sleep: float = 0.25) -> str:
    """After the first high period, a fall to ``fall`` of it and a later return to ``again`` of it;
    sleepers have few mentions in the first third."""
    base = f"""SELECT x.item_id, x.c, x.n_peak, min(CASE WHEN d.n >= {again} * x.n_peak THEN d.t END) AS first_high, sum(CASE WHEN d.t < {w // 3} THEN d.n ELSE 0 END) AS early
      FROM {{dense}} AS d JOIN ({_TOTALS}) AS x ON x.item_id = d.item_id GROUP BY x.item_id, x.c, x.n_peak"""
    low = f"SELECT b.item_id, min(d.t) AS low FROM {{dense}} AS d JOIN ({base}) AS b ON b.item_id = d.item_id WHERE d.t > b.first_high AND d.n <= {fall} * b.n_peak GROUP BY b.item_id"
    back = f"""SELECT b.item_id, min(d.t) AS back FROM {{dense}} AS d JOIN ({base}) AS b ON b.item_id = d.item_id JOIN ({low}) AS l ON l.item_id = d.item_id
      WHERE d.t > l.low AND d.n >= {again} * b.n_peak GROUP BY b.item_id"""
    return f"""SELECT b.item_id, b.first_high, l.low, k.back, CASE WHEN k.back IS NULL AND b.early <= {sleep} * b.c THEN 'single_peak_sleeper'
        WHEN k.back IS NOT NULL AND b.early <= {sleep} * b.c THEN 'second_act_sleeper' WHEN k.back IS NOT NULL THEN 'second_act' ELSE 'other' END AS class
      FROM ({base}) AS b LEFT JOIN ({low}) AS l ON l.item_id = b.item_id LEFT JOIN ({back}) AS k ON k.item_id = b.item_id"""


def revival(w: int, **options) -> str:
    """Whether a high period comes again after a fall."""
    return f"SELECT item_id, back IS NOT NULL AS revived, back - low AS quiet FROM ({second_act(w, **options)}) AS r"


def half_peak(w: int) -> str:
    """Peak of the series over each period's mean: first half hot, second half delayed."""
    return f"""SELECT item_id, t_norm_peak, CASE WHEN t_norm_peak < {w / 2} THEN 'hot' ELSE 'delayed' END AS class
      FROM (SELECT item_id, min(t) AS t_norm_peak FROM (SELECT *, max(r) OVER (PARTITION BY item_id) AS top FROM (SELECT item_id, t, n / nullif(avg(n) OVER (PARTITION BY t), 0) AS r FROM {{dense}}) AS x) AS z WHERE r = top GROUP BY item_id) AS y"""


def sleepers(w: int, length: int = 5, depth: float = 1.0, wake: int = 4) -> str:
    """Depth of the sleep of the first periods, the share of it in each (heartbeat) and the
    mentions in as many periods after it."""
    beats = ", ".join(f"sum(CASE WHEN t = {k} THEN n ELSE 0 END) / CAST(nullif(sum(CASE WHEN t < {length} THEN n ELSE 0 END), 0) AS DOUBLE) AS beat_{k}" for k in range(length))
    return f"""SELECT *, CASE WHEN asleep <= {depth} AND intensity >= {wake} AND beat_0 IS NULL THEN 'all_elements' WHEN asleep <= {depth} AND intensity >= {wake} THEN 'sleeper' ELSE 'other' END AS class
      FROM (SELECT item_id, sum(CASE WHEN t < {length} THEN n ELSE 0 END) / CAST({length} AS DOUBLE) AS asleep,
                   CAST(sum(CASE WHEN t >= {length} AND t < {2 * length} THEN n ELSE 0 END) AS BIGINT) AS intensity, {beats} FROM {{dense}} GROUP BY item_id) AS x"""


def poly_fit(w: int, degree: int = 5) -> str:
    """Coefficients on the shared basis (a projection, no solve per item) and R squared."""
    rows = ", ".join("(" + ", ".join([str(t), *(f"CAST({x!r} AS DOUBLE)" for x in row.tolist())]) + ")" for t, row in enumerate(poly_basis(w, degree)))
    names = ", ".join(f"q{j}" for j in range(degree + 1))
    proj = ", ".join(f"sum(n * q{j}) AS c{j}" for j in range(degree + 1))
    fit = " + ".join(f"c{j} * c{j}" for j in range(degree + 1))
    cols = ", ".join(f"round(c{j}, 6) + CAST(0 AS DOUBLE) AS c{j}" for j in range(degree + 1))
    return f"""SELECT item_id, {cols}, round(1 - (nn - ({fit})) / nullif(nn - c * c / CAST({w} AS DOUBLE), 0), 6) AS r2
      FROM (SELECT item_id, CAST(sum(n) AS DOUBLE) AS c, CAST(sum(n * n) AS DOUBLE) AS nn, {proj} FROM {{dense}} AS d JOIN (VALUES {rows}) AS b(t_, {names}) ON b.t_ = d.t GROUP BY item_id) AS x"""


def transient_sticky(w: int, early: float = 0.2, tail: float = 0.2) -> str:
    """An early peak and a steep fall, or still mentioned in the second half."""
    return f"""SELECT x.item_id, x.t_peak, y.tail_share, CASE WHEN x.t_peak <= {early * w} AND y.tail_share < {tail} THEN 'transient' WHEN y.tail_share >= {tail} THEN 'sticky' ELSE 'other' END AS class
      FROM ({_TOTALS}) AS x JOIN (SELECT item_id, sum(CASE WHEN t >= {w // 2} THEN n ELSE 0 END) / CAST(sum(n) AS DOUBLE) AS tail_share FROM {{dense}} GROUP BY item_id) AS y ON y.item_id = x.item_id"""


def spread_exponent() -> str:
    """Half the slope of log variance of the running totals on log time."""
    return f"""SELECT round(regr_slope(ln(v), ln(t + 1)) / 2, 6) AS h, count(*) AS periods FROM (SELECT CAST(t AS DOUBLE) AS t, var_pop(CAST(cum AS DOUBLE)) AS v FROM ({_CUM}) AS x GROUP BY t) AS y WHERE v > 0"""


def text(template: str, dense: str) -> str:
    return template.replace("{dense}", f"({dense})")
