"""Relational operators around the methods: one query each, with its SQL."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from trajkit.functions import python_side as PY
from trajkit.operators import features as FT
from trajkit.operators import panel as P
from trajkit.plans import sqltext as Q
from trajkit.plans.base_queries import PART, panel_of, register
from trajkit.plans.cluster_queries import CLASSED, classed
from trajkit.sources.tables import read_table

_q1 = lambda: (F.col("l_shipdate") >= "1996-01-01") & (F.col("l_shipdate") < "1996-04-01")
_Q1_SQL = "l_shipdate >= DATE '1996-01-01' AND l_shipdate < DATE '1996-04-01'"

register("op_scan_project", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem")(
    lambda s, d: read_table(s, d, "lineitem", "l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))
)
register("op_filter_range", f"SELECT l_orderkey, l_partkey, l_quantity FROM lineitem WHERE {_Q1_SQL} AND l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R')")(
    lambda s, d: read_table(s, d, "lineitem").filter(_q1() & F.col("l_quantity").between(10, 20) & F.col("l_returnflag").isin("A", "R")).select("l_orderkey", "l_partkey", "l_quantity")
)
register("op_filter_like", "SELECT p_partkey, p_name FROM part WHERE p_type LIKE '%E%' AND regexp_matches(p_name, '[aeiou]') AND p_brand IS NOT DISTINCT FROM p_brand")(
    lambda s, d: read_table(s, d, "part").filter(F.col("p_type").like("%E%") & F.col("p_name").rlike("[aeiou]") & F.col("p_brand").eqNullSafe(F.col("p_brand"))).select("p_partkey", "p_name")
)
register("op_case_bucket", "SELECT event_id, CASE WHEN value < 10 THEN 'low' WHEN value < 50 THEN 'mid' ELSE 'high' END AS band, floor(least(greatest(value, 0), 99.999) / 10)::BIGINT AS bucket FROM events")(
    lambda s, d: read_table(s, d, "events", "event_id", F.when(F.col("value") < 10, "low").when(F.col("value") < 50, "mid").otherwise("high").alias("band"), F.floor(F.least(F.greatest("value", F.lit(0)), F.lit(99.999)) / 10).alias("bucket"))
)
register("op_join_inner", "SELECT o_orderpriority, count(*) AS lines, round(sum(l_quantity), 2) AS qty FROM lineitem JOIN orders ON o_orderkey = l_orderkey GROUP BY 1")(
    lambda s, d: read_table(s, d, "lineitem", "l_orderkey", "l_quantity").join(read_table(s, d, "orders", F.col("o_orderkey").alias("l_orderkey"), "o_orderpriority"), "l_orderkey").groupBy("o_orderpriority").agg(F.count("*").alias("lines"), F.round(F.sum("l_quantity"), 2).alias("qty"))
)


@register("op_join_broadcast", "SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey")
def _(s, d):
    nation, region = read_table(s, d, "nation"), read_table(s, d, "region")  # 25 and 5 rows at any scale
    return read_table(s, d, "customer", "c_custkey", "c_nationkey").join(F.broadcast(nation), F.col("n_nationkey") == F.col("c_nationkey")).join(F.broadcast(region), F.col("r_regionkey") == F.col("n_regionkey")).select("c_custkey", "n_name", "r_name")


register("op_join_left", "SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1")(
    lambda s, d: read_table(s, d, "customer", "c_custkey").join(read_table(s, d, "orders", F.col("o_custkey").alias("c_custkey"), "o_orderkey"), "c_custkey", "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("orders"))
)
_HALVES = [f"SELECT item_id, sum(n)::BIGINT AS {n} FROM ({PART}) WHERE t >= {a} AND t < {b} GROUP BY 1" for n, a, b in (("early", 0, 4), ("late", 24, 28))]


@register("op_join_full", f"SELECT coalesce(a.item_id, b.item_id) AS item_id, early, late FROM ({_HALVES[0]}) AS a FULL JOIN ({_HALVES[1]}) AS b ON a.item_id = b.item_id")
def _(s, d):
    p = panel_of(s, d, "part_quarter")
    half = lambda name, a, b: p.filter((F.col("t") >= a) & (F.col("t") < b)).groupBy("item_id").agg(F.sum("n").cast("long").alias(name))
    return half("early", 0, 4).join(half("late", 24, 28), "item_id", "full")


for _how, _word in (("semi", "EXISTS"), ("anti", "NOT EXISTS")):
    register(f"op_join_{_how}", f"SELECT p_partkey FROM part WHERE {_word} (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND {_Q1_SQL})")(
        lambda s, d, h=_how: read_table(s, d, "part", "p_partkey").join(read_table(s, d, "lineitem", "l_partkey", "l_shipdate").filter(_q1()).select(F.col("l_partkey").alias("p_partkey")), "p_partkey", f"left_{h}")
    )
register("op_join_cross", "SELECT s_suppkey, r_regionkey FROM supplier CROSS JOIN region")(lambda s, d: read_table(s, d, "supplier", "s_suppkey").crossJoin(F.broadcast(read_table(s, d, "region", "r_regionkey"))))  # 5 rows
register("op_join_theta", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation AS a JOIN nation AS b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey = b.n_regionkey")(
    lambda s, d: read_table(s, d, "nation", F.col("n_nationkey").alias("a"), F.col("n_regionkey").alias("ra")).join(read_table(s, d, "nation", F.col("n_nationkey").alias("b"), F.col("n_regionkey").alias("rb")), (F.col("a") < F.col("b")) & (F.col("ra") == F.col("rb"))).select("a", "b")
)
register("op_join_range", f"SELECT p.item_id, sum(p.n)::BIGINT AS early FROM ({PART}) AS p JOIN ({Q.features_sql(PART, 28)}) AS f ON f.item_id = p.item_id AND p.t <= f.t_init GROUP BY 1")(
    lambda s, d: panel_of(s, d, "part_quarter").join(FT.extract_features(panel_of(s, d, "part_quarter"), 28).select("item_id", "t_init"), "item_id").filter(F.col("t") <= F.col("t_init")).groupBy("item_id").agg(F.sum("n").cast("long").alias("early"))
)


@register("op_join_asof", """SELECT a.event_id, arg_max(b.event_id, epoch_us(b.ts) * 1.0 + b.event_id / 1e9) AS last_event FROM events AS a JOIN events AS b ON a.user_id = b.user_id AND b.event_type <> 'purchase' AND (b.ts < a.ts) WHERE a.event_type = 'purchase' GROUP BY 1""")
def _(s, d):
    e = read_table(s, d, "events", "event_id", "user_id", "ts", "event_type")
    # One pass: the last other event strictly before, so equal times sort purchases first.
    before = W.partitionBy("user_id").orderBy("ts", (F.col("event_type") != "purchase").cast("int"), "event_id").rowsBetween(W.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") != "purchase", F.col("event_id")), ignorenulls=True).over(before)
    return e.withColumn("last_event", last).filter((F.col("event_type") == "purchase") & F.col("last_event").isNotNull()).select("event_id", "last_event")


@register("op_join_interval", "SELECT a.event_id AS a, b.event_id AS b FROM events AS a JOIN events AS b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def _(s, d):
    e = read_table(s, d, "events", "event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    hour = 3_600_000_000
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("us").alias("ua"), F.explode(F.array(F.floor(F.col("us") / hour), F.floor(F.col("us") / hour) + 1)).alias("bin"))
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("us").alias("ub"), F.floor(F.col("us") / hour).alias("bin"))
    return a.join(b, ["user_id", "bin"]).filter((F.col("ub") > F.col("ua")) & (F.col("ub") <= F.col("ua") + hour)).select("a", "b")


@register("op_join_salted", "SELECT r_name, count(*) AS lines FROM lineitem JOIN supplier ON s_suppkey = l_suppkey JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY 1")
def _(s, d):
    """Few keys on many rows: rows are salted, the small side is repeated once a salt."""
    salts = 8
    left = read_table(s, d, "lineitem", "l_orderkey", "l_suppkey").withColumn("salt", F.pmod(F.xxhash64("l_orderkey"), F.lit(salts)))
    right = read_table(s, d, "supplier", F.col("s_suppkey").alias("l_suppkey"), "s_nationkey").withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    n = F.broadcast(read_table(s, d, "nation", F.col("n_nationkey").alias("s_nationkey"), "n_regionkey"))
    r = F.broadcast(read_table(s, d, "region", F.col("r_regionkey").alias("n_regionkey"), "r_name"))
    return left.join(right, ["l_suppkey", "salt"]).join(n, "s_nationkey").join(r, "n_regionkey").groupBy("r_name").agg(F.count("*").alias("lines"))


_sums = lambda: (F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"), F.count("*").alias("lines"))
register("op_agg_partial_final", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS qty, round(avg(l_discount), 6) AS disc, count(*) AS lines FROM lineitem GROUP BY 1, 2")(
    lambda s, d: read_table(s, d, "lineitem", "l_returnflag", "l_linestatus", "l_quantity", "l_discount").groupBy("l_returnflag", "l_linestatus").agg(*_sums())
)
register("op_agg_distinct", "SELECT date_diff('day', DATE '2024-01-01', ts::DATE)::INTEGER AS day, count(DISTINCT user_id) AS users FROM events GROUP BY 1")(
    lambda s, d: read_table(s, d, "events", "user_id", P.day_index(F.col("ts")).alias("day")).groupBy("day").agg(F.count_distinct("user_id").alias("users"))
)
register("op_agg_approx_distinct")(lambda s, d: read_table(s, d, "events", "user_id", P.day_index(F.col("ts")).alias("day")).groupBy("day").agg(F.approx_count_distinct("user_id").alias("users")))
register("op_agg_percentile", "SELECT c_mktsegment, quantile_cont(c_acctbal, 0.25) AS q1, quantile_cont(c_acctbal, 0.5) AS q2, quantile_cont(c_acctbal, 0.75) AS q3 FROM customer GROUP BY 1")(
    lambda s, d: read_table(s, d, "customer", "c_mktsegment", "c_acctbal").groupBy("c_mktsegment").agg(*[F.percentile("c_acctbal", p).alias(f"q{i}") for i, p in ((1, 0.25), (2, 0.5), (3, 0.75))])
)
register("op_agg_stats", "SELECT event_type, round(stddev_pop(value), 6) AS sd, round(stddev_samp(value), 6) AS sds, round(corr(value, user_id), 6) AS r, round(regr_slope(value, user_id), 8) AS slope FROM events GROUP BY 1")(
    lambda s, d: read_table(s, d, "events", "event_type", "value", "user_id").groupBy("event_type").agg(F.round(F.stddev_pop("value"), 6).alias("sd"), F.round(F.stddev_samp("value"), 6).alias("sds"), F.round(F.corr("value", "user_id"), 6).alias("r"), F.round(F.regr_slope("value", "user_id"), 8).alias("slope"))
)
register("op_agg_maxby", f"SELECT item_id, arg_max(t, n * 1000 - t) AS t_peak, max(n) AS n_peak FROM ({PART}) GROUP BY 1")(lambda s, d: panel_of(s, d, "part_quarter").groupBy("item_id").agg(F.max_by("t", F.struct("n", -F.col("t"))).alias("t_peak"), F.max("n").alias("n_peak")))
_SEG = "SELECT c.class, p_brand AS brand, p_size % 3 AS size_class FROM " + CLASSED + " AS c JOIN part ON p_partkey = c.item_id"


def segments(s, d):
    return classed(s, d).select("item_id", "class").join(read_table(s, d, "part", F.col("p_partkey").alias("item_id"), F.col("p_brand").alias("brand"), (F.col("p_size") % 3).alias("size_class")), "item_id")


register("op_grouping_sets", f"SELECT class, size_class, count(*) AS items FROM ({_SEG}) GROUP BY GROUPING SETS ((class), (size_class), ())")(
    lambda s, d: segments(s, d).groupingSets([[F.col("class")], [F.col("size_class")], []], "class", "size_class").agg(F.count("*").alias("items"))
)
register("op_cube", f"SELECT class, size_class, count(*) AS items FROM ({_SEG}) GROUP BY CUBE (class, size_class)")(lambda s, d: segments(s, d).cube("class", "size_class").agg(F.count("*").alias("items")))
register("op_rollup", f"SELECT class, brand, count(*) AS items FROM ({_SEG}) GROUP BY ROLLUP (class, brand)")(lambda s, d: segments(s, d).rollup("class", "brand").agg(F.count("*").alias("items")))
_WIDE = f"SELECT size_class, count(CASE WHEN class = 0 THEN 1 END) AS c0, count(CASE WHEN class = 1 THEN 1 END) AS c1, count(CASE WHEN class = 2 THEN 1 END) AS c2 FROM ({_SEG}) GROUP BY 1"


def wide(s, d):
    x = segments(s, d).groupBy("size_class").pivot("class", [0, 1, 2]).agg(F.count(F.lit(1)))
    return x.select("size_class", *[F.coalesce(F.col(str(k)), F.lit(0)).alias(f"c{k}") for k in range(3)])


register("op_pivot", _WIDE)(wide)
register("op_unpivot", " UNION ALL ".join(f"SELECT size_class, 'c{k}' AS class, c{k} AS items FROM ({_WIDE})" for k in range(3)))(lambda s, d: wide(s, d).unpivot("size_class", ["c0", "c1", "c2"], "class", "items"))

TOTAL = f"SELECT item_id, p_brand AS brand, total FROM (SELECT item_id, sum(n)::BIGINT AS total FROM ({PART}) GROUP BY 1) JOIN part ON p_partkey = item_id"


def totals(s, d):
    return P.totals(panel_of(s, d, "part_quarter"), 28).join(read_table(s, d, "part", F.col("p_partkey").alias("item_id"), F.col("p_brand").alias("brand")), "item_id").select("item_id", "brand", "total")


@register("op_win_rank", f"SELECT item_id, row_number() OVER k::INTEGER AS rn, rank() OVER t::INTEGER AS rk, dense_rank() OVER t::INTEGER AS dr, round(percent_rank() OVER t, 9) AS pr, round(cume_dist() OVER t, 9) AS cd, ntile(4) OVER k::INTEGER AS nt FROM ({TOTAL}) WINDOW t AS (PARTITION BY brand ORDER BY total DESC), k AS (PARTITION BY brand ORDER BY total DESC, item_id)")
def _(s, d):
    t, k = W.partitionBy("brand").orderBy(F.desc("total")), W.partitionBy("brand").orderBy(F.desc("total"), "item_id")
    return totals(s, d).select("item_id", F.row_number().over(k).alias("rn"), F.rank().over(t).alias("rk"), F.dense_rank().over(t).alias("dr"), F.round(F.percent_rank().over(t), 9).alias("pr"), F.round(F.cume_dist().over(t), 9).alias("cd"), F.ntile(4).over(k).alias("nt"))


_i = lambda: W.partitionBy("item_id").orderBy("t")
DENSE = Q.dense_sql(PART, 28)
dense = lambda s, d: P.densify_long(panel_of(s, d, "part_quarter"), 28)
register("op_win_lag_lead", f"SELECT item_id, t, n - lag(n) OVER i AS change, n > coalesce(lag(n) OVER i, -1) AND n > coalesce(lead(n) OVER i, -1) AS top FROM ({DENSE}) WINDOW i AS (PARTITION BY item_id ORDER BY t)")(
    lambda s, d: dense(s, d).select("item_id", "t", (F.col("n") - F.lag("n").over(_i())).alias("change"), ((F.col("n") > F.coalesce(F.lag("n").over(_i()), F.lit(-1))) & (F.col("n") > F.coalesce(F.lead("n").over(_i()), F.lit(-1)))).alias("top"))
)
register("op_win_running", f"SELECT item_id, t, sum(n) OVER (PARTITION BY item_id ORDER BY t)::BIGINT AS cum FROM ({PART})")(lambda s, d: P.cumulate(panel_of(s, d, "part_quarter")).select("item_id", "t", "cum"))
register("op_win_centered", f"SELECT item_id, t, round(avg(n) OVER (PARTITION BY item_id ORDER BY t ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING), 9) AS smooth FROM ({DENSE})")(lambda s, d: dense(s, d).select("item_id", "t", F.round(F.avg("n").over(_i().rowsBetween(-1, 1)), 9).alias("smooth")))
register("op_win_range", f"SELECT item_id, t, sum(n) OVER (PARTITION BY item_id ORDER BY t RANGE BETWEEN 3 PRECEDING AND CURRENT ROW)::BIGINT AS last_4 FROM ({PART})")(lambda s, d: panel_of(s, d, "part_quarter").select("item_id", "t", F.sum("n").over(_i().rangeBetween(-3, 0)).alias("last_4")))


@register("op_win_first_last_nth", f"SELECT DISTINCT item_id, first_value(t) OVER i AS first_t, last_value(t) OVER i AS last_t, nth_value(t, 2) OVER i AS second_t FROM ({PART}) WINDOW i AS (PARTITION BY item_id ORDER BY t ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def _(s, d):
    w = _i().rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return panel_of(s, d, "part_quarter").select("item_id", F.first("t").over(w).alias("first_t"), F.last("t").over(w).alias("last_t"), F.nth_value("t", 2).over(w).alias("second_t")).distinct()


register("op_win_islands", f"SELECT item_id, max(len) AS longest_quiet FROM (SELECT item_id, count(*) AS len FROM (SELECT item_id, t - row_number() OVER (PARTITION BY item_id ORDER BY t) AS g FROM ({DENSE}) WHERE n = 0) GROUP BY item_id, g) GROUP BY 1")(
    lambda s, d: dense(s, d).filter("n = 0").withColumn("g", F.col("t") - F.row_number().over(_i())).groupBy("item_id", "g").agg(F.count("*").alias("len")).groupBy("item_id").agg(F.max("len").alias("longest_quiet"))
)
register("op_sort_limit", f"SELECT item_id, total FROM ({TOTAL}) ORDER BY total DESC, item_id LIMIT 20")(lambda s, d: totals(s, d).select("item_id", "total").orderBy(F.desc("total"), "item_id").limit(20))
register("op_topk_group", f"SELECT brand, item_id, total FROM ({TOTAL}) QUALIFY row_number() OVER (PARTITION BY brand ORDER BY total DESC, item_id) <= 3")(
    lambda s, d: totals(s, d).withColumn("r", F.row_number().over(W.partitionBy("brand").orderBy(F.desc("total"), "item_id"))).filter("r <= 3").select("brand", "item_id", "total")
)
register("op_sample_hash", "SELECT p_partkey FROM part ORDER BY md5('7|' || p_partkey) LIMIT 50")(lambda s, d: read_table(s, d, "part", "p_partkey").orderBy(F.md5(F.concat(F.lit("7|"), F.col("p_partkey").cast("string")).cast("binary"))).limit(50))
register("op_sample_stratified")(lambda s, d: read_table(s, d, "customer", "c_custkey", "c_mktsegment").sampleBy("c_mktsegment", {"BUILDING": 0.5, "AUTOMOBILE": 0.1}, seed=7))

_A, _B = f"SELECT item_id FROM ({PART}) WHERE t < 6", f"SELECT item_id FROM ({PART}) WHERE t >= 22"
_fa, _fb = (lambda s, d: panel_of(s, d, "part_quarter").filter("t < 6").select("item_id")), (lambda s, d: panel_of(s, d, "part_quarter").filter("t >= 22").select("item_id"))
register("op_union", f"{_A} UNION ALL {_B}")(lambda s, d: _fa(s, d).unionByName(_fb(s, d)))
register("op_intersect", f"({_A}) INTERSECT ({_B})")(lambda s, d: _fa(s, d).intersect(_fb(s, d)))
register("op_intersect_all", f"({_A}) INTERSECT ALL ({_B})")(lambda s, d: _fa(s, d).intersectAll(_fb(s, d)))
register("op_except", f"({_A}) EXCEPT ({_B})")(lambda s, d: _fa(s, d).subtract(_fb(s, d)))
register("op_except_all", f"({_A}) EXCEPT ALL ({_B})")(lambda s, d: _fa(s, d).exceptAll(_fb(s, d)))
register("op_dedup", "SELECT DISTINCT l_partkey, l_suppkey FROM lineitem")(lambda s, d: read_table(s, d, "lineitem", "l_partkey", "l_suppkey").dropDuplicates())

register("op_str", "SELECT p_partkey, lower(p_name) AS low, length(p_name)::INTEGER AS len, split_part(p_name, ' ', 1) AS first_word, regexp_replace(p_type, '[AEIOU]', '_', 'g') AS masked, md5(p_brand) AS h, lpad(p_size::VARCHAR, 4, '0') AS padded, levenshtein(p_name, p_type)::INTEGER AS lev, p_brand || '|' || p_type AS both FROM part")(
    lambda s, d: read_table(s, d, "part").select("p_partkey", F.lower("p_name").alias("low"), F.length("p_name").alias("len"), F.split("p_name", " ")[0].alias("first_word"), F.regexp_replace("p_type", "[AEIOU]", "_").alias("masked"), F.md5(F.col("p_brand").cast("binary")).alias("h"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("padded"), F.levenshtein("p_name", "p_type").alias("lev"), F.concat_ws("|", "p_brand", "p_type").alias("both"))
)
register("op_date", "SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, quarter(o_orderdate)::INTEGER AS q, date_diff('day', DATE '1995-01-01', o_orderdate::DATE)::INTEGER AS days, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, strftime(o_orderdate::DATE + INTERVAL 3 MONTH, '%Y-%m-%d') AS later FROM orders")(
    lambda s, d: read_table(s, d, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).alias("days"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("month"), F.date_format(F.add_months(F.to_date("o_orderdate"), 3), "yyyy-MM-dd").alias("later"))
)
register("op_math", "SELECT l_orderkey, l_linenumber, round(ln(l_extendedprice), 6) AS a, round(sqrt(l_quantity), 6) AS b, round(pow(1 + l_tax, 3), 6) AS c, round(degrees(atan2(l_quantity, l_extendedprice)), 6) AS e, floor(l_extendedprice)::BIGINT AS f, greatest(l_tax, l_discount) AS g, l_orderkey % 7 AS m FROM lineitem")(
    lambda s, d: read_table(s, d, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.ln("l_extendedprice"), 6).alias("a"), F.round(F.sqrt("l_quantity"), 6).alias("b"), F.round(F.pow(1 + F.col("l_tax"), F.lit(3)), 6).alias("c"), F.round(F.degrees(F.atan2("l_quantity", "l_extendedprice")), 6).alias("e"), F.floor("l_extendedprice").alias("f"), F.greatest("l_tax", "l_discount").alias("g"), F.pmod("l_orderkey", F.lit(7)).alias("m"))
)
_SERIES = f"SELECT item_id, list(n ORDER BY t) AS s FROM ({DENSE}) GROUP BY 1"
register("op_array", f"SELECT item_id, list_max(s) AS top, (list_position(s, list_max(s)) - 1)::INTEGER AS at, len(list_filter(s, lambda x: x > 0))::INTEGER AS active, list_sum(list_transform(s, lambda x: x * x))::BIGINT AS sq, s[1:3] AS head FROM ({_SERIES})")(
    lambda s, d: P.densify(panel_of(s, d, "part_quarter"), 28).select("item_id", F.array_max("series").alias("top"), (F.array_position("series", F.array_max("series")) - 1).cast("int").alias("at"), F.size(F.filter("series", lambda x: x > 0)).alias("active"), F.aggregate("series", F.lit(0).cast("long"), lambda a, x: a + x * x).alias("sq"), F.slice("series", 1, 3).alias("head"))
)
register("op_map", f"SELECT item_id, count(*) AS periods, sum(CASE WHEN n >= 2 THEN 1 ELSE 0 END)::BIGINT AS busy, max(CASE WHEN t = 5 THEN n END) AS at_5 FROM ({PART}) GROUP BY 1")(
    lambda s, d: panel_of(s, d, "part_quarter").groupBy("item_id").agg(F.map_from_entries(F.collect_list(F.struct("t", "n"))).alias("m")).select("item_id", F.size("m").cast("long").alias("periods"), F.size(F.map_filter("m", lambda k, v: v >= 2)).cast("long").alias("busy"), F.try_element_at("m", F.lit(5)).alias("at_5"))
)
register("op_struct", f"SELECT item_id, max(n) AS n, arg_max(t, n * 1000 - t) AS t FROM ({PART}) GROUP BY 1")(lambda s, d: panel_of(s, d, "part_quarter").groupBy("item_id").agg(F.max(F.struct("n", (-F.col("t")).alias("m"))).alias("x")).select("item_id", "x.n", (-F.col("x.m")).alias("t")))
register("op_json", "SELECT user_id, sum((props->>'k')::BIGINT)::BIGINT AS k, count(*) AS events FROM events GROUP BY 1")(
    lambda s, d: read_table(s, d, "events", "user_id", "props").groupBy("user_id").agg(F.sum(F.from_json("props", "k bigint")["k"]).alias("k"), F.count("*").alias("events"))
)
register("op_explode", DENSE)(lambda s, d: P.densify(panel_of(s, d, "part_quarter"), 28).select("item_id", F.posexplode("series").alias("t", "n")))
register("op_udf_arrow")(lambda s, d: PY.nearest_label(read_table(s, d, "embeddings", "vec_id", "embedding", "label")))
register("op_udaf_geomean", f"SELECT item_id, round(exp(avg(ln(n))), 6) AS gm FROM ({PART}) GROUP BY 1")(lambda s, d: panel_of(s, d, "part_quarter").groupBy("item_id").agg(F.round(PY.geometric_mean(F.col("n")), 6).alias("gm")))
register("op_map_arrow", f"SELECT count(*) AS active_rows, sum(n)::BIGINT AS total FROM ({PART})")(lambda s, d: PY.partial_sums(panel_of(s, d, "part_quarter")))
register("op_udtf_trajectory", f"SELECT item_id, t, n, sum(n) OVER (PARTITION BY item_id ORDER BY t)::BIGINT AS cum, CASE WHEN t <= p THEN 'growth' ELSE 'decay' END AS phase FROM ({DENSE}) JOIN (SELECT item_id, arg_max(t, n * 1000 - t) AS p FROM ({PART}) GROUP BY 1) USING (item_id)")(
    lambda s, d: PY.explode_trajectories(s, P.densify(panel_of(s, d, "part_quarter"), 28))
)
register("op_sql_surface", f"SELECT item_id, t_peak, gain, z FROM (SELECT item_id, t_peak, round(g_init, 9) AS gain, round((total - avg(total) OVER ()) / nullif(stddev_pop(total) OVER (), 0), 6) AS z FROM ({Q.features_sql(PART, 28)}))")(
    lambda s, d: PY.sql_surface(s, panel_of(s, d, "part_quarter"), 28)
)


@register("op_io_roundtrip", "SELECT fmt, items, total FROM (VALUES ('csv'), ('json'), ('orc'), ('parquet')) AS f(fmt) CROSS JOIN (SELECT count(*) AS items, sum(total)::BIGINT AS total FROM (" + TOTAL + "))")
def _(s, d):
    from trajkit.sources.shared import materialised, shared_dir
    from trajkit.sources.tables import read_any, write_any

    x, out = materialised(totals(s, d)), None
    for fmt in ("csv", "json", "orc", "parquet"):
        path = f"{shared_dir(s)}/io-{fmt}"
        write_any(x, path, fmt)
        one = read_any(s, path, fmt, x.schema).agg(F.lit(fmt).alias("fmt"), F.count("*").alias("items"), F.sum("total").alias("total"))
        out = one if out is None else out.unionByName(one)
    return out
