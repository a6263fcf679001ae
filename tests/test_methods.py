"""Worked examples, invariants and brute force for the methods."""

import itertools
import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from trajkit.operators.quantile import exact_quantile
from trajkit.operators import blocks as BL, density, ensemble as E, features as FT, graphcut, lloyd as L, measures as M, panel as P, rules as R, scaling
from trajkit.operators.features import FEATURES, FeatureOptions
from trajkit.plans import base_queries as B

SF = "/root/testdata/sf0.001"


def panel(spark, series: dict[int, list[int]]):
    rows = [(i, t, n) for i, s in series.items() for t, n in enumerate(s) if n]
    return spark.createDataFrame(rows, "item_id long, t int, n long")


def one(spark, series, w=None, **o):
    return FT.extract_features(panel(spark, {1: series}), w or len(series), FeatureOptions(**o)).first()


def test_worked_example(spark):
    r = one(spark, [0, 1, 2, 6, 3, 1, 0, 1])
    assert (r.t_init, r.t_grow, r.t_decay, r.t_peak, r.t_last, r.total) == (2, 1, 4, 3, 7, 14)
    assert np.allclose([r.g_init, r.g_grow, r.g_decay], [3 / 14, 1 / 14, 12 / 14])
    assert (r.lo_grow, r.lo_decay, r.md_grow, r.md_decay, r.hi_grow, r.hi_decay) == (1, 0, 1, 0, 0, 0)
    r = one(spark, [0, 1, 2, 6, 3, 1, 0, 1], gain_mode="phase")
    assert np.allclose([r.g_init, r.g_grow, r.g_decay], [3 / 14, 6 / 14, 5 / 14])


@pytest.mark.parametrize("series,want", [
    ([2, 2, 2, 2, 2], dict(t_init=0, t_peak=0, lo_grow=0, lo_decay=0)), ([0, 0, 0, 9, 0, 0, 0, 0, 0, 0], dict(hi_grow=1, t_init=3, t_grow=0, t_decay=0)),
    ([9, 1, 0, 0], dict(t_grow=0, t_decay=1)), ([0, 0, 1, 9], dict(t_decay=0, t_peak=3)), ([1, 5, 2, 5, 1], dict(t_peak=1)), ([1, 1, 1, 1], dict(t_init=0)), ([4, 0, 0, 0, 4], dict(t_peak=0, t_decay=4)), ([7], dict(t_init=0, t_peak=0, t_last=0)),
])
def test_hand_made_series(spark, series, want):
    r = one(spark, series)
    assert {k: r[k] for k in want} == want


def test_readings(spark):
    assert one(spark, [1, 5, 2, 5, 1], peak_tie="last").t_peak == 3
    assert one(spark, [2, 2, 2], flat="literal").lo_grow == 1 and one(spark, [2, 2, 2], flat="literal").lo_decay == 2
    assert one(spark, [9, 1, 0, 0], end_rule="window_end").t_last == 3
    # With ten periods the sample deviation puts the highest level out of reach.
    assert one(spark, [0, 0, 0, 9, 0, 0, 0, 0, 0, 0], sd="samp").hi_grow == 0
    assert FT.extract_features(panel(spark, {1: [0, 0, 0], 2: [1]}), 3).count() == 1


def test_invariants_and_both_paths(spark):
    p = B.panel_of(spark, SF, "part_quarter")
    f = {r.item_id: r for r in FT.extract_features(p, 28).collect()}
    phase = {r.item_id: r for r in FT.extract_features(p, 28, FeatureOptions(gain_mode="phase")).collect()}
    array = {r.item_id: r for r in FT.features_of_series(P.densify(p, 28), 28).collect()}
    for i, r in f.items():
        assert r.t_init + r.t_grow + r.t_decay == r.t_last and r.t_grow >= 0
        assert math.isclose(phase[i].g_init + phase[i].g_grow + phase[i].g_decay, 1.0)
        assert r.hi_grow <= r.md_grow <= r.lo_grow and r.hi_decay <= r.md_decay <= r.lo_decay
        assert all(math.isclose(r[c], array[i][c]) for c in ["total", *FEATURES])


def test_ratio_filter_is_a_sum(spark):
    rng = random.Random(1)
    p = panel(spark, {i: [rng.randrange(4) for _ in range(rng.choice([1, 3, 8]))] for i in range(60)})
    for w in (1, 4, 8):
        long = P.success_ratio(P.totals(p, w)).filter("ratio >= 1").select("item_id")
        assert {r[0] for r in long.collect()} == {r.item_id for r in P.eligible(p, w).collect()}
    assert P.eligible_panel(p, 8).select("item_id").distinct().count() == P.eligible(p, 8).count()


@pytest.fixture(scope="module")
def points(spark):
    rng = np.random.default_rng(3)
    x = np.concatenate([rng.normal(c, 0.4, (60, 2)) for c in ((0, 0), (4, 0), (2, 3.5))])
    return x, spark.createDataFrame([(i, float(a), float(b)) for i, (a, b) in enumerate(x)], "item_id long, x double, y double")


def test_lloyd_kernels_agree(spark, points, monkeypatch):
    x, z = points
    a = L.lloyd(z, ["x", "y"], 3, max_iter=5)
    one = L.assign(z, ["x", "y"], a).orderBy("item_id").collect()
    monkeypatch.setattr(L, "LITERALS", 0)
    assert [(r.label, r.d2) for r in L.assign(z, ["x", "y"], a).orderBy("item_id").collect()] == [(r.label, r.d2) for r in one]
    assert np.allclose(L.lloyd(z, ["x", "y"], 3, max_iter=5), a)
    assert L.lloyd(z, ["x", "y"], 3, "kmeans||", 3).shape == (3, 2)
    d = ((x[:, None] - a[None]) ** 2).sum(2)
    assert [r.label for r in one] == d.round(9).argmin(1).tolist()


def test_one_task_and_one_job_an_iteration_give_the_same_rounds(spark, points, monkeypatch):
    z, cols = points[1], ["x", "y"]
    for scope in ("final_center", "initial_center", "trimmed"):
        o = E.RoundOptions(k=4, eps=0.6, t_max=4, max_iter=4, stop="remaining", scope=scope)
        small = E.run_rounds(z, cols, o)
        monkeypatch.setattr(L, "ONE_TASK", 0)
        large = E.run_rounds(z.repartition(5), cols, o)
        monkeypatch.undo()
        assert small.sizes == large.sizes and np.array_equal(np.concatenate(small.centers), np.concatenate(large.centers))


def test_small_pools_need_few_jobs(spark, points):
    count = lambda: len(spark.sparkContext.statusTracker().getJobIdsForGroup(None))
    before = count()
    E.run_rounds(points[1], ["x", "y"], E.RoundOptions(k=4, eps=0.3, t_max=10, max_iter=10, stop="remaining"))
    assert count() - before <= 4  # a job for each of up to 100 iterations before


def test_passes_over_many_items_hand_over_few_rows(spark):
    """A row an item costs many times the kernel; blocks hold the same numbers."""
    cols = ["x", "y"]
    z = spark.range(40_000).selectExpr("id AS item_id", "round(sin(id) * 3, 9) AS x", "CAST(id % 7 AS double) AS y").repartition(2)
    b = BL.packed(z, cols)
    assert b.count() == 40_000 and b.table.count() <= 2 * (1 + 20_000 * 2 // BL.VALUES + 1)
    assert sum(i for i, in b.table.select("n").collect()) == 40_000
    c = L.seeds(b, cols, 5, "0|1")
    assert np.array_equal(c, L.seeds(z, cols, 5, "0|1")) and np.array_equal(L.step(b, cols, c), L.step(z, cols, c))
    assert sorted(E.affinity(b, cols, c, 1.0, own=True).collect()) == sorted(E.affinity(z, cols, c, 1.0, own=True).collect())
    many, (table, chunks) = BL.copies(b, 3), BL.source(BL.copies(b, 3), cols)
    got = sorted((i, *v) for ids, x in chunks(table.toArrow().to_batches()) for i, v in zip(ids.to_pylist(), x.T.tolist()))
    assert many.count() == 120_000 and got == sorted((r.item_id * 3 + i, r.x, r.y) for r in z.collect() for i in (1, 2, 3))


def test_few_different_vectors_among_copies_in_blocks(spark):
    z = spark.range(3_000).selectExpr("id AS item_id", "CASE WHEN id IN (5, 6) THEN CAST(id AS double) ELSE 0.0D END AS x")
    b = BL.packed(z.repartition(3), ["x"])
    assert sorted(L.seeds(b, ["x"], 3, "0").ravel()) == [0.0, 5.0, 6.0] and np.array_equal(L.seeds(b, ["x"], 3, "0"), L.seeds(z, ["x"], 3, "0"))
    assert len(L.seeds(b, ["x"], 5, "0")) == 3


def test_kernels_of_blocks_decide_as_those_of_rows():
    """Exact ties, distances that only rounding makes equal, balls whose edge holds items, odd values."""
    x = np.array([[0.5, 0.5 + 4e-10, 0.5 - 4e-10, 2.0, 1e7, np.inf, np.nan, 0.3], [0.0, 0.0, 0.0, 0.0, 1e7, 0.0, 0.0, 0.7]])
    c = np.array([[0.0, 0.0], [1.0, 0.0], [0.0, 0.0], [1e7, 1e7]])
    for cs in (c, c[:1]):
        for y in (x, x[:, :4]):
            with np.errstate(all="ignore"):
                label, d2 = L.closest(y.T, cs)
                assert np.array_equal(BL.labels(y, cs, L.closest), label)
                for eps in (0.5, 1.0, 2.0, np.sqrt(0.58)):
                    assert np.array_equal(BL.within(y, cs, eps, L.closest), d2 <= eps**2)
    rng = np.random.default_rng(0)
    for y in (np.round(rng.normal(size=(3, 500)), 9), rng.normal(size=(3, 500)), np.round(rng.normal(size=(3, 500)) * 1e6, 3)):
        label = rng.integers(0, 4, 500).astype(np.int32)
        assert all(np.array_equal(a, b) for a, b in zip(BL.exact_sums(y, label, 6, L.DIGITS, L.grid_sums), L.grid_sums(y.T, label, 6)))


def test_means_are_exact_at_half_a_unit():
    """Sums in doubles lose the halves that decide the last digit of a centre."""
    x = np.array([[0.1 + 1e-9], [0.1]] * 300_000 + [[0.3]] * 2)
    n, whole, rest = L.grid_sums(x[:600_000], np.zeros(600_000, int), 1)
    assert L.grid_mean(int(n[0]), whole[0, 0], rest[0, 0]) == 0.100000001 and rest[0, 0] == 0.0
    assert L.grid_mean(2, -1, 0.0) == -1e-9 and L.grid_mean(4, 1, 0.0) == 0.0


def test_agreement_from_cells_equals_the_plan(spark):
    a = spark.createDataFrame([(i, i % 3) for i in range(60)], "item_id long, class int")
    b = spark.createDataFrame([(i, (i * i + i // 7) % 4) for i in range(60)], "item_id long, class int")
    assert tuple(M.agreement(a, b).first()) == pytest.approx(M.agreement_of(a, b), abs=1e-6)


def test_population_of_midpoint_balls(spark, points):
    x, z = points
    c = np.array([[0, 0], [0.5, 0.2], [4, 0], [2, 3.5], [0.5, 0.2]])
    got = {(r.a, r.b): (r.pop, r.w) for r in E.affinity(z, ["x", "y"], c, 0.6).collect()}
    for i, j in itertools.combinations(range(5), 2):
        dist = np.linalg.norm(c[i] - c[j])
        if dist <= 2.4:
            pop = int((((x - (c[i] + c[j]) / 2) ** 2).sum(1) <= 0.36).sum())
            assert got[i, j][0] == pop and (got[i, j][1] is None) == (dist == 0)
        else:
            assert (i, j) not in got


def test_rounds_cover_each_item_once(spark, points):
    _, z = points
    r = E.run_rounds(z, ["x", "y"], E.RoundOptions(k=3, eps=0.5, t_max=4, max_iter=3, stop="remaining"))
    s = E.scan(z, ["x", "y"], r, 0.5)
    assert sum(c for _, c in r.sizes) == s.filter("captured_at IS NOT NULL").count()
    counts = {x.captured_at: x["count"] for x in s.groupBy("captured_at").count().collect()}
    assert [counts.get(h, 0) for h in range(len(r.sizes))] == [c for _, c in r.sizes]


def test_model_finds_the_groups_and_survives_storage(spark, points, tmp_path):
    _, z = points
    m = E.EnsembleModel.fit(z, ["x", "y"], E.RoundOptions(k=6, eps=0.6, t_max=4, max_iter=4, stop="remaining"), 3)
    truth = z.select("item_id", (F.col("item_id") / 60).cast("int").alias("class"))
    for how in ("credible", "majority", "distance_weighted"):
        assert M.agreement(m.transform(z, how), truth).first().ari > 0.9
    m.save(spark, str(tmp_path / "m"))
    back = E.EnsembleModel.load(spark, str(tmp_path / "m"))
    assert back.options == m.options and back.transform(z).orderBy("item_id").collect() == m.transform(z).orderBy("item_id").collect()


def test_transform_equals_the_long_form(spark, points):
    _, z = points
    m = E.EnsembleModel.fit(z, ["x", "y"], E.RoundOptions(k=5, eps=0.5, t_max=3, max_iter=3, stop="remaining"), 3)
    s = E.scan(z, m.cols, m.rounds, m.options.eps)
    long = E.relabel(E.labels_long(s, m.options.eps), m.offsets, m.groups)
    for how in ("credible", "majority"):
        assert {r.item_id: r["class"] for r in E.consensus(long, s, how).collect()} == {r.item_id: r["class"] for r in m.transform(z, how).collect()}


def test_cut_against_all_partitions():
    rng = np.random.default_rng(5)
    for _ in range(5):
        w = rng.random((8, 8)) * (rng.random((8, 8)) < 0.6)
        w = np.triu(w, 1) + np.triu(w, 1).T + 1e-3 * (1 - np.eye(8))
        best = min(graphcut.ncut_value(w, np.array([0, *p])) for p in itertools.product((0, 1), repeat=7) if any(p))
        assert graphcut.ncut_value(w, graphcut.normalized_cut(w, 2, "recursive")) <= 1.25 * best
    blocks = np.kron(np.eye(3), np.ones((4, 4))) + 1e-3
    np.fill_diagonal(blocks, 0)
    shuffle = rng.permutation(12)
    for method in ("spectral", "recursive"):
        g = graphcut.normalized_cut(blocks[np.ix_(shuffle, shuffle)], 3, method)
        assert len({(int(a), int(b)) for a, b in zip(g, shuffle // 4)}) == 3
    assert graphcut.components(np.kron(np.eye(3), np.ones((2, 2)))).tolist() == [0, 0, 1, 1, 2, 2]
    assert graphcut.eigengap(graphcut._embedding(blocks)[0]) == 3


def test_density_against_brute_force(spark, points):
    x, z = points
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(2))
    near = (d <= 0.3).sum(1)
    assert [r.neighbours for r in density.neighbour_counts(z, ["x", "y"], 0.3).orderBy("item_id").collect()] == near.tolist()
    core, label = near >= 5, np.arange(len(x))
    for _ in range(len(x)):
        new = np.array([min([label[i], *label[core & (d[i] <= 0.3)]]) if core[i] else label[i] for i in range(len(x))])
        if (new == label).all():
            break
        label = new
    got = {r.item_id: r.cluster for r in density.dbscan(z, ["x", "y"], 0.3, 5).collect()}
    for i in range(len(x)):
        reach = [int(label[j]) for j in range(len(x)) if core[j] and d[i, j] <= 0.3]
        assert got[i] == (int(label[i]) if core[i] else min(reach) if reach else None)


def test_measures_by_hand(spark):
    a = spark.createDataFrame([(i, c) for i, c in enumerate([0, 0, 0, 1, 1, 1])], "item_id int, class int")
    b = spark.createDataFrame([(i, c) for i, c in enumerate([5, 5, 6, 6, 6, 6])], "item_id int, class int")
    r = M.agreement(a, b).first()
    # pairs together in both 4, in a 6, in b 7, of 15
    assert math.isclose(r.ari, (4 - 6 * 7 / 15) / ((6 + 7) / 2 - 6 * 7 / 15), abs_tol=1e-6) and math.isclose(r.purity, 5 / 6, abs_tol=1e-6)
    assert M.agreement(a, a).first().ari == 1.0
    assert math.isclose(M.f_tail(4.0, 2, 27), 0.0300, abs_tol=2e-4) and M.f_tail(0.0, 2, 3) == 1.0
    rows = spark.createDataFrame([(0, 1.0), (0, 2.0), (1, 4.0), (1, 6.0)], "class int, x double")
    f = M.anova(rows, ["x"]).first()
    assert math.isclose(f.f, (12.25 / 1) / (2.5 / 2), abs_tol=1e-4) and math.isclose(f.eta2, 12.25 / 14.75, abs_tol=1e-6)


def series_of(spark, shapes):
    return spark.createDataFrame(list(shapes.items()), "item_id int, series array<bigint>")


def plain_rules(x, w):
    """Every scheme of one series, by loops."""
    c, m, t_peak, out = sum(x), max(x), x.index(max(x)), {}
    cum = [sum(x[: t + 1]) for t in range(w)]
    k = max(1, round(10 * w / 25))
    out["delayed"] = "delayed" if c >= 30 and sum(x[:k]) <= 0.25 * c else "other"
    f = w / 16
    rise, late = sum(x[: max(1, round(3 * f))]) / c, sum(x[round(6 * f) : round(12 * f)]) / c
    out["rise"] = "early" if rise > 0.3 else "medium" if rise >= 0.15 else "delayed"
    out["decline"] = "rapid" if late < 0.3 else "slow" if late <= 0.5 else "none"
    r = round(sum(n * t for t, n in enumerate(x)) / c / (w - 1), 9)
    holds = {"sleeping": c > 25 and r > 0.7, "discovery": c > 50 and r < 0.4, "hot": c > 35 and r > 2 / 3}
    out["age"] = next((z for z in ("sleeping", "discovery", "hot") if holds[z]), "other")
    t25, t50, t75 = (next(t for t in range(w) if 4 * cum[t] >= q * c) for q in (1, 2, 3))
    out["half_life"] = (t25, t50, t75)
    out["own"] = "delayed" if t50 - t25 > t75 - t50 else "flash" if t50 - t25 < t75 - t50 else "normal"
    k = max(1, round(5 * w / 20))
    tops = [t for t in range(w) if x[t] > (x[t - 1] if t else -1) and x[t] >= (x[t + 1] if t + 1 < w else -1) and x[t] >= 0.75 * m]
    if all(x[t] >= x[t - 1] for t in range(1, w)):
        out["shape"] = "monotone_up"
    elif all(x[t] <= x[t - 1] for t in range(2, w)) and tops and tops[0] <= 1:
        out["shape"] = "monotone_down"
    elif len(tops) > 1:
        out["shape"] = "several"
    elif tops[0] <= k and sum(x[tops[0] + 1 :]) <= 0.5 * m * (w - 1 - tops[0]):
        out["shape"] = "initial"
    elif k < tops[0] < w - 1 and sum(x[:k]) / k <= 0.5 * m:
        out["shape"] = "late"
    else:
        out["shape"] = "other"
    out["beauty"] = sum(((m - x[0]) / t_peak * t + x[0] - x[t]) / max(1, x[t]) for t in range(t_peak + 1)) if t_peak else 0.0
    far = [round(abs((m - x[0]) * t - t_peak * x[t] + t_peak * x[0]) / math.sqrt((m - x[0]) ** 2 + t_peak**2 + 1e-12), 6) for t in range(t_peak + 1)]
    out["awake"] = far.index(max(far))
    deg = math.degrees(math.atan2(m, max(t_peak, 0.5)))
    out["angle"] = "smart" if deg > 60 else "sleeping" if deg < 30 else "between"
    high = next(t for t in range(w) if x[t] >= 0.75 * m)
    low = next((t for t in range(high + 1, w) if x[t] <= 0.5 * m), None)
    back = next((t for t in range(low + 1, w) if x[t] >= 0.75 * m), None) if low is not None else None
    asleep = sum(x[: w // 3]) <= 0.25 * c
    out["second"] = ("second_act_sleeper" if asleep else "second_act") if back is not None else "single_peak_sleeper" if asleep else "other"
    out["revived"] = (back is not None, back - low if back is not None else None)
    sleeps = sum(x[:5]) / 5 <= 1.0 and sum(x[5:10]) >= 4
    out["sleepers"] = "all_elements" if sleeps and not sum(x[:5]) else "sleeper" if sleeps else "other"
    tail = sum(x[w // 2 :]) / c
    out["transient"] = "sticky" if tail >= 0.2 else "transient" if t_peak <= 0.2 * w else "other"
    return out


#: Between them these reach every class of every scheme.
SHAPES = {
    1: [9, 7, 5, 3, 2, 1, 0, 0, 0, 0], 2: [0, 0, 1, 1, 2, 3, 4, 5, 6, 9], 3: [1, 0, 0, 0, 0, 0, 0, 0, 9, 2], 4: [0, 0, 0, 0, 0, 3, 3, 2, 1, 1], 5: [9, 1, 1, 1, 9, 1, 1, 9, 1, 1],
    6: [1, 1, 0, 1, 0, 20, 4, 30, 2, 30], 7: [1, 0, 0, 0, 0, 0, 0, 0, 0, 0], 8: [0, 1, 1, 0, 0, 3, 9, 3, 0, 40], 9: [30, 20, 5, 1, 1, 1, 0, 1, 0, 1], 10: [5] * 10, 11: [0, 0, 0, 0, 0, 0, 0, 0, 1, 0],
    12: [4, 9, 4, 4, 5, 4, 4, 5, 4, 4], 13: [2, 2, 2, 2, 9, 2, 2, 2, 2, 1], 14: [0, 0, 0, 4, 0, 0, 0, 0, 0, 0], 15: [3, 3, 3, 3, 3, 3, 5, 3, 3, 3], 16: [0, 1, 0, 1, 0, 9, 1, 9, 9, 9], 17: [10, 11, 10, 9, 9, 9, 9, 9, 9, 9],
    18: [0, 1, 0, 1, 0, 2, 4, 9, 9, 9], 19: [0, 2, 3, 4, 9, 12, 14, 9, 5, 1], 20: [9, 0, 0, 0, 0, 0, 0, 0, 1, 3],
}


def test_rules_against_loops(spark):
    """Hand-made series and random ones through every scheme, beside plain loops."""
    w, rng = 10, np.random.default_rng(4)
    shapes = SHAPES | {100 + i: (rng.integers(0, 12, w) * (rng.random(w) < 0.6)).tolist() for i in range(300)}
    shapes = {i: x for i, x in shapes.items() if sum(x)}
    want = {i: plain_rules(x, w) for i, x in shapes.items()}
    series = series_of(spark, shapes).cache()
    got = {
        "delayed": R.delayed_recognition(series, w), "age": R.age_ratio(series, w, 0.1), "own": R.half_life(series, "own"), "shape": R.peak_shape(series, w), "angle": R.angle(series),
        "second": R.second_act(series, w), "sleepers": R.sleepers(series, w), "transient": R.transient_sticky(series, w),
    }
    for name, df in got.items():
        mine = {r.item_id: r["class"] for r in df.collect()}
        assert mine == {i: x[name] for i, x in want.items()}, name
    classes = {"delayed": 2, "age": 4, "own": 3, "shape": 6, "angle": 3, "second": 4, "sleepers": 3, "transient": 3}
    assert {k: len({x[k] for x in want.values()}) for k in classes} == classes
    grid = {r.item_id: (r.rise, r.decline) for r in R.rise_decline(series, w).collect()}
    assert grid == {i: (x["rise"], x["decline"]) for i, x in want.items()} and len({a for a, _ in grid.values()}) == len({b for _, b in grid.values()}) == 3
    half = {r.item_id: r for r in R.half_life(series).collect()}
    assert {i: (r.t25, r.t50, r.t75) for i, r in half.items()} == {i: x["half_life"] for i, x in want.items()}
    lo, hi = np.percentile([x["half_life"][1] for x in want.values()], [25, 75])
    assert {i: r["class"] for i, r in half.items()} == {i: "flash" if x["half_life"][1] < lo else "delayed" if x["half_life"][1] > hi else "normal" for i, x in want.items()}
    assert all(math.isclose(r.beauty, want[r.item_id]["beauty"], abs_tol=1e-8) for r in R.beauty(series).collect())
    assert {r.item_id: r.t_awake for r in R.awakening(series).collect()} == {i: x["awake"] for i, x in want.items()}
    assert {r.item_id: (r.revived, r.quiet) for r in R.revival(series, w).collect()} == {i: x["revived"] for i, x in want.items()}
    x = np.array(list(shapes.values()), float)
    ratio = x / x.mean(0)
    assert {r.item_id: r.t_norm_peak for r in R.half_peak(series, w).collect()} == dict(zip(shapes, ratio.argmax(1).tolist()))
    var = np.cumsum(x, 1).var(0)
    h = np.polyfit(np.log(np.arange(1, w + 1)), np.log(var), 1)[0] / 2
    assert math.isclose(R.spread_exponent(series, w).first().h, h, abs_tol=1e-5)
    for r in R.poly_fit(series, w).filter("item_id < 10").collect():
        s = np.array(shapes[r.item_id], float)
        fit = np.polynomial.Polynomial.fit(np.arange(w), s, 5)(np.arange(w))
        assert math.isclose(r.r2, 1 - ((s - fit) ** 2).sum() / ((s - s.mean()) ** 2).sum(), abs_tol=1e-5)
    series.unpersist()


def test_thresholds_and_precedence_of_the_age_ratio(spark):
    """Printed thresholds as defaults; where two rules hold the order decides."""
    series = series_of(spark, {1: [0, 0, 0, 0, 100, 300], 2: [600, 10, 10, 0, 0, 0], 3: [0, 0, 0, 100, 0, 160], 4: [100, 10, 0, 0, 0, 0]})
    assert {r.item_id: r["class"] for r in R.age_ratio(series, 6).collect()} == {1: "sleeping", 2: "discovery", 3: "sleeping", 4: "other"}
    assert {r.item_id: r["class"] for r in R.age_ratio(series, 6, order=("hot", "sleeping", "discovery")).collect()} == {1: "hot", 2: "discovery", 3: "sleeping", 4: "other"}


def test_half_peak_tells_near_ties_apart(spark):
    """A later ratio larger by five millionths wins over an earlier one."""
    a, b = [1_000_000] + [0] * 18 + [1_000_010], [1_000_000] + [0] * 18 + [1_000_000]
    got = {r.item_id: r["class"] for r in R.half_peak(series_of(spark, {1: a, 2: b}), 20).collect()}
    assert got == {1: "delayed", 2: "hot"}


def test_exact_quantile(spark):
    rng = np.random.default_rng(5)
    x = np.concatenate([rng.lognormal(0, 3, 30_000), np.full(12_000, 1.5), [float("nan")] * 3])
    df = spark.createDataFrame([(float(v),) for v in x], "v double")
    for q in (0.0, 0.25, 0.5, 0.9, 1.0):
        assert math.isclose(exact_quantile(df, df["v"], q), np.quantile(x[~np.isnan(x)], q), rel_tol=1e-12)
    assert exact_quantile(df.limit(0), df["v"], 0.5) is None


def test_diffusion_recovers_its_parameters(spark):
    p, q, m, total, series = 0.03, 0.4, 20000.0, 0.0, []
    for _ in range(20):
        n = (p + q * total / m) * (m - total)
        series.append(round(n))
        total += round(n)
    r = R.diffusion(series_of(spark, {1: series})).first()
    assert math.isclose(r.p, p, rel_tol=0.02) and math.isclose(r.q, q, rel_tol=0.02) and math.isclose(r.m, m, rel_tol=0.02)


def test_scaling_guards_constant_columns(spark):
    df = spark.createDataFrame([(1, 5.0, 1.0), (2, 5.0, 3.0)], "item_id int, a double, b double")
    rows = scaling.scaled(df, scaling.fit_zscore(df, ["a", "b"])).orderBy("item_id").collect()
    assert [(r.a, r.b) for r in rows] == [(0.0, -1.0), (0.0, 1.0)]


def test_names_on_the_grid(spark):
    p = spark.createDataFrame([(0, 1.5, 2.2, 2.1), (1, 2.1, 4.4, 20.8), (2, 4.1, 25.5, 0.0), (3, 4.7, 16.1, 7.9)], "class int, t_init_mean double, t_grow_mean double, t_decay_mean double")
    assert [r.name for r in M.name_classes(p, 30).orderBy("class").collect()] == ["FLASH", "EARLY_TAIL", "CLIMBER", "LATE_WAVE"]


def test_nearest_items_equal_all_pairs(spark):
    """Random, crowded and evenly spaced points, with ties, equal vectors and rows that take no part."""
    from trajkit.operators.nearest import nearest

    rng = np.random.default_rng(3)
    x = np.concatenate([rng.normal(size=(150, 3)), np.zeros((40, 3)), rng.integers(0, 3, (150, 3)).astype(float), np.full((1, 3), 90.0)])
    rows = [(i, *map(float, v)) for i, v in enumerate(x)] + [(900, None, 1.0, 1.0), (901, float("nan"), 0.0, 0.0), (902, float("inf"), 0.0, 0.0)]
    schema = "item_id long, a double, b double, c double"
    away = np.round(np.sqrt(sum((x[:, None, j] - x[None, :, j]) ** 2 for j in range(3))), 9)
    want = {(i, int(j), away[i, j]) for i in range(len(x)) for j in [j for j in np.lexsort((np.arange(len(x)), away[i])) if j != i][:3]}
    for per_leaf in (4, 64, 10_000):
        got = nearest(spark.createDataFrame(rows, schema), ["a", "b", "c"], 3, per_leaf).collect()
        assert len(got) == len(want) and {(r["item_id"], r["similar"], r["dist"]) for r in got} == want
    assert nearest(spark.createDataFrame([], schema), ["a", "b", "c"]).count() == 0
    assert nearest(spark.createDataFrame(rows[:1], schema), ["a", "b", "c"]).count() == 0
    assert nearest(spark.createDataFrame(rows[:2], schema), ["a", "b", "c"]).count() == 2
