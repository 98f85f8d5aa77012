import math
import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from cadenza.functions import arrays as A
from cadenza.functions import geometry as G
from cadenza.functions import transforms as T
from cadenza.functions.safety import is_safe
from cadenza.model import SeriesRelation
from cadenza.operators import dissimilarity, joins, kindex, measures, neighbours, range_search, spectrum
from cadenza.plans import planner
from cadenza.sources import series as S
from cadenza.streaming import windows


@pytest.mark.parametrize("n", [8, 9, 64])
def test_transform_identities(n):
    rng = np.random.default_rng(n)
    x, w = rng.normal(size=n), rng.normal(size=5)
    circular = np.array([sum(w[j] * x[(i - j) % n] for j in range(5)) for i in range(n)])
    assert np.allclose(T.kernel(n, w).on_values(x), circular)
    assert np.isclose((x**2).sum(), (np.abs(T.dft(x)) ** 2).sum())
    assert np.allclose(T.stretch(n, 3).on_values(x), np.repeat(x, 3))
    assert np.allclose(T.moving_average(n, 3, "center").on_values(x), (np.roll(x, 1) + x + np.roll(x, -1)) / 3)
    assert np.allclose(T.normalizer(n, x.mean(), x.std()).on_values(x), (x - x.mean()) / x.std())
    both = T.scale(n, 2.0) @ T.shift(n, 1.0) @ T.moving_average(n, 3)
    assert np.allclose(both.on_values(x), 2 * (T.moving_average(n, 3).on_values(x) + 1))
    assert np.allclose(T.moving_average(n, 3).power(2).on_values(x), T.moving_average(n, 3).on_values(T.moving_average(n, 3).on_values(x)))
    assert all(t.keeps_real for t in (both, T.stretch(n, 2), T.trend(n, 4), T.smooth_center(n, 5)))
    assert (T.scale(n, 2.0).with_cost(1) @ T.reverse(n).with_cost(2)).cost == 3
    with pytest.raises(ValueError):
        T.moving_average(n, 3).on_values(x[:-1])


def test_multiplier_is_not_normalised():
    a, b = np.array([36, 38, 40, 38, 42, 38, 36, 36, 37, 38, 39, 38, 40, 38, 37.0]), np.array([40, 37, 37, 42, 41, 35, 40, 35, 34, 42, 38, 35, 45, 36, 34.0])
    t = T.moving_average(15, 3)
    assert round(float(np.linalg.norm(a - b)), 2) == 11.92
    assert round(float(np.linalg.norm(t.on_values(a) - t.on_values(b))), 2) == 0.47


def test_safety_rules():
    mavg, shift = T.moving_average(16, 4), T.shift(16, 1.0)
    assert is_safe(mavg, "polar").safe and not is_safe(mavg, "rect").safe
    assert is_safe(shift, "rect").safe and not is_safe(shift, "polar").safe
    assert is_safe(T.reverse(16), "real").safe and not is_safe(mavg, "real").safe
    with pytest.raises(ValueError):
        is_safe(mavg, "round")


@settings(max_examples=200, deadline=None)
@given(st.floats(-7, 7), st.floats(0, 6.2), st.floats(-7, 7), st.floats(0, 6.2))
def test_arcs_meet_as_sampled(a, wa, b, wb):
    inside = lambda x, s, w: (x - s) % G.TURN <= w + 1e-7
    sampled = any(inside(a + wa * k / 400, b, wb) for k in range(401)) or any(inside(b + wb * k / 400, a, wa) for k in range(401))
    got = G.arcs_meet_np(a, wa, b, wb)
    assert got or not sampled


def test_arcs_as_columns_equal_numbers(spark):
    rng = random.Random(5)
    rows = [(rng.uniform(-7, 7), rng.uniform(0, 6.3), rng.uniform(-7, 7), rng.uniform(0, 6.3)) for _ in range(500)] + [(math.pi, 0.0, -math.pi, 0.0)]
    df = spark.createDataFrame(rows, "a double, wa double, b double, wb double")
    for r in df.withColumn("m", G.arcs_meet(*map(F.col, ("a", "wa", "b", "wb")))).collect():
        assert r.m == G.arcs_meet_np(r.a, r.wa, r.b, r.wb)


@settings(max_examples=200, deadline=None)
@given(st.complex_numbers(max_magnitude=10), st.floats(0.01, 12), st.floats(0, 1), st.floats(-math.pi, math.pi))
def test_search_axis_holds_the_disc(q, reach, part, angle):
    x = q + part * reach * complex(math.cos(angle), math.sin(angle))
    polar, rect = G.search_axis(q, reach, "polar"), G.search_axis(q, reach, "rect")
    assert rect.re[0] - 1e-9 <= x.real <= rect.re[1] + 1e-9 and rect.im[0] - 1e-9 <= x.imag <= rect.im[1] + 1e-9
    assert polar.magnitude[0] - 1e-9 <= abs(x) <= polar.magnitude[1] + 1e-9
    if polar.arc and abs(x) > 1e-9:
        assert G.arcs_meet_np(math.atan2(x.imag, x.real), 1e-7, *polar.arc)


def walks(spark, n=32, count=60, seed=3):
    rng = np.random.default_rng(seed)
    v = rng.normal(size=(count, n)).cumsum(axis=1)
    return SeriesRelation(spark.createDataFrame([(i, n, x.tolist()) for i, x in enumerate(v)], "series_id long, n int, values array<double>"), n), v


def norm(x):
    return (x - x.mean()) / x.std()


def test_range_search_equals_brute_force_in_all_spaces(spark):
    r, v = walks(spark)
    z = np.array([norm(x) for x in v])
    for space, k, t in (("polar", 1, T.moving_average(32, 5)), ("polar", 3, T.kernel(32, [0.25] * 16)), ("polar", 2, T.reverse(32)), ("rect", 2, T.scale(32, -0.7)), ("rect", 2, T.shift(32, 0.3))):
        ix = kindex.build(r, k, space, leaf_rows=4)
        for qid, eps in ((0, 3.0), (5, 6.5)):
            d = [np.linalg.norm(t.on_values(x) - z[qid]) for x in z]
            want = {i for i, x in enumerate(d) if x <= eps}
            for options in ({}, {"mirror": False}, {"push_bounds": False}, {"strategy": "auto"}, {"strategy": "scan"}):
                got = {x.series_id: x.dist for x in range_search.search(ix, v[qid], t, eps, **options).collect()}
                assert set(got) == want, (space, t.name, options)
                assert all(abs(got[i] - d[i]) < 1e-9 for i in got)


def test_zero_multipliers_and_wide_thresholds(spark):
    r, v = walks(spark)
    ix = kindex.build(r, leaf_rows=4)
    t = T.moving_average(32, 16)  # zero at even coefficients
    assert abs(t.a[2]) < 1e-12
    assert range_search.search(ix, v[1], t, 50.0).count() == 60
    assert [x.series_id for x in range_search.search(ix, v[1], None, 1e-6).collect()] == [1]
    with pytest.raises(ValueError):
        range_search.search(ix, v[1][:-1], t, 1.0)
    with pytest.raises(ValueError):
        range_search.search(ix, np.ones(32), t, 1.0)


def test_pushed_bounds_reach_the_scan(spark, tmp_path):
    r, v = walks(spark)
    kindex.build(r, leaf_rows=4).save(str(tmp_path / "index"))
    ix = kindex.open_index(spark, str(tmp_path / "index"))
    plan = planner.plan_search(ix, v[1], T.moving_average(32, 5), 1.0)
    text = range_search.candidates(ix, plan)._jdf.queryExecution().toString()
    assert "PushedFilters" in text and "GreaterThanOrEqual(m1" in text
    assert {x.series_id for x in range_search.search(ix, v[1], None, 4.0).collect()} == {i for i, x in enumerate(v) if np.linalg.norm(norm(x) - norm(v[1])) <= 4.0}
    assert "strategy" in range_search.explain(ix, v[1], None, 4.0)


def test_append_keeps_answers_whole(spark):
    r, v = walks(spark)
    ix = kindex.append(kindex.build(r.where("series_id < 50"), leaf_rows=4), r.where("series_id >= 50"))
    want = {i for i, x in enumerate(v) if np.linalg.norm(norm(x) - norm(v[1])) <= 6.0}
    assert {x.series_id for x in range_search.search(ix, v[1], None, 6.0).collect()} == want


def test_joins_agree_and_ties_of_neighbours(spark):
    r, v = walks(spark, count=40)
    ix = kindex.build(r, leaf_rows=4)
    t = T.moving_average(32, 5)
    z = np.array([t.on_values(norm(x)) for x in v])
    want = {(i, j) for i in range(40) for j in range(i + 1, 40) if np.linalg.norm(z[i] - z[j]) <= 3.0}
    pairs = lambda df: {(x.id_l, x.id_r) for x in df.collect()}
    assert pairs(joins.self_join(ix, t, 3.0)) == pairs(joins.scan_join(ix, t, 3.0, True)) == pairs(joins.grid_join(ix, ix, t, t, 3.0, True)) == want
    assert pairs(joins.index_nested_loop(ix, t, 3.0)) == want | {(j, i) for i, j in want} == pairs(joins.self_join(ix, t, 3.0, "ordered"))
    for bound in ("features", "mindist"):
        got = [x.series_id for x in neighbours.search_nearest(ix, v[2], t, 6, True, bound).collect()]
        assert got == sorted(range(40), key=lambda i: (np.linalg.norm(z[i] - z[2]), i))[:6]
    assert neighbours.search_nearest(ix, v[2], t, 100, True).count() == 40


def test_dissimilarity_equals_enumeration(spark):
    r, v = walks(spark, n=16, count=5)
    catalog = [T.moving_average(16, 3).with_cost(0.3), T.reverse(16).with_cost(0.5)]
    ids = r.df.select("series_id")
    pairs = ids.select(F.col("series_id").alias("id_l")).crossJoin(ids.select(F.col("series_id").alias("id_r"))).where("id_l < id_r")
    for x in dissimilarity.bounded(r, pairs, catalog).collect():
        assert abs(x.dist - dissimilarity.exhaustive_np(norm(v[x.id_l]), norm(v[x.id_r]), catalog, 2)) < 1e-9


def test_dissimilarity_with_translations_tries_each_order(spark):
    r, v = walks(spark, n=16, count=6)
    catalog = [T.shift(16, 4.0).with_cost(0.3), T.scale(16, 0.5).with_cost(0.5), T.moving_average(16, 3).with_cost(0.4)]
    assert {t.name for t in dissimilarity.closure(catalog[:2], 1.0, 2)} == {"identity", "shift(4)", "scale(0.5)", "shift(4)+shift(4)", "shift(4)+scale(0.5)", "scale(0.5)+shift(4)", "scale(0.5)+scale(0.5)"}
    assert len(dissimilarity.closure(catalog[:2], 0.7, 2)) == 4
    ids = r.df.select("series_id")
    pairs = ids.select(F.col("series_id").alias("id_l")).crossJoin(ids.select(F.col("series_id").alias("id_r"))).where("id_l < id_r")
    for normal in (True, False):
        form = norm if normal else np.array
        found = dissimilarity.bounded(r, pairs, catalog, normal=normal).collect()
        assert len(found) == 15
        for x in found:
            assert abs(x.dist - dissimilarity.exhaustive_np(form(v[x.id_l]), form(v[x.id_r]), catalog, 2)) < 1e-9
    # with a ratio no more is spent than that part of the plain distance
    plain = {(i, j): float(np.linalg.norm(np.array(v[i]) - np.array(v[j]))) for i in range(6) for j in range(6)}
    limited = dissimilarity.bounded(r, pairs, catalog, normal=False, ratio=0.01).collect()
    assert all(x.cost <= 0.01 * plain[x.id_l, x.id_r] + 1e-9 for x in limited) and len(limited) == 15


def test_odd_lengths_constants_gaps_and_empty_relations(spark):
    rows = [(1, p, float(x)) for p, x in enumerate([1, 5, 2, 8, 3])] + [(2, p, 4.0) for p in range(5)] + [(3, p, 1.0) for p in range(4)] + [(4, p, None if p == 2 else 1.0) for p in range(5)] + [(5, p, float("nan") if p == 0 else 1.0) for p in range(5)]
    r = SeriesRelation.from_long(spark.createDataFrame(rows, "series_id long, pos int, value double"), 5)
    assert sorted(x.series_id for x in r.df.collect()) == [1, 2]
    assert [x.series_id for x in spectrum.rejected(r).collect()] == [2]
    back = spectrum.idft(spectrum.dft(r), 5).where("series_id = 1").first().values
    assert np.allclose(back, [1, 5, 2, 8, 3])
    empty = kindex.build(r.where("series_id = 99"))
    assert range_search.search(empty, [1, 5, 2, 8, 3], None, 9.0).count() == 0 and joins.self_join(empty, None, 9.0).count() == 0


def test_energy_sits_in_few_coefficients_of_walks(spark, sf):
    share = lambda name: measures.energy_share(S.RELATIONS[name](spark, sf), 2).first().share
    assert share("supplier_walk") > 0.5 > 0.1 > share("supplier_level")


def test_sliding_coefficients_follow_the_window():
    rng = np.random.default_rng(0)
    v = rng.normal(size=500)
    x, w = windows._direct(v[:32]), v[:32]
    for new in v[32:]:
        x = windows._advance(w, x, new)
        w = np.append(w[1:], new)
    assert np.allclose(x, windows._direct(w))


def test_series_files_and_functions(spark, tmp_path):
    r, v = walks(spark, n=8, count=3)
    r.long().write.option("header", True).csv(str(tmp_path / "csv"))
    again = SeriesRelation.from_long(S.read_long(spark, str(tmp_path / "csv"), "csv", header=True), 8)
    assert np.allclose(again.one(1), v[1])
    S.write_series(r, str(tmp_path / "p"))
    assert spark.read.parquet(str(tmp_path / "p")).count() == 3
    df = spark.createDataFrame([([1.0, 2.0, 3.0],)], "v array<double>").select(A.cityblock(F.col("v"), F.reverse("v")).alias("c"), A.energy(F.col("v")).alias("e"), A.stretch(F.col("v"), 2).alias("s"))
    assert tuple(df.first()) == (4.0, 14.0, [1, 1, 2, 2, 3, 3])
