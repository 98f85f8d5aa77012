"""Joins and searches by classes of copies, on tables whose rows are repeated with other keys, against SQL and brute force."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from cadenza.functions import transforms as T
from cadenza.model import SeriesRelation
from cadenza.operators import copies, joins, kindex, neighbours, spectrum
from cadenza.plans import catalogue, workloads
from tests.duck import duck, same

KEYS = {"supplier": ["s_suppkey"], "lineitem": ["l_suppkey"], "events": ["event_id", "user_id"], "documents": ["doc_id"], "embeddings": ["vec_id"], "part": []}


@pytest.fixture(scope="module")
def repeated(sf_small, tmp_path_factory):
    at = str(tmp_path_factory.mktemp("repeated"))
    for name, keys in KEYS.items():
        moved = ", ".join(f"CAST({k} + r * 1000000 AS BIGINT) AS {k}" for k in keys)
        some = " WHERE vec_id < 60" if name == "embeddings" else ""
        duckdb.connect().execute(f"COPY (SELECT t.*{f' REPLACE ({moved})' if keys else ''} FROM '{sf_small}/{name}.parquet' t, (SELECT unnest(range({3 if keys else 1})) AS r){some}) TO '{at}/{name}.parquet'")
    return at


@pytest.mark.parametrize("name", ["join_d_index_mavg", "join_documents", "join_rect_unsafe", "surface_semi_anti", "knn_join", "join_a_full", "surface_setops", "lemma_joins_no_dismissals"])
def test_repeated_rows(spark, repeated, name):
    assert same(catalogue.queries()[name](spark, repeated), duck(repeated).sql(catalogue.oracle_sql()[name]))


def test_rows_grow_with_copies_and_not_with_their_square(spark, sf_small, repeated):
    """Three copies of all are two further members for each series, beside the same links."""
    once, thrice = (catalogue.queries()["join_d_index_mavg"](spark, at).groupBy("kind").count().collect() for at in (sf_small, repeated))
    once, thrice = ({r["kind"]: r["count"] for r in rows} for rows in (once, thrice))
    assert once.get("link") == thrice.get("link") and thrice["copy"] == 2 * workloads.index_of(spark, sf_small, "supplier_walk").features.count()


def test_timed_methods_count_all_pairs(spark, repeated):
    ix = workloads.index_of(spark, repeated, "supplier_walk")
    t = T.moving_average(ix.n, 20)
    got = {r.method: r.answers for r in workloads.timed_methods(spark, repeated).collect()}
    assert got["a"] == got["b"] == joins.scan_join(ix, t, 3.3, True).count() > 0
    assert got["c"] == joins.index_nested_loop(ix, None, 3.3).count() and got["d"] == joins.index_nested_loop(ix, t, 3.3).count()


def walks(spark, count=1500, n=32):
    x = np.random.default_rng(5).normal(size=(count, n)).cumsum(axis=1)
    x[1::3] = x[::3] + 0.02 * x[1::3]
    rows = [(i, n, v.tolist()) for i, v in enumerate(x)]
    return SeriesRelation(spark.createDataFrame(rows, "series_id long, n int, values array<double>"), n), x


def brute(x, t, other=None):
    z = (x - x.mean(axis=1, keepdims=True)) / x.std(axis=1, keepdims=True)
    a, b = (np.array([s.on_values(v) for v in z]).real for s in (t, other or t))
    return np.sqrt(np.square(a[:, None] - b[None]).sum(axis=2))


def test_scan_and_cells_over_several_blocks(spark):
    r, x = walks(spark)
    ix, t, eps = kindex.build(r), T.moving_average(32, 5), 1.0
    d = brute(x, t)
    want = {(i, j) for i, j in zip(*np.nonzero(d <= eps)) if i < j}
    for found in (joins.scan_join(ix, t, eps, False), joins.scan_join(ix, t, eps, True), joins.cell_join(spectrum.normal_dft(r), 32, t, eps)):
        rows = found.collect()
        assert len(rows) == len(want) and {(q.id_l, q.id_r) for q in rows} == want
        assert max(abs(q.dist - d[q.id_l, q.id_r]) for q in rows) < 1e-9
    one = T.identity(32)
    got = [(q.id_l, q.id_r) for q in joins.scan_join(ix, one, eps, True, t).collect()]
    want = {(i, j) for i, j in zip(*np.nonzero(brute(x, one, t) <= eps)) if i != j}
    assert len(got) == len(want) and set(got) == want


def test_nearest_join_takes_few_candidates(spark):
    r, x = walks(spark, 300)
    ix = kindex.build(r, leaf_rows=16)
    got = {(q.id_l, q["rank"]): q.id_r for q in neighbours.join_nearest(ix, ix, None, 3, distinct_ids=True).collect()}
    d = brute(x, T.identity(32))
    np.fill_diagonal(d, np.inf)
    assert got == {(i, k + 1): j for i in range(300) for k, j in enumerate(np.argsort(d[i], kind="stable")[:3])}


def test_two_of_each_class(spark):
    r, _ = walks(spark, 6)
    more = SeriesRelation(r.df.select(F.explode(F.array(*(F.lit(1000 * k) for k in range(1, 4)))).alias("k"), "*").select((F.col("series_id") + F.col("k")).alias("series_id"), "n", "values"), 32)
    of = copies.members(more)
    assert {(q.series_id, q.class_id) for q in of.collect()} == {(i + 1000 * k, i + 1000) for i in range(6) for k in range(1, 4)}
    assert sorted(q.series_id for q in copies.few(more, of, 2).df.collect()) == [*range(1000, 1006), *range(2000, 2006)]


def shuffled_rows(df):
    """Rows that all shuffles of a plan wrote, once it has run."""
    plan = df._jdf.queryExecution().executedPlan()
    count, todo = 0, [plan.finalPhysicalPlan() if plan.getClass().getSimpleName() == "AdaptiveSparkPlanExec" else plan]
    while todo:
        node = todo.pop()
        name = node.getClass().getSimpleName()
        if name.endswith("QueryStageExec"):
            todo.append(node.plan())
            continue
        if name == "ShuffleExchangeExec":
            count += node.metrics().apply("shuffleRecordsWritten").value()
        todo += [node.children().apply(i) for i in range(node.children().size())]
    return count


@pytest.mark.parametrize("join", [lambda ix, t: joins.index_nested_loop(ix, t, 3.0), lambda ix, t: joins.self_join(ix, t, 3.0)])
def test_no_pair_is_shuffled_before_it_is_an_answer(spark, join):
    """Most pairs are near in two coefficients here; only series and what to compare go to other tasks."""
    r, _ = walks(spark, 600)
    df = join(kindex.build(r), T.moving_average(32, 5))
    pairs = len(df.collect())
    assert pairs > 12_000 and shuffled_rows(df) < 12_000


def test_pairs_by_products_are_those_by_differences():
    rng = np.random.default_rng(2)
    x = rng.normal(size=(400, 18)) * 1000
    x[200:] = x[:200] + rng.normal(size=(200, 18)) * np.logspace(-9, 3, 200)[:, None]
    d = np.sqrt(np.square(x[:, None] - x[None]).sum(axis=2))
    for eps in (1e-6, 1.0, d[3, 203], 4000.0, rng.uniform(0, 5000, 400)):
        for first in (None, [0, 1]):
            i, j, dist = joins.within(x, x, eps, first)
            assert {*zip(i.tolist(), j.tolist())} == {*zip(*(c.tolist() for c in np.nonzero(d <= np.reshape(eps, (-1, 1)))))}
            assert np.abs(dist - d[i, j]).max() < 1e-5 and np.abs(dist - d[i, j])[d[i, j] < 1].max() < 1e-9


def test_pairs_of_two_joins_that_differ(spark):
    """Counts of what only one of two sets has; and where they are the same, no pair of either is shuffled."""
    pairs = lambda rows: spark.createDataFrame(rows, "id_l long, id_r long")
    all_of = [(i, j) for i in range(40) for j in range(i + 1, 40)]
    assert workloads.differing(lambda: pairs(all_of), lambda: pairs(all_of[::-1])) == (0, 0)
    assert workloads.differing(lambda: pairs(all_of), lambda: pairs([*all_of[7:], (50, 51), (0, 99)])) == (7, 2)
    assert workloads.differing(lambda: pairs(all_of[:0]), lambda: pairs(all_of)) == (0, len(all_of))
