"""Safety verdicts follow the given tables: each is held against all users' series."""

import duckdb
import pytest

from cadenza.plans import catalogue
from cadenza.sources.series import event_walk
from tests.duck import duck, same


def verdicts(spark, at):
    df = catalogue.queries()["safety_verdicts"](spark, at)
    assert same(df, duck(at).sql(catalogue.oracle_sql()["safety_verdicts"]))
    return df.collect()


def test_verdicts_hold_for_all_users(spark, sf):
    rows = verdicts(spark, sf)
    assert len(rows) == 27 and {r.series for r in rows} == {event_walk(spark, sf).df.count()}
    assert all((r.escaped == 0) == r.safe for r in rows)


ODD = {
    "none": "SELECT * FROM e WHERE false",
    "nulls": "SELECT * REPLACE (NULL AS user_id) FROM e",
    "one user": "SELECT * FROM e WHERE user_id = (SELECT min(user_id) FROM e)",
    "constant and single events": "SELECT * REPLACE (CASE WHEN user_id % 3 = 0 THEN 50.0 ELSE value END AS value) FROM e QUALIFY user_id % 3 <> 1 OR row_number() OVER (PARTITION BY user_id ORDER BY event_id) = 1",
    "not finite": "SELECT * REPLACE (CASE user_id % 4 WHEN 0 THEN 'nan'::DOUBLE WHEN 1 THEN 'inf'::DOUBLE ELSE value END AS value) FROM e",
    "copies": "SELECT * REPLACE (user_id + 1000 * k AS user_id) FROM e, (SELECT unnest(range(3)) AS k)",
}


@pytest.mark.parametrize("kind", ODD)
def test_odd_events(spark, sf_small, tmp_path, kind):
    duckdb.sql(f"COPY (WITH e AS (SELECT * FROM '{sf_small}/events.parquet') {ODD[kind]}) TO '{tmp_path}/events.parquet'")
    rows = verdicts(spark, str(tmp_path))
    assert len(rows) == 27 and all(r.escaped == 0 for r in rows if r.safe) and all(r.escaped <= r.series for r in rows)
    assert (kind in ("none", "nulls")) == all(r.series == 0 for r in rows)
