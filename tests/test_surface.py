"""Surface operators over all users, against loops over a few events of users with small and large ids."""

import datetime as dt

import pytest

from cadenza.plans import surface

BEGIN = dt.datetime(2024, 1, 1, tzinfo=dt.timezone.utc)
EVENTS = [(k, user, BEGIN + dt.timedelta(minutes=(k * 37 + user * 11) % 600), float(k * 7 % 23)) for k, user in enumerate([3, 25, 29, 1000, 1499] * 12)]


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    at = str(tmp_path_factory.mktemp("surface"))
    spark.createDataFrame(EVENTS, "event_id long, user_id long, ts timestamp, value double").write.parquet(f"{at}/events.parquet")
    return at


def micros(t):
    return (t - BEGIN) // dt.timedelta(microseconds=1)


def test_asof_fill_has_all_users(spark, folder):
    want = {}
    for user in {u for _, u, _, _ in EVENTS}:
        own = sorted((micros(t), e, v) for e, u, t, v in EVENTS if u == user)
        first, last = own[0][0], own[-1][0]
        for slot in range(13):
            want[user, slot] = [v for t, _, v in own if t <= first + slot * (last - first) // 12][-1]
    assert {(r.user_id, r.slot): r.value for r in surface.asof_fill(spark, folder).collect()} == want


def test_interval_join_has_all_users(spark, folder):
    want = sorted((a, b) for a, u, s, _ in EVENTS for b, v, t, _ in EVENTS if u == v and dt.timedelta(0) < t - s <= dt.timedelta(hours=1))
    assert sorted((r.a, r.b) for r in surface.interval_join(spark, folder).collect()) == want


def test_spine_has_a_row_for_each_event(spark, folder):
    """Before, the spine's 16 rows came from no table."""
    got = sorted((r.user_id, r.pos, r.remaining) for r in surface.udtf_spine(spark, folder).collect())
    assert got == sorted((u, k, 11 - k) for u in {u for _, u, _, _ in EVENTS} for k in range(12))
