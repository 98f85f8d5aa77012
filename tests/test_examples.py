"""The examples follow the given tables: a row for each user, and other rows for other tables."""

import pytest

from cadenza.plans import catalogue
from cadenza.sources.series import event_walk
from tests.duck import duck, same


@pytest.mark.parametrize("name", ["example_smoothing", "example_stretch", "safety_counterexample"])
def test_examples_read_events(spark, sf_small, name):
    df = catalogue.queries()[name](spark, sf_small)
    assert same(df, duck(sf_small).sql(catalogue.oracle_sql()[name]))
    assert {r.series_id for r in df.collect()} == {r.series_id for r in event_walk(spark, sf_small).df.collect()}
