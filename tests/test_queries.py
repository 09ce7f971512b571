"""Every query with SQL against DuckDB, and every other one for rows, on the smallest tables."""

from __future__ import annotations

import pytest

from gradsift.catalog import QUERIES, SQL
from tests.helpers import SF, assert_equal

#: Trained for minutes in all; run once each by the experiments' own tests.
SLOW = {n for n in QUERIES if n.startswith("exp_") and n.endswith("_trained")}


@pytest.mark.parametrize("name", sorted(SQL))
def test_sql(spark, name):
    assert_equal(spark, QUERIES[name], SQL[name])


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(SQL) - SLOW))
def test_rows(spark, name):
    assert QUERIES[name](spark, SF).count() > 0


def test_vector_search_takes_every_twentieth_vector(spark):
    probes = {r.probe for r in QUERIES["nl_cosine_twentieth"](spark, SF).select("probe").distinct().collect()}
    assert probes == set(range(0, 500, 20))
