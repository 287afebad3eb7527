"""Every registered query against its DuckDB text; streams against batches."""

from __future__ import annotations

import pytest

from nodeflux import user_queries  # noqa: F401
from nodeflux.queries import ORACLES, QUERIES
from tests.compare import assert_same

ROWS_ONLY = sorted(set(QUERIES) - set(ORACLES))


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_equals_oracle(spark, sf, name):
    assert_same(QUERIES[name](spark, sf), ORACLES[name], sf)


@pytest.mark.parametrize("name", ROWS_ONLY)
def test_query_runs(spark, sf, name):
    assert QUERIES[name](spark, sf).count() > 0


def test_late_events_are_dropped_and_a_watch_list_is_refreshed(spark, sf):
    from nodeflux.functions.params import Params
    from nodeflux.streaming import activity as st

    seen = []
    asked = spark.createDataFrame([(0, "u:1"), (1, "u:2")], "qid int, key string")
    query = st.watch(st.read_events(spark, sf), asked, Params(c=0.5), lambda df, n: seen.append((n, df.count())), theta=1e-2)
    query.awaitTermination()
    assert seen and seen[-1][1] >= 1
