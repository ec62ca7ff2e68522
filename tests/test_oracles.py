"""Registered queries against their SQL on the smallest tables."""

from __future__ import annotations

import pytest

from eventpulse.plans import burst_queries, cluster_queries, comparison_queries, relational, stream_queries
from tests.oracle import connect, rows

MODULES = (burst_queries, cluster_queries, comparison_queries, relational)
NAMES = [(m, k) for m in MODULES for k in m.ORACLES] + [(stream_queries, k) for k in ("M_K19_burst_stream", "M_C19_cluster_stream", "S_5_block_source", "G_4_late_rows", "G_10_restart")]


@pytest.fixture(scope="module")
def con(small):
    return connect(small)


@pytest.mark.parametrize(("module", "name"), NAMES, ids=[k for _, k in NAMES])
def test_query_equals_sql(spark, small, con, module, name):
    got = module.QUERIES[name](spark, small).toPandas()
    want = con.sql(module.ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


def test_every_oracle_has_a_query():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())


def test_entry_has_rows(spark):
    import __spark_entry__ as e

    assert e.entry(spark).columns == ["region", "block_no", "word", "cnt", "tfidf", "prev_tfidf", "rate", "reason"]
