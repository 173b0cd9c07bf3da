"""Every query that has a SQL twin equals it on the smallest tables; the others run."""

import pytest

from tests.oracle import assert_same, connect
from textgroups import queries as methods


@pytest.fixture(scope="module")
def con(small):
    return connect(small)


@pytest.mark.parametrize("name", sorted(methods.oracle_sql()))
def test_query_equals_sql(spark, small, con, name):
    assert_same(methods.queries()[name](spark, small), con, methods.oracle_sql()[name])


SLOW = {"micro_policies", "micro_sweep", "rss_compare", "nmf_labels", "bisecting_k", "bestseed_oversample", "mllib_kmeans_labels", "mllib_bisecting_labels"}


@pytest.mark.parametrize("name", sorted(set(methods.queries()) - set(methods.oracle_sql()) - SLOW))
def test_query_runs(spark, small, name):
    assert methods.queries()[name](spark, small).limit(5).collect()
