"""Queries whose answers are to come from a given table, not from the query itself."""

import pytest

from wdsum.catalogue import QUERIES

NAMES = ("choose_bits", "dense_variance", "logbucket_cellprob", "metric_memory", "metric_theory", "range_bounds", "stream_rate", "udtf_values")


@pytest.mark.parametrize("name", NAMES)
def test_answers_follow_the_table(spark, name):
    small, large = (sorted(map(str, QUERIES[name](spark, f"/root/testdata/{sf}").collect())) for sf in ("sf0.001", "sf0.01"))
    assert small and small != large
