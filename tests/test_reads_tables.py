"""Queries that once made their data up follow the given table."""

import pytest
from pyspark.sql import functions as F

from quorumlab.plans import queries
from quorumlab.sources import tables

NAMES = [
    "bound_equal_steps", "bound_homogeneous", "bound_table", "expected_counts_grid", "expected_first_step", "histogram_of_one_round", "means_against_formulas", "monotone_grid", "stage_plan",
    "step_size_table", "two_shapes", "uploads_over_settings",
]


@pytest.fixture(scope="module")
def changed(spark, small, tmp_path_factory):
    """Twice the events, with other durations."""
    e = tables.table(spark, small, "events")
    both = e.unionByName(e.withColumn("event_id", F.col("event_id") + e.count()))
    out = tmp_path_factory.mktemp("changed")
    both.withColumn("value", F.col("value") * (1 + F.col("event_id") % 7)).write.parquet(str(out / "events.parquet"))
    return str(out)


@pytest.mark.parametrize("name", NAMES)
def test_result_follows_the_table(spark, small, changed, name):
    f = queries.queries()[name]
    assert sorted(map(str, f(spark, changed).collect())) != sorted(map(str, f(spark, small).collect()))
