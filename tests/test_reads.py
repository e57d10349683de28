"""Results and inputs stay with Spark: nothing that grows is held or made up on the driver."""

from __future__ import annotations

import pytest

from test_queries import CORE


def test_distinct_events_are_counted_from_files(spark, sf):
    """Events that arrive once are written by executors, not gathered in the driver's memory."""
    got = CORE.QUERIES["stream_distinct_events"](spark, sf)
    assert got.inputFiles()
    assert spark.conf.get("spark.sql.streaming.stateStore.providerClass").endswith("HDFSBackedStateStoreProvider")


@pytest.mark.parametrize("name", [
    "bounds_of_training",
    "bounds_table",
    "cross_grid",
    "layer_policy",
    "lq_sign_zero",
    "lq_zero_vector",
    "omega_length_bound",
    "omega_lengths",
    "omega_strings",
    "skip_policy_share",
])
def test_query_reads_a_table(spark, sf, name):
    assert any("sf0.001" in f for f in CORE.QUERIES[name](spark, sf).inputFiles())
