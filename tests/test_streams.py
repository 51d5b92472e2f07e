"""Streams against their batch twins."""

import pytest

from dupflow import catalog


@pytest.mark.parametrize("name", ["st_tumbling", "st_ss_join", "st_filter_to_baf"])
def test_stream_equals_sql(same, name):
    same(catalog.QUERIES, catalog.ORACLES, name)


def test_stateful_marker_keeps_the_best(spark, sf):
    got = catalog.QUERIES["st_state_mark"](spark, sf).collect()
    events = spark.read.parquet(f"{sf}/events.parquet").selectExpr("user_id", "event_type", "event_id", "cast(round(value * 100) as bigint) score").collect()
    ids = {r["event_id"]: r for r in events}
    assert all((ids[r["kept"]]["user_id"], ids[r["kept"]]["event_type"]) == (r["user_id"], r["event_type"]) for r in got)
