"""Queries against their SQL twins on the smallest tables."""

import pytest

from telemetry_insight.operators import registry
from tests.helpers import same

SQL = registry.oracle_sql()
SLOW = {n for n in SQL if n.startswith(("stream_", "lake_", "json_", "scan_json")) or n in {"replay_stream", "buffered_ingest", "sink_upsert"}}


@pytest.mark.parametrize("name", sorted(set(SQL) - SLOW))
def test_twin(spark, data, twin, name):
    same(registry.queries()[name](spark, data), *twin(SQL[name]))


@pytest.mark.parametrize("name", ["stream_dedup", "stream_restart", "streaming_summary", "lake_write"])
def test_streams_and_lake(spark, data, twin, name):
    same(registry.queries()[name](spark, data), *twin(SQL[name]))
