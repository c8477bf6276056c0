"""Queries that once made their rows up read a given table: with fewer rows in it, their result is another."""

import pytest

from telemetry_insight.operators import registry
from telemetry_insight.sources import carriers as C

READ = [
    "api_calls",
    "call_cost",
    "centroid_separation",
    "daily_volume",
    "generation_config",
    "gps_bytes_sensitivity",
    "ingest_projection",
    "intent_category",
    "intent_classify",
    "intent_scope",
    "intent_unknown",
    "label_profiles",
]


@pytest.fixture(scope="module")
def few(spark, data, tmp_path_factory):
    d = str(tmp_path_factory.mktemp("few"))
    for t, some in (("events", "event_id < 300"), ("documents", "doc_id < 20"), ("conversations", "conv_id = 0"), ("nation", "true"), ("region", "true")):
        C.table(spark, data, t).where(some).write.parquet(f"{d}/{t}.parquet")
    return d


@pytest.mark.parametrize("name", READ)
def test_reads_a_given_table(spark, data, few, name):
    q = registry.queries()[name]
    assert sorted(map(str, q(spark, data).collect())) != sorted(map(str, q(spark, few).collect()))
