"""Pages without an id are archived too."""

from telemetry_insight.llm import archives

ROW = "page_id long, url string, html string"


def test_pages_without_an_id(spark, tmp_path):
    rows = [(None, "a", "same"), (7, "b", "same"), (3, "c", "same"), (None, "d", "own"), (None, "e", "own"), (0, "f", "zero"), (None, "g", "zero"), (None, None, None)]
    spark.createDataFrame(rows, ROW).write.parquet(f"{tmp_path}/pages.parquet")
    got = sorted((r["page_id"] is None, r["page_id"] or 0, r["payload_bytes"], r["record_type"], -1 if r["refers_to"] is None else r["refers_to"]) for r in archives.op6_warc(spark, str(tmp_path)).collect())
    assert got == [
        (False, 0, 4, "response", -1), (False, 3, 4, "response", -1), (False, 7, 4, "revisit", 3),
        (True, 0, 0, "response", -1), (True, 0, 3, "response", -1), (True, 0, 3, "response", -1), (True, 0, 4, "revisit", 0), (True, 0, 4, "revisit", 3),
    ]
    assert archives.record_id(None, b"x") != archives.record_id(None, b"y")
