"""Streams whose results must not be gathered in the driver."""

from erblock import registry


def test_sessions_come_from_files_and_the_last_ones_too(spark, tmp_path):
    """Sessions by hand, one of them open when the events end, and one of no user."""
    rows = [(1, "10:00:00", 7), (2, "10:29:59", 7), (3, "10:59:59", 7), (4, "10:00:00", None), (5, "23:59:59", 8)]
    spark.createDataFrame(rows, "event_id long, t string, user_id long").selectExpr(
        "event_id", "CAST('2024-01-01 ' || t AS timestamp_ntz) AS ts", "user_id", "'click' AS event_type", "1.0D AS value", "'{}' AS props"
    ).coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    found = registry.QUERIES["sm_session_users"](spark, str(tmp_path))
    assert sorted((x.user_id or 0, str(x.start)[11:], x.n) for x in found.collect()) == [(0, "10:00:00", 1), (7, "10:00:00", 2), (7, "10:59:59", 1), (8, "23:59:59", 1)]
    assert found.inputFiles()  # the memory sink has none
