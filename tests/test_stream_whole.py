"""The optional join of two streams on a stream shorter than a day."""

import datetime

from optjoin import registry


def test_every_view_of_a_short_stream(spark, tmp_path):
    at = lambda m: datetime.datetime(2024, 1, 1, 0, 0) + datetime.timedelta(minutes=m)
    rows = [(1, at(0), 7, "view"), (2, at(30), 7, "purchase"), (3, at(50), 8, "view"), (4, at(59), 7, "view"), (5, at(200), None, "view")]
    spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, event_type string").coalesce(1).write.parquet(str(tmp_path / "events.parquet"))
    got = registry.QUERIES["stream_o78_optional"](spark, str(tmp_path)).collect()
    assert sorted(map(tuple, got)) == [(1, 2), (3, None), (4, None), (5, None)]
