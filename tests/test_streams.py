"""Streams whose results grow with the input."""

import datetime

import __spark_entry__

DAY = datetime.datetime(2024, 1, 1)


def test_sessions_stay_off_the_driver(spark, tmp_path):
    hours = {1: (0, 1, 6.5, 13, 19.1), 2: (0, 6.01), 3: (5,)}
    rows = [(10 * u + i, DAY + datetime.timedelta(hours=h), u, "view") for u, hs in hours.items() for i, h in enumerate(hs)]
    schema = "event_id long, ts timestamp_ntz, user_id long, event_type string"
    spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"{tmp_path}/full/events.parquet")
    spark.createDataFrame([], schema).coalesce(1).write.parquet(f"{tmp_path}/none/events.parquet")
    sessions = __spark_entry__.queries()["stream_session"]
    df = sessions(spark, f"{tmp_path}/full")
    assert "parquet" in df._jdf.queryExecution().executedPlan().toString().lower()  # not a table in the driver's memory
    got = sorted((r["user_id"], r["start"][11:], r["n"]) for r in df.collect())
    assert got == [
        (1, "00:00:00", 3), (1, "13:00:00", 1), (1, "19:06:00", 1), (2, "00:00:00", 1), (2, "06:00:36", 1), (3, "05:00:00", 1),
    ]
    assert sessions(spark, f"{tmp_path}/none").count() == 0
