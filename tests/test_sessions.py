from pyspark.sql import functions as F

from corrsentry.streaming import live


def test_an_event_a_whole_gap_later_starts_a_session(spark):
    e = spark.createDataFrame([(1, 0), (1, 21_600), (1, 43_199), (2, 5)], "user_id long, s long").select("user_id", F.timestamp_seconds("s").alias("ts"))
    got = sorted(tuple(r) for r in live.sessions(e).select("user_id", "first_s", "end_s", "n").collect())
    assert got == [(1, 0, 21_600, 1), (1, 21_600, 64_799, 2), (2, 5, 21_605, 1)]
