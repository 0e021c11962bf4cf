from pyspark.sql import functions as F
from sitereach.sources import table
from sitereach.streaming import checkins

SF = "/root/testdata/sf0.001"


def test_stream_equals_batch(spark):
    batch = checkins.parsed(table(spark, SF, "events")).where("event_type = 'purchase'")
    want = {(r["k"], r["start"], r["visits"]) for r in checkins.tumbling(batch).collect()}
    assert {tuple(r) for r in checkins.drained(spark, SF, checkins.tumbling).collect()} == want
    seen = {r["k"]: r["n"] for r in batch.groupBy("k").agg(F.count_distinct("user_id").alias("n")).collect()}
    got = checkins.drained(spark, SF, checkins.visitors, "update").groupBy("k").agg(F.max("visitors").alias("n")).collect()
    assert {r["k"]: r["n"] for r in got} == seen
