from bisect import bisect_right
from collections import defaultdict

from pyspark.sql import functions as F

from plate_engine.queries import QUERIES

SF = "/root/testdata/sf0.001"


def test_posterior_asof_is_the_state_in_force(spark):
    """Every purchase gets its user's counts of all events up to its own time."""
    rows = spark.read.parquet(f"{SF}/events.parquet").select("event_id", "user_id", F.col("ts").cast("string").alias("ts"), "event_type").collect()
    times, errors = defaultdict(list), defaultdict(list)
    for r in sorted(rows, key=lambda r: r["ts"]):
        times[r["user_id"]].append(r["ts"])
        if r["event_type"] == "error":
            errors[r["user_id"]].append(r["ts"])
    want = {r["event_id"]: (bisect_right(errors[r["user_id"]], r["ts"]), bisect_right(times[r["user_id"]], r["ts"])) for r in rows if r["event_type"] == "purchase"}
    got = {r["event_id"]: (r["heads"], r["total"]) for r in QUERIES["posterior_asof"](spark, SF).collect()}
    assert got == want
