import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from plate_engine.functions import udfs
from plate_engine.streaming import posterior as S

EVENTS = "/root/testdata/sf0.001/events.parquet"


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """The events in time order, cut into four files, with late and repeated rows in a fifth."""
    path = tmp_path_factory.mktemp("events")
    rows = spark.read.parquet(EVENTS).orderBy("ts").toPandas()
    cuts = np.array_split(np.arange(len(rows)), 4)
    import pandas as pd

    for i, c in enumerate([*cuts, np.arange(20)]):
        part = rows.iloc[c] if i < 4 else pd.concat([rows.iloc[c]])
        f = path / f"{i}.parquet"
        spark.createDataFrame(part, spark.read.parquet(EVENTS).schema).coalesce(1).write.parquet(str(path / f"tmp{i}"))
        next((path / f"tmp{i}").glob("part-*.parquet")).rename(f)
        import os
        import shutil

        shutil.rmtree(path / f"tmp{i}")
        os.utime(f, (1_700_000_000 + i, 1_700_000_000 + i))
    return str(path)


def stream(spark, folder):
    return S.event_stream(spark, folder, spark.read.parquet(EVENTS).schema)


def test_closed_windows_equal_the_batch(spark, folder):
    S.run_to_end(S.windowed_coin(stream(spark, folder)), "windows")
    got = {(r["start"], r["event_type"]): r["n"] for r in spark.table("windows").collect()}
    batch = spark.read.parquet(EVENTS).withColumn("ts", F.col("ts").cast("timestamp")).groupBy(F.window("ts", "1 day").alias("w"), "event_type").count()
    want = {(r["w"]["start"], r["event_type"]): r["count"] for r in batch.collect()}
    assert got and all(want[k] == n for k, n in got.items())  # late rows of the last file were dropped
    last = max(k for k, _ in want)
    assert {k for k, _ in want} - {k for k, _ in got} <= {last}


def test_running_state_and_dedup(spark, folder):
    S.run_to_end(S.running_posterior(stream(spark, folder)), "running", "update")
    got = spark.table("running").groupBy("user_id").agg(F.max(F.col("a") + F.col("b") - 2).alias("n"))
    late = spark.read.parquet(EVENTS).orderBy("ts").limit(20).groupBy("user_id").count().withColumnRenamed("count", "more")
    want = spark.read.parquet(EVENTS).groupBy("user_id").count().join(late, "user_id", "left").select("user_id", (F.col("count") + F.coalesce("more", F.lit(0))).alias("n"))
    assert got.exceptAll(want).count() == 0 and got.count() == want.count()
    S.run_to_end(S.distinct_events(stream(spark, folder), "4000 days"), "once")
    assert spark.table("once").count() == 1000


def test_sessions_and_dictionary(spark, folder):
    S.run_to_end(S.session_coin(stream(spark, folder)), "sessions")
    assert spark.table("sessions").filter("a + b <> n + 2").count() == 0 and spark.table("sessions").count() > 0
    codes = spark.createDataFrame([("click", 0), ("error", 1)], "event_type string, w int")
    S.run_to_end(S.encoded_events(stream(spark, folder), codes), "coded")
    assert {r["w"] for r in spark.table("coded").select("w").distinct().collect()} == {0, 1}


def test_mini_batches_find_the_planted_topics(spark):
    rows = [(d, 5 * (d % 2) + w, 4) for d in range(40) for w in range(5)]
    topics = S.MiniBatchTopics(2, 10, 0.1, 0.1, 40)
    for a in range(0, 40, 10):
        topics.update(spark.createDataFrame(rows[5 * a : 5 * a + 50], "d long, w long, n long"))
    top = topics.phi[:5].sum(0) / topics.phi.sum(0)
    assert max(top) > 0.9 and min(top) < 0.1


def test_function_surface(spark):
    udfs.register(spark)
    spark.createDataFrame([(0.5,), (3.7,)], "x double").createOrReplaceTempView("xs")
    a, b = spark.sql("SELECT digamma(x), log_gamma(x) FROM xs ORDER BY x").collect()
    assert abs(a[0] + 1.9635100260214235) < 1e-11 and abs(b[1] - 1.4280723266653883) < 1e-11
    assert abs(spark.sql("SELECT log_sum_exp(x) FROM xs").first()[0] - math.log(math.exp(0.5) + math.exp(3.7))) < 1e-12
    assert [r[0] for r in spark.sql("SELECT * FROM plate_range(2, 5)").collect()] == [2, 3, 4]
