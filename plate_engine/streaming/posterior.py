"""Posteriors over streams.  Conjugate counts add up, so windows and running states are exact; the mini-batch
update of a topic model is an approximation and says so."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import StructType

from ..functions.special import digamma_np


def event_stream(spark: SparkSession, path: str, schema: StructType, files_a_trigger: int = 1) -> DataFrame:
    """Events from a folder of Parquet files; their local timestamps become instants, which watermarks need."""
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_a_trigger).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def windowed_coin(events: DataFrame, size: str = "1 day", slide: str | None = None, late: str = "1 hour", prior: float = 1.0) -> DataFrame:
    """``start, event_type, n, gamma`` by tumbling or sliding windows; rows later than ``late`` are dropped."""
    at = F.window("ts", size, slide) if slide else F.window("ts", size)
    rows = events.withWatermark("ts", late).groupBy(at.alias("w"), "event_type").agg(F.count("*").alias("n"))
    return rows.select(F.col("w.start").alias("start"), "event_type", "n", (prior + F.col("n")).alias("gamma"))


def session_coin(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    rows = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"), F.count_if(F.col("event_type") == "error").alias("heads"))
    return rows.select("user_id", F.col("w.start").alias("start"), "n", (1 + F.col("heads")).alias("a"), (1 + F.col("n") - F.col("heads")).alias("b"))


def distinct_events(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def encoded_events(events: DataFrame, dictionary: DataFrame) -> DataFrame:
    """Stream-static join with a dictionary (event_type, w)."""
    return events.join(dictionary, "event_type")


def running_posterior(events: DataFrame) -> DataFrame:
    """``user_id, a, b``: each user's Beta parameters after every micro-batch; the state is two counts."""

    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        a, b = state.get if state.exists else (1, 1)
        for f in frames:
            heads = int((f["event_type"] == "error").sum())
            a, b = a + heads, b + len(f) - heads
        state.update((a, b))
        yield pd.DataFrame({"user_id": [key[0]], "a": [a], "b": [b]})

    return events.select("user_id", "event_type").groupBy("user_id").applyInPandasWithState(update, "user_id long, a long, b long", "a long, b long", "update", GroupStateTimeout.NoTimeout)


class MiniBatchTopics:
    """Stochastic variational updates of the components from micro-batches (approximate).

    Step t moves the components by ``(t + delay) ** -decay`` towards what the batch, scaled to ``documents``, alone
    would give.  The components (V x K numbers) are on the driver, a batch's words are grouped by Spark.
    """

    def __init__(self, k: int, v: int, alpha: float, beta: float, documents: int, delay: float = 1.0, decay: float = 0.7, inner: int = 10, seed: int = 0):
        self.k, self.v, self.alpha, self.beta, self.documents = k, v, alpha, beta, documents
        self.delay, self.decay, self.inner, self.t = delay, decay, inner, 0
        self.phi = beta + np.random.default_rng(seed).gamma(100.0, 0.01, (v, k))

    def sums(self, tokens: DataFrame) -> tuple[np.ndarray, int]:
        e_phi = digamma_np(self.phi) - digamma_np(self.phi.sum(0))
        held = tokens.sparkSession.sparkContext.broadcast(e_phi)
        k, alpha, inner = self.k, self.alpha, self.inner

        def one(pdf: pd.DataFrame) -> pd.DataFrame:
            w, n = pdf["w"].to_numpy(), pdf["n"].to_numpy(float)
            theta = np.full(k, alpha + n.sum() / k)
            for _ in range(inner):
                s = digamma_np(theta) - digamma_np(theta.sum(keepdims=True)) + held.value[w]
                r = np.exp(s - s.max(1, keepdims=True))
                r /= r.sum(1, keepdims=True)
                theta = alpha + n @ r
            return pd.DataFrame({"w": np.repeat(w, k), "k": np.tile(np.arange(k), len(w)), "m": (n[:, None] * r).ravel(), "d": 1.0 / (len(w) * k)})

        rows = tokens.groupBy("d").applyInPandas(one, "w long, k long, m double, d double").groupBy("w", "k").agg(F.sum("m").alias("m"), F.sum("d").alias("d")).toPandas()
        out = np.zeros((self.v, k))
        out[rows["w"], rows["k"]] = rows["m"]
        return out, round(rows["d"].sum())

    def update(self, tokens: DataFrame, _batch: int = 0) -> None:
        found, docs = self.sums(tokens)
        if docs:
            self.t += 1
            rho = (self.t + self.delay) ** -self.decay
            self.phi = (1 - rho) * self.phi + rho * (self.beta + found * self.documents / docs)


def run_to_end(stream: DataFrame, name: str, mode: str = "append", each: Callable | None = None) -> None:
    """Work through what is there: into the memory table ``name``, or through ``each`` micro-batch."""
    writer = stream.writeStream.outputMode(mode).trigger(availableNow=True)
    query = (writer.foreachBatch(each) if each else writer.format("memory").queryName(name)).start()
    query.awaitTermination()
