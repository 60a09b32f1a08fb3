"""How good topics are: held-out likelihood, perplexity, agreement with a known label."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def topic_shares(theta: DataFrame, keys: list[str]) -> DataFrame:
    """``topics, share``: mean topic proportions over all groups."""
    return theta.groupBy(F.col("j").alias("topics")).agg(F.avg("mean").alias("share"))


def predictive_ll(held: DataFrame, phi: DataFrame, shares: DataFrame, keys: list[str]) -> DataFrame:
    """``keys, ll, words``: log-likelihood of held-out words (w, n) under the mean mixture; unknown words are left out."""
    mixture = phi.join(F.broadcast(shares), "topics").groupBy(F.col("j").alias("w")).agg(F.sum(F.col("mean") * F.col("share")).alias("p"))
    return held.join(mixture, "w").groupBy(*keys).agg(F.sum(F.col("n") * F.log("p")).alias("ll"), F.sum("n").alias("words"))


def perplexity(ll: DataFrame) -> DataFrame:
    return ll.agg(F.exp(-F.sum("ll") / F.sum("words")).alias("perplexity"))


def purity(theta: DataFrame, labels: DataFrame, key: str, label: str) -> DataFrame:
    """Share of groups whose likeliest topic's commonest label is their own; the lowest topic of equals."""
    best = theta.groupBy(key).agg(F.max(F.struct(F.round("mean", 9).alias("m"), (-F.col("j")).alias("k"))).alias("b"))
    counted = best.join(labels, key).groupBy(F.col("b.k").alias("topic"), label).agg(F.count("*").alias("n"))
    top = counted.groupBy("topic").agg(F.max("n").alias("top"), F.sum("n").alias("all"))
    return top.agg((F.sum("top") / F.sum("all")).alias("purity"))


def elbo_delta(history: DataFrame) -> DataFrame:
    over = Window.orderBy("iter")  # a row a round
    return history.select("iter", "elbo", (F.col("elbo") - F.lag("elbo").over(over)).alias("delta"))
