"""Exact evidence of the two-coin model: naive enumeration, and the polynomial form by exchangeability."""

from __future__ import annotations

import itertools
import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.special import log_gamma


def _log_beta(a: float, b: float) -> float:
    return math.lgamma(a) + math.lgamma(b) - math.lgamma(a + b)


def enumerated_log_evidence(h: int, t: int, alpha: float, beta: float) -> float:
    """All 2^N assignments; for N up to 16."""
    if h + t > 16:
        raise ValueError("enumeration is for 16 tosses at most")
    x = [1] * h + [0] * t
    logs = []
    for z in itertools.product((0, 1), repeat=len(x)):
        a = sum(z)
        h1 = sum(v for v, c in zip(x, z, strict=True) if c)
        h0, n = h - h1, len(x)
        logs.append(_log_beta(alpha + a, alpha + n - a) - _log_beta(alpha, alpha) + _log_beta(beta + h1, beta + a - h1) + _log_beta(beta + h0, beta + (n - a) - h0) - 2 * _log_beta(beta, beta))
    top = max(logs)
    return top + math.log(sum(math.exp(v - top) for v in logs))


def two_coin_log_evidence(h: int, t: int, alpha: float, beta: float) -> float:
    """(h + 1)(t + 1) terms: how many heads and tails the second coin made."""
    logs = []
    for a in range(h + 1):
        for b in range(t + 1):
            ways = math.lgamma(h + 1) - math.lgamma(a + 1) - math.lgamma(h - a + 1) + math.lgamma(t + 1) - math.lgamma(b + 1) - math.lgamma(t - b + 1)
            logs.append(ways + _log_beta(alpha + a + b, alpha + h + t - a - b) - _log_beta(alpha, alpha) + _log_beta(beta + a, beta + b) + _log_beta(beta + h - a, beta + t - b) - 2 * _log_beta(beta, beta))
    top = max(logs)
    return top + math.log(sum(math.exp(v - top) for v in logs))


def _lb(a: Column, b: Column) -> Column:
    return log_gamma(a) + log_gamma(b) - log_gamma(a + b)


def evidence_by_group(counts: DataFrame, keys: list[str], alpha: float, beta: float) -> DataFrame:
    """``keys, log_evidence`` of a two-coin model for each row (h, t): its terms are rows, added up as a log-sum-exp."""
    one = F.lit(1.0)
    rows = counts.select(*keys, "h", "t", F.explode(F.sequence(F.lit(0).cast("long"), F.col("h"))).alias("a")).select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.col("t"))).alias("b"))
    h, t, a, b = (F.col(c) for c in "htab")
    ways = log_gamma(h + one) - log_gamma(a + one) - log_gamma(h - a + one) + log_gamma(t + one) - log_gamma(b + one) - log_gamma(t - b + one)
    prior = 2 * _log_beta(beta, beta) + _log_beta(alpha, alpha)
    value = ways + _lb(alpha + a + b, alpha + h + t - a - b) + _lb(beta + a, beta + b) + _lb(beta + h - a, beta + t - b) - prior
    rows = rows.select(*keys, value.alias("v"))
    top = rows.groupBy(*keys).agg(F.max("v").alias("m"))
    return rows.join(top, keys).groupBy(*keys, "m").agg(F.sum(F.exp(F.col("v") - F.col("m"))).alias("z")).select(*keys, (F.col("m") + F.log("z")).alias("log_evidence"))
