"""Headline runs: the experiment workloads at matched word counts, and a few operators; prints one JSON line.

BENCH_SF_DIR, BENCH_CPUS and BENCH_ROUNDS choose the input, the cores and the rounds of message passing (10; the
experiments ran 50).  ``published_inference_for_rounds`` is the published inference time for as many rounds.  All words of a
workload are kept.  The topic models go through the model language, whose engine picks the layout; the stages are
those of the experiments.  A workload or operator that fails is named in ``failed`` and makes ``value`` null.
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from plate_engine.models import zoo
from plate_engine.plans.blocks import local_bursty
from plate_engine.queries import QUERIES
from plate_engine.sources import text as T

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = int(os.environ.get("BENCH_CPUS", os.cpu_count() or 4))
ROUNDS = int(os.environ.get("BENCH_ROUNDS", "10"))
PUBLISHED_ROUNDS = 50
#: Words of the workloads: model, words, topics, published seconds in all and of inference.
WORKLOADS = {
    "w1_lda": ("lda", 541_644, 96, 1637.9, 1566.692), "w2_lda": ("lda", 1_324_816, 96, 3115.661, 3002.1), "w3_slda": ("slda", 349_569, 96, 1241.447, 1182.2),
    "w4_slda": ("slda", 607_430, 96, 2268.1, 2193.391), "w5_dcmlda": ("dcmlda", 1_324_816, 10, 3502.8, 3448.699), "w6_dcmlda": ("dcmlda", 2_596_155, 10, 8227.726, 8153.969),
}
OPERATORS = ("token_weights", "vocabulary_ranked", "lda_customer_brands", "two_coin_nested_vmp", "coin_rollup", "posterior_asof", "replication_by_strategy")


def corpus(spark: SparkSession, words: int, sentences: bool):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    taken = docs.join(T.take_words(docs, words).select("doc_id"), "doc_id", "left_semi")
    keys = ["doc_id", "s"] if sentences else ["doc_id"]
    rows = T.token_weights(T.sentences(taken, ["doc_id"]), keys, "sentence") if sentences else T.token_weights(taken, keys)
    rows = rows.persist()
    vocab = T.vocabulary(rows, 1).persist()
    tokens = T.encoded(rows, vocab, keys).withColumnRenamed("doc_id", "d").persist()
    return tokens, tokens.agg(F.sum("n")).first()[0], vocab.count()


def workload(spark: SparkSession, model: str, words: int, k: int) -> dict:
    began = time.perf_counter()
    tokens, n, v = corpus(spark, words, model == "slda")
    stages = {"prepare": time.perf_counter() - began}
    if model == "dcmlda":
        at = time.perf_counter()
        found = local_bursty(tokens, k, v, 0.5, 0.1, ROUNDS, 4 * CPUS)
        sums = found.select(F.posexplode("bounds").alias("t", "b")).groupBy("t").agg(F.sum("b").alias("b")).orderBy("t").collect()
        bounds = [r["b"] for r in sums]
        stages["inference"] = time.perf_counter() - at
    else:
        bound = (zoo.slda() if model == "slda" else zoo.lda()).bind(spark, K=k, V=v, alpha=0.1, beta=0.01)
        bound["x"].observe(tokens, value="w", keys={"docs": "d", "sentences": "s"} if model == "slda" else {"docs": "d"}, weight="n")
        bound.infer(ROUNDS)
        bounds = [b for _, b, _ in bound.engine.history]
        stages |= {r["stage"]: r["seconds"] for r in bound.timings().collect()}
        stages["layout"] = type(bound.engine).__name__
    end = time.perf_counter()
    spark.catalog.clearCache()
    rising = all(b >= a - 1e-6 * abs(a) for a, b in zip(bounds, bounds[1:]))
    return {"seconds": round(end - began, 2), "stages": {a: b if isinstance(b, str) else round(b, 2) for a, b in stages.items()}, "words": int(n), "vocabulary": v, "elbo": round(bounds[-1], 1), "elbo_rises": rising, "word_updates_per_s": round(n * ROUNDS / stages["inference"])}


def main() -> None:
    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.driver.memory", "10g").config("spark.sql.shuffle.partitions", str(CPUS)).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    seconds, details = {}, {}
    for name, (model, words, k, published, inference) in WORKLOADS.items():
        try:
            details[name] = workload(spark, model, words, k) | {"rounds": ROUNDS, "published_seconds": published, "published_rounds": PUBLISHED_ROUNDS, "published_inference_for_rounds": round(inference * ROUNDS / PUBLISHED_ROUNDS, 1)}
            seconds[name] = details[name]["seconds"]
        except Exception as failure:
            details[name] = {"failed": str(failure)[:300]}
            spark.catalog.clearCache()
        print(name, details[name], file=sys.stderr, flush=True)
    for name in OPERATORS:
        began = time.perf_counter()
        try:
            QUERIES[name](spark, SF).write.format("noop").mode("overwrite").save()
        except Exception as failure:
            details[name] = {"failed": str(failure)[:300]}
            continue
        seconds[name] = round(time.perf_counter() - began, 2)
        print(name, seconds[name], file=sys.stderr, flush=True)
    failed = [name for name in [*WORKLOADS, *OPERATORS] if name not in seconds]
    print(json.dumps({"metric": "total_seconds", "value": None if failed else round(sum(seconds.values()), 2), "unit": "sec", "failed": failed, "queries": seconds, "sf": SF, "rounds": ROUNDS, "details": details}))


if __name__ == "__main__":
    main()
