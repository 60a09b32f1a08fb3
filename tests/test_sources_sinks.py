import pytest
from pyspark.sql import functions as F

from plate_engine.measures.cost import exchanges
from plate_engine.sources import text as T

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("form", ["parquet", "orc", "json", "csv"])
def test_sink_roundtrip(spark, tmp_path, form):
    rows = [(rv, g, k, 0.25 * (k + 1) + g) for rv in ("phi", "theta") for g in range(3) for k in range(2)]
    posterior = spark.createDataFrame(rows, "rv string, g long, k int, alpha double")
    path = f"{tmp_path}/posterior"
    posterior.write.partitionBy("rv").option("header", True).format(form).save(path)
    back = spark.read.format(form).option("header", True).schema("g long, k int, alpha double, rv string").load(path)
    assert sorted(map(tuple, back.select("rv", "g", "k", "alpha").collect())) == sorted(rows)
    one = back.filter("rv = 'phi'")
    assert one.count() == 6 and "PartitionFilters: [isnotnull(rv" in one._jdf.queryExecution().toString()


def test_skewed_word_join_equals_the_plain_join(spark, monkeypatch):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").withColumn("text", F.concat(F.lit("the the "), "text"))
    weights = T.token_weights(docs, ["doc_id"])
    vocab = T.vocabulary(weights, 2)
    plain = sorted(map(tuple, weights.join(vocab.select("word", "w"), "word").select("doc_id", "w", "n").collect()))
    assert plain
    for head in (0, 5, T.HEAD, 1 << 30):
        monkeypatch.setattr(T, "HEAD", head)
        assert sorted(map(tuple, T.encoded(weights, vocab, ["doc_id"]).collect())) == plain


def test_a_hot_word_is_not_dealt_to_one_task(spark):
    weights = spark.range(4000).select(F.col("id").alias("doc_id"), F.lit("the").alias("word"), F.lit(1).cast("long").alias("n"))
    vocab = spark.createDataFrame([("the", 0), ("rare", 5000)], "word string, w long")
    adaptive, bar = spark.conf.get("spark.sql.adaptive.enabled"), spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    try:
        spark.conf.set("spark.sql.adaptive.enabled", "false")
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        sizes = [len(p) for p in T.encoded(weights, vocab, ["doc_id"]).rdd.glom().collect()]
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", adaptive)
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", bar)
    assert sum(sizes) == 4000 and max(sizes) < 2 * 4000 / len(sizes)


def test_exchanges_are_counted_above_a_cached_table(spark):
    base = spark.range(100).withColumn("k", F.col("id") % 7)
    assert exchanges(base) == 0
    assert exchanges(base.groupBy("k").count()) == 1
    held = base.groupBy("k").count().persist()
    held.count()
    assert exchanges(held) == 0 and exchanges(held.groupBy("count").agg(F.max("k"))) == 1
    held.unpersist()

