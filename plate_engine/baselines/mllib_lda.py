"""MLlib's LDA on the same documents: the EM optimiser (maximum a posteriori only) and the online one."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.ml.clustering import LDA
from pyspark.ml.feature import CountVectorizer
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..runtime.loop import Scratch
from ..sources.text import WORD

#: Distinct words of documents in one partition of the vectors, which the EM optimiser turns into one of its graph. A round sends
#: every term of a partition to it and back, and MLlib keeps what all rounds sent: small partitions cost disk, large ones memory.
PARTITION_WORDS = 5_000_000
#: A vector as it is stored.
STORED = "features struct<type: tinyint, size: int, indices: array<int>, values: array<double>>"
#: MLlib asks for the input's partitions before it reads them, so a plan that runs by stages would be shuffled twice; a file is a partition.
PLANNED = {"spark.sql.adaptive.enabled": "false", "spark.sql.files.openCostInBytes": str(1 << 40)}


@contextmanager
def settings(spark: SparkSession, values: dict[str, str]) -> Iterator[None]:
    """Plans made inside follow the values."""
    before = {k: spark.conf.get(k) for k in values}
    for k, v in values.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)


def em_topics(found: DataFrame, lda: LDA, top: int) -> DataFrame:
    """The vectors are read several times to build the graph, an edge a word of a document, so they are stored first.

    A graph partition is an input partition and built in memory, so there must be enough; files that suffice are put together,
    not shuffled.
    """
    spark = found.sparkSession
    tables = Scratch(spark)
    try:
        vectors = tables.table(found.select(F.col("features").alias("features", metadata={})), "vectors", rows=0)
        edges = spark.read.schema(STORED).parquet(tables.paths["vectors"][-1]).agg(F.sum(F.size("features.indices"))).first()[0] or 0
        with settings(spark, PLANNED):
            parts = max(spark.sparkContext.defaultParallelism, -(-edges // PARTITION_WORDS))
            many = vectors.rdd.getNumPartitions() >= parts
            return lda.fit(vectors.coalesce(parts) if many else vectors.repartition(parts)).describeTopics(top)
    finally:
        tables.forget("vectors")


def mllib_lda(docs: DataFrame, k: int, iterations: int, optimizer: str = "em", least_docs: int = 5, top: int = 10) -> DataFrame:
    """``topic, place, word, weight`` of the heaviest words."""
    words = docs.select("doc_id", F.regexp_extract_all(F.lower("text"), F.lit(WORD), F.lit(0)).alias("words"))
    vectoriser = CountVectorizer(inputCol="words", outputCol="features", minDF=float(least_docs)).fit(words)
    vectors, lda = vectoriser.transform(words), LDA(k=k, maxIter=iterations, optimizer=optimizer, seed=1)
    heaviest = em_topics(vectors, lda, top) if optimizer == "em" else lda.fit(vectors.select("doc_id", "features")).describeTopics(top)
    vocabulary = docs.sparkSession.createDataFrame(list(enumerate(vectoriser.vocabulary)), "term int, word string")
    topics = heaviest.select("topic", F.posexplode(F.arrays_zip("termIndices", "termWeights")).alias("place", "t"))
    return topics.select("topic", "place", F.col("t.termIndices").alias("term"), F.col("t.termWeights").alias("weight")).join(vocabulary, "term").select("topic", "place", "word", "weight")
