"""Words, sentences and dictionaries from the text tables."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

WORD = r"[\p{L}\p{N}]+"
SENTENCE_END = r"[.!?\n]+"
#: The most frequent words of a vocabulary, which are broadcast; this many rows at most.
HEAD = 1024


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def words(df: DataFrame, keys: list[str], text: str = "text") -> DataFrame:
    """One row a word, lower-cased; a null text has none."""
    return df.select(*keys, F.explode(F.regexp_extract_all(F.lower(text), F.lit(WORD), F.lit(0))).alias("word"))


def token_weights(df: DataFrame, keys: list[str], text: str = "text") -> DataFrame:
    return words(df, keys, text).groupBy(*keys, "word").agg(F.count("*").alias("n"))


def sentences(df: DataFrame, keys: list[str], text: str = "text") -> DataFrame:
    """``keys, s, sentence``: pieces between sentence ends, blank ones dropped, numbered by their place."""
    return df.select(*keys, F.posexplode(F.split(text, SENTENCE_END)).alias("s", "sentence")).filter(F.trim("sentence") != "")


def prefix_sums(df: DataFrame, order: list[str], value: str, name: str) -> DataFrame:
    """``df`` with the sum of ``value`` over all earlier rows, by range partitions and their totals.

    No task sees more than a range: totals of the ranges (one row each) are summed apart.
    """
    ranged = df.repartitionByRange(*order).withColumn("_p", F.spark_partition_id()).persist()
    totals = ranged.groupBy("_p").agg(F.sum(value).alias("_t"))
    bases = totals.select("_p", (F.sum("_t").over(Window.orderBy("_p")) - F.col("_t")).alias("_b"))
    inside = F.sum(value).over(Window.partitionBy("_p").orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return ranged.withColumn("_i", inside).join(F.broadcast(bases), "_p").withColumn(name, F.col("_b") + F.col("_i") - F.col(value)).drop("_p", "_b", "_i")


def dense_index(df: DataFrame, order: list[str], name: str = "idx") -> DataFrame:
    """Consecutive numbers from 0 in the order of the columns (which should tell all rows apart)."""
    return prefix_sums(df.withColumn("_one", F.lit(1).cast("long")), order, "_one", name).drop("_one")


def vocabulary(weights: DataFrame, least_docs: int = 1) -> DataFrame:
    """``w, word, n, docs``: words in at least so many documents, numbered by falling count."""
    counted = weights.groupBy("word").agg(F.sum("n").alias("n"), F.count("*").alias("docs")).filter(F.col("docs") >= least_docs)
    return dense_index(counted.withColumn("_o", -F.col("n")), ["_o", "word"], "w").drop("_o")


def encoded(weights: DataFrame, vocab: DataFrame, keys: list[str]) -> DataFrame:
    """``keys, w, n`` of the words in the vocabulary, whose numbers fall with the count.

    The first ``HEAD`` words, which may each be in every text, are found by broadcast; their rows then go through the join
    with the others under keys of their own, so a frequent word's rows don't meet in one task.
    """
    head = vocab.filter(F.col("w") < HEAD).select("word", F.col("w").alias("_head"))
    tail = vocab.filter(F.col("w") >= HEAD).select(F.col("word").alias("_key"), F.col("w").alias("_tail"))
    spread = F.concat(F.lit("\0"), F.hex(F.xxhash64(*keys, "word")))
    placed = weights.join(F.broadcast(head), "word", "left").withColumn("_key", F.when(F.col("_head").isNull(), F.col("word")).otherwise(spread))
    return placed.join(tail, "_key", "left").select(*keys, F.coalesce("_head", "_tail").alias("w"), "n").filter("w is not null")


def word_units(df: DataFrame, key: str, text: str = "text", sentences: bool = False) -> DataFrame:
    """``key, units``: the words of every text, or of each of its sentences, as an array of (s, words); a row an id.

    Rows that share an id, null among them, are one document: their texts, and only theirs, are brought together.
    """
    rows = df.select(F.col(key), F.array(F.coalesce(text, F.lit(""))).alias("_texts"))
    again = df.groupBy(F.col(key).alias("_k")).agg(F.count("*").alias("_n")).filter("_n > 1").select("_k")
    if again.take(1):
        same = F.col(key).eqNullSafe(F.col("_k"))
        rows = rows.join(again, same, "left_anti").union(rows.join(again, same, "left_semi").groupBy(key).agg(F.flatten(F.collect_list("_texts"))))
    found = lambda t: F.regexp_extract_all(F.lower(t), F.lit(WORD), F.lit(0)).alias("words")
    if sentences:
        units = F.flatten(F.transform("_texts", lambda t: F.transform(F.split(t, SENTENCE_END), lambda x, i: F.struct(i.alias("s"), found(x)))))
    else:
        units = F.transform("_texts", lambda t: F.struct(F.lit(0).alias("s"), found(t)))
    return rows.select(key, units.alias("units"))


def flat_words(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, pa.DictionaryArray]:
    """Row number, s and word of every word of a batch of ``word_units``."""
    units = batch.column("units")
    each = units.flatten()
    words = pc.struct_field(each, "words")
    many = pc.fill_null(pc.list_value_length(words), 0).to_numpy(zero_copy_only=False)
    doc = np.repeat(np.arange(batch.num_rows), pc.fill_null(pc.list_value_length(units), 0).to_numpy(zero_copy_only=False))
    s = pc.struct_field(each, "s").to_numpy(zero_copy_only=False).astype(np.int64)
    return np.repeat(doc, many), np.repeat(s, many), words.flatten().dictionary_encode()


def document_vocabulary(df: DataFrame, key: str, least_docs: int = 1) -> DataFrame:
    """``vocabulary`` of whole texts, a document an id: tasks count whole documents and send one row a word and batch."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            doc, _, coded = flat_words(batch)
            size, code = len(coded.dictionary), coded.indices.to_numpy().astype(np.int64)
            if size:
                once = np.unique(doc * size + code) % size
                yield pa.RecordBatch.from_arrays([coded.dictionary, pa.array(np.bincount(code, minlength=size)), pa.array(np.bincount(once, minlength=size))], ["word", "n", "docs"])

    parts = word_units(df, key).mapInArrow(count, "word string, n long, docs long")
    counted = parts.groupBy("word").agg(F.sum("n").alias("n"), F.sum("docs").alias("docs")).filter(F.col("docs") >= least_docs)
    return dense_index(counted.withColumn("_o", -F.col("n")), ["_o", "word"], "w").drop("_o")


def take_words(df: DataFrame, target: int, key: str = "doc_id") -> DataFrame:
    """Documents in key order until their words reach ``target``, as ``key, n_words, before``."""
    counted = words(df, [key]).groupBy(key).agg(F.count("*").alias("n_words"))
    return prefix_sums(counted, [key], "n_words", "before").filter(F.col("before") < target)


def page_text(pages: DataFrame) -> DataFrame:
    """``page_id, text``: HTML without scripts, styles, comments and tags, basic entities undone."""
    t = F.col("html")
    for pattern in (r"(?is)<script[^>]*>.*?</script>", r"(?is)<style[^>]*>.*?</style>", r"(?s)<!--.*?-->", r"<[^>]*>"):
        t = F.regexp_replace(t, pattern, " ")
    for entity, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&")):
        t = F.replace(t, F.lit(entity), F.lit(char))
    return pages.select("page_id", F.trim(F.regexp_replace(t, r"[ \t\r\n]+", " ")).alias("text"))
