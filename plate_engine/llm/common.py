"""Shared pieces of the corpus operators: reading, scratch tables, text batches."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import SparkContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The six characters that separate words: 0x20 and 0x09 to 0x0D.
WORD_SPACES = " \t\n\x0b\x0c\r"
#: Keys with over 1 / HOT_SHARE of the rows, and over HOT_LEAST rows, are joined by broadcast.
HOT_SHARE, HOT_LEAST = 1000, 500


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet")


def fold(modulus: int, column: str = "doc_id") -> Column:
    """crc32 of the id as text, modulo ``modulus``; a null id counts as the empty text."""
    return F.crc32(F.coalesce(F.col(column).cast("string"), F.lit("")).cast("binary")) % modulus


def labelled_texts(docs: DataFrame, marks: DataFrame, label: str, most: int, where: Column | None = None) -> DataFrame:
    """``h, t, y``: hash, text and label of the distinct texts of at most ``most`` labelled documents.

    Documents are those of the lowest id hashes among the labelled rows that meet ``where``, so the sample is
    a fixed one and its list of ids, bounded by ``most``, can be broadcast.  A document or text with several
    labels has the largest.  Rows without an id or a label are left out; a null text counts as empty.
    """
    marks = marks.filter(F.col(label).isNotNull() & F.col("doc_id").isNotNull())
    marks = marks.filter(where) if where is not None else marks
    marks = marks.groupBy("doc_id").agg(F.max(label).cast("int").alias("y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    return distinct_texts(docs, marks)


def distinct_texts(docs: DataFrame, marks: DataFrame) -> DataFrame:
    """``h, t, y``: hash, text and largest label of the distinct texts of a bounded number of documents (doc_id, y)."""
    found = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("t")).join(F.broadcast(marks), "doc_id")
    return stored(found.groupBy(F.xxhash64("t").alias("h")).agg(F.min("t").alias("t"), F.max("y").alias("y")), "labelled")


def shared_folder(spark: SparkSession) -> str:
    """A folder of this application in the cluster's checkpoint folder, removed when the application ends.

    A folder of our own is made only in local mode, where driver and executors are one process.
    """
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not named:
        if not re.fullmatch(r"local(\[[\d*, ]+\])?", sc.master):
            raise RuntimeError("name a folder that driver and executors share in spark.checkpoint.dir")
        named = tempfile.mkdtemp(prefix="plates-")
        sc.setCheckpointDir(named)
        atexit.register(shutil.rmtree, named, True)
    path = f"{named}/corpus-{sc.applicationId}"
    if path not in _FOLDERS:
        _FOLDERS.add(path)
        atexit.register(_remove, sc, path)
    return path


_FOLDERS: set[str] = set()


def _remove(sc: SparkContext, path: str) -> None:
    if sc._jsc is None:  # stopped before the end of the program
        return
    target = sc._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(sc._jsc.hadoopConfiguration()).delete(target, True)


def scratch(spark: SparkSession, what: str) -> str:
    """A new path in the shared folder."""
    return f"{shared_folder(spark)}/{what}-{uuid.uuid4().hex}"


def stored(df: DataFrame, what: str, partition_by: list[str] | None = None) -> DataFrame:
    """Write ``df`` as a zstd Parquet table in the shared folder and read it back.

    This cuts the lineage: a lost executor costs a re-read, not a recomputation.
    """
    spark = df.sparkSession
    path = scratch(spark, what)
    writer = df.write.option("compression", "zstd")
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def hot_join(many: DataFrame, one: DataFrame, on: str, count: str = "n") -> DataFrame:
    """Inner join of ``many`` with ``one``, which has one row a key and in ``count`` how many rows of ``many`` may hold it.

    Keys of over 1 / ``HOT_SHARE`` of all rows, so at most ``HOT_SHARE`` keys, are broadcast and their rows stay where
    they are; the others are joined as usual.  Both sides should be tables, since they are read again.
    """
    size = one.agg(F.coalesce(F.sum(count), F.lit(0)).alias("total"), F.coalesce(F.max(count), F.lit(0)).alias("most")).first()
    bar = max(HOT_LEAST, size["total"] // HOT_SHARE)
    if size["most"] <= bar:
        return many.join(one.drop(count), on)
    hot, rest = one.filter(F.col(count) > bar), one.filter(F.col(count) <= bar).drop(count)
    by_broadcast = many.join(F.broadcast(hot.drop(count)), on)
    return by_broadcast.union(many.join(F.broadcast(hot.select(on)), on, "left_anti").join(rest, on).select(by_broadcast.columns))


def text_array(column: pa.Array | pa.ChunkedArray) -> pa.Array:
    """One string array without nulls; a null text counts as the empty one."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return pc.fill_null(column.cast(pa.string()), "")


def by_bytes(batches: Iterator[pa.RecordBatch], column: str, target: int) -> Iterator[pa.Table]:
    """Regroup record batches so that each holds about ``target`` bytes of ``column``.

    A row is never cut; one longer than the target forms a batch by itself.
    """
    held: list[pa.RecordBatch] = []
    size = 0
    for batch in batches:
        if not batch.num_rows:
            continue
        lengths = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
        ends = np.cumsum(lengths.astype(np.int64))
        start, base = 0, 0
        while start < batch.num_rows:
            stop = int(np.searchsorted(ends, base + target - size, side="right"))
            stop = min(batch.num_rows, max(stop, start + (0 if held else 1)))
            if stop > start:
                held.append(batch.slice(start, stop - start))
                size += int(ends[stop - 1] - base)
                base, start = int(ends[stop - 1]), stop
            if start < batch.num_rows or size >= target:
                yield pa.Table.from_batches(held)
                held, size = [], 0
    if held:
        yield pa.Table.from_batches(held)


def ragged(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Positions starts[i], starts[i]+1, ... (counts[i] of them) for every i, joined."""
    ends = np.cumsum(counts)
    total = int(ends[-1]) if len(ends) else 0
    return np.arange(total, dtype=np.int64) + np.repeat(starts - (ends - counts), counts)
