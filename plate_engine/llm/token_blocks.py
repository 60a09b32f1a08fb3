"""Token ids in files of patched frame-of-reference blocks.

A file holds up to ``SEGMENTS_A_FILE`` segments one behind the other.  A segment is self-contained: a header with its size,
place and counts, a document table (id, length), a block index (start of every block), blocks, exceptions, and a
closing byte 0x0A.  A block holds 128 ids less their minimum, packed at the width that
a percentile of them needs; ids beyond the width go to its exception list and are patched in on
reading.  Files are written by Spark's own writer, so any store that Spark reaches will do and a task that is
run again replaces its files; they are read as binary files.  Documents are in ascending order: ``part`` and ``seq``
of the header order the segments, and the ids before a document are its part's base plus the
running count inside the part.  ``read_documents`` decodes only the blocks of the documents asked for.

Defined cases: a null text counts as empty and holds the end id alone; null document ids come first and stay
null; repeated rows are encoded each, rows of one id in the order of their text's hash; an empty table gives no
segments; other columns are ignored.  Ids of documents are whole numbers (64 bits).
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import by_bytes, ragged, scratch, stored, text_array
from .encoders import encoder

BLOCK = 128
PERCENTILE = 0.9
BATCH_BYTES = 2 << 20
SEGMENTS_A_FILE = 16
HEAD = struct.Struct("<4sHHQQQQQQ")  # magic, version, block, size, part, seq, ids before in the part, documents, ids
MAGIC = b"PFR2"


def _bits(values: np.ndarray) -> np.ndarray:
    """Bits that each value needs (0 for 0)."""
    return np.frexp(values.astype(np.float64))[1].astype(np.int64)


def _runs(blocks: np.ndarray, most: int = 8192) -> list[np.ndarray]:
    """So many blocks at a time that their single bits take little memory."""
    return [blocks[i : i + most] for i in range(0, len(blocks), most)]


def pack_ids(ids: np.ndarray, percentile: float = PERCENTILE) -> bytes:
    """Blocks of ``ids`` (unsigned 32-bit), behind their index and before their exceptions."""
    n = len(ids)
    blocks = -(-n // BLOCK)
    padded = np.concatenate([ids, np.full(blocks * BLOCK - n, ids[-1] if n else 0, np.uint32)]).reshape(blocks, BLOCK)
    low = padded.min(axis=1) if blocks else np.zeros(0, np.uint32)
    rest = padded - low[:, None]
    rank = min(BLOCK - 1, int(percentile * BLOCK))
    width = _bits(np.partition(rest, rank, axis=1)[:, rank]) if blocks else np.zeros(0, np.int64)
    over = (rest.astype(np.uint64) >> width[:, None].astype(np.uint64)) > 0
    at = np.flatnonzero(over)
    sizes = width * (BLOCK // 8)
    starts = np.cumsum(sizes) - sizes
    body = np.zeros(int(sizes.sum()), np.uint8)
    for w in np.unique(width[width > 0]):
        for own in _runs(np.flatnonzero(width == w)):
            bits = (rest[own][:, :, None] >> np.arange(w, dtype=np.uint32)) & 1
            packed = np.packbits(bits.astype(np.uint8).reshape(len(own), -1), axis=1, bitorder="little")
            body[ragged(starts[own], sizes[own])] = packed.ravel()
    tables = [starts.astype("<u8"), low.astype("<u4"), width.astype("u1"), over.sum(axis=1).astype("<u2")]
    patches = [(at % BLOCK).astype("u1"), rest.ravel()[at].astype("<u4")]
    return struct.pack("<QQ", len(body), len(at)) + b"".join(x.tobytes() for x in [*tables, body, *patches])


def unpack_ids(data: memoryview, n: int, first: int = 0, last: int | None = None) -> np.ndarray:
    """The ids of blocks ``first`` to ``last``, found through the block index."""
    blocks = -(-n // BLOCK)
    body_size, n_patches = struct.unpack_from("<QQ", data)
    at = 16

    def take(kind: str, count: int) -> np.ndarray:
        nonlocal at
        got = np.frombuffer(data, kind, count, at)
        at += got.nbytes
        return got

    starts, low, width, patched = take("<u8", blocks), take("<u4", blocks), take("u1", blocks), take("<u2", blocks)
    body, place, value = take("u1", body_size), take("u1", n_patches), take("<u4", n_patches)
    last = blocks if last is None else last
    out = np.zeros((last - first, BLOCK), np.uint32)
    for w in np.unique(width[first:last]):
        if not w:
            continue
        for own in _runs(np.flatnonzero(width[first:last] == w)):
            size = np.full(len(own), int(w) * (BLOCK // 8))
            raw = body[ragged(starts[first:last][own].astype(np.int64), size)].reshape(len(own), -1)
            bits = np.unpackbits(raw, axis=1, bitorder="little").reshape(len(own), BLOCK, int(w))
            out[own] = np.packbits(np.pad(bits, ((0, 0), (0, 0), (0, 32 - int(w)))), axis=2, bitorder="little").view("<u4")[:, :, 0]
    ends = np.cumsum(patched, dtype=np.int64)
    a, b = (int(ends[first - 1]) if first else 0), (int(ends[last - 1]) if last else 0)
    block = np.repeat(np.arange(last - first), patched[first:last])
    out[block, place[a:b]] = value[a:b]
    return (out + low[first:last, None]).ravel()[: n - first * BLOCK]


@dataclass
class Segment:
    """One segment of a file: its place, document table and packed ids."""

    part: int
    seq: int
    first: int
    docs: list[int | None]
    lengths: np.ndarray
    n_ids: int
    packed: memoryview

    @classmethod
    def all_of(cls, data: bytes) -> Iterator[Segment]:
        """The segments of a file's bytes, in order."""
        view, at = memoryview(data), 0
        while at < len(view):
            magic, version, block, size, part, seq, first, n_docs, n_ids = HEAD.unpack_from(view, at)
            if magic != MAGIC or version != 2 or block != BLOCK or at + size > len(view):
                raise ValueError("not a segment of this format")
            table = at + HEAD.size
            numbers = np.frombuffer(view, "<i8", n_docs, table).tolist()
            null = np.frombuffer(view, "u1", n_docs, table + 8 * n_docs).tolist()
            lengths = np.frombuffer(view, "<u8", n_docs, table + 9 * n_docs).astype(np.int64)
            yield cls(part, seq, first, [None if z else x for x, z in zip(numbers, null, strict=True)], lengths, n_ids, view[table + 17 * n_docs : at + size - 1])
            at += size

    def starts(self) -> np.ndarray:
        return np.cumsum(self.lengths) - self.lengths

    def ids(self, start: int = 0, stop: int | None = None) -> np.ndarray:
        """Ids ``start`` to ``stop`` of the segment; only their blocks are decoded."""
        stop = self.n_ids if stop is None else stop
        first = start // BLOCK
        got = unpack_ids(self.packed, self.n_ids, first, -(-stop // BLOCK))
        return got[start - first * BLOCK : stop - first * BLOCK]


def write_segment(docs: list[int | None], lengths: np.ndarray, ids: np.ndarray, part: int = 0, seq: int = 0, first: int = 0) -> bytes:
    numbers = np.array([0 if d is None else d for d in docs], "<i8")
    null = np.array([d is None for d in docs], "u1")
    body = numbers.tobytes() + null.tobytes() + lengths.astype("<u8").tobytes() + pack_ids(ids) + b"\n"
    return HEAD.pack(MAGIC, 2, BLOCK, HEAD.size + len(body), part, seq, first, len(lengths), len(ids)) + body


def encode_segments(docs: DataFrame, tokenizer: str, end_id: int = 1, text: str = "text", key: str = "doc_id") -> DataFrame:
    """``payload``: segments in ascending order of the (long) ``key``."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, first = TaskContext.get().partitionId(), 0
        for seq, table in enumerate(by_bytes(batches, "t", BATCH_BYTES)):
            offsets, got = encoder(tokenizer).encode(text_array(table.column("t")))
            lengths = np.diff(offsets) + 1
            ids = np.full(len(got) + len(lengths), end_id, np.uint32)
            ids[ragged(offsets[:-1] + np.arange(len(lengths)), lengths - 1)] = got
            payload = write_segment(table.column("k").to_pylist(), lengths, ids, part, seq, first)
            yield pa.RecordBatch.from_pydict({"payload": [payload]})
            first += len(ids)

    ordered = docs.select(F.col(key).cast("long").alias("k"), F.col(text).alias("t"), F.xxhash64(text).alias("h")).repartitionByRange("k", "h").sortWithinPartitions("k", "h")
    return ordered.select("k", "t").mapInArrow(write, "payload binary")


def write_files(segments: DataFrame, path: str) -> None:
    """Write segments to files, each record's bytes as they are (the last is the line end that the writer adds)."""
    raw = F.expr("cast(substring(payload, 1, length(payload) - 1) as string)").alias("value")
    segments.select(raw).write.option("lineSep", "\n").option("maxRecordsPerFile", SEGMENTS_A_FILE).text(path)


def files(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.format("binaryFile").load(path).filter("length > 0").select("content")


def decode_files(content: DataFrame) -> DataFrame:
    """``doc_id, start, n_tokens, ids_crc32`` of every document, read from the files alone."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for data in batch.column("content"):
                for s in Segment.all_of(data.as_buffer()):
                    starts = s.starts()
                    raw = memoryview(s.ids().astype("<u4").tobytes())
                    crc = [zlib.crc32(raw[4 * a : 4 * (a + n)]) for a, n in zip(starts.tolist(), s.lengths.tolist(), strict=True)]
                    yield pa.RecordBatch.from_pydict({"part": pa.array([s.part] * len(crc), pa.int64()), "doc_id": pa.array(s.docs, pa.int64()), "inside": pa.array(s.first + starts, pa.int64()), "n_tokens": pa.array(s.lengths, pa.int64()), "ids_crc32": pa.array(crc, pa.int64())})

    rows = stored(content.mapInArrow(read, "part long, doc_id long, inside long, n_tokens long, ids_crc32 long"), "token-documents")
    # One row a part: as many as shuffle partitions, however large the corpus.
    bases = rows.groupBy("part").agg(F.sum("n_tokens").alias("n")).select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("base"))
    return rows.join(F.broadcast(bases), "part").select("doc_id", (F.col("base") + F.col("inside")).alias("start"), "n_tokens", "ids_crc32")


def read_documents(content: DataFrame, wanted: list[int]) -> DataFrame:
    """``doc_id, ids`` of the documents of a list of ids; of a segment only their blocks are decoded."""
    chosen = frozenset(wanted)

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for data in batch.column("content"):
                for s in Segment.all_of(data.as_buffer()):
                    for doc, start, n in zip(s.docs, s.starts().tolist(), s.lengths.tolist(), strict=True):
                        if doc in chosen:
                            yield pa.RecordBatch.from_pydict({"doc_id": pa.array([doc], pa.int64()), "ids": pa.array([s.ids(start, start + n).tolist()], pa.list_(pa.int64()))})

    return content.mapInArrow(read, "doc_id long, ids array<long>")


def token_blocks(docs: DataFrame, tokenizer: str, end_id: int = 1) -> DataFrame:
    """The documents as the files say, which are written to the shared folder and read again."""
    path = scratch(docs.sparkSession, "token-files")
    write_files(encode_segments(docs, tokenizer, end_id), path)
    return decode_files(files(docs.sparkSession, path))
