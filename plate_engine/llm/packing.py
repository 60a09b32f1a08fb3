"""Sum-of-squares packing of documents into sequences.

N(g) is the number of open sequences with g places left.  Each piece goes to the sequence, open or new,
that leaves the sum of N(g)^2 smallest, so no gap size piles up and later pieces find their fit; of equal sums an open
sequence goes before a new one, then the smallest gap left.  Longer pieces come first.  Pieces are dealt by hash over shards of
some ``SHARD_PIECES`` pieces, however many documents they are of, and a shard is packed by one task from lengths alone, so the state is one count a gap and the work grows in
proportion.  A shard wastes at most the few sequences that stay open at its end.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import by_bytes, ragged, stored, text_array
from .encoders import encoder

CAPACITY = 1024
SHARD_PIECES = 60_000
BATCH_BYTES = 8 << 20


def sum_of_squares(sizes: np.ndarray, capacity: int = CAPACITY) -> tuple[np.ndarray, np.ndarray]:
    """The bin and the place in it of every size (1 to ``capacity``), larger ones first."""
    open_bins: list[list[int]] = [[] for _ in range(capacity + 1)]
    count = np.zeros(capacity + 1, np.int64)
    bins, places = np.empty(len(sizes), np.int64), np.empty(len(sizes), np.int64)
    n = 0
    for k in np.argsort(-sizes, kind="stable"):
        size = int(sizes[k])
        # Change of the sum of squares: a bin leaves gap g for gap g - size; full bins aren't counted.
        left = count[: capacity + 1 - size].copy()
        change = 2 * (left + 1)
        change[0] = 1
        change -= 2 * count[size:]
        change[count[size:] == 0] = 1 << 60
        fresh = 2 * int(left[capacity - size]) + 1 if size < capacity else 0
        g = int(change.argmin())
        if change[g] <= fresh:
            gap = g + size
            b = open_bins[gap].pop()
            count[gap] -= 1
        else:
            gap, b = capacity, n
            n += 1
        bins[k], places[k] = b, capacity - gap
        if gap > size:
            open_bins[gap - size].append(b)
            count[gap - size] += 1
    return bins, places


def pieces(docs: DataFrame, tokenizer: str, end_id: int = 2, capacity: int = CAPACITY, text: str = "text", key: str = "doc_id", with_ids: bool = False) -> DataFrame:
    """``key, piece, start, length, ids_crc32`` (and ``ids``): each document's ids and the end id, those
    beyond the capacity cut into full pieces behind a first one that may be shorter."""
    kind = docs.schema[key].dataType.simpleString()

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in by_bytes(batches, "t", BATCH_BYTES):
            offsets, got = encoder(tokenizer).encode(text_array(table.column("t")))
            lengths = np.diff(offsets) + 1
            ids = np.full(len(got) + len(lengths), end_id, "<u4")
            ids[ragged(offsets[:-1] + np.arange(len(lengths)), lengths - 1)] = got
            number = -(-lengths // capacity)
            doc = np.repeat(np.arange(len(lengths)), number)
            piece = ragged(np.zeros(len(lengths), np.int64), number)
            head = lengths - (number - 1) * capacity
            start = np.where(piece == 0, 0, head[doc] + (piece - 1) * capacity)
            length = np.where(piece == 0, head[doc], capacity)
            raw = memoryview(ids.tobytes())
            spans = [raw[4 * a : 4 * b] for a, b in zip(np.cumsum(length) - length, np.cumsum(length), strict=True)]
            columns = {key: table.column("k").combine_chunks().take(pa.array(doc)), "piece": pa.array(piece, pa.int32()), "start": pa.array(start, pa.int64()), "length": pa.array(length, pa.int64()), "ids_crc32": pa.array([zlib.crc32(x) for x in spans], pa.int64())}
            if with_ids:
                columns["ids"] = pa.array([np.frombuffer(x, "<u4").astype(np.int32) for x in spans], pa.list_(pa.int32()))
            yield pa.RecordBatch.from_pydict(columns)

    schema = f"`{key}` {kind}, piece int, start long, length long, ids_crc32 long" + ", ids array<int>" * with_ids
    return docs.select(F.col(key).alias("k"), F.col(text).alias("t")).mapInArrow(cut, schema)


def pack(cut: DataFrame, capacity: int = CAPACITY, shard_pieces: int = SHARD_PIECES) -> DataFrame:
    """A table ``cut`` of pieces with ``sequence_id`` and ``offset``; its rows are counted first."""
    shards = max(1, -(-cut.count() // shard_pieces))
    schema = cut.schema.add("sequence_id", "long").add("offset", "long")

    def place(shard: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.drop(columns="shard").sort_values([c for c in ("length", "ids_crc32", "piece")], ascending=False, kind="stable")
        bins, places = sum_of_squares(rows["length"].to_numpy(), capacity)
        return rows.assign(sequence_id=bins * shards + int(shard[0]), offset=places)

    dealt = cut.withColumn("shard", F.pmod(F.xxhash64(cut.columns[0], "piece", "ids_crc32"), F.lit(shards)))
    return dealt.groupBy("shard").applyInPandas(place, schema)


def packed(docs: DataFrame, tokenizer: str, end_id: int = 2, capacity: int = CAPACITY) -> DataFrame:
    """One row a piece of every document of ``docs``, with its sequence and its place there.

    A null text counts as empty and is packed as the end id alone; repeated rows are packed each;
    an empty table gives no rows; other columns are ignored.
    """
    return pack(stored(pieces(docs, tokenizer, end_id, capacity), "pieces"), capacity)
