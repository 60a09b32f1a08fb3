"""SentencePiece encoding and decoding by a distinct-chunk table.

Where no piece crosses the white-space mark, a text's ids are those of its marked words in turn.  A
task encodes and decodes every distinct marked word of a batch once and joins ids, their decimal
forms and the decoded words back by position.  Texts with doubled or outer spaces or rare characters
go through the library whole.  A null text counts as empty; an empty text has no ids and decodes to
the empty text; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import sha256

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .chunks import summed
from .common import by_bytes, ragged, text_array
from .encoders import PieceEncoder, encoder

BATCH_BYTES = 24 << 20


def _round_trip(pieces: PieceEncoder, texts: pa.Array) -> Iterator[tuple[int, list[str], list[str]]]:
    """For each text: number of ids, its parts in decimal ids, its decoded parts."""
    cut, words, ids = pieces.table(texts)
    decoded = pieces.library.decode(ids) if words else []
    decimal = [",".join(map(str, x)) for x in ids]
    index = cut.index.tolist()
    counts = summed(np.array([len(x) for x in ids], np.int64)[cut.index], cut.offsets) if words else np.zeros(len(texts), np.int64)
    for i, plain in enumerate(cut.plain):
        if plain:
            own = index[cut.offsets[i] : cut.offsets[i + 1]]
            yield int(counts[i]), [decimal[k] for k in own], [decoded[k] for k in own]
        else:
            whole = pieces.library.encode(texts[i].as_py())
            yield len(whole), [",".join(map(str, whole))] if whole else [], [pieces.library.decode(whole)] if whole else []


def piece_digests(docs: DataFrame, tokenizer: str, text: str = "text", key: str = "doc_id") -> DataFrame:
    """``key, n_tokens, ids_sha256, decoded_sha256`` for every row."""
    kind = docs.schema[key].dataType.simpleString()

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in by_bytes(batches, "t", BATCH_BYTES):
            rows = [(n, sha256(",".join(d).encode()).hexdigest(), sha256(" ".join(w).encode()).hexdigest()) for n, d, w in _round_trip(encoder(tokenizer), text_array(table.column("t")))]
            n, ids, decoded = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([table.column("k").combine_chunks(), pa.array(n, pa.int64()), pa.array(ids), pa.array(decoded)], [key, "n_tokens", "ids_sha256", "decoded_sha256"])

    narrow = docs.select(F.col(key).alias("k"), F.col(text).alias("t"))
    return narrow.mapInArrow(digest, f"`{key}` {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")


def piece_ids(docs: DataFrame, tokenizer: str, text: str = "text", key: str = "doc_id") -> DataFrame:
    """``key, ids array<int>, decoded string`` for every row: the ids and the decoded text themselves."""
    kind = docs.schema[key].dataType.simpleString()

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in by_bytes(batches, "t", BATCH_BYTES):
            pieces, texts = encoder(tokenizer), text_array(table.column("t"))
            cut, words, ids = pieces.table(texts)
            each = np.array([len(x) for x in ids], np.int64)
            flat = np.array([x for own in ids for x in own], np.int32)
            counts = summed(each[cut.index], cut.offsets) if words else np.zeros(len(texts), np.int64)
            starts = (np.cumsum(each) - each)[cut.index] if words else np.zeros(0, np.int64)
            fast = np.split(flat[ragged(starts, each[cut.index])] if words else flat, np.cumsum(counts)[:-1])
            lists = [fast[i].tolist() if cut.plain[i] else pieces.library.encode(texts[i].as_py()) for i in range(len(texts))]
            decoded = [pieces.library.decode(x) if x else "" for x in lists]
            yield pa.RecordBatch.from_arrays([table.column("k").combine_chunks(), pa.array(lists, pa.list_(pa.int32())), pa.array(decoded, pa.string())], [key, "ids", "decoded"])

    narrow = docs.select(F.col(key).alias("k"), F.col(text).alias("t"))
    return narrow.mapInArrow(encode, f"`{key}` {kind}, ids array<int>, decoded string")
