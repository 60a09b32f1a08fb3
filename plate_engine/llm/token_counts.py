"""Token counts: encoding in Arrow batches that returns lengths only.

Batches are balanced by bytes, not rows, and a text is cut at boundaries that no token crosses, so a
20,000-word text and a batch of short ones cost what their bytes cost.  Null and empty texts have no
tokens, repeated rows are counted each, an empty table gives none; columns other than the id and the
text are ignored, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import by_bytes, text_array
from .encoders import encoder

BATCH_BYTES = 24 << 20


def token_counts(docs: DataFrame, tokenizer: str, limit: int = 512, text: str = "text", key: str = "doc_id") -> DataFrame:
    """``key, n_bytes, n_tokens, over_limit`` for every row of ``docs``."""
    kind = docs.schema[key].dataType.simpleString()

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in by_bytes(batches, "t", BATCH_BYTES):
            texts = text_array(table.column("t"))
            n = pa.array(encoder(tokenizer).counts(texts), pa.int64())
            keys = table.column("k").combine_chunks()
            yield pa.RecordBatch.from_arrays([keys, pc.binary_length(texts).cast(pa.int64()), n, pc.greater(n, limit)], [key, "n_bytes", "n_tokens", "over_limit"])

    narrow = docs.select(F.col(key).alias("k"), F.col(text).alias("t"))
    return narrow.mapInArrow(count, f"`{key}` {kind}, n_bytes long, n_tokens long, over_limit boolean")
