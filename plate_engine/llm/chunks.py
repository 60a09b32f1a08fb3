"""Texts as sequences of distinct chunks, so that a tokenizer sees every chunk once a batch."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: RE2 class of the characters whose letter, digit and space classes no Unicode version has changed:
#: ASCII without control characters, Latin-1 and Latin Extended-A (no dotted I), common punctuation.
SETTLED = r"\t\n\r\x20-\x7e\x{a1}-\x{ac}\x{ae}-\x{12f}\x{131}-\x{17e}\x{2010}-\x{2027}\x{20ac}"
#: Chunks beyond this many bytes are left to the library.
LONG_CHUNK = 2000


@dataclass
class ChunkedTexts:
    """``index[offsets[i]:offsets[i+1]]`` are the chunks of text i in ``table``; ``plain`` marks the
    texts for which the pieces between single spaces can be encoded one by one."""

    offsets: np.ndarray
    index: np.ndarray
    table: pa.Array
    plain: np.ndarray


def between_spaces(texts: pa.Array, odd: str) -> ChunkedTexts:
    """Cut plain texts at every space.  A text that matches the RE2 expression ``odd``, or has an
    over-long chunk, isn't plain and gets no chunks."""
    strange = pc.match_substring_regex(texts, odd)
    plain = ~strange.to_numpy(zero_copy_only=False)
    plain &= pc.binary_length(texts).to_numpy() > 0
    pieces = pc.split_pattern(pc.if_else(pa.array(plain), texts, ""), " ")
    offsets = pieces.offsets.to_numpy().astype(np.int64)
    values = pieces.values
    if len(values):
        size = pc.binary_length(values).to_numpy()
        if int(size.max()) > LONG_CHUNK:
            longest = np.maximum.reduceat(size, offsets[:-1])
            plain &= longest <= LONG_CHUNK
    kept = np.where(plain, np.diff(offsets), 0)
    if int(kept.sum()) != len(values):
        values = values.take(pa.array(np.flatnonzero(np.repeat(plain, np.diff(offsets)))))
    offsets = np.concatenate([[0], np.cumsum(kept)])
    coded = values.dictionary_encode()
    return ChunkedTexts(offsets, coded.indices.to_numpy(), coded.dictionary, plain)


def summed(values: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Sums of values[offsets[i]:offsets[i+1]]."""
    total = np.concatenate([[0], np.cumsum(values, dtype=np.int64)])
    return total[offsets[1:]] - total[offsets[:-1]]
