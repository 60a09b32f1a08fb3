"""Batch encoders over Arrow string arrays, equal to the tokenizer libraries id for id.

Every encoder takes an array of texts and gives ``(offsets, ids)``: the ids of text i are
``ids[offsets[i]:offsets[i+1]]``.  Texts made of settled characters are cut at boundaries that no
token can cross, each distinct chunk is encoded once a batch and its ids are gathered by position;
all other texts (special strings, doubled spaces, rare characters, huge words) go to the library whole.
"""

from __future__ import annotations

import json
import os
from functools import cached_property, lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .chunks import LONG_CHUNK, SETTLED, between_spaces, summed
from .common import ragged

# The published byte-level pre-tokenizer patterns.
BYTE_LEVEL_PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
WORD_PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"""

Encoded = tuple[np.ndarray, np.ndarray]


def _literal(text: str) -> str:
    return "".join(c if c.isalnum() else "\\" + c for c in text)


def byte_alphabet() -> dict[str, int]:
    """The published printable stand-ins of byte-level vocabularies: character to byte."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in set(shown)]
    return {chr(b): b for b in shown} | {chr(256 + k): b for k, b in enumerate(hidden)}


def token_bytes(token: str, alphabet: dict[str, int]) -> bytes:
    return bytes(alphabet[c] for c in token)


def _merge_pairs(model: dict) -> list[tuple[str, str]]:
    return [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]


def _assembled(n: int, plain: np.ndarray, counts: np.ndarray, fast_ids: np.ndarray, slow: dict[int, list[int]]) -> Encoded:
    """Put the ids of the plain texts and those of the others in the order of the texts."""
    if not slow:
        return np.concatenate([[0], np.cumsum(counts)]), fast_ids
    total = counts.copy()
    for i, got in slow.items():
        total[i] = len(got)
    offsets = np.concatenate([[0], np.cumsum(total)])
    ids = np.empty(int(offsets[-1]), np.uint32)
    ids[ragged(offsets[:-1][plain], total[plain])] = fast_ids
    for i, got in slow.items():
        ids[offsets[i] : offsets[i + 1]] = got
    return offsets, ids


class _Library:
    """What the encoders of ``.json`` files share: the library itself, and its special strings."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        with open(path, encoding="utf-8") as file:
            self.spec = json.load(file)
        self.path = path
        self.special = [t["content"] for t in self.spec["added_tokens"]]

    @cached_property
    def library(self):
        from tokenizers import Tokenizer

        return Tokenizer.from_file(self.path)

    def whole(self, texts: list[str]) -> list[list[int]]:
        return [e.ids for e in self.library.encode_batch(texts, add_special_tokens=False)]

    def _slow(self, texts: pa.Array, plain: np.ndarray) -> dict[int, list[int]]:
        where = np.flatnonzero(~plain & (pc.binary_length(texts).to_numpy() > 0))
        return {int(i): self.whole([texts[int(i)].as_py()])[0] for i in where}


class ByteLevelEncoder(_Library):
    """Byte-level BPE whose ids follow the merge order, so a rank-driven engine gives the same ids."""

    def __init__(self, path: str):
        super().__init__(path)
        model, alphabet = self.spec["model"], byte_alphabet()
        vocab = model["vocab"]
        pre = self.spec["pre_tokenizer"]
        ordered = all(vocab[a + b] == 256 + k for k, (a, b) in enumerate(_merge_pairs(model)))
        self.by_rank = ordered and self.spec["normalizer"] is None and pre["type"] == "ByteLevel" and not pre["add_prefix_space"] and not model.get("end_of_word_suffix")
        if self.by_rank:
            import tiktoken

            ranks = {token_bytes(t, alphabet): i for t, i in vocab.items() if i < 256 + len(model["merges"])}
            self.engine = tiktoken.Encoding("ranks", pat_str=BYTE_LEVEL_PATTERN, mergeable_ranks=ranks, special_tokens={})
            self.width = np.zeros(max(ranks.values()) + 1, np.int64)
            for token, i in ranks.items():
                self.width[i] = len(token)
        spaces = r"[\s] | [\s]| $"
        self.odd = "|".join([spaces, rf"[^{SETTLED}]", *map(_literal, self.special)]) if self.by_rank else ""

    def _table(self, texts: pa.Array):
        """Chunks of the plain texts, with each chunk's number of ids and the joined ids.

        A space between two other characters always starts a token, so a chunk after such a space
        is encoded with it, and joined chunks have the ids of each one in turn.
        """
        cut = between_spaces(texts, self.odd)
        words = cut.table.to_pylist()
        ids = self.engine.encode_to_numpy("".join([" " + w for w in words])) if words else np.zeros(0, np.uint32)
        ends = np.cumsum(pc.binary_length(cut.table).to_numpy().astype(np.int64) + 1) if words else np.zeros(0, np.int64)
        last = np.searchsorted(np.cumsum(self.width[ids]), ends, side="left") + 1
        counts = np.diff(np.concatenate([[0], last]))
        first = cut.offsets[:-1][cut.plain]
        heads = np.unique(cut.index[first])
        own = [self.engine.encode_ordinary(words[h]) for h in heads]
        index = cut.index.astype(np.int64)
        index[first] = len(words) + np.searchsorted(heads, cut.index[first])
        counts = np.concatenate([counts, np.array([len(x) for x in own], np.int64)]).astype(np.int64)
        ids = np.concatenate([ids, *[np.array(x, np.uint32) for x in own]]).astype(np.uint32)
        return cut, index, counts, ids

    def counts(self, texts: pa.Array) -> np.ndarray:
        """Numbers of ids only; no id list of a plain text is ever formed."""
        if not self.by_rank:
            return np.array([len(x) for x in self.whole(texts.to_pylist())], np.int64)
        cut, index, counts, _ = self._table(texts)
        out = summed(counts[index], cut.offsets)
        for i, got in self._slow(texts, cut.plain).items():
            out[i] = len(got)
        return out

    def encode(self, texts: pa.Array) -> Encoded:
        if not self.by_rank:
            lists = self.whole(texts.to_pylist())
            return np.cumsum([0, *map(len, lists)]), np.array([x for ids in lists for x in ids], np.uint32)
        cut, index, counts, ids = self._table(texts)
        starts = np.cumsum(counts) - counts
        each = counts[index]
        return _assembled(len(texts), cut.plain, summed(each, cut.offsets), ids[ragged(starts[index], each)], self._slow(texts, cut.plain))


class WordEndEncoder(_Library):
    """BPE with a word-end suffix over lower-cased text without white space.

    The suffix becomes one byte 0, which settled texts don't hold: joining it to a word's last byte
    ranks before all merges, then the merges keep their order.
    """

    def __init__(self, path: str):
        super().__init__(path)
        import regex
        import tiktoken

        model, alphabet = self.spec["model"], byte_alphabet()
        vocab, suffix = model["vocab"], model["end_of_word_suffix"]

        def marked(token: str) -> bytes:
            ended = token.endswith(suffix)
            return token_bytes(token[: -len(suffix)] if ended else token, alphabet) + b"\0" * ended

        ranks = {bytes([b]): b for b in range(256)} | {bytes([b, 0]): 256 + b for b in range(256)}
        ids = {c_byte: vocab[c] for c, b in alphabet.items() for c_byte in [bytes([b])]}
        ids |= {bytes([b, 0]): vocab[c + suffix] for c, b in alphabet.items()}
        for a, b in _merge_pairs(model):
            token = marked(a)[:None] + marked(b)
            ranks.setdefault(token, len(ranks))
            ids.setdefault(token, vocab[a + b])
        self.id_of = np.zeros(len(ranks), np.uint32)
        self.ends = np.zeros(len(ranks), bool)
        for token, rank in ranks.items():
            self.id_of[rank] = ids[token]
            self.ends[rank] = token.endswith(b"\0")
        self.gap = ranks[b" \0"]
        self.engine = tiktoken.Encoding("words", pat_str=r"[^\x00]*\x00", mergeable_ranks=ranks, special_tokens={})
        self.cut = regex.compile(WORD_PATTERN + "| ")
        self.odd = "|".join([rf"[^{SETTLED}]", *map(_literal, self.special)])

    def encode(self, texts: pa.Array) -> Encoded:
        plain = ~pc.match_substring_regex(texts, self.odd).to_numpy(zero_copy_only=False)
        pieces = pc.ascii_split_whitespace(pc.if_else(pa.array(plain), texts, ""))
        offsets = pieces.offsets.to_numpy().astype(np.int64)
        values = pieces.values
        filled = pc.binary_length(values).to_numpy() > 0
        if len(values) and int(pc.max(pc.binary_length(values)).as_py()) > LONG_CHUNK:
            short = np.maximum.reduceat(pc.binary_length(values).to_numpy(), np.minimum(offsets[:-1], len(values) - 1)) <= LONG_CHUNK
            plain &= short
            filled &= np.repeat(short, np.diff(offsets))
        offsets = np.concatenate([[0], np.cumsum(filled)])[offsets]
        coded = values.filter(pa.array(filled)).dictionary_encode()
        chunks = coded.dictionary.to_pylist()
        parts = self.cut.findall(" ".join(chunks).lower())
        ranks = self.engine.encode_to_numpy("".join([p + "\0" for p in parts])) if parts else np.zeros(0, np.uint32)
        split = ranks == self.gap
        ids = self.id_of[ranks[~split]]
        chunk = np.cumsum(split)[~split]
        counts = np.bincount(chunk, minlength=len(chunks)).astype(np.int64)
        starts = np.cumsum(counts) - counts
        index = coded.indices.to_numpy()
        each = counts[index]
        return _assembled(len(texts), plain, summed(each, offsets), ids[ragged(starts[index], each)], self._slow(texts, plain))


class PieceEncoder:
    """SentencePiece BPE.  Where no piece but runs of the white-space mark holds the mark after its
    first character, every marked word is segmented by itself."""

    MARK = "▁"

    def __init__(self, path: str):
        import sentencepiece

        self.library = sentencepiece.SentencePieceProcessor(model_file=path)
        pieces = [self.library.id_to_piece(i) for i in range(self.library.get_piece_size())]
        self.separable = not any(self.MARK in p[1:] and p.strip(self.MARK) for p in pieces)
        self.odd = rf"  |^ | $|[^{SETTLED}]"

    def table(self, texts: pa.Array):
        """The distinct-chunk table of a batch: chunks, their ids, and the texts' chunk positions."""
        cut = between_spaces(texts, self.odd if self.separable else "")
        words = cut.table.to_pylist()
        return cut, words, self.library.encode(words, num_threads=1) if words else []

    def counts(self, texts: pa.Array) -> np.ndarray:
        cut, words, ids = self.table(texts)
        each = np.array([len(x) for x in ids], np.int64)
        out = summed(each[cut.index], cut.offsets) if words else np.zeros(len(texts), np.int64)
        for i in np.flatnonzero(~cut.plain):
            out[i] = len(self.library.encode(texts[int(i)].as_py()))
        return out


@lru_cache(maxsize=4)
def encoder(path: str):
    """The encoder of a tokenizer file, built once a Python worker."""
    if not path.endswith(".json"):
        return PieceEncoder(path)
    with open(path, encoding="utf-8") as file:
        suffix = json.load(file)["model"].get("end_of_word_suffix")
    return WordEndEncoder(path) if suffix else ByteLevelEncoder(path)
