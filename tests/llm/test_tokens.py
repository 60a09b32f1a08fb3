import os
import zlib
from hashlib import sha256

import numpy as np
import public_tokenizers as P
import pyarrow as pa
import pytest
import sentencepiece
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from plate_engine.llm import packing, piece_codec, token_blocks, token_counts
from plate_engine.llm.encoders import encoder

from .conftest import AWKWARD

TEXTS = [t or "" for _, t in AWKWARD]
BYTE, WORD, PIECE = (P.path(x) for x in ("byte_bpe_50k.json", "word_bpe_49k.json", "piece_bpe_32k.model"))


@pytest.mark.parametrize("path", [BYTE, WORD])
def test_ids_equal_the_library(path):
    library = Tokenizer.from_file(path)
    offsets, ids = encoder(path).encode(pa.array(TEXTS))
    want = [e.ids for e in library.encode_batch(TEXTS, add_special_tokens=False)]
    assert [ids[a:b].tolist() for a, b in zip(offsets[:-1], offsets[1:], strict=True)] == want


@settings(max_examples=150, deadline=None)
@given(st.lists(st.text(alphabet=st.sampled_from(list("aAbB xX\n\t 1é€'s.|<>!ß")) | st.characters(codec="utf-8"), max_size=40), max_size=6))
def test_any_text_equals_the_libraries(texts):
    for path in (BYTE, WORD):
        offsets, ids = encoder(path).encode(pa.array(texts, pa.string()))
        want = [e.ids for e in encoder(path).library.encode_batch(texts, add_special_tokens=False)]
        assert [ids[a:b].tolist() for a, b in zip(offsets[:-1], offsets[1:], strict=True)] == want
    pieces = encoder(PIECE)
    assert pieces.counts(pa.array(texts, pa.string())).tolist() == [len(pieces.library.encode(t)) for t in texts]


def test_counts(spark, awkward):
    library = Tokenizer.from_file(BYTE)
    got = {r["doc_id"]: r for r in token_counts.token_counts(awkward, BYTE).collect()}
    for (i, _), t in zip(AWKWARD, TEXTS, strict=True):
        n = len(library.encode(t, add_special_tokens=False).ids)
        assert (got[i]["n_bytes"], got[i]["n_tokens"], got[i]["over_limit"]) == (len(t.encode()), n, n > 512)
    assert token_counts.token_counts(awkward.limit(0), BYTE).count() == 0


def test_pieces(spark, awkward):
    library = sentencepiece.SentencePieceProcessor(model_file=PIECE)
    got = {r["doc_id"]: r for r in piece_codec.piece_digests(awkward, PIECE).collect()}
    whole = {r["doc_id"]: r for r in piece_codec.piece_ids(awkward, PIECE).collect()}
    for (i, _), t in zip(AWKWARD, TEXTS, strict=True):
        ids = library.encode(t)
        text = library.decode(ids) if ids else ""
        assert got[i]["n_tokens"] == len(ids) and whole[i]["ids"] == ids and whole[i]["decoded"] == text
        assert got[i]["ids_sha256"] == sha256(",".join(map(str, ids)).encode()).hexdigest()
        assert got[i]["decoded_sha256"] == sha256(text.encode()).hexdigest()


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 2**32 - 1) | st.integers(0, 300), max_size=700))
def test_blocks_round_trip(ids):
    x = np.array(ids, np.uint32)
    packed = memoryview(token_blocks.pack_ids(x))
    assert token_blocks.unpack_ids(packed, len(x)).tolist() == ids
    if len(x) > 300:
        assert token_blocks.unpack_ids(packed, len(x), 1, 2).tolist() == ids[128:256]


def test_outliers_are_patched_not_packed():
    x = np.full(12800, 5, np.uint32)
    x[::128] = 4_000_000_000
    assert len(token_blocks.pack_ids(x)) < 12800


def test_token_files(spark, awkward):
    library = Tokenizer.from_file(WORD)
    rows = token_blocks.token_blocks(awkward.repartition(3), WORD).orderBy("doc_id").collect()
    start = 0
    for r, (i, _), t in zip(rows, AWKWARD, TEXTS, strict=True):
        ids = np.array([*library.encode(t, add_special_tokens=False).ids, 1], "<u4")
        assert (r["doc_id"], r["start"], r["n_tokens"], r["ids_crc32"]) == (i, start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)
    assert token_blocks.token_blocks(awkward.limit(0), WORD).count() == 0
    twice = awkward.union(awkward).union(awkward.limit(2).selectExpr("cast(null as long)", "text", "lang", "source", "n_tokens", "score"))
    again = token_blocks.token_blocks(twice, WORD).orderBy("start").collect()
    assert [r["doc_id"] for r in again] == [None, None] + sorted([i for i, _ in AWKWARD] * 2)
    assert [r["start"] for r in again] == np.cumsum([0] + [r["n_tokens"] for r in again])[:-1].tolist()
    assert {(r["doc_id"], r["ids_crc32"]) for r in again if r["doc_id"] is not None} == {(r["doc_id"], r["ids_crc32"]) for r in rows}


def test_documents_are_read_by_their_blocks(spark, awkward, monkeypatch):
    path = token_blocks.scratch(spark, "some-files")
    token_blocks.write_files(token_blocks.encode_segments(awkward, WORD), path)
    library = Tokenizer.from_file(WORD)
    got = {r["doc_id"]: r["ids"] for r in token_blocks.read_documents(token_blocks.files(spark, path), [4, 8, 13]).collect()}
    assert got == {i: [*library.encode(TEXTS[i], add_special_tokens=False).ids, 1] for i in (4, 8, 13)}
    names = [f for _, _, fs in os.walk(path.removeprefix("file:")) for f in fs if f.endswith(".txt")]
    assert names  # the format's own files, not tables


def brute_pack(sizes, capacity):
    """The rule as it reads: try every open gap and a new sequence, take the smallest sum of squares."""
    gaps, n = {}, 0
    for s in sorted(sizes, reverse=True):
        def after(g, s=s):
            c = dict(gaps)
            if g is not None:
                c[g] -= 1
            left = (capacity if g is None else g) - s
            if left:
                c[left] = c.get(left, 0) + 1
            return sum(v * v for v in c.values()), c
        options = [(after(g)[0], g) for g in gaps if gaps[g] and g >= s]
        best = min(options, default=None)
        fresh = after(None)[0]
        if best is None or best[0] > fresh:
            n += 1
            gaps = after(None)[1]
        else:
            gaps = after(best[1])[1]
    return n


def test_sum_of_squares_follows_the_rule():
    rng = np.random.default_rng(1)
    for turn in range(300):
        capacity = int(rng.integers(8, 60))
        sizes = np.minimum(rng.zipf(1.4, 120) if turn % 2 else rng.integers(1, capacity + 1, 120), capacity)
        bins, places = packing.sum_of_squares(sizes, capacity)
        assert bins.max() + 1 == brute_pack(sizes.tolist(), capacity)
        for b in range(bins.max() + 1):
            own = sorted(zip(places[bins == b], sizes[bins == b], strict=True))
            assert own[0][0] == 0 and all(p + s == q for (p, s), (q, _) in zip(own, own[1:], strict=False)) and sum(own[-1]) <= capacity


def test_packed_documents(spark, awkward):
    library = Tokenizer.from_file(BYTE)
    rows = packing.packed(awkward, BYTE).collect()
    by_doc, by_sequence = {}, {}
    for r in rows:
        by_doc.setdefault(r["doc_id"], []).append(r)
        by_sequence.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for (i, _), t in zip(AWKWARD, TEXTS, strict=True):
        ids = np.array([*library.encode(t, add_special_tokens=False).ids, 2], "<u4")
        own = sorted(by_doc[i], key=lambda r: r["piece"])
        assert [r["piece"] for r in own] == list(range(len(own))) and sum(r["length"] for r in own) == len(ids)
        assert all(r["length"] == 1024 for r in own[1:]) and len(own) == -(-len(ids) // 1024)
        for r in own:
            assert r["ids_crc32"] == zlib.crc32(ids[r["start"] : r["start"] + r["length"]].tobytes())
    for spans in by_sequence.values():
        spans.sort()
        assert spans[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(spans, spans[1:], strict=False)) and sum(spans[-1]) <= 1024
    assert packing.packed(awkward.limit(0), BYTE).count() == 0
