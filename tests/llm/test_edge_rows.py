"""Repeated rows, null ids, clashing columns and empty tables, for the operators on tokens and the pipeline's stages."""

from collections import Counter

import public_tokenizers as P
import pytest
from pyspark.sql import functions as F

from plate_engine.llm import near_dedup, packing, piece_codec, quality_rules, token_counts, toxicity

from .conftest import AWKWARD

BYTE, PIECE = P.path("byte_bpe_50k.json"), P.path("piece_bpe_32k.model")
CLASHING = ("k", "t", "h", "n", "y", "id", "root", "band", "same", "size", "words", "stratum", "label", "kept", "toxic", "quality")


@pytest.fixture
def repeated(awkward):
    nameless = awkward.filter("doc_id in (3, 10)").withColumn("doc_id", F.lit(None).cast("long"))
    return awkward.union(awkward.filter("doc_id < 6")).union(nameless)


@pytest.fixture
def marks(spark):
    rows = [(i, i % 2, 1 - i % 2) for i, _ in AWKWARD] + [(3, 0, 1), (None, 1, 1), (4, None, None), (999, 1, 0)]
    return spark.createDataFrame(rows, "doc_id long, toxic int, quality int")


def counted(df, *columns):
    return Counter(tuple(r) for r in df.select(*columns).collect())


def test_token_counts_keep_every_row(awkward, repeated):
    once = {r["doc_id"]: (r["n_bytes"], r["n_tokens"]) for r in token_counts.token_counts(awkward, BYTE).collect()}
    got = counted(token_counts.token_counts(repeated, BYTE), "doc_id", "n_bytes", "n_tokens")
    want = Counter((i, *once[i]) for i, _ in AWKWARD) + Counter((i, *once[i]) for i in range(6)) + Counter((None, *once[i]) for i in (3, 10))
    assert got == want


def test_pieces_keep_every_row(awkward, repeated):
    once = {r["doc_id"]: (r["n_tokens"], r["ids_sha256"]) for r in piece_codec.piece_digests(awkward, PIECE).collect()}
    got = counted(piece_codec.piece_digests(repeated, PIECE), "doc_id", "n_tokens", "ids_sha256")
    want = Counter((i, *once[i]) for i, _ in AWKWARD) + Counter((i, *once[i]) for i in range(6)) + Counter((None, *once[i]) for i in (3, 10))
    assert got == want
    assert piece_codec.piece_digests(awkward.limit(0), PIECE).count() == 0


def test_packing_keeps_every_row(awkward, repeated):
    columns = ("doc_id", "piece", "start", "length", "ids_crc32")
    once = packing.packed(awkward, BYTE)
    again = packing.packed(repeated, BYTE)
    want = counted(once, *columns) + counted(once.filter("doc_id < 6"), *columns)
    want += counted(once.filter("doc_id in (3, 10)").withColumn("doc_id", F.lit(None).cast("long")), *columns)
    rows = again.collect()
    assert Counter(tuple(r[c] for c in columns) for r in rows) == want
    spans = {}
    for r in rows:
        spans.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for own in spans.values():
        own.sort()
        assert own[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(own, own[1:], strict=False)) and sum(own[-1]) <= 1024


def test_stages_keep_clashing_columns_and_empty_tables(awkward, repeated, marks):
    wide = repeated.select("*", *[F.lit(i).alias(c) for i, c in enumerate(CLASHING)])
    for stage in (lambda d: quality_rules.keep_good(d, marks), lambda d: toxicity.keep_clean(d, marks), near_dedup.keep_one):
        out = stage(wide)
        assert out.columns == wide.columns
        got = out.collect()
        assert len(got) <= wide.count() and {r["doc_id"] for r in got} <= {r["doc_id"] for r in wide.select("doc_id").collect()}
        assert all(tuple(r[c] for c in CLASHING) == tuple(range(len(CLASHING))) for r in got)
        assert stage(wide.limit(0)).count() == 0
    # Nobody is toxic or bad by labels alone where there are none.
    assert toxicity.keep_clean(awkward, marks.limit(0)).count() == awkward.count()
