"""Topic models of whole documents: words packed by the tasks that read them, no responsibility a row."""

import pytest
from pyspark.sql import functions as F

from plate_engine.models import zoo
from plate_engine.plans import blocks as B
from plate_engine.queries import methods
from plate_engine.sources import text as T

TEXTS = [
    (3, "One two two. Three one!\nOne"), (1, "two Three four"), (7, None), (9, ""), (2, "ÄRGER ärger 12 two. ... four four"), (3, "one five. Two two"),
    (None, "one two six"), (None, "six one"), (-4, "four four four one"),
]
SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(TEXTS, "doc_id long, text string").repartition(3)


def table(df):
    return sorted(map(tuple, df.collect()), key=repr)


@pytest.mark.parametrize("least", [1, 2])
def test_vocabulary_counts_repeated_and_null_ids_once(spark, docs, least):
    want = T.vocabulary(T.token_weights(docs, ["doc_id"]), least)
    assert table(T.document_vocabulary(docs, "doc_id", least).select("w", "word", "n", "docs")) == table(want.select("w", "word", "n", "docs"))


@pytest.mark.parametrize("sentences", [False, True])
@pytest.mark.parametrize("rows", [1, 1 << 19])
def test_packed_words_are_the_joined_ones(spark, docs, monkeypatch, sentences, rows):
    monkeypatch.setattr(B, "BLOCK_ROWS", rows)
    vocab = T.document_vocabulary(docs, "doc_id", 2).persist()
    keys = ["doc_id", "s"] if sentences else ["doc_id"]
    weights = T.token_weights(T.sentences(docs, ["doc_id"]), keys, "sentence") if sentences else T.token_weights(docs, keys)
    want = T.encoded(weights, vocab, keys).filter("doc_id is not null").groupBy(*keys, "w").agg(F.sum("n").cast("double").alias("n"))
    packed = B.pack_texts(docs, "doc_id", vocab, sentences)
    assert table(B.unpacked(packed, [*keys, "w"])) == table(want)
    ids = [r["block"] for r in packed.collect()]
    assert len(set(ids)) == len(ids) and (rows > 1 or len(ids) == 4)


@pytest.mark.parametrize(("spec", "sentences"), [(zoo.lda, False), (zoo.slda, True), (zoo.dcmlda, False)])
def test_packed_model_equals_the_long_layout(spark, docs, spec, sentences):
    vocab = T.document_vocabulary(docs, "doc_id").persist()
    got = {}
    for layout in ("auto", "long"):
        bounds = []
        model = spec().bind(spark, K=3, V=vocab.count(), alpha=0.3, beta=0.1)
        model.observe_packed("x", B.pack_texts(docs, "doc_id", vocab, sentences))
        model.infer(3, callback=lambda view: bounds.append(view.elbo) or view.round < 2, layout=layout)
        got[layout] = [{tuple(r)[:-2]: tuple(r)[-2:] for r in model[v].posterior().collect()} for v in ("phi", "theta")], bounds[1:], type(model.engine).__name__
    assert got["long"][2] == "LongEngine" and got["auto"][2] == ("BurstyEngine" if spec is zoo.dcmlda else "BlockEngine")
    assert got["auto"][1] == pytest.approx(got["long"][1], rel=1e-10) and len(got["auto"][1]) == 2
    for a, b in zip(got["auto"][0], got["long"][0], strict=True):
        assert a.keys() == b.keys()
        assert all(a[k] == pytest.approx(b[k], rel=1e-9) for k in a)


def test_a_topic_without_weight_keeps_its_row(spark):
    """exp() of a long sentence's score is 0 for all topics but one; the long layout and the SQL have a row for each."""
    rows = [(d, 0, w, 4000) for d in range(2) for w in ([0, 1] if d else [2, 3])]
    df = spark.createDataFrame(rows, "d long, s long, w long, n long")
    model = zoo.slda().bind(spark, K=2, V=4, alpha=0.3, beta=0.1)
    model["x"].observe(df, "w", keys={"docs": "d", "sentences": "s"}, weight="n")
    model.infer(4, layout="block")
    assert model["theta"].posterior().count() == 4 and model["phi"].posterior().count() == 8


@pytest.mark.parametrize("name", ["lda_docs_vmp", "lda_elbo", "slda_docs_vmp", "dcmlda_docs_vmp", "perplexity", "predictive_ll", "topic_lang_purity"])
def test_document_queries_keep_no_responsibility_a_row(spark, monkeypatch, name):
    from plate_engine.vmp.engine import LongEngine

    monkeypatch.setattr(LongEngine, "__init__", lambda *a, **k: pytest.fail("responsibilities as rows"))
    assert getattr(methods, name)(spark, SF).count() > 0


def test_a_vocabulary_too_large_to_hold_is_joined(spark, monkeypatch):
    monkeypatch.setattr(methods, "HELD_WORDS", 1)
    joined = table(methods.lda_docs_vmp(spark, SF))
    monkeypatch.undo()
    assert joined == table(methods.lda_docs_vmp(spark, SF))
