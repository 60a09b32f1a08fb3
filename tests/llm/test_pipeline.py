import corpus_pipeline
from pyspark.sql import functions as F

from plate_engine.llm import near_dedup, packing, quality_rules, toxicity
from plate_engine.llm.common import documents, labels

SF = "/root/testdata/sf0.001"


def test_stages_take_effect(spark):
    docs, marks = documents(spark, SF), labels(spark, SF)
    rows = corpus_pipeline.run(spark, SF).persist()
    left = {r["doc_id"] for r in rows.select("doc_id").distinct().collect()}
    kept = quality_rules.verdicts(docs, marks).filter("kept").select("doc_id")
    good = docs.join(kept, "doc_id", "left_semi")
    model = toxicity.learnt(good, marks)
    clean = good.join(toxicity.scored(good, model).filter("score < 0.7").select("doc_id"), "doc_id", "left_semi")
    classes = near_dedup.near_classes(clean).agg(F.collect_set("class_id")).first()[0]
    assert left == set(classes)
    want = packing.pieces(clean.filter(F.col("doc_id").isin(classes)), corpus_pipeline.public_tokenizers.path("byte_bpe_50k.json"))
    same = ["doc_id", "piece", "start", "length", "ids_crc32"]
    assert rows.select(same).exceptAll(want.select(same)).count() == 0 and rows.count() == want.count()
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "toxicity", "minhash_near_dedup", "best_fit_packing"]
