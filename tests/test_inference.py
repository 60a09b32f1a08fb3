import numpy as np
import pytest
from pyspark.sql import functions as F

from plate_engine.baselines import local_vmp as local
from plate_engine.baselines.exact import enumerated_log_evidence, evidence_by_group, two_coin_log_evidence
from plate_engine.lang.builder import ModelError
from plate_engine.models import zoo
from plate_engine.plans.blocks import BlockTopics, local_bursty
from plate_engine.runtime.loop import stop_on_elbo


def coins(spark, h, t, steps, callback=None, **options):
    m = zoo.two_coins().bind(spark, alpha=1.0, beta=1.0)
    m["x"].observe(spark.createDataFrame([(1, h), (0, t)], "value int, n long"), "value", weight="n")
    return m.infer(steps, callback, **options)


def test_two_coins_equal_the_known_values(spark):
    bounds = []
    m = coins(spark, 87, 89, 5, lambda v: bounds.append(v.elbo) or True)
    assert bounds[0] == float("-inf") and len(bounds) == 6
    assert abs(bounds[1] + 128.525407) < 1e-6 and abs(bounds[5] + 128.501307) < 1e-6
    assert all(b >= a for a, b in zip(bounds, bounds[1:], strict=False))
    pi = {r["j"]: r["gamma"] for r in m["pi"].posterior().collect()}
    assert abs(pi[0] - 38.572467) < 1e-6 and abs(pi[1] - 139.427533) < 1e-6
    phi = {(r["coins"], r["j"]): r["gamma"] for r in m["phi"].posterior().collect()}
    assert abs(phi[0, 0] - 11.924442) < 1e-6 and abs(phi[1, 1] - 61.351975) < 1e-6
    assert abs(sum(phi.values()) - 4 - 176) < 1e-9
    assert bounds[5] <= two_coin_log_evidence(87, 89, 1.0, 1.0)
    assert {r["stage"] for r in m.timings().collect()} >= {"inference"}
    assert m.history().count() == 5
    assert sorted(r["mode"] for r in m["z"].mode().collect()) == [1, 1]


def test_callback_stops(spark):
    seen = []
    coins(spark, 3, 2, 10, lambda v: seen.append(v.round) or v.round < 2)
    assert seen == [0, 1, 2]
    m = coins(spark, 3, 2, 10, stop_on_elbo(rel=1e-1, min_rounds=2))
    assert len(m.engine.history) == 2


def test_evidence(spark):
    assert abs(two_coin_log_evidence(5, 4, 1.0, 1.0) + 6.883240892672) < 1e-9
    assert abs(two_coin_log_evidence(5, 4, 0.7, 2.0) + 6.680965960307) < 1e-9
    assert abs(enumerated_log_evidence(5, 4, 0.7, 2.0) - two_coin_log_evidence(5, 4, 0.7, 2.0)) < 1e-9
    got = evidence_by_group(spark.createDataFrame([(1, 3, 2), (2, 0, 0)], "o long, h long, t long"), ["o"], 1.0, 1.0)
    assert {r["o"]: round(r["log_evidence"], 6) for r in got.collect()} == {1: -3.884624, 2: 0.0}


@pytest.fixture(scope="module")
def small():
    rng = np.random.default_rng(5)
    rows = {(int(d), int(w)): int(n) for d, w, n in zip(rng.integers(0, 12, 90), rng.integers(0, 20, 90), rng.integers(1, 5, 90), strict=True)}
    d, w, n = (np.array(x) for x in zip(*[(*k, v) for k, v in sorted(rows.items())], strict=True))
    return np.unique(d, return_inverse=True)[1], w, n


def frame(spark, small):
    return spark.createDataFrame([tuple(map(int, r)) for r in zip(*small, strict=True)], "d long, w long, n long")


def test_layouts_agree_with_the_local_baseline(spark, small):
    d, w, n = small
    theta, phi, bounds = local.local_lda(d, w, n.astype(float), 3, 20, 0.3, 0.1, 4)
    assert all(b >= a - 1e-9 for a, b in zip(bounds, bounds[1:], strict=False))
    m = zoo.lda().bind(spark, K=3, V=20, alpha=0.3, beta=0.1)
    m["x"].observe(frame(spark, small), "w", keys={"docs": "d"}, weight="n")
    seen = []
    m.infer(4, lambda v: seen.append(v.elbo) or True)
    assert np.allclose(seen[1:], bounds, rtol=1e-10)
    got = {(r["docs"], r["j"]): r["gamma"] for r in m["theta"].posterior().collect()}
    assert all(abs(got[i, j] - theta[i, j]) < 1e-8 for i in range(theta.shape[0]) for j in range(3))
    assert m["phi"].posterior(dense=True).count() == 60
    block = BlockTopics(frame(spark, small), 3, 20, 0.3, 0.1, blocks=3).infer(4)
    assert np.allclose([b for _, b, _ in block.history], bounds, rtol=1e-10)
    assert np.allclose(block.phi.T, phi, rtol=1e-9)
    mine = {(r["docs"], r["j"]): r["gamma"] for r in block.proportions().collect()}
    assert all(abs(mine[k] - v) < 1e-8 for k, v in got.items())
    one = local.one_vertex_at_a_time(d, w, n.astype(float), 3, 20, 0.3, 0.1, 60)
    long_run = local.local_lda(d, w, n.astype(float), 3, 20, 0.3, 0.1, 300)[2]
    assert one[-1] >= one[0] and abs(one[-1] - long_run[-1]) < 0.05 * abs(long_run[-1])


def test_full_bound_equals_fused(spark, small):
    m = zoo.lda().bind(spark, K=2, V=20, alpha=0.3, beta=0.1)
    m["x"].observe(frame(spark, small), "w", keys={"docs": "d"}, weight="n")
    m.infer(2, lambda v: True)
    e = m.engine
    z = e.latent[0]
    e.r[z.rid] = e.update_latent(z).persist()
    full = e.elbo_terms().agg(F.sum("value")).first()[0]
    assert abs(full - e.fused_bound().first()["elbo"]) < 1e-8 * abs(full)


def test_bursty_block_equals_long_layout(spark, small):
    m = zoo.dcmlda().bind(spark, K=3, V=20, alpha=0.5, beta=0.1)
    m["x"].observe(frame(spark, small), "w", keys={"docs": "d"}, weight="n")
    seen = []
    m.infer(3, lambda v: seen.append(v.elbo) or True)
    got = local_bursty(frame(spark, small), 3, 20, 0.5, 0.1, 3, blocks=3)
    sums = [r["b"] for r in got.select(F.posexplode("bounds").alias("t", "b")).groupBy("t").agg(F.sum("b").alias("b")).orderBy("t").collect()]
    assert np.allclose(sums, seen[1:], rtol=1e-10)


def test_sentence_block_equals_long_layout(spark):
    rows = [(d, s, (3 * d + 5 * s + k) % 11, 1 + k % 2) for d in range(6) for s in range(4) for k in range(3)]
    df = spark.createDataFrame(rows, "d long, s long, w long, n long")
    m = zoo.slda().bind(spark, K=3, V=11, alpha=0.3, beta=0.2)
    m["x"].observe(df, "w", keys={"docs": "d", "sentences": "s"}, weight="n")
    seen = []
    m.infer(3, lambda v: seen.append(v.elbo) or True)
    block = BlockTopics(df, 3, 11, 0.3, 0.2, blocks=2, sentences=True).infer(3)
    assert np.allclose([b for _, b, _ in block.history], seen[1:], rtol=1e-10)


def test_degenerate_inputs(spark):
    m = zoo.lda().bind(spark, K=1, V=3, alpha=1.0, beta=0.5)
    m["x"].observe(spark.createDataFrame([(0, 2, 4), (1, None, 3), (1, 0, 0), (2, 1, None)], "d long, w long, n long"), "w", keys={"docs": "d"}, weight="n")
    m.infer(1)
    assert [tuple(r) for r in m["phi"].posterior().collect()] == [(0, 2, 4.5, 4.5 / 5.5)]
    empty = zoo.coin().bind(spark, a=1.0)
    empty["x"].observe(spark.createDataFrame([], "v int"), "v")
    assert empty.infer(1)["p"].posterior().count() == 0
    with pytest.raises(ModelError, match="observed"):
        zoo.coin().bind(spark, a=1.0).infer(1)
    with pytest.raises(ModelError, match="whole numbers"):
        zoo.coin().bind(spark, a=1.0)["x"].observe(spark.createDataFrame([("a",)], "v string"), "v")
    with pytest.raises(ModelError, match="missing"):
        zoo.coin().bind(spark)
    with pytest.raises(ModelError, match="must be double"):
        zoo.coin().bind(spark, a="one")


def test_nested_plates_have_sizes(spark):
    m = zoo.two_coins_nested().bind(spark, alpha=1.0, beta=1.0)
    m["x"].observe(spark.createDataFrame([(1, 0), (1, 1), (1, 1), (2, 1)], "o long, v int"), "v", keys={"groups": "o"})
    assert m.infer_plate_sizes() == {"coins": 2, "tosses": 4, "groups": 2}
    assert {r["groups"]: r["size"] for r in m.plate_sizes("tosses").collect()} == {1: 3.0, 2: 1.0}
    pi = m.infer(2)["pi"].posterior().agg(F.sum("gamma")).first()[0]
    assert abs(pi - 2 - 2) < 1e-9  # one selector a group, not a toss


@pytest.mark.parametrize("sentences", [False, True])
def test_layouts_agree_through_the_model_language(spark, small, sentences):
    df = frame(spark, small).withColumn("s", (F.col("w") % 3).cast("long"))
    spec = zoo.slda() if sentences else zoo.lda()
    keys = {"docs": "d", **({"sentences": "s"} if sentences else {})}
    got = {}
    for layout in ("long", "block"):
        model = spec.bind(spark, K=4, V=20, alpha=0.3, beta=0.1)
        model["x"].observe(df, value="w", keys=keys, weight="n")
        model.infer(3, callback=lambda view: True, layout=layout)
        rows = model.posterior("phi", dense=True).collect()
        plate = model.rv("phi").plate.name
        got[layout] = {(r[plate], r["j"]): r["gamma"] for r in rows}, model.lower_bound(), type(model.engine).__name__
    assert got["long"][2] == "LongEngine" and got["block"][2] == "BlockEngine"
    assert got["long"][0].keys() == got["block"][0].keys()
    assert all(abs(got["long"][0][i] - got["block"][0][i]) < 1e-6 for i in got["long"][0])
    assert abs(got["long"][1] - got["block"][1]) < 1e-5 * abs(got["long"][1])
    model = spec.bind(spark, K=16, V=20, alpha=0.3, beta=0.1)
    model["x"].observe(df, value="w", keys=keys, weight="n")
    assert type(model.infer(1).engine).__name__ == "BlockEngine"


def test_mllib_graph_has_enough_partitions(spark, monkeypatch):
    """An edge a word of a document: a partition of the graph holds a bounded number of them."""
    from plate_engine.baselines import mllib_lda as M

    seen = []

    class Spy(M.LDA):
        def _fit(self, dataset):
            seen.append(dataset.rdd.getNumPartitions())
            return super()._fit(dataset)

    monkeypatch.setattr(M, "LDA", Spy)
    monkeypatch.setattr(M, "PARTITION_WORDS", 30)
    docs = spark.createDataFrame([(i, " ".join(f"w{j}" for j in range(i % 5, 12))) for i in range(60)], "doc_id long, text string").coalesce(1)
    found = M.mllib_lda(docs, 2, 2, "em", least_docs=1)
    assert found.count() == 20 and seen[0] == 20


def test_mllib_vectors_are_stored_and_whole(spark, monkeypatch):
    """Texts are searched once for the graph, files that suffice are put together without a shuffle, and every word is there."""
    from pyspark.ml.functions import vector_to_array

    from plate_engine.baselines import mllib_lda as M

    seen, settings = [], {k: spark.conf.get(k) for k in ("spark.sql.adaptive.enabled", "spark.sql.files.openCostInBytes")}

    class Spy(M.LDA):
        def _fit(self, dataset):
            words = dataset.select(F.aggregate(vector_to_array("features"), F.lit(0.0), lambda a, x: a + x).alias("n")).agg(F.sum("n")).first()[0]
            seen.append((dataset.rdd.getNumPartitions(), dataset._jdf.queryExecution().executedPlan().toString(), dataset.count(), words))
            return super()._fit(dataset)

    monkeypatch.setattr(M, "LDA", Spy)
    docs = spark.createDataFrame([(i, " ".join(f"w{j}" for j in range(i % 5, 12)) + " w11") for i in range(60)], "doc_id long, text string").repartition(8)
    found = M.mllib_lda(docs, 2, 2, "em", least_docs=1).collect()
    parts, plan, rows, words = seen[0]
    assert len(found) == 20 and (parts, rows, words) == (spark.sparkContext.defaultParallelism, 60, 660)
    assert "Exchange" not in plan and "regexp" not in plan.lower()
    assert settings == {k: spark.conf.get(k) for k in settings}
