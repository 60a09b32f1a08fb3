import tracemalloc

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from plate_engine.llm import common, near_dedup, quality_model, quality_rules, toxicity, version_sketch

from .conftest import AWKWARD

RNG = np.random.default_rng(4)
VOCAB = [f"w{k}" for k in range(400)]


def prose(n, rng=RNG):
    return " ".join(VOCAB[int(k) % 400] for k in rng.zipf(1.3, n))


# Quality rules.


def brute_measures(t):
    w = (t or "").split()
    runs = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
    covered = {i + k for i, r in enumerate(runs) if runs.count(r) > 1 for k in range(5)} if len(runs) < 500 else set(range(len(w)))
    lines = [x for x in (t or "").split("\n") if x.split()]
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t or ""), len(lines) - len(set(lines)), len(covered)


def test_measures(spark):
    texts = [t for _, t in AWKWARD if t is None or ("\x00" not in t and "日" not in t)] + ["a b c d e a b c d e f", "x y\nx y\n\n \nz", "a a a a a a a", "p q r s t u p q r s t p q r s t", "#a *b*"]
    df = spark.createDataFrame([(i, t, None) for i, t in enumerate(texts)], "doc_id long, text string, lang string")
    for r in quality_rules.measured(df).select("row.doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words").collect():
        assert tuple(r)[1:] == brute_measures(texts[r["doc_id"]]), texts[r["doc_id"]]


def test_binomial_bound_is_exact(spark):
    from math import comb

    cases = [(n, k, p) for n in (1, 7, 50, 300) for k in (0, 1, 3) for p in (0.02, 0.2) if k <= n * p]
    for n, k, p in cases:
        got = spark.range(1).select(quality_rules.binomial_cdf(F.lit(n).cast("long"), F.lit(k).cast("long"), p)).first()[0]
        assert abs(got - sum(comb(n, j) * p**j * (1 - p) ** (n - j) for j in range(k + 1))) < 1e-12
    assert spark.range(1).select(quality_rules.binomial_cdf(F.lit(200_000).cast("long"), F.lit(900).cast("long"), 0.005)).first()[0] < 1e-2


def test_certified_cutoffs_bound_the_false_rejections(spark):
    rows = [("en", True, 0, 100) for _ in range(3000)] + [("en", True, 6, 100) for _ in range(30)] + [("en", False, 40, 100) for _ in range(200)] + [("es", True, 0, 100) for _ in range(50)] + [("es", False, 90, 100) for _ in range(50)]
    df = spark.createDataFrame(rows, "stratum string, good boolean, n_symbols long, word_chars long")
    for c in ("n_repeat_words", "n_dup_lines", "n_capitals"):
        df = df.withColumn(c, F.lit(0))
    for c in ("n_words", "n_lines"):
        df = df.withColumn(c, F.lit(10))
    got = {r["stratum"]: r for r in quality_rules.certified_rungs(df).collect()}
    assert (got["en"]["rung"], got["en"]["caught"], got["en"]["wrong"]) == (4, 200, 0)
    assert set(got) == {"en"}  # too few Spanish ones to certify anything


def test_certified_rungs_keep_the_risk(spark):
    """Good documents that break the rules in 4 % of cases: a rung with a true risk over 2 % is certified in few holdouts."""
    rng = np.random.default_rng(5)
    rows = [(f"s{k}", True, int(x), 100) for k in range(40) for x in np.where(rng.random(300) < 0.04, 12, 0)] + [(f"s{k}", False, 50, 100) for k in range(40) for _ in range(20)]
    df = spark.createDataFrame(rows, "stratum string, good boolean, n_symbols long, word_chars long")
    for c in ("n_repeat_words", "n_dup_lines", "n_capitals"):
        df = df.withColumn(c, F.lit(0))
    for c in ("n_words", "n_lines"):
        df = df.withColumn(c, F.lit(10))
    got = quality_rules.certified_rungs(df, delta=2.0).collect()  # 5 % a stratum
    strict = [r for r in got if quality_rules.LADDER["symbols"][r["rung"] - 1] < 120]
    assert len(got) == 40 and not strict and all(r["caught"] == 20 for r in got)


def test_verdicts_on_awkward_rows(spark, awkward):
    marks = spark.createDataFrame([(10, 1, 0), (10, 0, 0), (None, 1, 1), (3, None, None)], "doc_id long, quality int, toxic int")
    got = {r["doc_id"]: r for r in quality_rules.verdicts(awkward, marks).collect()}
    assert len(got) == len(AWKWARD) and not got[0]["kept"] and got[0]["n_words"] == 0 and got[8]["base_failed"] and got[10]["kept"]
    kept = quality_rules.keep_good(awkward, marks)
    assert kept.columns == awkward.columns and kept.count() == sum(r["kept"] for r in got.values())
    assert quality_rules.verdicts(awkward.limit(0), marks.limit(0)).count() == 0


# Toxicity.


def brute_nearest(index, words, weights, k, n_words):
    m = np.zeros((index.n_examples, n_words))
    for w in range(n_words):
        a, b = index.starts[w], index.starts[w + 1]
        m[index.example[a:b], w] = index.weight[a:b]
    q = np.zeros(n_words)
    q[words] = weights
    s = m @ q
    order = np.lexsort((np.arange(len(s)), -np.round(s, 12)))
    return [int(i) for i in order if s[i] > 0][:k]


def test_block_max_search_is_exact():
    rng = np.random.default_rng(2)
    for _ in range(20):
        n, v = 700, 30
        mask = rng.random((n, v)) < rng.random(v) * 0.4
        ex, word = np.nonzero(mask)
        weight = rng.random(len(ex))
        weight /= np.sqrt(np.bincount(ex, weight**2, n))[ex]
        index = toxicity.BlockMaxIndex.build(word, ex, weight, v, n)
        q = np.sort(rng.choice(v, 8, replace=False))
        w = rng.random(8) * np.array([3, 1, 1, 0.2, 0.1, 0.05, 0.05, 0.01])
        near, cos = index.nearest(q, w / np.linalg.norm(w), 10)
        assert near.tolist() == brute_nearest(index, q, w / np.linalg.norm(w), 10, v)
        assert (np.diff(cos) <= 1e-12).all()


def test_texts_searched_together_find_the_same(monkeypatch):
    """With terms in the matrix and out of it, texts without a term, ties, an example left out, and rows that need no product."""
    monkeypatch.setattr(toxicity, "FREQUENT", 12)
    monkeypatch.setattr(toxicity, "TOGETHER", 7)
    monkeypatch.setattr(toxicity, "POSTINGS", 900)
    rng = np.random.default_rng(5)
    n, v, k = 700, 60, 9
    mask = rng.random((n, v)) < rng.random(v) ** 3
    mask[1::9] = mask[0::9][: len(mask[1::9])]
    ex, word = np.nonzero(mask)
    weight = np.where(np.isin(ex % 9, (0, 1)), 1.0, rng.random(len(ex)))
    weight = (weight / np.sqrt(np.bincount(ex, weight**2, n))[ex]).astype(np.float32)
    index = toxicity.BlockMaxIndex.build(word, ex, weight, v, n)
    queries, skip = [(np.zeros(0, np.int64), np.zeros(0))], [-1]
    for i in range(60):
        held = np.flatnonzero(mask[i]) if i % 2 else np.sort(rng.choice(v, 8, replace=False))
        w = rng.random(len(held)) ** 4 + 1e-6
        queries.append((held, w / max(1e-9, np.linalg.norm(w))))
        skip.append(i if i % 4 == 1 else -1)
    for (words, w), left, (near, _) in zip(queries, skip, index.nearest_each(queries, k, skip), strict=True):
        assert near.tolist() == [e for e in brute_nearest(index, words, w, k + 1, v) if e != left][:k]


def test_terms_are_looked_up_together():
    texts = pa.array(["Straße straßenbahn words word wo", "", "éééé ééééé éééééé, wörter-buch", "zzzz word"])
    number = {}
    doc, term, _ = toxicity.term_counts(texts, number)
    held = sorted(number, key=number.get)[::2] + ["=never", "^neve"]
    terms = toxicity.Terms.of(pa.array(sorted(held)))
    got = zip(*toxicity.term_counts(texts, terms), strict=True)
    want = [(int(d), t) for d, i in zip(doc, term, strict=True) for t, n in number.items() if n == i and t in held]
    assert sorted((int(d), sorted(held)[i]) for d, i, _ in got) == sorted(want)
    assert [len(x) for x in toxicity.term_counts(pa.array(["", " .,"]), terms)] == [0, 0, 0]
    assert len(terms) == len(held) and len(toxicity.term_counts(texts, toxicity.Terms.of(pa.array([], pa.string())))[0]) == 0


def test_a_batch_of_texts_fits_a_worker():
    """What a worker holds while it counts the terms of a batch."""
    rng = np.random.default_rng(4)
    words = np.array([f"w{i:04d}" for i in range(5000)])
    texts, size = [], 0
    while size < toxicity.BATCH_BYTES:
        texts.append(" ".join(words[rng.integers(0, 5000, 300)]))
        size += len(texts[-1])
    array = pa.array(texts)
    tracemalloc.start()
    toxicity.term_counts(array, {})
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 64e6


@pytest.fixture(scope="module")
def marked(spark):
    rng = np.random.default_rng(3)
    bad = ["vilefool", "nastyfool", "uglyfool"]
    rows = []
    for i in range(240):
        t = prose(60, rng).split()
        if i % 4 == 0:
            for _ in range(3):
                t.insert(int(rng.integers(len(t))), bad[int(rng.integers(3))].capitalize() + ",")
        rows.append((i, " ".join(t) + ("\n### *** $$$ |||" * 6 if i % 5 == 0 else "."), int(i % 4 == 0), int(i % 5 != 0)))
    docs = spark.createDataFrame([(i, t, 9.0) for i, t, _, _ in rows], "doc_id long, text string, score double")
    return docs, spark.createDataFrame([(i, q, y) for i, _, y, q in rows], "doc_id long, quality int, toxic int")


def test_toxic_documents_are_found(spark, marked, awkward):
    docs, marks = marked
    train = F.col("doc_id") < 160
    got = toxicity.toxicity(docs, marks, train=train).join(marks, "doc_id").filter("doc_id >= 160").collect()
    assert all(r["predicted"] == r["toxic"] for r in got)
    hit = next(r for r in got if r["toxic"])
    assert hit["evidence"] and all(e["toxic"] == 1 for e in hit["evidence"]) and 0 <= hit["score"] <= 1
    more = toxicity.scored(awkward, toxicity.fit(common.labelled_texts(docs, marks, "toxic", 1000))).collect()
    assert len(more) == len(AWKWARD) and all(0 <= r["score"] <= 1 for r in more)
    kept = toxicity.keep_clean(docs, marks)
    assert kept.columns == docs.columns and kept.join(marks, "doc_id").filter("toxic = 1").count() == 0 and kept.count() == 180
    none = toxicity.toxicity(docs, marks.limit(0)).agg(F.max("score")).first()[0]
    assert none == 0.0


def test_every_term_of_a_labelled_text_weighs(spark):
    """A source with 2 % of the toxic labels is judged by its own words."""
    rng = np.random.default_rng(11)
    hot = [prose(40, rng) + " vilefool" * 3 for _ in range(294)]
    rare = [" ".join(f"k{int(i)}" for i in rng.integers(0, 60, 40)) + " zlobny zlobny" for _ in range(9)]
    good = [prose(40, rng) for _ in range(1500)] + [" ".join(f"k{int(i)}" for i in rng.integers(0, 60, 40)) for _ in range(100)]
    texts = hot + rare + good
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    marks = spark.createDataFrame([(i, int(i < 303)) for i in range(len(texts))], "doc_id long, toxic int")
    model = toxicity.fit(common.labelled_texts(docs, marks.filter("doc_id not in (294, 295, 296)"), "toxic", 5000), docs)
    assert {"=" + w for t in texts[297:] for w in t.split()} <= set(model.words)
    n, toxic, held = len(texts) - 3, 300, 6  # nine documents hold the word, six of them labelled
    z = (held - held * toxic / n) / np.sqrt(held * toxic / n * (1 - toxic / n) * (1 - held / n))
    assert np.isclose(model.scale[model.words["=zlobny"]], np.log1p(len(texts) / 9) * (1 + z)) and (model.scale > 0).all()
    near = toxicity.scored(docs, model, evidence=6).filter("doc_id between 294 and 296").collect()
    assert len(near) == 3 and all([e["toxic"] for e in r["evidence"]] == [1] * 6 for r in near)


# Quality by passages.


def test_attention_gradients():
    rng = np.random.default_rng(0)
    x, ends, y = rng.normal(size=(9, 6)), np.array([0, 2, 3, 9]), np.array([1.0, 0.0, 1.0])
    m = quality_model.train(x, ends, y, hidden=4, gate=3, epochs=1, batch=3)

    def loss():
        s = m.forward(x, ends)["score"]
        return -(y * np.log(s) + (1 - y) * np.log(1 - s)).mean()

    f = m.forward(x, ends)
    assert np.allclose(np.add.reduceat(f["a"], ends[:-1]), 1)
    for name, g in m.gradients(f, ends, y, 0.0).items():
        p = m.p[name]
        at = tuple(rng.integers(n) for n in p.shape)
        old = p[at]
        p[at] = old + 1e-6
        up = loss()
        p[at] = old - 1e-6
        down = loss()
        p[at] = old
        assert abs((up - down) / 2e-6 - g[at]) < 1e-6, name


def test_quality_is_learnt(spark, marked, awkward):
    docs, marks = marked
    got = quality_model.quality(docs, marks, train=F.col("doc_id") < 160).join(marks, "doc_id").filter("doc_id >= 160").collect()
    assert sum(r["predicted"] == r["quality"] for r in got) >= 0.9 * len(got)
    model = quality_model.fit(common.labelled_texts(docs, marks, "quality", 1000), epochs=3)
    more = quality_model.scored(awkward, model).collect()
    assert len(more) == len(AWKWARD) and all(0 <= r["score"] <= 1 for r in more)
    assert {r["score"] for r in quality_model.quality(docs, marks.limit(0)).collect()} == {0.5}


def test_passage_features_cover_the_whole_text():
    x, ends = quality_model.passages(pa.array(["", "a b", "w " * 1000]))
    assert np.diff(ends).tolist() == [1, 1, 16] and not x[0].any() and x[1].any()


# Near duplicates.


def brute_classes(ids, texts, least=0.8):
    doc, value, count = near_dedup.runs(pa.array(texts))
    cut = np.searchsorted(doc, np.arange(len(ids) + 1))
    own = [(value[a:b], count[a:b]) for a, b in zip(cut[:-1], cut[1:], strict=True)]
    root = list(range(len(ids)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(ids)):
        for j in range(i):
            if near_dedup.similarity(own[i], own[j]) >= least:
                a, b = sorted((find(i), find(j)))
                root[b] = a
    return {ids[i]: ids[find(i)] for i in range(len(ids))}


def test_signatures_are_unbiased():
    rng = np.random.default_rng(3)
    gaps, spread = [], []
    for _ in range(30):
        n = int(rng.integers(30, 300))
        v = np.sort(rng.integers(0, 2**63, n).astype(np.uint64))
        a, keep = rng.zipf(1.6, n).clip(1, 500), rng.random(n) < 0.9
        b = np.where(rng.random(n) < 0.6, a, rng.zipf(1.6, n).clip(1, 500))
        s = near_dedup.signatures(np.repeat([0, 1], [n, keep.sum()]), np.concatenate([v, v[keep]]), np.concatenate([a, b[keep]]), 2, m=512)
        true = near_dedup.similarity((v, a), (v[keep], b[keep]))
        gaps.append((s[0] == s[1]).mean() - true)
        spread.append(true * (1 - true) / 512)
    assert abs(np.mean(gaps)) < 4 * np.sqrt(np.mean(spread) / 30)
    assert 0.6 < np.mean(np.square(gaps)) / np.mean(spread) < 1.6


def test_what_leaders_leave_open_is_compared_whole(spark, monkeypatch):
    """Without any leader all links are found, as are those that random leaders miss."""
    monkeypatch.setattr(near_dedup, "TURNS", 0)
    rng = np.random.default_rng(11)
    base = [f"w{i}" for i in range(90)]
    texts = []
    for _ in range(12):  # pairs near to each other, all at some distance from one text in the middle
        one = list(base)
        for at in rng.choice(90, 2, replace=False):
            one[at] = f"x{rng.integers(1 << 30)}"
        two = list(one)
        two[int(rng.integers(90))] = "y"
        texts += [" ".join(one), " ".join(two)]
    texts += [" ".join(base), texts[0], "", " ".join(f"z{i}" for i in range(40))]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r["class_id"] for r in near_dedup.near_classes(df).collect()}
    assert got == brute_classes(list(range(len(texts))), texts)


@pytest.mark.parametrize("held", [1 << 17, 700])
def test_no_pairs_are_made_of_what_is_left_open(spark, monkeypatch, held):
    """A large family, few of it near to each other: its texts are sent to each group once, or once a block."""
    monkeypatch.setattr(near_dedup, "HELD", held)
    monkeypatch.setattr(near_dedup, "STREAM", 4 * held)
    monkeypatch.setattr(near_dedup, "MATCHES", 1 << 10)
    rng = np.random.default_rng(12)
    base, texts = [f"w{i}" for i in range(120)], []
    for i in range(90):
        one = list(base)
        for at in rng.choice(120, 3 if i % 3 else 1, replace=False):
            one[at] = f"x{rng.integers(1 << 30)}"
        texts.append(" ".join(one))
    ids = list(range(len(texts)))
    doc, value, count = near_dedup.runs(pa.array(texts))
    # One band that all share, each text a class of its own.
    members = spark.createDataFrame([(i, int(n), i, 7) for i, n in zip(ids, np.bincount(doc, count), strict=True)], "id long, size long, root long, band long")
    blocks = near_dedup._blocks(members, 0.8)
    blocks_needed = 1 if held > 700 else blocks.select("p").distinct().count()
    assert (blocks_needed > 1) == (held == 700) and blocks.count() <= 2 * blocks_needed * len(ids)
    links = near_dedup._compared(spark.createDataFrame(list(zip(ids, texts, strict=True)), "k long, t string"), blocks, 0.8).collect()
    root = {i: i for i in ids}
    for a, b in links:
        lo, hi = sorted((root[a], root[b]))
        root = {i: lo if r == hi else r for i, r in root.items()}
    assert root == brute_classes(ids, texts) and 1 < len(set(root.values())) < len(ids)


@pytest.mark.parametrize("hot", [500, 1])
def test_classes_equal_brute_force(spark, awkward, monkeypatch, hot):
    """Also with every key of two rows or more joined by broadcast, and texts compared in chunks of two."""
    monkeypatch.setattr(common, "HOT_LEAST", hot)
    monkeypatch.setattr(near_dedup, "CHUNK", 256 if hot > 1 else 2)
    rng = np.random.default_rng(6)
    texts = [t or "" for _, t in AWKWARD]
    passage = prose(60, rng)
    for _ in range(12):
        base = prose(int(rng.integers(20, 150)), rng).split()
        for _ in range(int(rng.integers(1, 5))):
            edit = list(base)
            edit[int(rng.integers(len(edit)))] = "edited"
            texts.append(" ".join(edit))
    texts += [passage + " " + prose(int(rng.integers(1, 40)), rng) for _ in range(25)] + ["same again " * 30] * 4
    ids = [3 * i for i in range(len(texts))]
    df = spark.createDataFrame([(i, t, 1, "x") for i, t in zip(ids, texts, strict=True)], "doc_id long, text string, class_id int, root string")
    got = {r["doc_id"]: r["class_id"] for r in near_dedup.near_classes(df).collect()}
    assert got == brute_classes(ids, texts)
    kept = near_dedup.keep_one(df.union(df.filter("doc_id = 3")))
    assert kept.columns == df.columns and sorted(r["doc_id"] for r in kept.collect()) == sorted(set(got.values()))
    assert near_dedup.near_classes(df.limit(0)).count() == 0


# Versions.


def test_sketch_peels_what_differs(spark):
    rng = np.random.default_rng(8)
    rows = []
    for shared, a, b in ((0, 0, 0), (5, 0, 0), (10, 3, 4), (0, 20, 20), (50, 200, 100), (3, 900, 2)):
        x = rng.integers(-(2**62), 2**62, shared + a + b).tolist()
        rows.append((x[: shared + a], x[:shared] + x[shared + a :]))
    df = spark.createDataFrame(rows, "a array<long>, b array<long>")
    a, b = F.col("a"), F.col("b")
    for (x, y), r in zip(rows, df.select(version_sketch.recovered(a, b).alias("r"), version_sketch.likeness(a, b).alias("s")).collect(), strict=True):
        assert {(e["x"], e["n"]) for e in r["r"]} == {(v, 1) for v in set(x) - set(y)} | {(v, -1) for v in set(y) - set(x)}
        assert abs(r["s"] - (len(set(x) & set(y)) / len(set(x) | set(y)) if x or y else 1.0)) < 1e-12


def test_few_edits_of_a_long_text_stay_near(spark):
    rng = np.random.default_rng(12)
    base = [f"u{int(i)}" for i in rng.integers(0, 10**6, 6000)]
    edit = list(base)
    for i in rng.choice(6000, 12, replace=False):
        edit[int(i)] = "edited"
    df = spark.createDataFrame([(1, " ".join(base)), (2, " ".join(edit))], "doc_id long, text string")
    got = {r["doc_id"]: r for r in version_sketch.versions(df).collect()}
    assert got[1]["near_next"] == got[2]["near_next"] > 0.75  # 12 edits touch at most 24 of some 190 paragraphs
    digests = spark.createDataFrame([(base,)], "w array<string>").select(version_sketch.paragraphs(F.transform("w", lambda w: F.xxhash64(w))).alias("d")).first()["d"]
    assert 6000 / version_sketch.SCALE * 0.7 < len(digests) < 6000 / version_sketch.SCALE * 1.4


def test_versions(spark, awkward):
    from hashlib import sha256

    got = {r["doc_id"]: r for r in version_sketch.versions(awkward.repartition(3)).collect()}
    texts = [t or "" for _, t in AWKWARD]
    for i, t in enumerate(texts):
        after = texts[(i + 1) % len(texts)]
        edited = t[: len(t) - len(t) // 2] + after[: len(t) // 2]
        assert got[i]["n_chars"] == len(t) and got[i]["edited_sha256"] == sha256(edited.encode()).hexdigest()
        assert 0 <= got[i]["near_edited"] <= 1 and 0 <= got[i]["near_next"] <= 1
    digests = {r["doc_id"]: set(r["d"]) for r in awkward.select("doc_id", version_sketch.paragraphs(version_sketch.word_hashes(F.coalesce("text", F.lit("")))).alias("d")).collect()}
    for i in digests:  # the likeness of the query is that of the sets of digests
        x, y = digests[i], digests[(i + 1) % len(texts)]
        assert abs(got[i]["near_next"] - (len(x & y) / len(x | y) if x or y else 1.0)) < 1e-12
    assert got[10]["fingerprint"] == got[11]["fingerprint"] and got[10]["near_next"] == 1.0
    assert got[10]["fingerprint"] != got[12]["fingerprint"]
    one = version_sketch.versions(awkward.filter("doc_id = 10")).collect()
    assert len(one) == 1 and one[0]["near_next"] == 1.0
    assert version_sketch.versions(awkward.limit(0)).count() == 0
    assert version_sketch.versions(awkward.union(awkward)).count() == 2 * len(AWKWARD)
