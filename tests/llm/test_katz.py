import math
import random
import zlib
from collections import Counter, defaultdict

import numpy as np

from plate_engine.llm import katz
from plate_engine.llm.common import fold


def brute(rows, train):
    tokens = {i: [*(w.lower() for w in (t or "").split()), None] for i, t in rows}
    uni, bi = Counter(), Counter()
    for i in tokens:
        if train(i):
            uni.update(tokens[i])
            bi.update(zip([0, *tokens[i]], tokens[i]))
    total = sum(uni.values())
    hist = lambda c: np.array([0] + [sum(v == r for v in c.values()) for r in range(1, 8)])
    du, db = katz.Discounts.of(hist(uni)), katz.Discounts.of(hist(bi))
    d = lambda disc, c: c * disc.factor[min(c, 6)]
    unknown = 1 - sum(d(du, c) for c in uni.values()) / total
    p1 = lambda w: d(du, uni[w]) / total if uni[w] else unknown
    after = defaultdict(dict)
    for (a, b), c in bi.items():
        after[a][b] = c

    def p2(h, w):
        own = after.get(h)
        if not own:
            return p1(w)
        n = sum(own.values())
        kept = sum(d(db, c) for c in own.values())
        more = kept >= n * (1 - 1e-12)
        kept, m = (n * n / (n + 1), n + 1) if more else (kept, n)
        if w in own:
            return d(db, own[w]) / m
        return (1 - kept / n) / (1 - sum(p1(x) for x in own)) * p1(w)

    for h in [0, *list(uni)[:20], "never seen"]:  # every history's probabilities sum to 1
        assert abs(sum(p2(h, w) for w in uni) + p2(h, "never seen") - 1) < 1e-9
    v = len(uni)
    return {i: (len(t), sum(uni[w] > 0 for w in t), total, sum(math.log10((uni[w] + 1) / (total + v + 1)) for w in t), sum(math.log10(p2(h, w)) for h, w in zip([0, *t], t))) for i, t in tokens.items()}


def check(spark, rows, hot=None):
    df = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, score string")
    got = {r["doc_id"]: r for r in katz.katz_scores(df, fold(7) != 2).collect()}
    want = brute(rows, lambda i: zlib.crc32(str(i).encode()) % 7 != 2)
    assert got.keys() == want.keys()
    for i, w in want.items():
        g = got[i]
        assert (g["n_tokens"], g["n_known"], g["train_tokens"]) == w[:3]
        assert abs(g["base_score"] - w[3]) < 1e-6 * abs(w[3])
        assert abs(g["score"] - w[4]) < 1e-6 * max(1, abs(w[4])), (i, g["score"], w[4])


def test_against_brute_force(spark):
    rng = random.Random(1)
    words = [f"W{k}" for k in range(300)]
    rows = [(i, " ".join(words[int(rng.paretovariate(0.6)) % 300] for _ in range(rng.randrange(0, 90)))) for i in range(120)]
    check(spark, [*rows, (500, None), (501, ""), (502, "only unknown zzz yyy"), (503, rows[3][1])])


def test_hot_histories_are_spread(spark, monkeypatch):
    rng = random.Random(2)
    monkeypatch.setattr(katz, "HOT_LEAST", 20)
    rows = [(i, " ".join(rng.choice(["a", "b", "c", "d", f"r{rng.randrange(80)}"]) for _ in range(40))) for i in range(60)]
    check(spark, rows)


def test_no_rows(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert katz.katz_scores(empty, fold(7) != 2).count() == 0
