"""The models, baselines and measures as queries over whole tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..baselines.exact import evidence_by_group
from ..baselines.mllib_lda import mllib_lda
from ..functions.special import digamma, digamma_sql
from ..measures import cost, quality
from ..models import zoo
from ..mpg import graph as G
from ..oracle.chain import Child, lit, vmp_chain
from ..plans.blocks import HELD_WORDS, pack_texts
from ..sources import text as T
from .base import query, read, rounded
from .preparation import SENTENCES, VOCAB5, WEIGHTS, W

ROUNDS = 3

# Coins.

FLIPS = "SELECT CASE WHEN l_linestatus = 'O' THEN 1 ELSE 0 END AS value, count(*) AS n FROM lineitem GROUP BY 1"


def flips(spark, sf, keys=()):
    return read(spark, sf, "lineitem").select(*keys, F.when(F.col("l_linestatus") == "O", 1).otherwise(0).alias("value")).groupBy(*keys, "value").agg(F.count("*").alias("n"))


def _heads(spark, sf):
    return flips(spark, sf).agg(F.sum(F.when(F.col("value") == 1, F.col("n")).otherwise(0)).alias("h"), F.sum("n").alias("m"))


HEADS = "SELECT count(*) FILTER (l_linestatus = 'O') AS h, count(*) AS m FROM lineitem"


@query(f"SELECT round(h * 1e0 / m, 9) AS p FROM ({HEADS})")
def coin_frequentist(spark, sf):
    return _heads(spark, sf).select(F.round(F.col("h") / F.col("m"), 9).alias("p"))


@query(f"SELECT round((h + 5e-1) / (m + 1e0), 9) AS p FROM ({HEADS})")
def coin_smoothed(spark, sf):
    return _heads(spark, sf).select(F.round((F.col("h") + 0.5) / (F.col("m") + 1.0), 9).alias("p"))


@query(f"SELECT CAST(1 + m - h AS DOUBLE) AS alpha_tail, CAST(1 + h AS DOUBLE) AS alpha_head FROM ({HEADS})")
def coin_bayes(spark, sf):
    model = zoo.coin().bind(spark, a=1.0)
    model["x"].observe(flips(spark, sf), "value", weight="n")
    return model.infer(1)["p"].posterior(dense=True).agg(F.sum(F.when(F.col("j") == 0, F.col("gamma"))).alias("alpha_tail"), F.sum(F.when(F.col("j") == 1, F.col("gamma"))).alias("alpha_head"))


@query("SELECT n_name, 1e0 + count(*) FILTER (l_linestatus <> 'O') AS alpha_tail, 1e0 + count(*) FILTER (l_linestatus = 'O') AS alpha_head FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name")
def coin_bayes_by_group(spark, sf):
    s, n = read(spark, sf, "supplier"), read(spark, sf, "nation")
    per = flips(spark, sf, ["l_suppkey"]).join(s.join(n, s["s_nationkey"] == n["n_nationkey"]).select("s_suppkey", "n_name"), F.col("l_suppkey") == F.col("s_suppkey"))
    side = lambda v: (1.0 + F.sum(F.when(F.col("value") == v, F.col("n")).otherwise(0))).alias("alpha_head" if v else "alpha_tail")
    return per.groupBy("n_name").agg(side(0), side(1))


def two_coins(spark, sf, rounds=ROUNDS, callback=None):
    model = zoo.two_coins().bind(spark, alpha=1.0, beta=1.0)
    model["x"].observe(flips(spark, sf), "value", weight="n")
    return model.infer(rounds, callback)


TWO_COINS = vmp_chain(f"SELECT 0 AS d, value AS i, n FROM ({FLIPS})", [Child("ph", "SELECT 0 AS d, i, i AS v, 1 AS m FROM inst", 1.0, "2")], 2, 1.0, ROUNDS, a="i", b="0")


@query(TWO_COINS + f" SELECT CAST(k AS BIGINT) AS coins, CAST(v AS BIGINT) AS j, round(g, 5) AS gamma FROM ph_{ROUNDS}")
def two_coin_vmp(spark, sf):
    return two_coins(spark, sf)["phi"].posterior().select("coins", "j", F.round("gamma", 5).alias("gamma"))


@query(TWO_COINS + " " + " UNION ALL ".join(f"SELECT {t} AS iter, round(v, 3) AS elbo FROM elbo_{t}" for t in range(1, ROUNDS + 1)))
def two_coin_elbo(spark, sf):
    return two_coins(spark, sf, callback=lambda view: True).history().select("iter", F.round("elbo", 3).alias("elbo"))


PER_ORDER = "SELECT l_orderkey AS o, count(*) FILTER (l_linestatus = 'O') AS h, count(*) FILTER (l_linestatus <> 'O') AS t FROM lineitem GROUP BY 1"


def _lb(a, b):
    return f"(lgamma({a}) + lgamma({b}) - lgamma({a} + {b}))"


EVIDENCE = f"""SELECT o, m + ln(sum(exp(v - m))) AS log_evidence FROM (SELECT o, v, max(v) OVER (PARTITION BY o) AS m FROM (SELECT o,
  lgamma(h + 1) - lgamma(a + 1) - lgamma(h - a + 1) + lgamma(t + 1) - lgamma(b + 1) - lgamma(t - b + 1) + {_lb('(1e0 + a + b)', '(1e0 + h + t - a - b)')}
  + {_lb('(1e0 + a)', '(1e0 + b)')} + {_lb('(1e0 + h - a)', '(1e0 + t - b)')} - 3 * {_lb('1e0', '1e0')} AS v
  FROM (SELECT o, h, t, a, unnest(range(t + 1)) AS b FROM (SELECT o, h, t, unnest(range(h + 1)) AS a FROM ({PER_ORDER})))))  GROUP BY o, m"""


def evidence(spark, sf):
    side = lambda v, name: F.sum(F.when(F.col("value") == v, F.col("n")).otherwise(0)).alias(name)
    per = flips(spark, sf, ["l_orderkey"]).groupBy(F.col("l_orderkey").alias("o")).agg(side(1, "h"), side(0, "t"))
    return evidence_by_group(per, ["o"], 1.0, 1.0)


@query(f"SELECT o, round(log_evidence, 6) AS log_evidence FROM ({EVIDENCE})")
def two_coin_evidence(spark, sf):
    return evidence(spark, sf).select("o", F.round("log_evidence", 6).alias("log_evidence"))


GAP = vmp_chain("SELECT l_orderkey AS d, CASE WHEN l_linestatus = 'O' THEN 1 ELSE 0 END AS i, count(*) AS n FROM lineitem GROUP BY 1, 2", [Child("ph", "SELECT d, i, i AS v, 1 AS m FROM inst", 1.0, "2", per_group=True)], 2, 1.0, ROUNDS)


@query(GAP + f", ev AS (SELECT sum(log_evidence) AS e FROM ({EVIDENCE})) SELECT round(e, 3) AS log_evidence, round(v, 3) AS elbo, e >= v AS bounded FROM ev, elbo_{ROUNDS}")
def two_coin_bound_gap(spark, sf):
    """A two-coin model for every order: exact evidence against the bound."""
    model = zoo.dcmlda().bind(spark, K=2, V=2, alpha=1.0, beta=1.0)
    model["x"].observe(flips(spark, sf, ["l_orderkey"]), "value", keys={"docs": "l_orderkey"}, weight="n")
    bounds = []
    model.infer(ROUNDS, callback=lambda view: bounds.append(view.elbo) or True)
    exact = evidence(spark, sf).agg(F.sum("log_evidence").alias("e"))
    return exact.select(F.round("e", 3).alias("log_evidence"), F.round(F.lit(bounds[-1]), 3).alias("elbo"), (F.col("e") >= bounds[-1]).alias("bounded"))


NESTED = vmp_chain("SELECT 0 AS d, l_orderkey AS i, 1 AS n FROM lineitem GROUP BY l_orderkey", [Child("ph", "SELECT 0 AS d, l_orderkey AS i, CASE WHEN l_linestatus = 'O' THEN 1 ELSE 0 END AS v, count(*) AS m FROM lineitem GROUP BY 2, 3", 1.0, "2")], 2, 1.0, ROUNDS, a="i", b="0")


@query(NESTED + f" SELECT CAST(k AS BIGINT) AS coins, CAST(v AS BIGINT) AS j, round(g, 4) AS gamma FROM ph_{ROUNDS}")
def two_coin_nested_vmp(spark, sf):
    model = zoo.two_coins_nested().bind(spark, alpha=1.0, beta=1.0)
    model["x"].observe(flips(spark, sf, ["l_orderkey"]), "value", keys={"groups": "l_orderkey"}, weight="n")
    return model.infer(ROUNDS)["phi"].posterior().select("coins", "j", F.round("gamma", 4).alias("gamma"))


ROLLS = "SELECT CASE WHEN event_type = 'error' THEN 1 ELSE 0 END AS coin, CAST(json_extract(props, '$.k') AS BIGINT) % 6 AS die, count(*) AS n FROM events GROUP BY 1, 2"


def rolls(spark, sf):
    k = F.get_json_object("props", "$.k").cast("long")
    return read(spark, sf, "events").select(F.when(F.col("event_type") == "error", 1).otherwise(0).alias("coin"), F.pmod(k, F.lit(6)).alias("die")).groupBy("coin", "die").agg(F.count("*").alias("n"))


DIE = vmp_chain(
    f"SELECT coin AS d0, die AS i0, 0 AS d, coin * 10 + die AS i, n FROM ({ROLLS})",
    [Child("co", "SELECT d, i, d0 AS v, 1 AS m FROM inst", 1.0, "2"), Child("di", "SELECT d, i, i0 AS v, 1 AS m FROM inst", 0.5, "6")], 2, 1.0, ROUNDS, a="i // 10", b="i % 10",
)


@query(DIE + f" SELECT 'coin' AS part, CAST(k AS BIGINT) AS sides, CAST(v AS BIGINT) AS j, round(g, 5) AS gamma FROM co_{ROUNDS} UNION ALL SELECT 'die', CAST(k AS BIGINT), CAST(v AS BIGINT), round(g, 5) FROM di_{ROUNDS}")
def coins_and_die_vmp(spark, sf):
    model = zoo.coins_and_die().bind(spark, alpha=1.0, beta=1.0, delta=0.5)
    model.observe("rolls", rolls(spark, sf), {"coin": "coin", "die": "die"}, weight="n")
    model.infer(ROUNDS)
    parts = [model[v].posterior().select(F.lit(name).alias("part"), "sides", "j", F.round("gamma", 5).alias("gamma")) for v, name in (("phi", "coin"), ("rho", "die"))]
    return parts[0].union(parts[1])


LEAF_ROUNDS = 2


@query(
    f"""WITH inst AS MATERIALIZED (SELECT die AS i, sum(n) AS n FROM ({ROLLS}) GROUP BY die),
z_0 AS (SELECT i, n, k, u / sum(u) OVER (PARTITION BY i) AS r FROM (SELECT *, CAST(1 + (31 * i + 7 * k) % 13 AS DOUBLE) AS u FROM inst, range(2) t(k))),
c_0 AS (SELECT i, n, k AS v, r FROM z_0),"""
    + "".join(
        f"""
pi_{t} AS MATERIALIZED (SELECT k, g, {digamma_sql('g')} - {digamma_sql('tot')} AS e FROM (SELECT *, sum(g) OVER () AS tot FROM (SELECT k, 1e0 + sum(n * r) AS g FROM z_{t} GROUP BY k))),
ph_{t} AS MATERIALIZED (SELECT k, v, g, {digamma_sql('g')} - {digamma_sql('tot')} AS e FROM (SELECT *, sum(g) OVER (PARTITION BY k) AS tot FROM (SELECT z.k, c.v, 1e0 + sum(z.n * z.r * c.r) AS g FROM z_{t} z JOIN c_{t} c USING (i) GROUP BY ALL))),
ro_{t} AS MATERIALIZED (SELECT k, v, g, {digamma_sql('g')} - {digamma_sql('tot')} AS e FROM (SELECT *, sum(g) OVER (PARTITION BY k) + (6 - count(*) OVER (PARTITION BY k)) * 5e-1 AS tot FROM (SELECT k, i AS v, 5e-1 + sum(n * r) AS g FROM z_{t} GROUP BY k, i))),
z_{t + 1} AS MATERIALIZED (SELECT i, n, k, exp(s - m) / sum(exp(s - m)) OVER (PARTITION BY i) AS r FROM (SELECT *, max(s) OVER (PARTITION BY i) AS m FROM (SELECT c.i, c.n, p.k, any_value(p.e) + sum(c.r * h.e) + any_value(r.e) AS s
  FROM c_{t} c JOIN pi_{t} p ON true JOIN ph_{t} h ON h.k = p.k AND h.v = c.v JOIN ro_{t} r ON r.k = p.k AND r.v = c.i GROUP BY c.i, c.n, p.k))),
c_{t + 1} AS MATERIALIZED (SELECT i, n, v, exp(s - m) / sum(exp(s - m)) OVER (PARTITION BY i) AS r FROM (SELECT *, max(s) OVER (PARTITION BY i) AS m FROM (SELECT z.i, z.n, h.v, sum(z.r * h.e) AS s FROM z_{t + 1} z JOIN ph_{t} h USING (k) GROUP BY ALL))),"""
        for t in range(LEAF_ROUNDS)
    ).rstrip(",")
    + f" SELECT CAST(i AS BIGINT) AS die, CAST(v AS BIGINT) AS state, round(r, 6) AS r FROM c_{LEAF_ROUNDS}"
)
def latent_leaf_predictive(spark, sf):
    """The die is seen, the coin isn't: its posterior for each face."""
    model = zoo.coins_and_die().bind(spark, alpha=1.0, beta=1.0, delta=0.5)
    model.observe("rolls", rolls(spark, sf).groupBy("die").agg(F.sum("n").alias("n")), {"die": "die"}, weight="n")
    return model.infer(LEAF_ROUNDS)["coin"].posterior().select("die", F.col("state").cast("long").alias("state"), F.round("r", 6).alias("r"))


# Topics.

CODE = "CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END"


def user_types(spark, sf):
    c = F.col("event_type")
    code = F.when(c == "click", 0).when(c == "error", 1).when(c == "purchase", 2).when(c == "signup", 3).otherwise(4)
    return read(spark, sf, "events").select(F.col("user_id").alias("d"), code.alias("w")).groupBy("d", "w").agg(F.count("*").alias("n"))


def observe_words(model, docs, vocab, size: int, sentences: bool = False):
    """The words of whole documents: packed by the tasks that read them, or joined with a vocabulary too large to hold."""
    if size <= HELD_WORDS:
        return model.observe_packed("x", pack_texts(docs, "doc_id", vocab, sentences))
    keys = ["doc_id", "s"] if sentences else ["doc_id"]
    rows = T.token_weights(T.sentences(docs, ["doc_id"]), keys, "sentence") if sentences else T.token_weights(docs, keys)
    model["x"].observe(T.encoded(rows, vocab, keys), "w", keys={"docs": "doc_id", "sentences": "s"} if sentences else {"docs": "doc_id"}, weight="n")


def documents_model(spark, sf, spec, rounds, callback=None, sentences=False, **constants):
    """A topic model of the words in five documents or more, and that vocabulary."""
    docs = read(spark, sf, "documents").select("doc_id", "text")
    vocab = T.document_vocabulary(docs, "doc_id", 5).persist()
    size = vocab.count()
    model = spec.bind(spark, V=size, **constants)
    observe_words(model, docs, vocab, size, sentences)
    return model.infer(rounds, callback), vocab


def lda(spark, tokens: DataFrame, k, v, alpha, beta, rounds, callback=None):
    model = zoo.lda().bind(spark, K=k, V=v, alpha=alpha, beta=beta)
    model["x"].observe(tokens, "w", keys={"docs": "d"}, weight="n")
    return model.infer(rounds, callback)


SAME = "SELECT d, i, i AS v, 1 AS m FROM inst"
LDA_EVENTS = vmp_chain(f"SELECT user_id AS d, {CODE} AS i, count(*) AS n FROM events GROUP BY 1, 2", [Child("ph", SAME, 0.1, "5")], 3, 0.5, ROUNDS)


@query(LDA_EVENTS + f" SELECT CAST(d AS BIGINT) AS docs, CAST(k AS BIGINT) AS j, round(g, 5) AS gamma FROM th_{ROUNDS}")
def lda_events_vmp(spark, sf):
    return lda(spark, user_types(spark, sf), 3, 5, 0.5, 0.1, ROUNDS)["theta"].posterior().select("docs", "j", F.round("gamma", 5).alias("gamma"))


def doc_tokens(spark, sf):
    t = T.token_weights(read(spark, sf, "documents"), ["doc_id"]).persist()
    vocab = T.vocabulary(t, 5).persist()
    return T.encoded(t, vocab, ["doc_id"]).withColumnRenamed("doc_id", "d"), vocab


DOC_CTES = f"vocab AS MATERIALIZED ({VOCAB5}), toks AS MATERIALIZED (SELECT t.doc_id AS d, v.w AS i, t.n FROM ({WEIGHTS}) t JOIN vocab v USING (word))"
SIZE = "(SELECT count(*) FROM vocab)"
DOC_ROUNDS = 2
LDA_DOCS = vmp_chain("SELECT * FROM toks", [Child("ph", SAME, 0.01, SIZE)], 4, 0.1, DOC_ROUNDS, before=DOC_CTES)


def lda_documents(spark, sf, callback=None):
    return documents_model(spark, sf, zoo.lda(), DOC_ROUNDS, callback, K=4, alpha=0.1, beta=0.01)[0]


@query(LDA_DOCS + f" SELECT CAST(d AS BIGINT) AS docs, CAST(k AS BIGINT) AS j, round(g, 4) AS gamma FROM th_{DOC_ROUNDS}")
def lda_docs_vmp(spark, sf):
    return lda_documents(spark, sf)["theta"].posterior().select("docs", "j", F.round("gamma", 4).alias("gamma"))


@query(LDA_DOCS + " " + " UNION ALL ".join(f"SELECT {t} AS iter, round(v, 2) AS elbo FROM elbo_{t}" for t in range(1, DOC_ROUNDS + 1)))
def lda_elbo(spark, sf):
    return lda_documents(spark, sf, lambda view: True).history().select("iter", F.round("elbo", 2).alias("elbo"))


@query(LDA_EVENTS + " SELECT iter, round(elbo, 3) AS elbo, round(elbo - lag(elbo) OVER (ORDER BY iter), 3) AS delta FROM (" + " UNION ALL ".join(f"SELECT {t} AS iter, v AS elbo FROM elbo_{t}" for t in range(1, ROUNDS + 1)) + ")")
def elbo_delta(spark, sf):
    history = lda(spark, user_types(spark, sf), 3, 5, 0.5, 0.1, ROUNDS, lambda view: True).history()
    return quality.elbo_delta(history).select("iter", F.round("elbo", 3).alias("elbo"), F.round("delta", 3).alias("delta"))


BRANDS = "SELECT o_custkey AS d, CAST(dense_rank() OVER (ORDER BY p_brand) - 1 AS BIGINT) AS i, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey GROUP BY o_custkey, p_brand"
LDA_BRANDS = vmp_chain(f"SELECT d, i, sum(n) AS n FROM ({BRANDS}) GROUP BY d, i", [Child("ph", SAME, 0.1, "25")], 3, 0.5, ROUNDS)


@query(LDA_BRANDS + f" SELECT CAST(k AS BIGINT) AS topics, CAST(v AS BIGINT) AS j, round(g, 4) AS gamma FROM ph_{ROUNDS}")
def lda_customer_brands(spark, sf):
    l, o, p = (read(spark, sf, t) for t in ("lineitem", "orders", "part"))
    brands = T.dense_index(p.select("p_brand").distinct(), ["p_brand"], "w")
    rows = l.select("l_orderkey", "l_partkey").join(p.select("p_partkey", "p_brand"), l["l_partkey"] == p["p_partkey"]).join(o.select("o_orderkey", "o_custkey"), l["l_orderkey"] == o["o_orderkey"])
    tokens = rows.groupBy(F.col("o_custkey").alias("d"), "p_brand").agg(F.count("*").alias("n")).join(F.broadcast(brands), "p_brand")
    return lda(spark, tokens, 3, 25, 0.5, 0.1, ROUNDS)["phi"].posterior().select("topics", "j", F.round("gamma", 4).alias("gamma"))


def slda(spark, tokens, k, v, alpha, beta, rounds):
    model = zoo.slda().bind(spark, K=k, V=v, alpha=alpha, beta=beta)
    model["x"].observe(tokens, "w", keys={"docs": "d", "sentences": "s"}, weight="n")
    return model.infer(rounds)


SENT = f"SELECT doc_id, s, unnest(regexp_extract_all(lower(sentence), '{W}')) AS word FROM ({SENTENCES})"
SLDA_CTES = f"vocab AS MATERIALIZED ({VOCAB5}), st AS MATERIALIZED (SELECT t.doc_id AS d, t.s AS i, v.w AS v, count(*) AS m FROM ({SENT}) t JOIN vocab v USING (word) GROUP BY ALL)"
SLDA_DOCS = vmp_chain("SELECT d, i, 1 AS n FROM st GROUP BY d, i", [Child("ph", "SELECT d, i, v, m FROM st", 0.01, SIZE)], 4, 0.1, DOC_ROUNDS, before=SLDA_CTES)


@query(SLDA_DOCS + f" SELECT CAST(d AS BIGINT) AS docs, CAST(k AS BIGINT) AS j, round(g, 4) AS gamma FROM th_{DOC_ROUNDS}")
def slda_docs_vmp(spark, sf):
    model, _ = documents_model(spark, sf, zoo.slda(), DOC_ROUNDS, sentences=True, K=4, alpha=0.1, beta=0.01)
    return model["theta"].posterior().select("docs", "j", F.round("gamma", 4).alias("gamma"))


CONV = f"SELECT conv_id, turn, unnest(regexp_extract_all(lower(text), '{W}')) AS word FROM conversations"
CONV_CTES = f"cw AS MATERIALIZED (SELECT conv_id, turn, word, count(*) AS m FROM ({CONV}) GROUP BY ALL), vocab AS MATERIALIZED (SELECT word, row_number() OVER (ORDER BY n DESC, word) - 1 AS w FROM (SELECT word, sum(m) AS n FROM cw GROUP BY word)), st AS MATERIALIZED (SELECT conv_id AS d, turn AS i, w AS v, m FROM cw JOIN vocab USING (word))"
SLDA_CONV = vmp_chain("SELECT d, i, 1 AS n FROM st GROUP BY d, i", [Child("ph", "SELECT d, i, v, m FROM st", 0.01, SIZE)], 3, 0.1, DOC_ROUNDS, before=CONV_CTES)


@query(SLDA_CONV + f" SELECT CAST(d AS BIGINT) AS docs, CAST(k AS BIGINT) AS j, round(g, 4) AS gamma FROM th_{DOC_ROUNDS}")
def slda_conversations_vmp(spark, sf):
    turns = T.token_weights(read(spark, sf, "conversations"), ["conv_id", "turn"]).persist()
    vocab = T.vocabulary(turns).persist()
    tokens = T.encoded(turns, vocab, ["conv_id", "turn"]).withColumnsRenamed({"conv_id": "d", "turn": "s"})
    return slda(spark, tokens, 3, vocab.count(), 0.1, 0.01, DOC_ROUNDS)["theta"].posterior().select("docs", "j", F.round("gamma", 4).alias("gamma"))


DCM = vmp_chain("SELECT * FROM toks", [Child("ph", SAME, 0.1, SIZE, per_group=True)], 3, 0.5, DOC_ROUNDS, before=DOC_CTES)


@query(DCM + f" SELECT CAST(d AS BIGINT) AS docs, CAST(k AS BIGINT) AS j, round(g, 4) AS gamma FROM th_{DOC_ROUNDS}")
def dcmlda_docs_vmp(spark, sf):
    model, _ = documents_model(spark, sf, zoo.dcmlda(), DOC_ROUNDS, K=3, alpha=0.5, beta=0.1)
    return model["theta"].posterior().select("docs", "j", F.round("gamma", 4).alias("gamma"))


PARTS = "SELECT CAST(dense_rank() OVER (ORDER BY p_brand) - 1 AS BIGINT) AS i, p_partkey FROM part"
MIXTURE = vmp_chain(f"SELECT 0 AS d, i, count(*) AS n FROM ({PARTS}) GROUP BY i", [Child("ph", SAME, 0.5, "25")], 3, 0.5, ROUNDS, a="i", b="0")


@query(MIXTURE + f" SELECT CAST(k AS BIGINT) AS parts, CAST(v AS BIGINT) AS j, round(g, 5) AS gamma FROM ph_{ROUNDS}")
def mixture_parts_vmp(spark, sf):
    parts = read(spark, sf, "part")
    brands = T.dense_index(parts.select("p_brand").distinct(), ["p_brand"], "w")
    model = zoo.categorical_mixture().bind(spark, K=3, V=25, alpha=0.5, beta=0.5)
    model["x"].observe(parts.groupBy("p_brand").agg(F.count("*").alias("n")).join(F.broadcast(brands), "p_brand"), "w", weight="n")
    return model.infer(ROUNDS)["phi"].posterior().select("parts", "j", F.round("gamma", 5).alias("gamma"))


# Observed and partly observed selectors.

ROLE = "CASE role WHEN 'assistant' THEN 0 WHEN 'system' THEN 1 ELSE 2 END"
ROLE_WORDS = f"SELECT role, word, count(*) AS n FROM (SELECT {ROLE} AS role, unnest(regexp_extract_all(lower(text), '{W}')) AS word FROM conversations) GROUP BY ALL"


@query(f"SELECT CAST(role AS BIGINT) AS classes, word, round(1e-1 + n, 6) AS gamma FROM ({ROLE_WORDS})")
def naive_bayes_params(spark, sf):
    """A turn is a document with an observed class: one pass of counts is the exact posterior."""
    turns, code = _turns(spark, sf)
    vocab = T.vocabulary(turns).persist()
    model = _nb(spark, turns, vocab, code)
    return model["phi"].posterior().join(vocab.select(F.col("w").alias("j"), "word"), "j").select("classes", "word", F.round("gamma", 6).alias("gamma"))


def _turns(spark, sf):
    c = read(spark, sf, "conversations").withColumn("id", F.col("conv_id") * 1000 + F.col("turn"))
    role = F.col("role")
    code = c.select("id", F.when(role == "assistant", 0).when(role == "system", 1).otherwise(2).alias("y"))
    return T.token_weights(c, ["id"]).persist(), code


def _nb(spark, turns, vocab, code):
    model = zoo.naive_bayes().bind(spark, C=3, V=vocab.count(), alpha=1.0, beta=0.1)
    model["y"].observe(code, "y", keys={"docs": "id"})
    model["x"].observe(T.encoded(turns, vocab, ["id"]), "w", keys={"docs": "id"}, weight="n")
    return model.infer(1)


@query(
    f"""WITH cw AS MATERIALIZED (SELECT id, y, word, count(*) AS n FROM (SELECT conv_id * 1000 + turn AS id, {ROLE} AS y, unnest(regexp_extract_all(lower(text), '{W}')) AS word FROM conversations) GROUP BY ALL),
size AS (SELECT count(DISTINCT word) AS v FROM cw), ph AS (SELECT y, word, 1e-1 + sum(n) AS g FROM cw GROUP BY ALL), tot AS (SELECT y, sum(g) + (v - count(*)) * 1e-1 AS t FROM ph, size GROUP BY y, v),
pi AS (SELECT y, 1e0 + count(*) AS g FROM (SELECT {ROLE} AS y FROM conversations) GROUP BY y),
s AS (SELECT c.id, t.y, sum(c.n * (ln(coalesce(p.g, 1e-1)) - ln(t.t))) + ln(any_value(pi.g)) AS s FROM (SELECT id, word, n FROM cw) c CROSS JOIN tot t JOIN pi USING (y) LEFT JOIN ph p ON p.y = t.y AND p.word = c.word GROUP BY ALL)
SELECT id, CAST(y AS INTEGER) AS predicted FROM s QUALIFY row_number() OVER (PARTITION BY id ORDER BY round(s, 6) DESC, y) = 1"""
)
def naive_bayes_predict(spark, sf):
    turns, code = _turns(spark, sf)
    vocab = T.vocabulary(turns).persist()
    model = _nb(spark, turns, vocab, code)
    v = vocab.count()
    phi = model["phi"].posterior()
    total = phi.groupBy("classes").agg((F.sum("gamma") + (v - F.count("*")) * 0.1).alias("t"))
    pi = model["pi"].posterior().select(F.col("j").alias("classes"), F.col("gamma").alias("p"))
    # A word unseen with a class has the prior's 0.1: add its difference where it was seen.
    seen = phi.join(F.broadcast(total), "classes").select("classes", F.col("j").alias("w"), (F.log("gamma") - F.log(F.lit(0.1))).alias("more"))
    tokens = T.encoded(turns, vocab, ["id"])
    base = tokens.groupBy("id").agg(F.sum("n").alias("words")).crossJoin(F.broadcast(total.join(pi, "classes"))).select("id", "classes", (F.col("words") * (F.log(F.lit(0.1)) - F.log("t")) + F.log("p")).alias("s"))
    parts = base.union(tokens.join(seen, "w").select("id", "classes", (F.col("n") * F.col("more")).alias("s")))
    best = F.max(F.struct(F.round("s", 6).alias("s"), (-F.col("classes")).alias("c")))
    return parts.groupBy("id", "classes").agg(F.sum("s").alias("s")).groupBy("id").agg(best.alias("b")).select("id", (-F.col("b.c")).cast("int").alias("predicted"))


SEMI = vmp_chain(
    "SELECT 0 AS d, d AS i, 1 AS n, toxic AS y FROM (SELECT doc_id AS d FROM documents) LEFT JOIN (SELECT doc_id AS d, toxic FROM labels) USING (d)",
    [Child("ph", "SELECT 0 AS d, d AS i, i AS v, n AS m FROM toks", 0.1, SIZE)], 2, 1.0, DOC_ROUNDS, a="i", b="0", before=DOC_CTES, known=True,
)


@query(SEMI + f" SELECT CAST(i AS BIGINT) AS docs, CAST(k AS BIGINT) AS state, round(r, 5) + 0e0 AS r FROM r_{DOC_ROUNDS}")
def semi_observed_nb(spark, sf):
    tokens, vocab = doc_tokens(spark, sf)
    known = read(spark, sf, "documents").select("doc_id").join(read(spark, sf, "labels").select("doc_id", "toxic"), "doc_id", "left")
    model = zoo.naive_bayes().bind(spark, C=2, V=vocab.count(), alpha=1.0, beta=0.1)
    model.observe("docs", known, {"y": "toxic"}, keys={"docs": "doc_id"}, partial=True)
    model["x"].observe(tokens, "w", keys={"docs": "d"}, weight="n")
    return model.infer(DOC_ROUNDS)["y"].posterior().select("docs", F.col("state").cast("long").alias("state"), rounded("r", 5).alias("r"))


def _tone_sql(rounds: int) -> str:
    k, s, alpha, gamma, beta, dim = 2, 2, 0.5, 0.5, 0.1, 5
    ctes = [f"inst AS MATERIALIZED (SELECT user_id AS d, {CODE} AS w, count(*) AS n FROM events GROUP BY 1, 2)"]
    for name, size in (("z", k), ("u", s)):
        ctes.append(f"{name}_0 AS MATERIALIZED (SELECT d, w, n, k, u / sum(u) OVER (PARTITION BY d, w) AS r FROM (SELECT *, CAST(1 + (31 * d + 17 * w + 7 * k) % 13 AS DOUBLE) AS u FROM inst, range({size}) t(k)))")
    for t in range(rounds + 1):
        if t:
            p = t - 1
            soft = "SELECT d, w, n, k, exp(s - m) / sum(exp(s - m)) OVER (PARTITION BY d, w) AS r FROM (SELECT *, max(s) OVER (PARTITION BY d, w) AS m FROM ({}))"
            ctes.append(f"z_{t} AS MATERIALIZED ({soft.format(f'SELECT u.d, u.w, u.n, e.k, any_value(e.e) + sum(u.r * h.e) AS s FROM u_{p} u JOIN th_{p} e ON e.d = u.d JOIN ph_{p} h ON h.k = e.k AND h.s = u.k AND h.w = u.w GROUP BY ALL')})")
            ctes.append(f"u_{t} AS MATERIALIZED ({soft.format(f'SELECT z.d, z.w, z.n, e.k, any_value(e.e) + sum(z.r * h.e) AS s FROM z_{t} z JOIN sg_{p} e ON e.d = z.d JOIN ph_{p} h ON h.k = z.k AND h.s = e.k AND h.w = z.w GROUP BY ALL')})")
        for name, of, prior in (("th", "z", alpha), ("sg", "u", gamma)):
            ctes.append(f"{name}_{t} AS MATERIALIZED (SELECT d, k, g, {digamma_sql('g')} - {digamma_sql('tot')} AS e FROM (SELECT *, sum(g) OVER (PARTITION BY d) AS tot FROM (SELECT d, k, {lit(prior)} + sum(n * r) AS g FROM {of}_{t} GROUP BY d, k)))")
        ctes.append(f"ph_{t} AS MATERIALIZED (SELECT k, s, w, g, {digamma_sql('g')} - {digamma_sql('tot')} AS e FROM (SELECT *, sum(g) OVER x + ({dim} - count(*) OVER x) * {lit(beta)} AS tot FROM (SELECT z.k, u.k AS s, z.w, {lit(beta)} + sum(z.n * z.r * u.r) AS g FROM z_{t} z JOIN u_{t} u ON u.d = z.d AND u.w = z.w GROUP BY ALL) WINDOW x AS (PARTITION BY k, s)))")
    return "WITH " + ",\n".join(ctes) + f" SELECT CAST(k AS BIGINT) AS topics, CAST(s AS BIGINT) AS tones, CAST(w AS BIGINT) AS j, round(g, 5) AS gamma FROM ph_{rounds}"


@query(_tone_sql(2))
def topic_sentiment_vmp(spark, sf):
    """Two selectors that share a child are updated in turn, each averaging over the other."""
    model = zoo.topic_sentiment().bind(spark, K=2, S=2, V=5, alpha=0.5, gamma=0.5, beta=0.1)
    model["x"].observe(user_types(spark, sf), "w", keys={"docs": "d"}, weight="n")
    return model.infer(2)["phi"].posterior().select("topics", "tones", "j", F.round("gamma", 5).alias("gamma"))


# Quality.

HELD = f"SELECT item_id, w, count(*) AS n FROM (SELECT item_id, unnest(regexp_extract_all(lower(text), '{W}')) AS word FROM benchmark) JOIN vocab USING (word) GROUP BY ALL"
LL = LDA_DOCS + f""", share AS (SELECT k, avg(g / t) AS share FROM (SELECT *, sum(g) OVER (PARTITION BY d) AS t FROM th_{DOC_ROUNDS}) GROUP BY k),
mix AS (SELECT v AS w, sum(share * g / tot) AS p FROM eph_{DOC_ROUNDS} JOIN share USING (k) GROUP BY v),
ll AS (SELECT item_id, sum(n * ln(p)) AS ll, CAST(sum(n) AS BIGINT) AS words FROM ({HELD}) JOIN mix USING (w) GROUP BY item_id)"""


def _ll(spark, sf):
    model, vocab = documents_model(spark, sf, zoo.lda(), DOC_ROUNDS, K=4, alpha=0.1, beta=0.01)
    held = T.encoded(T.token_weights(read(spark, sf, "benchmark"), ["item_id"]), vocab, ["item_id"])
    return quality.predictive_ll(held, model["phi"].posterior(), quality.topic_shares(model["theta"].posterior(), ["docs"]), ["item_id"])


@query(LL + " SELECT item_id, round(ll, 4) AS ll, words FROM ll")
def predictive_ll(spark, sf):
    return _ll(spark, sf).select("item_id", F.round("ll", 4).alias("ll"), "words")


@query(LL + " SELECT round(exp(-sum(ll) / sum(words)), 3) AS perplexity FROM ll")
def perplexity(spark, sf):
    return quality.perplexity(_ll(spark, sf)).select(F.round("perplexity", 3).alias("perplexity"))


@query(LDA_DOCS + f", best AS (SELECT d, k FROM (SELECT d, k, g / sum(g) OVER (PARTITION BY d) AS m FROM th_{DOC_ROUNDS}) QUALIFY row_number() OVER (PARTITION BY d ORDER BY round(m, 9) DESC, k) = 1) SELECT round(sum(top) * 1e0 / sum(n), 6) AS purity FROM (SELECT k, max(n) AS top, sum(n) AS n FROM (SELECT k, lang, count(*) AS n FROM best JOIN (SELECT doc_id AS d, lang FROM documents) USING (d) GROUP BY ALL) GROUP BY k)")
def topic_lang_purity(spark, sf):
    theta = lda_documents(spark, sf)["theta"].posterior()
    langs = read(spark, sf, "documents").select(F.col("doc_id").alias("docs"), "lang")
    return quality.purity(theta, langs, "docs", "lang").select(F.round("purity", 6).alias("purity"))


# The message-passing graph.

K, M = 8, 16


def event_graph(spark, sf):
    return G.MessageGraph.of(read(spark, sf, "events").select("user_id", "event_id"), "user_id", ["event_id"], K)


GRAPH = f"""WITH tok AS MATERIALIZED (SELECT row_number() OVER (ORDER BY event_id) - 1 AS i, dense_rank() OVER (ORDER BY user_id) - 1 AS g FROM events),
c AS (SELECT count(*) AS n, count(DISTINCT g) AS u FROM tok),
verts AS (SELECT i AS vid, 'x' AS rv, i AS idx FROM tok UNION ALL SELECT i + n, 'z', i FROM tok, c UNION ALL SELECT DISTINCT g + 2 * n, 'theta', g FROM tok, c UNION ALL SELECT k + 2 * n + u, 'phi', k FROM range({K}) t(k), c),
edges AS MATERIALIZED (SELECT g + 2 * n AS src, i + n AS dst, 'theta-z' AS etype, g AS root FROM tok, c UNION ALL SELECT i + n, i, 'z-x', g FROM tok, c UNION ALL SELECT k + 2 * n + u, i, 'phi-x', g FROM tok, c, range({K}) t(k)),
sized AS (SELECT e.*, CASE WHEN src < n THEN n WHEN src < 2 * n THEN n WHEN src < 2 * n + u THEN u ELSE {K} END AS ss, CASE WHEN dst < n THEN n ELSE n END AS ds,
  CASE WHEN src < n THEN 0 WHEN src < 2 * n THEN n WHEN src < 2 * n + u THEN 2 * n ELSE 2 * n + u END AS sl, CASE WHEN dst < n THEN 0 ELSE n END AS dl, u FROM edges e, c)"""
SIDE = 4
PIDS = {
    "1d": f"{G.mix_sql('src')} % {M}",
    "2d": f"{G.mix_sql('src')} % {SIDE} * {SIDE} + {G.mix_sql('dst')} % {SIDE}",
    "rvc": G.mix_sql("a + b") + f" % {M}",
    "crvc": G.mix_sql("a + b") + f" % {M}",
    "tailored": f"CASE WHEN ss > ds THEN (src - sl) * {M} // ss ELSE (dst - dl) * {M} // ds END",
    "root_range": f"root * {M} // u",
}


def _pid_sql(strategy: str) -> str:
    rows = "sized"
    if strategy in ("rvc", "crvc"):
        a, b = ("src", "dst") if strategy == "rvc" else ("least(src, dst)", "greatest(src, dst)")
        rows = f"(SELECT *, {G.mix_sql(a)} AS a, {G.mix_sql(f'{b} + 1000003')} AS b FROM sized)"
    return f"SELECT src, dst, CAST({PIDS[strategy]} AS BIGINT) AS pid FROM {rows}"


@query(GRAPH + " SELECT * FROM verts")
def mpg_vertices(spark, sf):
    return event_graph(spark, sf).vertices()


@query(GRAPH + " SELECT src, dst, etype FROM edges")
def mpg_edges(spark, sf):
    return event_graph(spark, sf).edges().drop("root")


@query(GRAPH + " SELECT vid, rv FROM verts")
def vertex_ids(spark, sf):
    """Interval lookup finds the variable again from the id alone."""
    g = event_graph(spark, sf)
    return G.id_to_rv(g.vertices().select("vid"), "vid", g.ids).select("vid", "rv")


@query(GRAPH + " SELECT i AS x, i + n AS z FROM tok, c")
def sibling_ids(spark, sf):
    g = event_graph(spark, sf)
    return g.vertices().filter("rv = 'x'").select(F.col("vid").alias("x"), G.sibling_id(F.col("vid"), g.ids["x"], g.ids["z"]).alias("z"))


def _pid(strategy):
    def run(spark, sf):
        g = event_graph(spark, sf)
        return G.partition_ids(g.edges(), g.ids, strategy, M).select("src", "dst", "pid")

    run.__name__ = f"pid_{strategy}"
    query(f"{GRAPH} {_pid_sql(strategy)}")(run)


for _strategy in G.STRATEGIES:
    _pid(_strategy)

ALL_PIDS = GRAPH + ", placed AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT '{s}' AS strategy, src, dst, pid FROM ({_pid_sql(s)})" for s in G.STRATEGIES) + ")"


def by_strategy(spark, sf, measure):
    g = event_graph(spark, sf)
    edges = g.edges().persist()
    out = None
    for s in G.STRATEGIES:
        own = measure(g, G.partition_ids(edges, g.ids, s, M)).select(F.lit(s).alias("strategy"), "*")
        out = own if out is None else out.union(own)
    return out


@query(ALL_PIDS + " SELECT strategy, round(avg(n), 6) AS replicas FROM (SELECT strategy, vid, count(DISTINCT pid) AS n FROM (SELECT strategy, dst AS vid, pid FROM placed UNION ALL SELECT strategy, src, pid FROM placed), c WHERE vid < c.n GROUP BY strategy, vid) GROUP BY strategy")
def replication_by_strategy(spark, sf):
    """Mean number of partitions that need an observation."""
    return by_strategy(spark, sf, lambda g, e: G.replicas(e).filter(F.col("vid") <= g.ids["x"].hi).agg(F.round(F.avg("n"), 6).alias("replicas")))


@query(ALL_PIDS + " SELECT strategy, max(n) AS vertices FROM (SELECT strategy, pid, count(DISTINCT vid) AS n FROM (SELECT strategy, dst AS vid, pid FROM placed UNION ALL SELECT strategy, src, pid FROM placed) GROUP BY strategy, pid) GROUP BY strategy")
def largest_partition_by_strategy(spark, sf):
    return by_strategy(spark, sf, lambda g, e: G.partition_loads(e).agg(F.max("n").alias("vertices")))


@query(ALL_PIDS + " SELECT strategy, count(*) AS edges, any_value(v) AS replicated FROM placed JOIN (SELECT strategy, count(*) AS v FROM (SELECT DISTINCT strategy, vid, pid FROM (SELECT strategy, dst AS vid, pid FROM placed UNION ALL SELECT strategy, src, pid FROM placed)) GROUP BY strategy) USING (strategy) GROUP BY strategy")
def edge_size_by_strategy(spark, sf):
    def size(g, e):
        return e.agg(F.count("*").alias("edges")).crossJoin(G.replicas(e).agg(F.sum("n").alias("replicated")))

    return by_strategy(spark, sf, size)


REPLICAS = "CASE strategy WHEN 'tailored' THEN 1e0 WHEN 'root_range' THEN 1e0 WHEN '2d' THEN sqrt(m) * (1 - pow(1 - 1 / sqrt(m), {k} + 1)) ELSE m * (1 - pow(1 - 1e0 / m, {k} + 1)) END"


@query(f"SELECT strategy, m, k, orders, round({REPLICAS.format(k='k')}, 6) AS replicas FROM (VALUES ('1d'), ('2d'), ('rvc'), ('crvc'), ('tailored'), ('root_range')) s(strategy), (VALUES (4), (16), (64)) p(m), (SELECT n - 1 AS k, count(*) AS orders FROM (SELECT count(*) AS n FROM lineitem GROUP BY l_orderkey) GROUP BY n)")
def expected_replicas_table(spark, sf):
    """Partitions that an order with k + 1 lines is expected in, as an observation with its selector and k components is."""
    degrees = read(spark, sf, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("n")).groupBy((F.col("n") - 1).alias("k")).agg(F.count("*").alias("orders"))
    cases = spark.createDataFrame([(s, m) for s in G.STRATEGIES for m in (4, 16, 64)], "strategy string, m int")
    return degrees.crossJoin(F.broadcast(cases)).select("strategy", "m", "k", "orders", F.round(G.expected_replicas_column(F.col("strategy"), F.col("m"), F.col("k")), 6).alias("replicas"))


@query(
    "SELECT strategy, k, replicas, largest, m, n, round(" + REPLICAS.format(k="c") + ", 6) AS expected, round(CASE strategy WHEN '1d' THEN n WHEN '2d' THEN n / sqrt(m) * (1 - pow(1 - 1 / sqrt(m), c + 1)) WHEN 'tailored' THEN 3 * ((n + m - 1) // m) + c ELSE n * (1 - pow(1 - 1e0 / m, c + 1)) END, 3) AS bound"
    + f" FROM (SELECT *, CASE k WHEN 'O(1)' THEN {K} ELSE m END AS c FROM (VALUES " + ", ".join(str(r) for r in G.ASYMPTOTIC) + ") t(strategy, k, replicas, largest), (VALUES (16), (64)) p(m)), (SELECT count(*) AS n FROM events WHERE user_id IS NOT NULL AND event_id IS NOT NULL)"
)
def asymptotic_table(spark, sf):
    return G.asymptotic_table(read(spark, sf, "events"), "user_id", "event_id", (16, 64), K)


@query(GRAPH + " SELECT etype, needed, sent, needed - sent AS starved FROM (SELECT etype, 2 * count(*) AS needed, count(*) FILTER (etype = 'phi-x') AS sent FROM edges GROUP BY etype)")
def pregel_starved(spark, sf):
    return G.starved_messages(event_graph(spark, sf))


# Baselines, times, memory.


@query()
def mllib_lda_em(spark, sf):
    return mllib_lda(read(spark, sf, "documents"), 4, 5, "em")


@query()
def mllib_lda_online(spark, sf):
    return mllib_lda(read(spark, sf, "documents"), 4, 5, "online")


@query()
def time_breakdown(spark, sf):
    return lda(spark, user_types(spark, sf), 3, 5, 0.5, 0.1, ROUNDS).timings()


@query(f"SELECT n, v, CAST(8 * (4 * n * 96 + n * 96 + 2 * g * 96 + 2 * v * 96) AS BIGINT) AS bytes FROM (SELECT CAST(sum(n) AS BIGINT) AS n, count(DISTINCT word) AS v, count(DISTINCT doc_id) AS g FROM ({WEIGHTS}))")
def memory_estimate(spark, sf):
    w = T.token_weights(read(spark, sf, "documents"), ["doc_id"]).agg(F.sum("n").alias("n"), F.count_distinct("word").alias("v"), F.count_distinct("doc_id").alias("g"))
    return w.select("n", "v", F.expr(f"8 * (4 * n * {96} + n * 96 + 2 * g * 96 + 2 * v * 96)").alias("bytes"))
