"""Sources, text preparation, projections and scalar functions."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.special import digamma, log_gamma
from ..functions.special import digamma_sql
from ..sources import text as T
from .base import query, read, rounded

W = r"[\p{L}\p{N}]+"
TOKENS = f"SELECT doc_id, unnest(regexp_extract_all(lower(text), '{W}')) AS word FROM documents"
WEIGHTS = f"SELECT doc_id, word, count(*) AS n FROM ({TOKENS}) GROUP BY doc_id, word"
VOCAB = f"SELECT row_number() OVER (ORDER BY n DESC, word) - 1 AS w, word, n, docs FROM (SELECT word, CAST(sum(n) AS BIGINT) AS n, count(*) AS docs FROM ({WEIGHTS}) GROUP BY word)"
VOCAB5 = VOCAB.replace("GROUP BY word)", "GROUP BY word HAVING count(*) >= 5)")


def weights(spark, sf):
    return T.token_weights(read(spark, sf, "documents"), ["doc_id"])


@query("SELECT doc_id, n_chars FROM documents WHERE lang = 'en'")
def scan_documents_pruned(spark, sf):
    return read(spark, sf, "documents").filter("lang = 'en'").select("doc_id", "n_chars")


@query(TOKENS)
def tokens_doc_word(spark, sf):
    return T.words(read(spark, sf, "documents"), ["doc_id"])


@query(WEIGHTS)
def token_weights(spark, sf):
    return weights(spark, sf)


@query(VOCAB)
def vocabulary_ranked(spark, sf):
    return T.vocabulary(weights(spark, sf)).select("w", "word", "n", "docs")


@query(VOCAB5)
def vocabulary_pruned(spark, sf):
    return T.vocabulary(weights(spark, sf), 5).select("w", "word", "n", "docs")


@query(f"SELECT t.doc_id, v.w, t.n FROM ({WEIGHTS}) t JOIN ({VOCAB5}) v USING (word)")
def encoded_tokens(spark, sf):
    t = weights(spark, sf).persist()
    return T.encoded(t, T.vocabulary(t, 5), ["doc_id"])


SENTENCES = r"""SELECT doc_id, CAST(s - 1 AS INTEGER) AS s, sentence FROM (SELECT doc_id, unnest(regexp_split_to_array(text, '[.!?\n]+')) AS sentence,
  generate_subscripts(regexp_split_to_array(text, '[.!?\n]+'), 1) AS s FROM documents) WHERE trim(sentence) <> ''"""


@query(SENTENCES)
def sentences(spark, sf):
    return T.sentences(read(spark, sf, "documents"), ["doc_id"])


@query(f"SELECT doc_id, s, word, count(*) AS n FROM (SELECT doc_id, s, unnest(regexp_extract_all(lower(sentence), '{W}')) AS word FROM ({SENTENCES})) GROUP BY ALL")
def sentence_tokens(spark, sf):
    return T.token_weights(T.sentences(read(spark, sf, "documents"), ["doc_id"]), ["doc_id", "s"], "sentence")


@query(f"SELECT conv_id, turn, word, count(*) AS n FROM (SELECT conv_id, turn, unnest(regexp_extract_all(lower(text), '{W}')) AS word FROM conversations) GROUP BY ALL")
def conversation_tokens(spark, sf):
    return T.token_weights(read(spark, sf, "conversations"), ["conv_id", "turn"])


def _page_sql() -> str:
    t = "html"
    for pattern in (r"(?is)<script[^>]*>.*?</script>", r"(?is)<style[^>]*>.*?</style>", r"(?s)<!--.*?-->", r"<[^>]*>"):
        t = f"regexp_replace({t}, '{pattern}', ' ', 'g')"
    for entity, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "''"), ("&nbsp;", " "), ("&amp;", "&")):
        t = f"replace({t}, '{entity}', '{char}')"
    return f"SELECT page_id, trim(regexp_replace({t}, '[ \\t\\r\\n]+', ' ', 'g')) AS text FROM pages"


@query(_page_sql())
def page_text(spark, sf):
    return T.page_text(read(spark, sf, "pages"))


@query(f"SELECT doc_id, n_words, before FROM (SELECT doc_id, n_words, CAST(sum(n_words) OVER (ORDER BY doc_id) - n_words AS BIGINT) AS before FROM (SELECT doc_id, count(*) AS n_words FROM ({TOKENS}) GROUP BY doc_id)) WHERE before < 100000")
def take_words_prefix(spark, sf):
    return T.take_words(read(spark, sf, "documents"), 100_000).select("doc_id", "n_words", "before")


@query("SELECT doc_id, (doc_id * 48271 + 12345) % 2147483647 % 100 AS bucket FROM documents WHERE (doc_id * 48271 + 12345) % 2147483647 % 100 < 20")
def doc_sample_hash(spark, sf):
    bucket = F.pmod(F.pmod(F.col("doc_id") * 48271 + 12345, F.lit(2147483647)), F.lit(100))
    return read(spark, sf, "documents").select("doc_id", bucket.alias("bucket")).filter("bucket < 20")


@query("SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def events_props_json(spark, sf):
    return read(spark, sf, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("SELECT l_orderkey, CASE WHEN l_linestatus = 'O' THEN 1 ELSE 0 END AS value, count(*) AS n FROM lineitem GROUP BY ALL")
def coin_encode(spark, sf):
    return read(spark, sf, "lineitem").select("l_orderkey", F.when(F.col("l_linestatus") == "O", 1).otherwise(0).alias("value")).groupBy("l_orderkey", "value").agg(F.count("*").alias("n"))


@query(f"SELECT o_orderkey, round({digamma_sql('o_totalprice / 1e3')}, 9) + 0e0 AS psi, round((lgamma(o_totalprice / 1e3 + 1e-4) - lgamma(o_totalprice / 1e3 - 1e-4)) / 2e-4, 3) + 0e0 AS slope FROM orders")
def digamma_grid(spark, sf):
    x = F.col("o_totalprice") / 1e3
    return read(spark, sf, "orders").select("o_orderkey", rounded(digamma(x), 9).alias("psi"), rounded(digamma(x), 3).alias("slope"))


@query("SELECT o_orderkey, round(lgamma(o_totalprice / 1e3), 7) + 0e0 AS lg FROM orders")
def log_gamma_grid(spark, sf):
    return read(spark, sf, "orders").select("o_orderkey", rounded(log_gamma(F.col("o_totalprice") / 1e3), 7).alias("lg"))


@query("SELECT user_id, event_type, round(exp(v - max(v) OVER w) / sum(exp(v - m)) OVER w, 9) + 0e0 AS p FROM (SELECT *, max(v) OVER (PARTITION BY user_id) AS m FROM (SELECT user_id, event_type, avg(value) / 1e2 AS v FROM events GROUP BY ALL)) WINDOW w AS (PARTITION BY user_id)")
def softmax_rows(spark, sf):
    from pyspark.sql import Window

    over = Window.partitionBy("user_id")
    rows = read(spark, sf, "events").groupBy("user_id", "event_type").agg((F.avg("value") / 1e2).alias("v")).withColumn("e", F.exp(F.col("v") - F.max("v").over(over)))
    return rows.select("user_id", "event_type", rounded(F.col("e") / F.sum("e").over(over), 9).alias("p"))


@query("SELECT l_returnflag, a, b, round(a / (a + b), 9) + 0e0 AS mean, round(a * b / ((a + b) * (a + b) * (a + b + 1)), 12) + 0e0 AS variance, round((a - 1) / (a + b - 2), 9) + 0e0 AS mode FROM (SELECT l_returnflag, 1e0 + count(*) FILTER (l_linestatus = 'O') AS a, 1e0 + count(*) FILTER (l_linestatus <> 'O') AS b FROM lineitem GROUP BY ALL)")
def beta_mean_var(spark, sf):
    head = F.count_if(F.col("l_linestatus") == "O")
    rows = read(spark, sf, "lineitem").groupBy("l_returnflag").agg((1.0 + head).alias("a"), (1.0 + F.count("*") - head).alias("b"))
    a, b = F.col("a"), F.col("b")
    return rows.select("l_returnflag", "a", "b", rounded(a / (a + b), 9).alias("mean"), rounded(a * b / ((a + b) * (a + b) * (a + b + 1)), 12).alias("variance"), rounded((a - 1) / (a + b - 2), 9).alias("mode"))


@query("SELECT vec_id, CAST(dim - 1 AS INTEGER) AS dim, CASE WHEN embedding[dim] > 0 THEN 1 ELSE 0 END AS value FROM (SELECT vec_id, embedding, unnest(range(1, len(embedding) + 1)) AS dim FROM embeddings)")
def embedding_sign_bits(spark, sf):
    return read(spark, sf, "embeddings").select("vec_id", F.posexplode(F.transform("embedding", lambda x: F.when(x > 0, 1).otherwise(0))).alias("dim", "value"))


COUNTS = "SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL"


@query(f"SELECT user_id, CAST(row_number() OVER (PARTITION BY user_id ORDER BY event_type) - 1 AS INTEGER) AS pos, event_type, round((1 + n) / (sum(n) OVER w + count(*) OVER w), 9) + 0e0 AS mean FROM ({COUNTS}) WINDOW w AS (PARTITION BY user_id)")
def posterior_arrays(spark, sf):
    rows = read(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    packed = rows.groupBy("user_id").agg(F.array_sort(F.collect_list(F.struct("event_type", "n"))).alias("a"))
    gamma = F.transform("a", lambda x: x["n"] + 1.0)
    total = F.aggregate(gamma, F.lit(0.0), lambda s, x: s + x)
    both = F.zip_with(F.transform("a", lambda x: x["event_type"]), F.transform(gamma, lambda g: g / total), lambda t, m: F.struct(t.alias("event_type"), m.alias("mean")))
    return packed.select("user_id", F.posexplode(both).alias("pos", "x")).select("user_id", "pos", "x.event_type", rounded("x.mean", 9).alias("mean"))


@query(f"SELECT user_id, max(n) FILTER (event_type = 'click') AS clicks, max(n) FILTER (event_type = 'error') AS errors, count(*) AS kinds FROM ({COUNTS}) GROUP BY user_id")
def posterior_map(spark, sf):
    rows = read(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = rows.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.element_at("m", "click").alias("clicks"), F.element_at("m", "error").alias("errors"), F.size(F.map_keys("m")).cast("long").alias("kinds"))


@query("SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(count(*) FILTER (o_orderstatus = 'F') AS BIGINT) AS heads, count(*) AS n FROM orders GROUP BY date_trunc('month', o_orderdate), y, m")
def date_month_flips(spark, sf):
    rows = read(spark, sf, "orders").groupBy(F.date_trunc("month", "o_orderdate").alias("at")).agg(F.count_if(F.col("o_orderstatus") == "F").alias("heads"), F.count("*").alias("n"))
    return rows.select(F.year("at").alias("y"), F.month("at").alias("m"), "heads", "n")


@query("SELECT doc_id, length(trim(lower(text))) AS n, substring(lower(text), 1, 20) AS head, length(regexp_replace(text, '[0-9]+', '#', 'g')) AS masked FROM documents")
def string_norm(spark, sf):
    t = F.lower("text")
    return read(spark, sf, "documents").select("doc_id", F.length(F.trim(t)).cast("long").alias("n"), F.substring(t, 1, 20).alias("head"), F.length(F.regexp_replace("text", "[0-9]+", "#")).cast("long").alias("masked"))
