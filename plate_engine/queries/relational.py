"""Joins, aggregates, windows and set operations that the inference rounds and their users are made of."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..sources import text as T
from .base import query, read, rounded
from .preparation import VOCAB5, WEIGHTS, weights

COUNTS = "SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL"
CODE = "CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END"
#: A component table over event types: probabilities by a whole-number rule.
PHI = "SELECT k, w, ln((1e0 + (7 * k + 3 * w) % 5) / 15e0) AS el FROM range(3) a(k), range(5) b(w)"


def counts(spark, sf):
    return read(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))


def coded(df):
    c = F.col("event_type")
    return df.withColumn("w", F.when(c == "click", 0).when(c == "error", 1).when(c == "purchase", 2).when(c == "signup", 3).otherwise(4).cast("long"))


def phi(spark):
    k, w = spark.range(3).withColumnRenamed("id", "k"), spark.range(5).withColumnRenamed("id", "w")
    return k.crossJoin(w).withColumn("el", F.log((1.0 + F.pmod(7 * F.col("k") + 3 * F.col("w"), F.lit(5))) / 15.0))


SCORES = f"SELECT user_id, k, round(sum(n * el), 6) + 0e0 AS s FROM (SELECT user_id, {CODE} AS w, n FROM ({COUNTS})) t JOIN ({PHI}) p USING (w) GROUP BY ALL"


@query(SCORES)
def score_broadcast_join(spark, sf):
    return coded(counts(spark, sf)).join(F.broadcast(phi(spark)), "w").groupBy("user_id", "k").agg(rounded(F.sum(F.col("n") * F.col("el"))).alias("s"))


@query(SCORES)
def score_shuffle_join(spark, sf):
    return coded(counts(spark, sf)).join(phi(spark).hint("merge"), "w").groupBy("user_id", "k").agg(rounded(F.sum(F.col("n") * F.col("el"))).alias("s"))


@query(f"SELECT c_custkey, c.w, 1e-1 + coalesce(n, 0) AS gamma FROM (SELECT c_custkey, w FROM customer, range(5) t(w)) c LEFT JOIN (SELECT user_id, {CODE} AS w, n FROM ({COUNTS})) e ON e.user_id = c_custkey AND e.w = c.w")
def outer_update_join(spark, sf):
    index = read(spark, sf, "customer").select("c_custkey").crossJoin(F.broadcast(spark.range(5).withColumnRenamed("id", "w")))
    got = coded(counts(spark, sf)).select(F.col("user_id").alias("c_custkey"), "w", "n")
    return index.join(got, ["c_custkey", "w"], "left").select("c_custkey", "w", (0.1 + F.coalesce("n", F.lit(0))).alias("gamma"))


CATALOGUE = [("x", 0, 4999), ("z", 5000, 9999), ("theta", 10000, 10149)]


@query("SELECT event_id, rv, event_id - lo AS idx FROM events JOIN (VALUES " + ", ".join(f"('{n}', {a}, {b})" for n, a, b in CATALOGUE) + ") c(rv, lo, hi) ON event_id BETWEEN lo AND hi")
def id_interval_join(spark, sf):
    catalogue = spark.createDataFrame(CATALOGUE, "rv string, lo long, hi long")  # a row a variable
    return read(spark, sf, "events").join(F.broadcast(catalogue), F.col("event_id").between(F.col("lo"), F.col("hi"))).select("event_id", "rv", (F.col("event_id") - F.col("lo")).alias("idx"))


@query("SELECT doc_id, lang FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
def holdout_anti(spark, sf):
    return read(spark, sf, "documents").select("doc_id", "lang").join(read(spark, sf, "labels").select("doc_id"), "doc_id", "left_anti")


@query("SELECT doc_id, lang FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
def labelled_semi(spark, sf):
    return read(spark, sf, "documents").select("doc_id", "lang").join(read(spark, sf, "labels").select("doc_id"), "doc_id", "left_semi")


@query("SELECT p.k AS p_key, o.k AS o_key, coalesce(p.n, 0) - coalesce(o.n, 0) AS gap FROM (SELECT l_suppkey AS k, count(*) AS n FROM lineitem WHERE l_linestatus = 'O' GROUP BY 1) p FULL JOIN (SELECT o_custkey AS k, count(*) AS n FROM orders GROUP BY 1) o ON p.k = o.k")
def full_outer_compare(spark, sf):
    p = read(spark, sf, "lineitem").filter("l_linestatus = 'O'").groupBy(F.col("l_suppkey").alias("p_key")).agg(F.count("*").alias("a"))
    o = read(spark, sf, "orders").groupBy(F.col("o_custkey").alias("o_key")).agg(F.count("*").alias("b"))
    return p.join(o, F.col("p_key") == F.col("o_key"), "full").select("p_key", "o_key", (F.coalesce("a", F.lit(0)) - F.coalesce("b", F.lit(0))).alias("gap"))


@query("SELECT e.event_id, p.heads, p.total FROM (SELECT * FROM events WHERE event_type = 'purchase') e ASOF LEFT JOIN (SELECT user_id, ts, max(heads) AS heads, max(total) AS total FROM (SELECT user_id, ts, CAST(sum(CASE WHEN event_type = 'error' THEN 1 ELSE 0 END) OVER w AS BIGINT) AS heads, count(*) OVER w AS total FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING)) GROUP BY user_id, ts) p ON e.user_id = p.user_id AND e.ts >= p.ts")
def posterior_asof(spark, sf):
    e = read(spark, sf, "events")
    by = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    states = e.withColumn("heads", F.sum((F.col("event_type") == "error").cast("long")).over(by)).withColumn("total", F.count("*").over(by))
    states = states.groupBy("user_id", "ts").agg(F.struct(F.max("heads").alias("heads"), F.max("total").alias("total")).alias("p"))
    asked = e.filter("event_type = 'purchase'").select("user_id", "ts", "event_id", F.lit(None).cast("struct<heads:bigint,total:bigint>").alias("p"), F.lit(1).alias("o"))
    both = asked.unionByName(states.select("user_id", "ts", F.lit(None).cast("long").alias("event_id"), "p", F.lit(0).alias("o")))
    last = F.last("p", ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts", "o").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return both.withColumn("q", last).filter("o = 1").select("event_id", "q.heads", "q.total")


@query("SELECT a.event_id, count(b.event_id) AS near FROM (SELECT * FROM events WHERE event_type = 'signup') a LEFT JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts + INTERVAL 1 HOUR GROUP BY a.event_id")
def event_interval_join(spark, sf):
    """Range join by hour buckets: an anchor looks in three of them, so no user's events meet all anchors."""
    e = read(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    hour = F.floor(F.unix_timestamp("ts") / 3600)
    anchors = e.filter("event_type = 'signup'").select(F.col("event_id"), "user_id", F.col("ts").alias("at"), F.explode(F.sequence(hour - 1, hour + 1)).alias("hour"))
    near = e.select("user_id", "ts", hour.alias("hour"), F.col("event_id").alias("other"))
    inside = F.abs(F.unix_micros("ts") - F.unix_micros("at")) <= 3_600_000_000
    found = anchors.join(near, ["user_id", "hour"], "left").groupBy("event_id").agg(F.count(F.when(inside, F.col("other"))).alias("near"))
    return found


@query(f"SELECT user_id, w, k FROM (SELECT user_id, {CODE} AS w FROM ({COUNTS})), range(4) t(k)")
def component_cross(spark, sf):
    return coded(counts(spark, sf)).select("user_id", "w").crossJoin(F.broadcast(spark.range(4).withColumnRenamed("id", "k")))


@query("SELECT l_orderkey AS o, count(*) AS size FROM lineitem GROUP BY 1")
def plate_sizes_orders(spark, sf):
    return read(spark, sf, "lineitem").groupBy(F.col("l_orderkey").alias("o")).agg(F.count("*").alias("size"))


@query(f"SELECT 'orders' AS plate, CAST(sum(n) AS BIGINT) AS size FROM (SELECT count(*) AS n FROM lineitem GROUP BY l_orderkey) UNION ALL SELECT 'documents', CAST(sum(n) AS BIGINT) FROM ({WEIGHTS})")
def flattened_size(spark, sf):
    orders = plate_sizes_orders(spark, sf).agg(F.sum("size").alias("size")).select(F.lit("orders").alias("plate"), "size")
    return orders.union(weights(spark, sf).agg(F.sum("n").alias("size")).select(F.lit("documents").alias("plate"), "size"))


@query(f"SELECT w, k, round(sum(n * r), 6) + 0e0 AS m FROM (SELECT {CODE} AS w, n, k, (1e0 + (user_id + 3 * k) % 4) / sum(1e0 + (user_id + 3 * k) % 4) OVER (PARTITION BY user_id, event_type) AS r FROM ({COUNTS}), range(3) t(k)) GROUP BY w, k")
def expected_counts(spark, sf):
    k = spark.range(3).withColumnRenamed("id", "k")
    u = 1.0 + F.pmod(F.col("user_id") + 3 * F.col("k"), F.lit(4))
    rows = coded(counts(spark, sf)).crossJoin(F.broadcast(k)).withColumn("r", u / F.sum(u).over(Window.partitionBy("user_id", "w")))
    return rows.groupBy("w", "k").agg(rounded(F.sum(F.col("n") * F.col("r"))).alias("m"))


@query(f"SELECT count(DISTINCT word) AS v, count(*) AS pairs FROM ({WEIGHTS})")
def distinct_vocab(spark, sf):
    return weights(spark, sf).agg(F.count_distinct("word").alias("v"), F.count("*").alias("pairs"))


@query()
def approx_vocab(spark, sf):
    return weights(spark, sf).agg(F.approx_count_distinct("word", 0.02).alias("v"))


STAR = "FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN orders ON o_custkey = c_custkey"


def _star(spark, sf):
    c, n, r, o = (read(spark, sf, t) for t in ("customer", "nation", "region", "orders"))
    return o.join(c, o["o_custkey"] == c["c_custkey"]).join(n, c["c_nationkey"] == n["n_nationkey"]).join(r, n["n_regionkey"] == r["r_regionkey"])


@query(f"SELECT r_name, n_name, CAST(count(*) FILTER (o_orderstatus = 'F') AS BIGINT) AS heads, count(*) AS n {STAR} GROUP BY ROLLUP (r_name, n_name)")
def coin_rollup(spark, sf):
    return _star(spark, sf).rollup("r_name", "n_name").agg(F.count_if(F.col("o_orderstatus") == "F").alias("heads"), F.count("*").alias("n"))


@query("SELECT l_returnflag, m, count(*) FILTER (l_linestatus = 'O') AS heads, count(*) AS n FROM (SELECT *, CAST(month(l_shipdate) AS INTEGER) AS m FROM lineitem) GROUP BY CUBE (l_returnflag, m)")
def coin_cube(spark, sf):
    return read(spark, sf, "lineitem").withColumn("m", F.month("l_shipdate")).cube("l_returnflag", "m").agg(F.count_if(F.col("l_linestatus") == "O").alias("heads"), F.count("*").alias("n"))


@query("SELECT l_returnflag, l_linestatus, CAST(grouping_id(l_returnflag, l_linestatus) AS BIGINT) AS g, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def coin_grouping_sets(spark, sf):
    return spark.sql("SELECT l_returnflag, l_linestatus, grouping_id() AS g, count(*) AS n FROM {l} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())", l=read(spark, sf, "lineitem"))


@query(r"SELECT word, CAST(count(*) FILTER (role = 'assistant') AS BIGINT) AS assistant, CAST(count(*) FILTER (role = 'system') AS BIGINT) AS system, CAST(count(*) FILTER (role = 'user') AS BIGINT) AS user FROM (SELECT role, unnest(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')) AS word FROM conversations) GROUP BY word")
def pivot_role_words(spark, sf):
    roles = ["assistant", "system", "user"]
    return T.words(read(spark, sf, "conversations"), ["role"]).groupBy("word").pivot("role", roles).count().na.fill(0, roles)


@query("SELECT user_id, round(m + ln(sum(exp(v - m))), 6) + 0e0 AS lse FROM (SELECT user_id, value / 1e2 AS v, max(value / 1e2) OVER (PARTITION BY user_id) AS m FROM events) GROUP BY user_id, m")
def logsumexp_agg(spark, sf):
    rows = read(spark, sf, "events").select("user_id", (F.col("value") / 1e2).alias("v"))
    top = rows.groupBy("user_id").agg(F.max("v").alias("m"))
    return rows.join(top, "user_id").groupBy("user_id", "m").agg(F.sum(F.exp(F.col("v") - F.col("m"))).alias("z")).select("user_id", rounded(F.col("m") + F.log("z")).alias("lse"))


@query(f"SELECT round(quantile_cont(n, 5e-1), 6) AS median, round(quantile_cont(n, 9e-1), 6) AS p90, round(quantile_cont(n, 99e-2), 6) AS p99, CAST(max(n) AS BIGINT) AS longest FROM (SELECT sum(n) AS n FROM ({WEIGHTS}) GROUP BY doc_id)")
def doc_length_quantiles(spark, sf):
    rows = weights(spark, sf).groupBy("doc_id").agg(F.sum("n").alias("n"))
    return rows.agg(F.round(F.percentile("n", 0.5), 6).alias("median"), F.round(F.percentile("n", 0.9), 6).alias("p90"), F.round(F.percentile("n", 0.99), 6).alias("p99"), F.max("n").alias("longest"))


@query(f"SELECT lang, word, n, CAST(row_number() OVER (PARTITION BY lang ORDER BY n DESC, word) AS INTEGER) AS place FROM (SELECT lang, word, CAST(sum(n) AS BIGINT) AS n FROM ({WEIGHTS}) JOIN (SELECT doc_id, lang FROM documents) USING (doc_id) GROUP BY ALL) QUALIFY place <= 10")
def top_words_per_topic(spark, sf):
    langs = read(spark, sf, "documents").select("doc_id", "lang")
    rows = weights(spark, sf).join(langs, "doc_id").groupBy("lang", "word").agg(F.sum("n").alias("n"))
    return rows.withColumn("place", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "word"))).filter("place <= 10")


@query(f"SELECT event_type, user_id, CAST(rank() OVER w AS INTEGER) AS r, CAST(dense_rank() OVER w AS INTEGER) AS dr, CAST(ntile(4) OVER x AS INTEGER) AS quarter, round(percent_rank() OVER w, 9) AS pr FROM ({COUNTS}) WINDOW w AS (PARTITION BY event_type ORDER BY n DESC), x AS (PARTITION BY event_type ORDER BY n DESC, user_id)")
def topic_rank_dense(spark, sf):
    w = Window.partitionBy("event_type").orderBy(F.desc("n"))
    x = w.orderBy(F.desc("n"), "user_id")
    return counts(spark, sf).select("event_type", "user_id", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(x).alias("quarter"), F.round(F.percent_rank().over(w), 9).alias("pr"))


@query("SELECT event_id, 1 + CAST(sum(CASE WHEN event_type = 'error' THEN 1 ELSE 0 END) OVER w AS BIGINT) AS a, 1 + CAST(sum(CASE WHEN event_type = 'error' THEN 0 ELSE 1 END) OVER w AS BIGINT) AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING)")
def running_coin_posterior(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    head = (F.col("event_type") == "error").cast("long")
    return read(spark, sf, "events").select("event_id", (1 + F.sum(head).over(w)).alias("a"), (1 + F.sum(1 - head).over(w)).alias("b"))


@query("SELECT event_id, round(avg(CASE WHEN event_type = 'error' THEN 1e0 ELSE 0e0 END) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW), 9) + 0e0 AS rate FROM events")
def sliding_coin_rate(spark, sf):
    e = read(spark, sf, "events").withColumn("sec", F.unix_timestamp(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("user_id").orderBy("sec").rangeBetween(-86400, 0)
    return e.select("event_id", rounded(F.avg((F.col("event_type") == "error").cast("double")).over(w), 9).alias("rate"))


@query("SELECT user_id, first_event, last_event, third FROM (SELECT user_id, first_value(event_id) OVER w AS first_event, last_value(event_id) OVER w AS last_event, nth_value(event_id, 3) OVER w AS third, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)) WHERE p = 1")
def first_last_event(spark, sf):
    at = F.struct("ts", "event_id")
    rows = read(spark, sf, "events").groupBy("user_id").agg(F.min(at).alias("a"), F.max(at).alias("b"), F.array_sort(F.collect_list(at)).alias("c"))
    return rows.select("user_id", F.col("a.event_id").alias("first_event"), F.col("b.event_id").alias("last_event"), F.get("c", F.lit(2))["event_id"].alias("third"))


@query(f"SELECT doc_id, share FROM (SELECT doc_id, round(max(n) * 1e0 / sum(n), 9) + 0e0 AS share FROM ({WEIGHTS}) GROUP BY doc_id) ORDER BY share DESC, doc_id LIMIT 20")
def topk_docs_for_topic(spark, sf):
    rows = weights(spark, sf).groupBy("doc_id").agg(rounded(F.max("n") * 1.0 / F.sum("n"), 9).alias("share"))
    return rows.orderBy(F.desc("share"), "doc_id").limit(20)


@query("SELECT o_orderkey, row_number() OVER (ORDER BY o_orderdate, o_orderkey) - 1 AS idx FROM orders")
def dense_index_sorted(spark, sf):
    return T.dense_index(read(spark, sf, "orders").select("o_orderkey", "o_orderdate"), ["o_orderdate", "o_orderkey"]).select("o_orderkey", "idx")


@query("SELECT 'x' AS rv, event_id AS vid FROM events UNION ALL SELECT 'z', event_id + 1000000 FROM events UNION ALL SELECT 'theta', user_id + 2000000 FROM (SELECT DISTINCT user_id FROM events)")
def vertices_union(spark, sf):
    e = read(spark, sf, "events")
    x = e.select(F.lit("x").alias("rv"), F.col("event_id").alias("vid"))
    z = e.select((F.col("event_id") + 1000000).alias("vid"), F.lit("z").alias("rv"))
    return x.unionByName(z).unionByName(e.select("user_id").distinct().select(F.lit("theta").alias("rv"), (F.col("user_id") + 2000000).alias("vid")))


HELD = r"SELECT unnest(regexp_extract_all(lower(text), '[\p{L}\p{N}]+')) AS word FROM benchmark"


@query(f"SELECT word FROM ({HELD}) INTERSECT SELECT word FROM ({WEIGHTS})")
def vocab_intersect(spark, sf):
    return T.words(read(spark, sf, "benchmark"), []).intersect(weights(spark, sf).select("word"))


@query(f"SELECT word FROM ({HELD}) EXCEPT SELECT word FROM ({VOCAB5})")
def vocab_except(spark, sf):
    common = weights(spark, sf).groupBy("word").count().filter("count >= 5").select("word")
    return T.words(read(spark, sf, "benchmark"), []).subtract(common)


@query("SELECT user_id AS src, 100000 + value AS dst FROM (SELECT user_id, CAST(floor(value) AS BIGINT) AS value FROM events) UNION SELECT 100000 + value, user_id FROM (SELECT user_id, CAST(floor(value) AS BIGINT) AS value FROM events)")
def union_distinct_edges(spark, sf):
    e = read(spark, sf, "events").select("user_id", (100000 + F.floor("value")).alias("v"))
    return e.select(F.col("user_id").alias("src"), F.col("v").alias("dst")).union(e.select("v", "user_id")).distinct()
