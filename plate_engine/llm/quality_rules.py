"""Quality rules whose cutoffs carry a risk guarantee; DataFrame functions only.

Each rule rejects a text when ``1000 * part > cutoff * whole`` for two whole numbers measured on it.  ``LADDER`` names
joint vectors of cutoffs, one cutoff a rule, from the loosest to the strictest, so a text that is rejected at a rung
is rejected at all later ones.  The rung comes from a labelled holdout: in every stratum (language) the ladder is walked
from its loosest rung; a rung is certified while the exact binomial test rejects "its rules together turn away more
than ``risk`` of the good documents" at the stratum's level, and the walk ends at the first that isn't (fixed-sequence
testing).  The levels are shares of ``delta`` in proportion to the strata's good documents (weighted Bonferroni; these numbers
don't depend on what is rejected).  So with probability ``1 - delta`` no stratum loses more than ``risk`` of its good
documents to all rules together; some 170 to 220 good documents without a false rejection certify a rung.
Among certified rungs the one with most bad less good rejections is used, the loosest of equals.

Defined cases: a null text has no words and fails the base rule; a null language is the stratum of the
empty string; repeated rows are judged each, but one text counts once in a stratum's holdout (bad if any
copy is); a stratum with too few good documents gets no rung and rejects by the base rule alone; an empty table gives no rows; no columns of
``docs`` but the id, text and language are read, and names that clash with measures do no harm.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import stored

WORD_GAP = r"[\x20\x09-\x0D]+"
WINDOW = 5
#: Rule: its part and its whole.
RULES = {"symbols": ("n_symbols", "word_chars"), "repeats": ("n_repeat_words", "n_words"), "lines": ("n_dup_lines", "n_lines"), "capitals": ("n_capitals", "word_chars")}
#: Cutoffs in thousandths of each rule at every rung, loosest first.
LADDER = {
    "symbols": (900, 700, 500, 300, 200, 150, 100, 80, 60, 40, 20, 10),
    "repeats": (900, 800, 600, 500, 400, 350, 300, 250, 200, 180, 160, 140),
    "lines": (900, 800, 700, 600, 500, 400, 350, 300, 250, 220, 200, 180),
    "capitals": (900, 800, 700, 600, 500, 400, 300, 250, 200, 180, 150, 120),
}
RUNGS = 12
RISK, DELTA = 0.02, 0.05


def _let(value: Column, body) -> Column:
    """``body(value)`` with the value evaluated once, as the one element of a transformed array."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _window_hashes(words: Column) -> Column:
    """64-bit hashes of all runs of five words."""

    def hashes(w: Column) -> Column:
        return F.transform(F.sequence(F.lit(0), F.size(w) - WINDOW), lambda i: F.xxhash64(*[F.get(w, i + k) for k in range(WINDOW)]))

    return _let(words, lambda w: F.when(F.size(w) >= WINDOW, hashes(w)).otherwise(F.array().cast("array<bigint>")))


def _covered(hashes: Column) -> Column:
    """Words inside windows whose hash occurs twice or more: sort, keep equal neighbours, sum the steps."""

    def repeated(s: Column) -> Column:
        def has_equal(x: Column, k: Column) -> Column:
            before = F.get(s, F.when(k > 0, k - 1))["h"] == x["h"]
            return F.coalesce(before, F.lit(False)) | F.coalesce(F.get(s, k + 1)["h"] == x["h"], F.lit(False))

        return F.array_sort(F.transform(F.filter(s, has_equal), lambda x: x["i"]))

    def steps(p: Column) -> Column:
        inner = F.when(F.size(p) > 1, F.sequence(F.lit(1), F.size(p) - 1)).otherwise(F.array().cast("array<int>"))
        return F.aggregate(inner, F.lit(WINDOW).cast("long"), lambda n, k: n + F.least(F.lit(WINDOW), F.get(p, k) - F.get(p, k - 1)))

    ordered = F.array_sort(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    return F.when(F.size(F.array_distinct(hashes)) == F.size(hashes), F.lit(0).cast("long")).otherwise(_let(ordered, lambda s: _let(repeated(s), steps)))


def measured(docs: DataFrame, text: str = "text", lang: str = "lang") -> DataFrame:
    """``row`` (all columns of ``docs``) beside the measures, base verdict, stratum and text digest."""
    t = F.col("t")
    worded = F.filter(F.split(t, "\n"), lambda line: line.rlike(r"[^\x20\x09-\x0D]"))
    step = docs.select(F.struct("*").alias("row"), F.coalesce(F.col(text), F.lit("")).alias("t"), F.coalesce(F.col(lang), F.lit("")).alias("stratum"))
    step = step.withColumns({"w": F.array_remove(F.split(t, WORD_GAP), ""), "l": worded})
    step = step.withColumns({"h": _window_hashes(F.col("w"))})
    size = lambda c: c.cast("long")
    step = step.select(
        "row",
        "stratum",
        F.md5(t.cast("binary")).alias("digest"),
        size(F.size("w")).alias("n_words"),
        size(F.length(F.array_join("w", ""))).alias("word_chars"),
        size(F.length(t) - F.length(F.regexp_replace(t, r"[#*$%&|<>]+", ""))).alias("n_symbols"),
        size(F.size("l")).alias("n_lines"),
        size(F.size("l") - F.size(F.array_distinct("l"))).alias("n_dup_lines"),
        size(F.length(t) - F.length(F.regexp_replace(t, r"[A-Z]+", ""))).alias("n_capitals"),
        _covered(F.col("h")).alias("n_repeat_words"),
    )
    return step.withColumn("base_failed", (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words")))


def binomial_cdf(n: Column, k: Column, p: float) -> Column:
    """P(Bin(n, p) <= k) exactly, for 0 <= k <= n*p: terms grow up to k, so they are summed relative to the last."""
    odds = math.log(p) - math.log1p(-p)
    start = F.struct((n * math.log1p(-p)).alias("term"), F.lit(1.0).alias("total"))

    def add(acc: Column, j: Column) -> Column:
        step = F.log((n - j + 1) / j) + odds
        return F.struct((acc["term"] + step).alias("term"), (acc["total"] * F.exp(-step) + 1.0).alias("total"))

    js = F.when(k >= 1, F.sequence(F.lit(1).cast("long"), k)).otherwise(F.array().cast("array<bigint>"))
    return F.aggregate(js, start, add, lambda acc: acc["total"] * F.exp(acc["term"]))


def first_rung() -> Column:
    """The loosest rung (from 1) at which a row of measures is rejected, RUNGS + 1 if none."""

    def of(rule: str) -> Column:
        part, whole = RULES[rule]
        over = F.transform(F.array(*map(F.lit, LADDER[rule])), lambda c: 1000 * F.col(part) > c * F.col(whole))
        return F.coalesce(F.nullif(F.array_position(over, True), F.lit(0)), F.lit(RUNGS + 1))

    return F.least(*[of(rule) for rule in RULES])


def certified_rungs(holdout: DataFrame, risk: float = RISK, delta: float = DELTA) -> DataFrame:
    """``stratum, rung, n_good, wrong, caught`` from rows of measures and ``good`` (boolean), for strata with a rung."""
    strata = holdout.groupBy("stratum").agg(F.count_if("good").alias("n_good"))
    # A row a stratum; the window sees no other rows.
    strata = strata.withColumn("level", delta * F.col("n_good") / F.greatest(F.sum("n_good").over(Window.partitionBy()), F.lit(1)))
    first = holdout.select("stratum", "good", first_rung().alias("first")).filter(F.col("first") <= RUNGS)
    hits = first.select("stratum", "good", F.explode(F.sequence("first", F.lit(RUNGS).cast("long"))).alias("rung")).groupBy("stratum", "rung").agg(F.count_if("good").alias("wrong"), F.count_if(~F.col("good")).alias("caught"))
    rungs = strata.select("*", F.explode(F.sequence(F.lit(1).cast("long"), F.lit(RUNGS).cast("long"))).alias("rung"))
    tested = rungs.join(hits, ["stratum", "rung"], "left").na.fill(0, ["wrong", "caught"])
    p_value = F.when(F.col("wrong") > F.col("n_good") * risk, 1.0).otherwise(binomial_cdf(F.col("n_good"), F.col("wrong"), risk))
    walked = tested.withColumn("passed", p_value <= F.col("level")).groupBy("stratum").agg(F.min(F.when(~F.col("passed"), F.col("rung"))).alias("failed"), F.collect_list(F.struct((F.col("caught") - F.col("wrong")).alias("gain"), (-F.col("rung")).alias("loose"), "n_good", "wrong", "caught")).alias("rows"))
    best = F.array_max(F.filter("rows", lambda x: F.col("failed").isNull() | (-x["loose"] < F.col("failed"))))
    return walked.select("stratum", best.alias("b")).filter("b is not null").select("stratum", (-F.col("b.loose")).alias("rung"), "b.n_good", "b.wrong", "b.caught")


def judged(rows: DataFrame, marks: DataFrame, risk: float = RISK, delta: float = DELTA, key: str = "doc_id", good: str = "quality") -> DataFrame:
    """``rows`` of :func:`measured` with ``kept`` and the first rule (by name) that rejected."""
    marks = marks.select(F.col(key).alias("k"), F.col(good).alias("g")).filter("k is not null and g is not null").groupBy("k").agg(F.min("g").alias("g"))
    labelled = rows.filter(~F.col("base_failed")).join(marks, F.col(f"row.{key}") == F.col("k"))
    measures = sorted({m for pair in RULES.values() for m in pair})
    holdout = labelled.groupBy("stratum", "digest").agg((F.min("g") > 0).alias("good"), *[F.first(m).alias(m) for m in measures])
    rungs = certified_rungs(holdout, risk, delta).select("stratum", F.col("rung").cast("int"))
    found = rows.join(rungs, "stratum", "left")
    at = {rule: F.get(F.array(*map(F.lit, LADDER[rule])), F.col("rung") - 1) for rule in RULES}
    broken = F.array_sort(F.filter(F.array(*[F.when(1000 * F.col(p) > at[r] * F.col(w), F.lit(r)) for r, (p, w) in RULES.items()]), lambda x: x.isNotNull()))
    found = found.withColumn("broken", F.get(broken, F.lit(0)))
    return found.withColumn("kept", ~F.col("base_failed") & F.col("broken").isNull())


def verdicts(docs: DataFrame, marks: DataFrame) -> DataFrame:
    """One row a document: its measures, the base verdict, and whether it is kept."""
    rows = measured(docs.select("doc_id", "text", "lang")).withColumn("row", F.struct("row.doc_id"))
    out = judged(stored(rows, "quality-measures"), marks)
    return out.select("row.doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "stratum", F.when(F.col("base_failed"), "base").otherwise(F.col("broken")).alias("rejected_by"))


def keep_good(docs: DataFrame, marks: DataFrame) -> DataFrame:
    """The rows of ``docs`` that the rules keep, with its columns."""
    return judged(stored(measured(docs), "quality-rows"), marks).filter("kept").select("row.*")
