"""The quality rules in DuckDB SQL, built from the operator's parameters."""

from __future__ import annotations

from .quality_rules import DELTA, LADDER, RISK, RULES, RUNGS


def quality_ctes(docs: str = "documents") -> str:
    ladder = ", ".join(str((k + 1, *[LADDER[r][k] for r in RULES])) for k in range(RUNGS))
    over = {r: f"1000 * {p} > l.{r} * {w}" for r, (p, w) in RULES.items()}
    broken = ", ".join(f"CASE WHEN {test} THEN '{r}' END" for r, test in over.items())
    return rf"""
texts AS (SELECT doc_id, coalesce(text, '') AS t, coalesce(lang, '') AS stratum FROM {docs}),
cut AS (SELECT *, list_filter(regexp_split_to_array(t, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w,
  list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM texts),
places AS (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM cut WHERE len(w) >= 5),
runs AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, w[i:i+4]) AS n FROM places),
steps AS (SELECT doc_id, least(5, coalesce(lead(i) OVER (PARTITION BY doc_id ORDER BY i) - i, 5)) AS step FROM runs WHERE n > 1),
repeats AS (SELECT doc_id, CAST(sum(step) AS BIGINT) AS n FROM steps GROUP BY doc_id),
measures AS (SELECT c.doc_id, c.stratum, md5(c.t) AS digest, len(w) AS n_words, length(array_to_string(w, '')) AS word_chars,
  length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS n_symbols, len(l) AS n_lines,
  len(l) - len(list_distinct(l)) AS n_dup_lines, length(t) - length(regexp_replace(t, '[A-Z]', '', 'g')) AS n_capitals,
  coalesce(r.n, 0) AS n_repeat_words FROM cut c LEFT JOIN repeats r USING (doc_id)),
based AS (SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM measures),
marks AS (SELECT doc_id, min(quality) AS g FROM labels WHERE doc_id IS NOT NULL AND quality IS NOT NULL GROUP BY doc_id),
holdout AS (SELECT stratum, digest, min(g) > 0 AS good, any_value(n_symbols) AS n_symbols, any_value(word_chars) AS word_chars,
  any_value(n_repeat_words) AS n_repeat_words, any_value(n_words) AS n_words, any_value(n_dup_lines) AS n_dup_lines,
  any_value(n_lines) AS n_lines, any_value(n_capitals) AS n_capitals
  FROM based JOIN marks USING (doc_id) WHERE NOT base_failed GROUP BY stratum, digest),
strata AS (SELECT stratum, count(*) FILTER (good) AS n_good FROM holdout GROUP BY stratum),
ladder(rung, {", ".join(RULES)}) AS (VALUES {ladder}),
hits AS (SELECT stratum, rung, count(*) FILTER (good) AS wrong, count(*) FILTER (NOT good) AS caught
  FROM holdout, ladder l WHERE {" OR ".join(over.values())} GROUP BY ALL),
tested AS (SELECT s.stratum, l.rung, s.n_good, coalesce(h.wrong, 0) AS wrong, coalesce(h.caught, 0) AS caught
  FROM strata s CROSS JOIN ladder l LEFT JOIN hits h ON h.stratum = s.stratum AND h.rung = l.rung),
valued AS (SELECT *, CASE WHEN wrong > n_good * {RISK!r}::DOUBLE THEN 1e0 ELSE list_sum(list_transform(range(0, wrong + 1),
  lambda j: exp(lgamma(n_good + 1) - lgamma(j + 1) - lgamma(n_good - j + 1) + j * ln({RISK!r}::DOUBLE) + (n_good - j) * ln(1 - {RISK!r}::DOUBLE)))) END AS p FROM tested),
walked AS (SELECT *, min(CASE WHEN p > {DELTA!r}::DOUBLE * n_good / (SELECT greatest(sum(n_good), 1) FROM strata) THEN rung END) OVER (PARTITION BY stratum) AS failed FROM valued),
chosen AS (SELECT stratum, rung FROM walked WHERE failed IS NULL OR rung < failed
  QUALIFY row_number() OVER (PARTITION BY stratum ORDER BY caught - wrong DESC, rung) = 1),
judged AS (SELECT b.*, least({broken}) AS broken FROM based b LEFT JOIN chosen c USING (stratum) LEFT JOIN ladder l USING (rung))"""


OP1_SQL = f"""WITH {quality_ctes()}
SELECT doc_id, CAST(n_words AS BIGINT) AS n_words, CAST(word_chars AS BIGINT) AS word_chars, CAST(n_symbols AS BIGINT) AS n_symbols,
  CAST(n_dup_lines AS BIGINT) AS n_dup_lines, CAST(n_repeat_words AS BIGINT) AS n_repeat_words, base_failed,
  NOT base_failed AND broken IS NULL AS kept, stratum, CASE WHEN base_failed THEN 'base' ELSE broken END AS rejected_by FROM judged"""
