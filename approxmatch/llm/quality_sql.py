"""The quality rules and their certified cutoffs in DuckDB SQL."""

from __future__ import annotations

from . import quality

WORD = r"[^\x20\x09-\x0D]"


def sql() -> str:
    rate = quality.RISK / len(quality.GRIDS)
    grid = ", ".join(f"('{rule}', {k}, {cutoff}::DOUBLE)" for rule, g in quality.GRIDS.items() for k, cutoff in enumerate(g))
    ratios = {"symbols": ("n_symbols", "word_chars"), "dup_lines": ("n_dup_lines", "n_lines"), "repeats": ("n_repeat_words", "n_words"), "word_length": ("word_chars", "n_words")}
    long = " UNION ALL ".join(f"SELECT doc_id, stratum, base_failed, '{rule}' AS rule, {a} / greatest({b}, 1)::DOUBLE AS x FROM f" for rule, (a, b) in ratios.items())
    return rf"""
WITH t AS (SELECT doc_id, lang AS stratum, coalesce(text, '') AS text FROM documents),
w AS (SELECT doc_id, stratum, text, regexp_extract_all(text, '{WORD}+') AS w FROM t),
win AS (SELECT doc_id, i, array_to_string(w[i:i+7], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM w)),
rep AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS n FROM win) WHERE n > 1),
cov AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(range(i, i + 8)) AS p FROM rep) GROUP BY doc_id),
lines AS (SELECT doc_id, count(*) AS n, count(*) - count(DISTINCT line) AS twice
          FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM t) WHERE regexp_matches(line, '{WORD}') GROUP BY doc_id),
f0 AS (SELECT w.doc_id, stratum, len(w.w)::BIGINT AS n_words, length(regexp_replace(text, '[\x20\x09-\x0D]+', '', 'g'))::BIGINT AS word_chars,
              (length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
              coalesce(lines.twice, 0)::BIGINT AS n_dup_lines, coalesce(cov.n, 0)::BIGINT AS n_repeat_words, coalesce(lines.n, 0)::BIGINT AS n_lines
       FROM w LEFT JOIN cov ON cov.doc_id = w.doc_id LEFT JOIN lines ON lines.doc_id = w.doc_id),
f AS (SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM f0),
r AS ({long}),
grid(rule, place, cutoff) AS (VALUES {grid}),
cal AS (SELECT stratum, r.rule AS rule, place, cutoff, count(*) FILTER (quality > 0) AS n, count(*) FILTER (quality > 0 AND x > cutoff) AS k, count(*) FILTER (quality <= 0 AND x > cutoff) AS b
        FROM r JOIN labels l ON l.doc_id = r.doc_id JOIN grid ON grid.rule = r.rule WHERE NOT base_failed AND quality IS NOT NULL GROUP BY stratum, r.rule, place, cutoff),
seq AS (SELECT count(*) AS sequences FROM (SELECT DISTINCT stratum, rule FROM cal)),
p AS (SELECT *, CASE WHEN k < n * {rate}::DOUBLE THEN least(1.0::DOUBLE, list_sum(list_transform(range(0, k + 1),
        lambda i: exp(lgamma(n + 1) - lgamma(i + 1) - lgamma(n - i + 1) + i * ln({rate}::DOUBLE) + (n - i) * ln(1 - {rate}::DOUBLE))))) ELSE 1 END AS p FROM cal),
c AS (SELECT *, max(p) OVER (PARTITION BY stratum, rule ORDER BY place) <= {quality.ERROR}::DOUBLE / sequences AS certified, b - {quality.PRICE} * k AS gain FROM p CROSS JOIN seq),
used AS (SELECT stratum, rule, cutoff FROM (SELECT *, row_number() OVER (PARTITION BY stratum, rule ORDER BY gain DESC, place) AS turn FROM c WHERE certified AND gain > 0) WHERE turn = 1),
hit AS (SELECT doc_id, list_sort(list(r.rule)) AS rules FROM r JOIN used ON used.rule = r.rule AND used.stratum IS NOT DISTINCT FROM r.stratum WHERE x > cutoff GROUP BY doc_id)
SELECT f.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND rules IS NULL AS kept, array_to_string(coalesce(rules, []), ',') AS rejected_by
FROM f LEFT JOIN hit ON hit.doc_id = f.doc_id
"""
