"""SQL, for DuckDB, of the queries of this package that SQL can express beyond those that state it beside their operator."""

from __future__ import annotations

from .quality import DELTA, MEASURES, RISK, SYMBOLS
from .substring import MIN_WORDS, SENTENCE_RE

WORDS = "regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')"


def ngram_join() -> str:
    """All pairs of different sets by a join on n-grams; classes by closure."""
    return f"""
WITH RECURSIVE w AS MATERIALIZED (SELECT doc_id, {WORDS} AS w FROM documents),
sets AS MATERIALIZED (SELECT doc_id, list_sort(list_distinct(list_transform(range(1, greatest(len(w) - 3, 2)), lambda i: array_to_string(w[i:i + 4], ' ')))) AS s FROM w WHERE len(w) > 0),
classes AS MATERIALIZED (SELECT min(doc_id) AS id, count(*) AS n, s, len(s) AS z FROM sets GROUP BY s),
grams AS MATERIALIZED (SELECT id, n, z, unnest(s) AS g FROM classes),
pairs AS MATERIALIZED (SELECT a.id AS a, b.id AS b, any_value(b.n) AS n FROM grams a JOIN grams b ON a.g = b.g AND a.id <> b.id GROUP BY a.id, b.id HAVING 5 * count(*) >= 4 * (any_value(a.z) + any_value(b.z) - count(*))),
reach AS (SELECT id, id AS r FROM classes UNION SELECT p.a, reach.r FROM reach JOIN pairs p ON p.b = reach.id),
tops AS (SELECT id, min(r) AS class_id FROM reach GROUP BY id), links AS (SELECT a AS id, sum(n) AS l FROM pairs GROUP BY a),
named AS (SELECT s, c.id, n, class_id, coalesce(l, 0) + n - 1 AS n_links FROM classes c JOIN tops USING (id) LEFT JOIN links USING (id))
SELECT d.doc_id, coalesce(named.id, d.doc_id) AS copy_of, coalesce(n, 1)::BIGINT AS n_copies, coalesce(class_id, d.doc_id) AS class_id, coalesce(n_links, 0)::BIGINT AS n_links
FROM documents d LEFT JOIN sets USING (doc_id) LEFT JOIN named USING (s)"""


def quality() -> str:
    """Measures, certified cutoffs and verdicts."""
    ratio = {"symbol": "1000 * n_symbols // nullif(word_chars, 0)", "repeat": "1000 * n_repeat_words // nullif(n_words, 0)", "dupline": "1000 * n_dup_lines // nullif(n_lines, 0)", "wordlen": "10 * word_chars // nullif(n_words, 0)"}
    cells = " UNION ALL ".join(f"SELECT stratum, quality, '{m}' AS measure, ceil(coalesce({ratio[m]}, 0) / {step}.0)::BIGINT AS cell, {step} AS step FROM held" for m, step in MEASURES.items())
    over = " OR ".join(f"coalesce(coalesce({ratio[m]}, 0) > (SELECT cut FROM best WHERE best.stratum IS NOT DISTINCT FROM f.stratum AND measure = '{m}'), false)" for m in MEASURES)
    rate = RISK / len(MEASURES)
    return f"""
WITH w AS MATERIALIZED (SELECT doc_id, lang AS stratum, coalesce(text, '') AS text, {WORDS} AS w, list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS lines FROM documents),
wins AS (SELECT doc_id, i, array_to_string(w[i:i + 4], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM w)),
twice AS (SELECT doc_id, unnest(range(i, i + 5)) AS p FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, g) AS c FROM wins) WHERE c > 1),
rep AS (SELECT doc_id, count(DISTINCT p) AS n FROM twice GROUP BY doc_id),
m AS MATERIALIZED (SELECT doc_id, stratum, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars, (length(text) - length(translate(text, '{SYMBOLS}', '')))::BIGINT AS n_symbols, (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines, coalesce(rep.n, 0)::BIGINT AS n_repeat_words, len(lines)::BIGINT AS n_lines FROM w LEFT JOIN rep USING (doc_id)),
f AS MATERIALIZED (SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM m),
marks AS (SELECT doc_id, max(quality) AS quality FROM labels WHERE quality IS NOT NULL GROUP BY doc_id),
held AS MATERIALIZED (SELECT * FROM f JOIN marks USING (doc_id) WHERE NOT base_failed),
counts AS (SELECT stratum, measure, step, cell, count(*) FILTER (quality = 1) AS g, count(*) FILTER (quality IS DISTINCT FROM 1) AS b FROM ({cells}) GROUP BY ALL),
sums AS MATERIALIZED (SELECT *, sum(g) OVER (PARTITION BY stratum, measure) AS ng, sum(b) OVER (PARTITION BY stratum, measure) AS nb, coalesce(sum(g) OVER a, 0) AS kg, coalesce(sum(b) OVER a, 0) AS kb FROM counts WINDOW a AS (PARTITION BY stratum, measure ORDER BY cell DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
tails AS (SELECT *, kb * ng - kg * nb AS gain, CASE WHEN kg >= ng * {rate} THEN 1.0 ELSE list_sum(list_transform(range(0, kg::BIGINT + 1), lambda j: exp(lgamma(ng + 1.0) - lgamma(j + 1.0) - lgamma(ng - j + 1.0) + j * ln({rate}) + (ng - j) * ln(1 - {rate})))) END AS p FROM sums),
best AS MATERIALIZED (SELECT stratum, measure, cell * step AS cut FROM tails WHERE gain > 0 AND p <= {DELTA} / ({len(MEASURES)} * (SELECT count(*) FROM (SELECT DISTINCT stratum FROM f))) QUALIFY row_number() OVER (PARTITION BY stratum, measure ORDER BY gain DESC, cell DESC) = 1)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT (base_failed OR {over}) AS kept FROM f"""


def substring() -> str:
    """Runs of two sentences or more as texts, and what stays without their later places."""
    k = MIN_WORDS - 1
    return f"""
WITH parts AS MATERIALIZED (SELECT doc_id, i - 1 AS i, s FROM (SELECT doc_id, unnest(p) AS s, generate_subscripts(p, 1) AS i FROM (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '{SENTENCE_RE}') AS p FROM documents))),
texts AS (SELECT doc_id, i, regexp_extract_all(s, '[^\\x20\\x09-\\x0D]+') AS w FROM parts),
said AS MATERIALIZED (SELECT doc_id, i, len(w) AS n, array_to_string(w, ' ') AS t, coalesce(sum(len(w)) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS o FROM texts WHERE len(w) > 0),
ahead AS (SELECT doc_id, i, greatest(o + {k}, o + n) AS p FROM said),
back AS (SELECT doc_id, i, least(o + n - 1 - {k}, o - 1) AS p FROM said),
spans AS (SELECT a.doc_id, a.i AS first, b.i AS last FROM ahead a JOIN said b ON a.doc_id = b.doc_id AND b.o <= p AND p < b.o + b.n
    UNION SELECT a.doc_id, b.i, a.i FROM back a JOIN said b ON a.doc_id = b.doc_id AND b.o <= p AND p < b.o + b.n),
places AS MATERIALIZED (SELECT s.doc_id, first, last, string_agg(t, ' ' ORDER BY i) AS t FROM spans s JOIN said x ON x.doc_id = s.doc_id AND x.i BETWEEN first AND last GROUP BY s.doc_id, first, last),
ranked AS (SELECT doc_id, first, last, row_number() OVER (PARTITION BY t ORDER BY doc_id, first) AS rn FROM places),
gone AS MATERIALIZED (SELECT DISTINCT doc_id, unnest(range(first, last + 1)) AS i FROM ranked WHERE rn > 1),
left_over AS (SELECT p.doc_id, count(*) AS n, count(g.i) AS r, string_agg(s, '' ORDER BY p.i) FILTER (g.i IS NULL) AS t FROM parts p LEFT JOIN gone g ON g.doc_id = p.doc_id AND g.i = p.i GROUP BY p.doc_id)
SELECT d.doc_id, coalesce(n, 0)::BIGINT AS n_sentences, coalesce(r, 0)::BIGINT AS n_removed, CASE WHEN d.text IS NULL THEN NULL ELSE coalesce(t, '') END AS text FROM documents d LEFT JOIN left_over l ON l.doc_id = d.doc_id"""
