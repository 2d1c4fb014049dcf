"""DuckDB SQL for queries of this subpackage that SQL can express on whole tables."""

from __future__ import annotations

import string

_LOWERED = f"translate(coalesce(text, ''), '{string.ascii_uppercase}', '{string.ascii_lowercase}')"

#: Distinct shingles, all pairs that share one with their counts, and the smallest id that links reach.
OP9_SQL = rf"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all({_LOWERED}, '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN []::VARCHAR[] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
         ELSE list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) END AS g FROM d),
e AS (SELECT doc_id, len(g)::BIGINT AS n, unnest(g) AS x FROM s),
c AS (SELECT a.doc_id AS a, b.doc_id AS b, a.n AS na, b.n AS nb, count(*) AS shared FROM e a JOIN e b ON a.x = b.x AND a.doc_id < b.doc_id GROUP BY ALL),
l AS (SELECT a, b FROM c WHERE 100 * shared >= 80 * (na + nb - shared)),
u AS (SELECT a, b FROM l UNION SELECT b, a FROM l),
r(doc_id, x) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.doc_id, u.b FROM r JOIN u ON u.a = r.x)
SELECT s.doc_id, len(s.g)::BIGINT AS n_shingles, m.component_id FROM s JOIN (SELECT doc_id, min(x) AS component_id FROM r GROUP BY doc_id) m USING (doc_id)
"""

#: Every window of every item against every run of as many words of every document.
OP8_SQL = rf"""
WITH d AS (SELECT doc_id, regexp_extract_all({_LOWERED}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all({_LOWERED}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
t AS (
  SELECT DISTINCT item_id, least(len(w), 13) AS n, array_to_string(w[p:p + 12], ' ') AS x
  FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 12, 1) + 1)) AS p FROM b WHERE len(w) > 0)),
h AS (
  SELECT doc_id, item_id, p, q.n FROM (
    SELECT doc_id, n, p, array_to_string(w[p:p + n - 1], ' ') AS x FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS p FROM d, (SELECT DISTINCT n FROM t) WHERE len(w) >= n)) q
  JOIN t ON t.n = q.n AND t.x = q.x),
m AS (SELECT doc_id, count(DISTINCT place) AS n_hit FROM (SELECT doc_id, unnest(range(p, p + n)) AS place FROM h) GROUP BY doc_id),
i AS (SELECT doc_id, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS listed FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS item_id FROM h WHERE item_id IS NOT NULL) GROUP BY doc_id)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(m.n_hit, 0)::BIGINT AS n_hit, coalesce(i.n_items, 0)::BIGINT AS n_items, sha256(coalesce(i.listed, '')) AS items_sha256,
       coalesce(m.n_hit, 0) > 0 AND 20 * coalesce(m.n_hit, 0) >= len(d.w) AS contaminated
FROM d LEFT JOIN m USING (doc_id) LEFT JOIN i USING (doc_id)
"""


def _licenses() -> str:
    """The template table of the licence scan: label, words, key phrase, the phrase's length and place, whether licence words must be counted, and the places of those."""
    from facetgraph.llm import licenses

    known, rows = set(licenses.vocabulary()), []
    for label, template, key in licenses.TEMPLATES:
        words, phrase = template.split(), key.split()
        marks = [j + 1 for j, w in enumerate(words) if w in known]
        rows.append(f"('{label}', string_split('{template}', ' '), '{key}', {len(phrase)}, {licenses.phrase_offset(words, phrase)}, {str(sum(w in known for w in phrase) < licenses.AGREE).lower()}, {marks})")
    return "VALUES " + ", ".join(rows)


def op7_sql() -> str:
    """Key phrases and base phrases wherever they stand, and the share of each template's words around."""
    from facetgraph.llm import licenses

    firsts = sorted({key.split()[0] for _, _, key in licenses.TEMPLATES} | {phrase.split()[0] for phrase, _ in licenses.BASE})
    base = "VALUES " + ", ".join(f"('{phrase}', '{label}', {len(phrase.split())})" for phrase, label in licenses.BASE)
    return rf"""
WITH d AS (SELECT doc_id, regexp_extract_all({_LOWERED}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
t(label, words, phrase, k, lead, counted, marks) AS ({_licenses()}),
b(phrase, label, k) AS ({base}),
g AS (SELECT DISTINCT k FROM (SELECT k FROM t UNION ALL SELECT k FROM b)),
r AS (
  SELECT doc_id, w, k, p, array_to_string(w[p:p + k - 1], ' ') AS x
  FROM (SELECT doc_id, w, unnest(list_filter(range(1, len(w) + 1), lambda i: list_contains({firsts}, w[i]))) AS p FROM d), g WHERE p + k - 1 <= len(w)),
m AS (SELECT doc_id, label, words, marks, counted, list_transform(range(1, len(words) + 1), lambda j: coalesce(w[p - t.lead + j - 1] = words[j], false)) AS same FROM r JOIN t ON t.k = r.k AND t.phrase = r.x WHERE p > t.lead),
v AS (SELECT doc_id, label, len(list_filter(same, lambda y: y)) / len(words) AS share FROM m WHERE NOT counted OR len(list_filter(marks, lambda j: same[j])) >= {licenses.AGREE}),
s AS (SELECT doc_id, count(*) AS n_base, min(p) - 1 AS first_word, max(p) - 1 AS last_word, list(DISTINCT b.label ORDER BY b.label) AS labels FROM r JOIN b ON b.k = r.k AND b.phrase = r.x GROUP BY doc_id),
l AS (SELECT doc_id, list(DISTINCT label) AS labels, max(share) AS share FROM v GROUP BY doc_id)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(s.n_base, 0)::BIGINT AS n_base, s.first_word::BIGINT AS first_word, s.last_word::BIGINT AS last_word, coalesce(array_to_string(s.labels, ','), '') AS base_labels,
       coalesce(array_to_string(list_sort(list_distinct(list_concat(coalesce(s.labels, []::VARCHAR[]), coalesce(l.labels, []::VARCHAR[])))), ','), '') AS labels,
       greatest(coalesce(l.share, 0), CASE WHEN s.n_base > 0 THEN 0.5 ELSE 0 END)::DOUBLE AS score
FROM d LEFT JOIN s USING (doc_id) LEFT JOIN l USING (doc_id)
"""


def op10_sql() -> str:
    """Both models from counts of bigrams, words and words before, and each document's mean losses."""
    from facetgraph.llm import lm_score

    a, b, c = lm_score.MIXTURE

    def loss(n: str) -> str:
        one = f"CASE WHEN sum_{n} > 0 THEN one_{n}::DOUBLE / sum_{n} ELSE 1.0::DOUBLE / {lm_score.UNIGRAMS} END"
        return f"-ln({a}::DOUBLE * CASE WHEN before_{n} > 0 THEN two_{n}::DOUBLE / before_{n} ELSE {one} END + {b}::DOUBLE * {one} + {c}::DOUBLE / {lm_score.UNIGRAMS})"

    return rf"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, doc_id IN (SELECT doc_id FROM labels WHERE quality = 1 AND doc_id IS NOT NULL) AS good, regexp_extract_all({_LOWERED}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
t AS (SELECT r, coalesce(good, false)::INT AS good, CASE WHEN i > 1 THEN w[i - 1] ELSE '' END AS u, w[i] AS x FROM (SELECT r, good, w, unnest(range(1, len(w) + 1)) AS i FROM d)),
two AS (SELECT u, x, count(*) AS two_b, sum(good) AS two_t FROM t GROUP BY u, x),
one AS (SELECT x, count(*) AS one_b, sum(good) AS one_t FROM t GROUP BY x),
pre AS (SELECT u, count(*) AS before_b, sum(good) AS before_t FROM t GROUP BY u),
n AS (SELECT count(*) AS sum_b, coalesce(sum(good), 0) AS sum_t FROM t),
g AS (SELECT u, x, {loss("t")} AS target_loss, {loss("b")} AS background_loss FROM two JOIN one USING (x) JOIN pre USING (u), n),
m AS (SELECT r, avg(target_loss) AS target_loss, avg(background_loss) AS background_loss FROM t JOIN g USING (u, x) GROUP BY r)
SELECT doc_id, len(w)::BIGINT AS n_tokens, round(coalesce(target_loss, 0), 6) AS target_loss, round(coalesce(background_loss, 0), 6) AS background_loss, round(coalesce(target_loss - background_loss, 0), 6) AS score FROM d LEFT JOIN m USING (r)
"""
