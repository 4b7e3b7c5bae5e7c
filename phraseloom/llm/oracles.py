"""DuckDB SQL for the training-data queries that SQL can say, on whole tables."""

from __future__ import annotations

from phraseloom.llm.quality_rules import DEFAULT_TABLE, STOP_WORDS

_LOWER = "translate({text}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_RUNS = r"[^\x20\x09-\x0D]+"
_ALNUM = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def _words(text: str, pattern: str, lower: bool = True) -> str:
    return f"regexp_extract_all({_LOWER.format(text=text) if lower else text}, '{pattern}')"


DECONTAMINATION = f"""WITH d AS MATERIALIZED (SELECT doc_id, {_words("coalesce(text, '')", _ALNUM)} AS w FROM documents),
b AS (SELECT CAST(item_id AS VARCHAR) AS item, {_words("coalesce(text, '')", _ALNUM)} AS w FROM benchmark),
bw AS MATERIALIZED (SELECT DISTINCT item, k, w[i:i + k - 1] AS g FROM (SELECT item, w, least(10, len(w)) AS k FROM b WHERE len(w) > 0), LATERAL (SELECT unnest(range(1, len(w) - k + 2)) AS i)),
dg AS (SELECT doc_id, i, k, w[i:i + k - 1] AS g FROM d, (SELECT DISTINCT k FROM bw) ks, LATERAL (SELECT unnest(range(1, len(w) - k + 2)) AS i)),
m AS MATERIALIZED (SELECT doc_id, i, k, item FROM dg JOIN bw USING (k, g)),
h AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + k)) AS p FROM m) GROUP BY doc_id),
t AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS names FROM (SELECT DISTINCT doc_id, item FROM m) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN h USING (doc_id) LEFT JOIN t USING (doc_id)"""

NEAR_DUPLICATES = f"""WITH RECURSIVE d AS MATERIALIZED (SELECT doc_id, {_words("coalesce(text, '')", _RUNS)} AS w FROM documents),
g AS MATERIALIZED (SELECT DISTINCT doc_id, CASE WHEN len(w) < 4 THEN w ELSE w[i:i + 3] END AS gram FROM d, LATERAL (SELECT unnest(range(1, greatest(len(w) - 3, 1) + 1)) AS i) WHERE len(w) > 0),
n AS MATERIALIZED (SELECT doc_id, count(*) AS size FROM g GROUP BY doc_id),
p AS (SELECT a.doc_id AS u, b.doc_id AS v, count(*) AS shared FROM g a JOIN g b ON a.gram = b.gram AND a.doc_id < b.doc_id GROUP BY 1, 2),
e AS MATERIALIZED (SELECT u, v FROM p JOIN n x ON x.doc_id = u JOIN n y ON y.doc_id = v WHERE 100 * shared >= 85 * (x.size + y.size - shared)),
e2 AS MATERIALIZED (SELECT u, v FROM e UNION ALL SELECT v, u FROM e),
r AS (SELECT u AS doc_id, u AS other FROM e2 UNION SELECT r.doc_id, e2.v FROM r JOIN e2 ON e2.u = r.other)
SELECT d.doc_id, coalesce(n.size, 0) AS n_shingles, coalesce(c.smallest, d.doc_id) AS component_id FROM d LEFT JOIN n USING (doc_id) LEFT JOIN (SELECT doc_id, min(other) AS smallest FROM r GROUP BY doc_id) c USING (doc_id)"""


def _threshold(measure: str) -> str:
    out = []
    for t in DEFAULT_TABLE:
        if t.measure == measure:
            out += [f"{measure} >= {t.least}"] * (t.least is not None) + [f"{measure} <= {t.most}"] * (t.most is not None)
    return " AND ".join(out) or "TRUE"


_STOPS = ", ".join("'" + w + "'" for w in sorted({f for w in STOP_WORDS for f in (w, w.capitalize())}))
_MEASURES = dict.fromkeys(t.measure for t in DEFAULT_TABLE)

QUALITY_RULES = rf"""WITH d AS MATERIALIZED (SELECT doc_id, coalesce(text, '') AS text, {_words("coalesce(text, '')", _RUNS, lower=False)} AS w, list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls FROM documents),
x AS (SELECT doc_id, i, w[i:i + 7] AS g FROM d, LATERAL (SELECT unnest(range(1, len(w) - 6)) AS i)),
y AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c FROM x) WHERE c > 1),
z AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(range(i, i + 8)) AS p FROM y) GROUP BY doc_id),
m AS (SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(list_sum(list_transform(w, lambda x: length(x))), 0) AS BIGINT) AS word_chars, CAST(length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
  CAST(len(ls) AS BIGINT) AS n_lines, CAST(len(ls) - len(list_distinct(ls)) AS BIGINT) AS n_dup_lines, CAST(len(list_filter(w, lambda x: x IN ({_STOPS}))) AS BIGINT) AS n_stop_words, coalesce(z.n, 0) AS n_repeat_words FROM d LEFT JOIN z USING (doc_id)),
q AS (SELECT *, word_chars / CAST(greatest(n_words, 1) AS DOUBLE) AS mean_word_chars, n_symbols / CAST(greatest(n_words, 1) AS DOUBLE) AS symbols_per_word, n_stop_words / CAST(greatest(n_words, 1) AS DOUBLE) AS stop_word_ratio, n_dup_lines / CAST(greatest(n_lines, 1) AS DOUBLE) AS dup_line_ratio, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND {' AND '.join(f'({_threshold(k)})' for k in _MEASURES)} AS kept FROM q"""

ORACLES = {"op4_decontamination": DECONTAMINATION, "op9_quality_rules": QUALITY_RULES, "op10_ngram_jaccard_join": NEAR_DUPLICATES}
