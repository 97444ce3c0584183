"""The queries that an independent engine's SQL can express, as such SQL."""

from __future__ import annotations

from rankflow.llm import quality
from rankflow.llm.common import UPPER

_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"
_WS = "chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)"
_LOWER = f"translate({{}}, '{UPPER}', '{UPPER.lower()}')"


def _broken() -> str:
    tests = []
    for rule in quality.RULES:
        tests += [f"{rule.measure} < {rule.low}"] * (rule.low is not None) + [f"{rule.measure} > {rule.high}"] * (rule.high is not None)
    return " OR ".join(tests)


def quality_sql() -> str:
    stops = ", ".join(f"'{w}'" for w in quality.STOP_FORMS)
    each = lambda a, b: f"coalesce({a} / nullif(CAST({b} AS DOUBLE), 0), 0)"
    ratios = {
        "mean_word_length": ("word_chars", "n_words"), "symbol_ratio": ("n_symbols", "n_words"), "letter_ratio": ("n_letters", "word_chars"), "stop_word_ratio": ("n_stop", "n_words"),
        "dup_line_ratio": ("n_dup_lines", "n_lines"), "repeat_word_ratio": ("n_repeat_words", "n_words"), "bullet_line_ratio": ("n_bullets", "n_lines"), "ellipsis_line_ratio": ("n_ellipses", "n_lines"),
    }
    listed = ", ".join(f"{each(*v)} AS {k}" for k, v in ratios.items())
    return f"""
WITH d AS (SELECT doc_id, {_WORDS} AS w, list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: length(trim(x, {_WS})) > 0) AS l FROM documents),
t AS (SELECT doc_id, i, w[i] AS a, w[i + 1] AS b, w[i + 2] AS c FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM d)),
twice AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, a, b, c) AS k FROM t) WHERE k > 1),
covered AS (SELECT doc_id, count(DISTINCT i + s) AS n FROM twice, range(3) AS r(s) GROUP BY doc_id),
m AS (SELECT doc_id, len(w) AS n_words, array_to_string(w, '') AS j, len(l) AS n_lines, len(l) - len(list_distinct(l)) AS n_dup_lines,
  CAST(coalesce(n, 0) AS BIGINT) AS n_repeat_words, len(list_filter(w, lambda x: x IN ({stops}))) AS n_stop,
  len(list_filter(l, lambda x: regexp_matches(x, '^\\s*[-*•‣]'))) AS n_bullets, len(list_filter(l, lambda x: regexp_matches(x, '(?:\\.\\.\\.|…)\\s*$'))) AS n_ellipses
  FROM d LEFT JOIN covered USING (doc_id)),
c AS (SELECT *, length(j) AS word_chars, length(j) - length(translate(j, '#*$%&|<>', '')) AS n_symbols, length(j) - length(regexp_replace(j, '\\p{{L}}+', '', 'g')) AS n_letters FROM m),
f AS (SELECT *, {listed}, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM c)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND NOT ({_broken()}) AS kept FROM f
"""


def line_dedup_sql(min_chars: int = 40, min_docs: int = 5) -> str:
    return f"""
WITH l AS (SELECT doc_id, unnest(x) AS line, generate_subscripts(x, 1) AS pos FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS x FROM documents)),
k AS (SELECT *, {_LOWER.format(f"trim(line, {_WS})")} AS key FROM l),
s AS (SELECT key, max(doc_id) AS keeper FROM k WHERE length(key) >= {min_chars} GROUP BY key HAVING count(DISTINCT doc_id) >= {min_docs}),
f AS (SELECT doc_id, line, pos, keeper IS NOT NULL AND keeper <> doc_id AS lost FROM k LEFT JOIN s USING (key))
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (lost) AS n_dropped, sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT lost), '')) AS kept_sha256 FROM f GROUP BY doc_id
"""


def ngram_join_sql(n: int = 3, num: int = 90, den: int = 100) -> str:
    run = " || ' ' || ".join(f"w[i + {k}]" for k in range(n))
    return f"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all({_LOWER.format("coalesce(text, '')")}, '[^\\x20\\x09-\\x0D]+') AS w FROM documents),
s AS MATERIALIZED (SELECT DISTINCT doc_id, sh FROM (
  SELECT doc_id, {run} AS sh FROM (SELECT doc_id, w, unnest(range(1, len(w) - {n - 2})) AS i FROM d WHERE len(w) >= {n})
  UNION ALL SELECT doc_id, array_to_string(w, ' ') FROM d WHERE len(w) BETWEEN 1 AND {n - 1})),
c AS MATERIALIZED (SELECT doc_id, count(*) AS n, string_agg(sh, '|' ORDER BY sh) AS k FROM s GROUP BY doc_id),
o AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS same FROM s x JOIN s y ON x.sh = y.sh AND x.doc_id < y.doc_id GROUP BY 1, 2),
e AS MATERIALIZED (SELECT a, b FROM o JOIN c x ON x.doc_id = a JOIN c y ON y.doc_id = b WHERE {den} * same >= {num} * (x.n + y.n - same)),
g AS MATERIALIZED (SELECT a, b FROM e UNION SELECT b, a FROM e),
r AS (SELECT doc_id AS v, doc_id AS u FROM d UNION SELECT r.v, g.b FROM r JOIN g ON g.a = r.u),
m AS (SELECT v AS doc_id, min(u) AS component_id FROM r GROUP BY v),
q AS (SELECT doc_id, n, min(doc_id) OVER (PARTITION BY k) AS class_id FROM c)
SELECT d.doc_id, coalesce(n, 0) AS n_shingles, coalesce(class_id, d.doc_id) AS class_id, component_id FROM d JOIN m USING (doc_id) LEFT JOIN q USING (doc_id)
"""
