"""What SQL can express of the operators on texts: their fixed columns, each with its DuckDB SQL.

Every query here runs the whole operator over its whole table and leaves out what is learnt.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sift.llm import lm, quality, secrets

_SPACE = r"[\x20\x09-\x0D]+"
_WORDS = f"list_filter(string_split_regex(coalesce(text, ''), '{_SPACE}'), lambda x: x <> '')"


def quality_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op1's statistics and base verdict."""
    return quality.op1_quality_rules(spark, sf_dir).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")


_EIGHT = " || ' ' || ".join(["w", *(f"lead(w, {k}) OVER o" for k in range(1, quality.WINDOW))])
QUALITY = rf"""
WITH d AS MATERIALIZED (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t, {_WORDS} AS words FROM documents),
places AS (SELECT r, unnest(words) AS w, unnest(range(1, len(words) + 1)) AS i FROM d),
eights AS (SELECT r, i, {_EIGHT} AS eight FROM places WINDOW o AS (PARTITION BY r ORDER BY i)),
windows AS (SELECT r, i, count(*) OVER (PARTITION BY r, eight) AS n FROM eights WHERE eight IS NOT NULL),
covered AS (SELECT r, count(DISTINCT i + k) AS n FROM windows, range(8) AS o(k) WHERE n > 1 GROUP BY r),
lines AS (SELECT r, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM d),
s AS (SELECT doc_id, CAST(len(words) AS BIGINT) AS n_words, CAST(length(array_to_string(words, '')) AS BIGINT) AS word_chars,
  CAST(length(regexp_replace(t, '[^#*$%&|<>]+', '', 'g')) AS BIGINT) AS n_symbols, CAST(len(l) - len(list_distinct(l)) AS BIGINT) AS n_dup_lines,
  CAST(coalesce(n, 0) AS BIGINT) AS n_repeat_words FROM d JOIN lines USING (r) LEFT JOIN covered USING (r))
SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM s
"""


def secrets_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op6's counts and spans of the fixed patterns."""
    return secrets.op6_secret_scans(spark, sf_dir).select("doc_id", "n_assign", "n_access", "n_hex", "base_sha256")


def _either_case(word: str) -> str:
    return re.sub("[a-z]", lambda m: f"[{m[0].upper()}{m[0]}]", word)


_NAMES = _either_case("password|passwd|secret|token|api_?key")
#: Kind, pattern, group, least length of the group.
_PATTERNS = (("assign", rf"""({_NAMES})["'']?\x20*[:=]\x20*["'']?([A-Za-z0-9+/_.=-]+)""", 2, 6), ("access", "AKIA[A-Z0-9]+", 0, 20), ("hex", "[0-9a-f]+", 0, 24))
_FOUND = " UNION ALL ".join(f"SELECT r, {k} AS k, '{kind}' AS kind, {least} AS least, regexp_extract_all(t, '{p}') AS m, regexp_extract_all(t, '{p}', {group}) AS g, string_split_regex(t, '{p}') AS b FROM d" for k, (kind, p, group, least) in enumerate(_PATTERNS))
SECRETS = f"""
WITH d AS MATERIALIZED (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t FROM documents),
found AS ({_FOUND}),
sized AS (SELECT r, k, kind, least, unnest(g) AS g, unnest(m) AS m, unnest(b[1:len(m)]) AS b, unnest(range(1, len(m) + 1)) AS i FROM found WHERE len(m) > 0),
ended AS (SELECT *, CAST(sum(length(b) + length(m)) OVER (PARTITION BY r, k ORDER BY i) AS BIGINT) AS e FROM sized),
kept AS (SELECT r, k, kind, e - length(m) AS s, e FROM ended WHERE length(g) >= least),
told AS (SELECT r, string_agg(kind || ':' || s || ':' || e, ',' ORDER BY s, k) AS spans, count(*) FILTER (WHERE k = 0) AS a, count(*) FILTER (WHERE k = 1) AS c, count(*) FILTER (WHERE k = 2) AS h FROM kept GROUP BY r)
SELECT doc_id, CAST(coalesce(a, 0) AS BIGINT) AS n_assign, CAST(coalesce(c, 0) AS BIGINT) AS n_access, CAST(coalesce(h, 0) AS BIGINT) AS n_hex, sha256(coalesce(spans, '')) AS base_sha256
FROM d LEFT JOIN told USING (r)
"""


def lm_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op9's folds, counts and score by single words, rounded to six places."""
    return lm.op9_lm_scoring(spark, sf_dir).select("doc_id", "held_out", "n_tokens", "n_known", "train_tokens", F.round("base_score", 6).alias("base_score"))


#: The end is a blank, which no word holds. The checksum goes byte by byte through a table made from its polynomial.
LM = f"""
WITH tab AS (SELECT list_transform(range(256), lambda i: list_reduce(list_prepend(i, [0, 0, 0, 0, 0, 0, 0, 0]), lambda c, x: xor(c >> 1, (c & 1) * 3988292384))) AS steps),
d AS MATERIALIZED (SELECT row_number() OVER () AS r, doc_id,
  xor(list_reduce(list_prepend(4294967295, list_transform(string_split(CAST(doc_id AS VARCHAR), ''), lambda y: CAST(ascii(y) AS BIGINT))), lambda c, x: xor(c >> 8, steps[(xor(c, x) & 255) + 1])), 4294967295) % 7 = 2 AS held_out,
  list_append(list_transform({_WORDS}, lambda x: translate(x, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')), ' ') AS tokens FROM documents, tab),
t AS (SELECT r, held_out, unnest(tokens) AS w FROM d),
c AS (SELECT w, count(*) AS c FROM t WHERE NOT held_out GROUP BY w),
n AS (SELECT CAST(coalesce(sum(c), 0) AS BIGINT) AS n, count(*) AS v FROM c),
s AS (SELECT r, count(*) AS n_tokens, count(c) AS n_known, any_value(n) AS train_tokens, sum(log10((coalesce(c, 0) + 1) / (n + v + 1))) AS base_score FROM t LEFT JOIN c USING (w) CROSS JOIN n GROUP BY r)
SELECT doc_id, held_out, n_tokens, n_known, train_tokens, round(base_score, 6) AS base_score FROM d JOIN s USING (r)
"""
