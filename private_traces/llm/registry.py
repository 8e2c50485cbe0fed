"""Queries of the training-data operators, each over its whole tables, with DuckDB SQL where SQL can express it."""

from __future__ import annotations

from pyspark.sql import functions as F

from . import bpe, decontaminate, language, lines, minhash, quality, secrets, suffixes, token_files, toxicity
from .common import table


def _vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_line_dedup(spark, sf_dir):
    """Per document: its non-blank lines, how many are removed, and a digest of what stays."""
    done = lines.dedup(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return done.select("doc_id", F.col("n_lines").cast("long").alias("n_lines"), F.col("n_removed").cast("long").alias("n_removed"), F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


def op2_quality_rules(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    return quality.judge(docs, quality.fit(docs, table(spark, sf_dir, "labels")))


def op3_toxicity(spark, sf_dir):
    return toxicity.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op4_language_id(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    return language.identify(docs, language.learnable(docs))


def op5_token_files(spark, sf_dir):
    return token_files.round_trip(table(spark, sf_dir, "documents"), _vocabulary("word_bpe_49k.json"))


def op6_suffix_dedup(spark, sf_dir):
    return suffixes.digests(table(spark, sf_dir, "documents"))


def op7_minhash(spark, sf_dir):
    """Per document its class of near duplicates; a row with a null id stays only in a class without any id."""
    found = minhash.classes(table(spark, sf_dir, "documents"), width=2, percent=80)
    return found.select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"))


def op8_secret_scan(spark, sf_dir):
    return secrets.digests(table(spark, sf_dir, "documents"))


def op9_decontaminate(spark, sf_dir):
    return decontaminate.flags(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op10_byte_bpe(spark, sf_dir):
    import public_tokenizers

    return bpe.digests(table(spark, sf_dir, "documents"), _vocabulary("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


def quality_base_counts(spark, sf_dir):
    """The base of op2: counts and base verdict of every document."""
    return quality.base(table(spark, sf_dir, "documents"))


def secret_base_spans(spark, sf_dir):
    """The base of op8: spans of the three base kinds of every document."""
    return secrets.digests(table(spark, sf_dir, "documents")).select("doc_id", "n_assign", "n_access", "n_hex", "base_sha256")


QUERIES = {
    "quality_base_counts": quality_base_counts,
    "secret_base_spans": secret_base_spans,
    "op1_line_dedup": op1_line_dedup,
    "op2_quality_rules": op2_quality_rules,
    "op3_toxicity": op3_toxicity,
    "op4_language_id": op4_language_id,
    "op5_token_files": op5_token_files,
    "op6_suffix_dedup": op6_suffix_dedup,
    "op7_minhash": op7_minhash,
    "op8_secret_scan": op8_secret_scan,
    "op9_decontaminate": op9_decontaminate,
    "op10_byte_bpe": op10_byte_bpe,
}
#: Lines one edit apart share the first or the last half; places compared as (doc_id, line number).
LINE_DEDUP_SQL = r"""
WITH raw AS (SELECT doc_id, text, unnest(string_split(text, chr(10))) AS raw, generate_subscripts(string_split(text, chr(10)), 1) AS n FROM documents WHERE text IS NOT NULL),
lines AS (SELECT doc_id, n, raw, trim(raw, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)) AS line FROM raw),
firsts AS (SELECT line, min((doc_id, n)) AS at, length(line) AS len FROM lines WHERE line <> '' GROUP BY line),
pairs AS (
  SELECT a.line AS longer, b.line AS shorter, a.at AS long_at, b.at AS short_at, a.len AS len
  FROM firsts a JOIN firsts b ON b.len BETWEEN a.len - 1 AND a.len AND a.len >= 16 AND b.len >= 16 AND a.line <> b.line
    AND (substr(a.line, 1, b.len // 2) = substr(b.line, 1, b.len // 2) OR substr(a.line, a.len - (b.len - b.len // 2) + 1) = substr(b.line, b.len // 2 + 1))
),
near AS (
  SELECT longer, shorter, long_at, short_at FROM pairs
  WHERE len(list_filter(range(0, len), lambda i: substr(longer, 1, i) = substr(shorter, 1, i)
    AND (substr(longer, i + 2) = substr(shorter, i + 2) AND length(longer) = length(shorter) OR substr(longer, i + 2) = substr(shorter, i + 1) AND length(longer) > length(shorter)))) > 0
),
gone AS (SELECT longer AS line FROM near WHERE short_at < long_at UNION SELECT shorter FROM near WHERE long_at < short_at),
judged AS (SELECT l.doc_id, l.n, l.raw, l.line = '' AS blank, f.at = (l.doc_id, l.n) AND g.line IS NULL AS stays FROM lines l LEFT JOIN firsts f ON f.line = l.line LEFT JOIN gone g ON g.line = l.line),
done AS (SELECT doc_id, count(*) FILTER (WHERE NOT blank) AS n_lines, count(*) FILTER (WHERE NOT blank AND NOT stays) AS n_removed, coalesce(string_agg(raw, chr(10) ORDER BY n) FILTER (WHERE blank OR stays), '') AS kept FROM judged GROUP BY doc_id)
SELECT d.doc_id, coalesce(n_lines, 0) AS n_lines, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM documents d LEFT JOIN done USING (doc_id)
"""

#: All pairs of distinct sets that share a shingle, then the classes by recursion.
NEAR_DUPLICATE_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
sets AS (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 2 THEN [w[1]] ELSE list_distinct(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) END AS s FROM w
),
flat AS (SELECT doc_id, len(s) AS n, unnest(s) AS x FROM sets),
shared AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k, any_value(a.n) AS na, any_value(b.n) AS nb FROM flat a JOIN flat b ON a.x = b.x AND a.doc_id < b.doc_id AND least(a.n, b.n) >= 0.8 * greatest(a.n, b.n) - 1e-9 GROUP BY 1, 2),
links AS (SELECT a, b FROM shared WHERE 100 * k >= 80 * (na + nb - k)),
twoway AS (SELECT a, b FROM links UNION SELECT b, a FROM links),
reach AS (SELECT doc_id AS a, doc_id AS b FROM sets UNION SELECT r.a, e.b FROM reach r JOIN twoway e ON e.a = r.b),
least_id AS (SELECT a AS doc_id, min(b) AS component_id FROM reach GROUP BY a)
SELECT doc_id, len(s)::BIGINT AS n_shingles, component_id, doc_id = component_id AS kept FROM sets JOIN least_id USING (doc_id)
"""

QUALITY_BASE_SQL = r"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
lines AS (SELECT doc_id, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM t),
windows AS (SELECT doc_id, unnest(range(1, len(w) - 1)) AS i, unnest(list_transform(range(1, len(w) - 1), lambda i: [w[i], w[i + 1], w[i + 2]])) AS x FROM t WHERE len(w) > 3),
again AS (SELECT doc_id, unnest([i, i + 1, i + 2]) AS place FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, x) AS k FROM windows) WHERE k > 1),
covered AS (SELECT doc_id, count(DISTINCT place) AS n FROM again GROUP BY doc_id),
counted AS (
  SELECT t.doc_id, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars, length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
    (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines, coalesce(c.n, 0)::BIGINT AS n_repeat_words
  FROM t JOIN lines USING (doc_id) LEFT JOIN covered c USING (doc_id)
)
SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM counted
"""

#: Matches and the pieces between them give the places: a match starts behind all pieces and matches before it.
SECRET_BASE_SQL = r"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
cut AS (
  SELECT doc_id, 'assign' AS kind, 0 AS rank, 6 AS least, string_split_regex(text, '(?i:(password|passwd|secret|token|api_?key))["'']?\x20*[:=]\x20*["'']?([A-Za-z0-9+/_.=-]+)') AS between, regexp_extract_all(text, '(?i:(password|passwd|secret|token|api_?key))["'']?\x20*[:=]\x20*["'']?([A-Za-z0-9+/_.=-]+)') AS hit,
    regexp_extract_all(text, '(?i:(password|passwd|secret|token|api_?key))["'']?\x20*[:=]\x20*["'']?([A-Za-z0-9+/_.=-]+)', 2) AS value FROM t
  UNION ALL SELECT doc_id, 'access', 1, 20, string_split_regex(text, 'AKIA[A-Z0-9]+'), regexp_extract_all(text, 'AKIA[A-Z0-9]+'), regexp_extract_all(text, 'AKIA[A-Z0-9]+') FROM t
  UNION ALL SELECT doc_id, 'hex', 2, 24, string_split_regex(text, '[0-9a-f]+'), regexp_extract_all(text, '[0-9a-f]+'), regexp_extract_all(text, '[0-9a-f]+') FROM t
),
placed AS (
  SELECT doc_id, kind, rank, least, unnest(range(1, len(hit) + 1)) AS i, unnest(hit) AS m, unnest(value) AS v, unnest(between[:len(hit)]) AS gap FROM cut WHERE len(hit) > 0
),
spans AS (
  SELECT doc_id, kind, rank, least, v, sum(length(gap)) OVER w + sum(length(m)) OVER w - length(m) AS a, length(m) AS n FROM placed WINDOW w AS (PARTITION BY doc_id, kind ORDER BY i)
),
held AS (SELECT doc_id, kind, rank, a::BIGINT AS a, (a + n)::BIGINT AS b FROM spans WHERE length(v) >= least),
done AS (SELECT doc_id, count(*) FILTER (WHERE rank = 0) AS x, count(*) FILTER (WHERE rank = 1) AS y, count(*) FILTER (WHERE rank = 2) AS z, string_agg(kind || ':' || a || ':' || b, ',' ORDER BY a, rank) AS s FROM held GROUP BY doc_id)
SELECT doc_id, coalesce(x, 0)::BIGINT AS n_assign, coalesce(y, 0)::BIGINT AS n_access, coalesce(z, 0)::BIGINT AS n_hex, sha256(coalesce(s, '')) AS base_sha256 FROM t LEFT JOIN done USING (doc_id)
"""

ORACLES: dict[str, str] = {
    "op1_line_dedup": LINE_DEDUP_SQL,
    "op7_minhash": NEAR_DUPLICATE_SQL,
    "quality_base_counts": QUALITY_BASE_SQL,
    "secret_base_spans": SECRET_BASE_SQL,
}
