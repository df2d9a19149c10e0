"""The thin queries over the operators, and DuckDB SQL where it can say the same."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slicecode.llm import anchor_simhash, decontaminate, html_main, language, line_dedup, line_frequency, piece_tokenizer, secret_scan, shards, toxicity
from slicecode.llm.common import table


def op1_line_frequency(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_frequency.line_frequency_rules(table(spark, sf_dir, "documents"))


def op2_html_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_main.extract_pages(table(spark, sf_dir, "pages"))


def op3_edit_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contaminated_passages(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op4_piece_encoding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return piece_tokenizer.encode(table(spark, sf_dir, "documents"))


def op5_byte_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shards.byte_shards(table(spark, sf_dir, "documents"), 24)


def op6_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.language_id(table(spark, sf_dir, "documents"))


def op7_unit_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row for each document, over the sentences of its lines; every repeated unit of one word or more is in ``spans``."""
    return line_dedup.passage_report(table(spark, sf_dir, "documents"))


def op8_anchor_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = anchor_simhash.near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op10_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.scan(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_line_frequency, op2_html_main_text, op3_edit_decontamination, op4_piece_encoding, op5_byte_shards, op6_language_id, op7_unit_dedup, op8_anchor_simhash, op9_toxicity, op10_secret_scan)}


OP1_SQL = r"""
WITH docs AS (SELECT row_number() OVER () AS k, doc_id, source, coalesce(text, '') AS t FROM documents),
words AS (SELECT k, unnest(w) AS word, generate_subscripts(w, 1) AS i FROM (SELECT k, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS w FROM docs)),
grams AS (SELECT k, i, word, lead(word) OVER o AS b, lead(word, 2) OVER o AS c FROM words WINDOW o AS (PARTITION BY k ORDER BY i)),
often AS (SELECT k, i FROM (SELECT k, i, count(*) OVER (PARTITION BY k, word, b, c) AS n FROM grams WHERE c IS NOT NULL) WHERE n > 1),
rep AS (SELECT k, count(*) AS n FROM (SELECT k, i FROM often UNION SELECT k, i + 1 FROM often UNION SELECT k, i + 2 FROM often) GROUP BY k),
base AS (SELECT k, count(*) AS n_words, sum(length(word)) AS word_chars FROM words GROUP BY k),
lines AS (SELECT k, doc_id, source, unnest(l) AS line, generate_subscripts(l, 1) AS i FROM (SELECT k, doc_id, source, string_split(t, chr(10)) AS l FROM docs)),
lined AS (SELECT k, doc_id, source, line, len(w) AS words, translate(array_to_string(w, ' '), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS norm
  FROM (SELECT *, regexp_extract_all(line, '[^\x20\x09-\x0D]+') AS w FROM lines) WHERE len(w) > 0),
dups AS (SELECT k, count(*) - count(DISTINCT line) AS n FROM lined GROUP BY k),
hosts AS (SELECT source, count(DISTINCT doc_id) AS docs FROM docs GROUP BY source),
hot AS (SELECT c.source, c.norm FROM (SELECT source, norm, count(DISTINCT doc_id) AS n FROM lined GROUP BY source, norm) c JOIN hosts h ON c.source IS NOT DISTINCT FROM h.source WHERE c.n >= 20 AND c.n > 0.01 * h.docs),
gone AS (SELECT k, sum(words) AS n FROM lined l JOIN hot h ON l.source IS NOT DISTINCT FROM h.source AND l.norm = h.norm GROUP BY k),
m AS (SELECT d.doc_id, coalesce(b.n_words, 0) AS n_words, coalesce(b.word_chars, 0) AS word_chars, length(d.t) - length(regexp_replace(d.t, '[#*$%&|<>]', '', 'g')) AS n_symbols,
  coalesce(u.n, 0) AS n_dup_lines, coalesce(r.n, 0) AS n_repeat_words, coalesce(g.n, 0) AS removed_words
  FROM docs d LEFT JOIN base b USING (k) LEFT JOIN rep r USING (k) LEFT JOIN dups u USING (k) LEFT JOIN gone g USING (k))
SELECT doc_id, CAST(n_words AS BIGINT) AS n_words, CAST(word_chars AS BIGINT) AS word_chars, CAST(n_symbols AS BIGINT) AS n_symbols, CAST(n_dup_lines AS BIGINT) AS n_dup_lines, CAST(n_repeat_words AS BIGINT) AS n_repeat_words,
  (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AS base_failed,
  (NOT (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AND n_words - removed_words >= 0.5 * n_words) AS kept,
  CAST(removed_words AS BIGINT) AS removed_words, CAST(n_words - removed_words AS BIGINT) AS words_left FROM m
"""

OP7_SQL = r"""
WITH docs AS (SELECT row_number() OVER () AS k, doc_id, coalesce(text, '') AS t FROM documents),
lines AS (SELECT k, doc_id, unnest(l) AS line, generate_subscripts(l, 1) AS i FROM (SELECT k, doc_id, string_split(t, chr(10)) AS l FROM docs)),
placed AS (SELECT *, sum(length(line) + 1) OVER (PARTITION BY k ORDER BY i) - length(line) - 1 AS base FROM lines),
pieces AS (SELECT k, doc_id, i, base, unnest(p) AS piece, generate_subscripts(p, 1) AS j FROM (SELECT *, regexp_extract_all(line, '.*?[.!?][\x20\x09\x0B-\x0D]+|.+') AS p FROM placed)),
spots AS (SELECT *, base + sum(length(piece)) OVER (PARTITION BY k, i ORDER BY j) - length(piece) AS s, regexp_extract_all(piece, '[^\x20\x09-\x0D]+') AS w FROM pieces),
units AS (SELECT k, doc_id, s, s + length(regexp_replace(piece, '([.!?])[\x20\x09\x0B-\x0D]+$', '\1')) AS e, len(w) AS n, translate(array_to_string(w, ' '), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS norm,
  row_number() OVER (PARTITION BY k ORDER BY s) AS u FROM spots WHERE len(w) > 0),
firsts AS (SELECT *, first_value(doc_id) OVER o AS kd, first_value(s) OVER o AS ks FROM units WINDOW o AS (PARTITION BY norm ORDER BY doc_id, s)),
hits AS (SELECT * FROM firsts WHERE NOT (doc_id = kd AND s = ks)),
runs AS (SELECT k, sum(n) AS n FROM (SELECT k, n, u - row_number() OVER (PARTITION BY k ORDER BY u) AS run FROM hits WHERE kd <> doc_id) GROUP BY k, run),
found AS (SELECT k, count(*) AS c, sum(n) AS n, string_agg(concat_ws(':', CAST(s AS BIGINT), CAST(e AS BIGINT), kd, CAST(ks AS BIGINT)), ',' ORDER BY s) AS spans FROM hits GROUP BY k),
m AS (SELECT doc_id, coalesce(u.c, 0) AS units, coalesce(f.c, 0) AS c, coalesce(f.n, 0) AS n, coalesce(r.n, 0) AS longest, coalesce(spans, '') AS spans
  FROM docs LEFT JOIN (SELECT k, count(*) AS c FROM units GROUP BY k) u USING (k) LEFT JOIN found f USING (k) LEFT JOIN (SELECT k, max(n) AS n FROM runs GROUP BY k) r USING (k))
SELECT doc_id, CAST(units AS BIGINT) AS n_units, CAST(c AS BIGINT) AS repeated_units, CAST(n AS BIGINT) AS repeated_words, CAST(longest AS BIGINT) AS longest_words,
  NOT (c > 0 AND (c = units OR longest >= 30)) AS kept, spans FROM m
"""


def oracle_sql() -> dict[str, str]:
    return {"op1_line_frequency": OP1_SQL, "op7_unit_dedup": OP7_SQL}
