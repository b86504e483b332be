"""The registered query of each operator, over its whole table with production parameters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import fingerprints, jaccard_join, licenses, mixing, pieces, quality, quotation, secrets, substring_dedup, token_count
from .common import table


def op1_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.near_duplicates(table(spark, sf_dir, "documents"))


def op2_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents")
    return fingerprints.edited_fingerprints(documents, fingerprints.lexicon(documents))


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_count.count_tokens(table(spark, sf_dir, "documents"), token_count.vocabulary_path("byte_bpe_50k.json"), limit=1024)


def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    kept = substring_dedup.without_repeats(table(spark, sf_dir, "documents"), length=20)
    return kept.select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


def op5_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    coded = pieces.encode_documents(table(spark, sf_dir, "documents").select("doc_id", "text"), token_count.vocabulary_path("piece_bpe_32k.model"), decoded=True)
    same = F.col("decoded") == F.regexp_replace(F.coalesce("text", F.lit("")), pieces.MARK, " ")
    return coded.select("doc_id", F.size("ids").cast("long").alias("n_pieces"), F.sha2("decoded", 256).alias("decoded_sha256"), same.alias("round_trip"), "ids")


def op6_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secrets.secret_report(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_candidates", "n_secrets", F.sha2("redacted", 256).alias("redacted_sha256"), "secrets")


def op7_reply_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The table's messages quote nothing, so they are sent as mail first, by a fixed rule; what comes back has the messages' own texts."""
    ordered = quotation.reply_ordered(quotation.as_mail(table(spark, sf_dir, "conversations")))
    return ordered.select("conv_id", "turn", "role", "parent", "depth", "linked", "quote_levels", F.size("links").cast("long").alias("n_links"), "text")


def op8_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.Mix(mixing.slim_sizes(table(spark, sf_dir, "documents"))).taken()


def op9_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.license_summary(licenses.scan_licenses(table(spark, sf_dir, "documents")))


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = quality.quality_figures(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "class_distance", "word_distance")


QUERIES = {
    "op1_jaccard_join": op1_jaccard_join,
    "op2_fingerprints": op2_fingerprints,
    "op3_token_counts": op3_token_counts,
    "op4_substring_dedup": op4_substring_dedup,
    "op5_pieces": op5_pieces,
    "op6_secret_scan": op6_secret_scan,
    "op7_reply_order": op7_reply_order,
    "op8_source_mix": op8_source_mix,
    "op9_license_scan": op9_license_scan,
    "op10_quality_rules": op10_quality_rules,
}

_OP8_SQL = r"""
WITH sized AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
         ('0x' || substr(md5(coalesce(doc_id::VARCHAR, '')), 1, 12))::BIGINT AS key
  FROM documents),
per_source AS (SELECT source, sum(size)::BIGINT AS source_size FROM sized GROUP BY source),
weighed AS (
  SELECT *, source_size * 3 AS top,
         [5.0, 2.0, 1.0][1 + (row_number() OVER (ORDER BY source IS NULL, source) - 1) % 3]::DOUBLE AS weight
  FROM per_source),
running AS (
  SELECT *, (sum(source_size) OVER () - coalesce(sum(top) OVER before, 0))::BIGINT AS words_left,
         sum(weight) OVER () - coalesce(sum(weight) OVER before, 0) AS weight_left
  FROM weighed
  WINDOW before AS (ORDER BY top / weight, source IS NULL, source ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
judged AS (SELECT *, top * weight_left <= weight * words_left AS full_ FROM running),
rest AS (SELECT words_left, weight_left FROM judged WHERE NOT full_ ORDER BY top / weight, source IS NULL, source LIMIT 1),
targets AS (
  SELECT source, source_size,
         CASE WHEN full_ THEN top::DOUBLE ELSE weight * (SELECT words_left FROM rest) / (SELECT weight_left FROM rest) END AS target
  FROM judged),
total AS (SELECT coalesce(sum(size), 0)::BIGINT AS n FROM sized),
params AS (SELECT greatest(1, least(4096, (n + 65535) // 65536)) AS block, n FROM total),
stretches AS (
  SELECT source, source_size, (upto - target) / whole AS low, CASE WHEN upto >= last THEN 1.0 ELSE upto / whole END AS high
  FROM (SELECT *, sum(target) OVER (ORDER BY source IS NULL, source ROWS UNBOUNDED PRECEDING) AS upto,
               sum(target) OVER () AS whole FROM targets WHERE target > 0) a,
       (SELECT max(x) AS last FROM (SELECT sum(target) OVER (ORDER BY source IS NULL, source ROWS UNBOUNDED PRECEDING) AS x
                                    FROM targets WHERE target > 0)) b),
slots AS (
  SELECT t AS slot, ((t % 2147483648) * 1327217885) % 2147483648 / 2147483648.0::DOUBLE AS point
  FROM (SELECT unnest(range((n + block // 2) // block)) AS t FROM params)),
drawn AS (
  SELECT s.source, s.source_size, row_number() OVER (PARTITION BY s.source ORDER BY slot) AS nth
  FROM slots JOIN stretches s ON point >= low AND point < high),
reach AS (
  SELECT source, (count(*) * any_value(block))::BIGINT AS reach FROM drawn, params
  WHERE nth * block <= source_size * 3 GROUP BY source),
placed AS (
  SELECT doc_id, source, size,
         coalesce(sum(size) OVER (PARTITION BY source ORDER BY key, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS start
  FROM sized)
SELECT p.doc_id, p.size, t.source_size, t.target,
       coalesce((SELECT sum(greatest(0, least(p.size, coalesce(r.reach, 0) - p.start - lap * t.source_size)))
        FROM (VALUES (0), (1), (2)) laps(lap)), 0)::BIGINT AS taken
FROM placed p
JOIN targets t ON p.source IS NOT DISTINCT FROM t.source
LEFT JOIN reach r ON p.source IS NOT DISTINCT FROM r.source
"""

_OP1_SQL = r"""
WITH RECURSIVE texts AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
grams AS (
  SELECT DISTINCT doc_id, gram FROM (
    SELECT doc_id, unnest([array_to_string(w[i : i + 4], ' ') FOR i IN range(1, len(w) - 3)]) AS gram FROM texts WHERE len(w) >= 5
    UNION ALL SELECT doc_id, array_to_string(w, ' ') FROM texts WHERE len(w) BETWEEN 1 AND 4)),
sets AS (SELECT doc_id, count(*) AS n, md5(string_agg(gram, chr(10) ORDER BY gram)) AS name FROM grams GROUP BY doc_id),
shared AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS n FROM grams a JOIN grams b ON a.gram = b.gram AND a.doc_id <> b.doc_id GROUP BY 1, 2),
links AS (
  SELECT s.a, s.b, x.name AS a_name, y.name AS b_name FROM shared s JOIN sets x ON x.doc_id = s.a JOIN sets y ON y.doc_id = s.b
  WHERE 5 * s.n >= 4 * (x.n + y.n - s.n)),
reach(v, c) AS (SELECT doc_id, doc_id FROM documents UNION SELECT l.b, r.c FROM reach r JOIN links l ON l.a = r.v),
classes AS (SELECT v, min(c) AS class_id FROM reach GROUP BY v)
SELECT d.doc_id, c.class_id, count(l.b) AS n_links, count(DISTINCT l.b_name) FILTER (WHERE l.b_name <> l.a_name) AS n_texts
FROM documents d JOIN classes c ON c.v = d.doc_id LEFT JOIN links l ON l.a = d.doc_id GROUP BY 1, 2
"""

_OP4_SQL = r"""
WITH texts AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
words AS (SELECT doc_id, len(w) AS n, unnest(w) AS word, unnest(range(len(w))) AS pos FROM texts),
windows AS (
  SELECT doc_id, pos, n, word, CASE WHEN pos + 20 <= n THEN
    md5(string_agg(word, ' ') OVER (PARTITION BY doc_id ORDER BY pos ROWS BETWEEN CURRENT ROW AND 19 FOLLOWING)) END AS h FROM words),
judged AS (SELECT *, CASE WHEN h IS NOT NULL AND row_number() OVER (PARTITION BY h ORDER BY doc_id, pos) > 1 THEN 1 ELSE 0 END AS later FROM windows),
covered AS (SELECT doc_id, pos, word, max(later) OVER (PARTITION BY doc_id ORDER BY pos ROWS BETWEEN 19 PRECEDING AND CURRENT ROW) AS gone FROM judged),
told AS (SELECT doc_id, sum(gone)::BIGINT AS n_removed, string_agg(word, ' ' ORDER BY pos) FILTER (WHERE gone = 0) AS kept FROM covered GROUP BY doc_id)
SELECT t.doc_id, len(w)::BIGINT AS n_words, coalesce(n_removed, 0)::BIGINT AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM texts t LEFT JOIN told USING (doc_id)
"""

ORACLE_SQL = {"op1_jaccard_join": _OP1_SQL, "op4_substring_dedup": _OP4_SQL, "op8_source_mix": _OP8_SQL}
