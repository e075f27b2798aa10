"""Queries of the text operators over the given tables, with SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from forkline.llm.common import shared_folder, table


def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from forkline.llm.repeats import line_dedup

    kept = line_dedup(table(spark, sf_dir, "documents"), run=2, long_line=50)
    return kept.select("doc_id", F.col("n_units").alias("n_lines"), "n_removed", F.sha2("text", 256).alias("kept_sha256"))


def op2_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from forkline.llm.repeats import substring_dedup

    kept = substring_dedup(table(spark, sf_dir, "documents"), width=13)
    return kept.select("doc_id", F.col("n_units").alias("n_words"), "n_removed", F.sha2("text", 256).alias("kept_sha256"))


def op3_simhash_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    from forkline.llm.simhash import simhash_groups

    return simhash_groups(table(spark, sf_dir, "documents"), shingle=3, radius=2)


def op4_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    from forkline.llm.language_model import score

    held_out = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 7 == 2
    return score(table(spark, sf_dir, "documents"), held_out)


def op5_line_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from forkline.llm.line_quality import fit, judge

    docs = table(spark, sf_dir, "documents")
    return judge(docs, fit(docs, table(spark, sf_dir, "labels")))


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from forkline.llm.decontaminate import decontaminate

    found = decontaminate(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), width=10)
    return found.select("doc_id", "n_words", "n_hit", F.size("item_ids").cast("bigint").alias("n_items"), F.sha2(F.concat_ws(",", "item_ids"), 256).alias("items_sha256"), "contaminated")


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from forkline.llm.packing import pack, pieces_digest

    return pieces_digest(pack(table(spark, sf_dir, "documents"), "byte_bpe_50k.json", sequence_length=1024, end_id=0))


def op8_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from forkline.llm.secrets import scan_secrets

    found = scan_secrets(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_assign", "n_access", "n_hex", F.sha2("base_spans", 256).alias("base_sha256"), "spans", "n_random", "n_confirmed")


def op9_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    from forkline.llm.quality_classifier import fit, score

    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    held_out = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1
    found = score(docs, fit(docs, labels.where(~held_out)))
    return found.select("doc_id", F.coalesce(held_out, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op10_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    from forkline.llm.token_files import documents_digest, read_token_files, write_token_files

    folder = shared_folder(spark, "token-files")
    manifest = write_token_files(table(spark, sf_dir, "documents"), folder, "word_bpe_49k.json", end_id=1)
    return documents_digest(read_token_files(spark, manifest, folder))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_line_dedup": op1_line_dedup,
    "op2_substring_dedup": op2_substring_dedup,
    "op3_simhash_groups": op3_simhash_groups,
    "op4_language_model": op4_language_model,
    "op5_line_quality": op5_line_quality,
    "op6_decontamination": op6_decontamination,
    "op7_packing": op7_packing,
    "op8_secret_scan": op8_secret_scan,
    "op9_quality_classifier": op9_quality_classifier,
    "op10_token_files": op10_token_files,
}

#: The characters that part words, for SQL.
_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"

_OP1 = r"""
WITH lines AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
         generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS nr
  FROM documents),
worded AS (
  SELECT doc_id, line, nr, row_number() OVER (PARTITION BY doc_id ORDER BY nr) AS pos,
         count(*) OVER (PARTITION BY doc_id) AS n_lines,
         lead(line) OVER (PARTITION BY doc_id ORDER BY nr) AS next_line,
         len(regexp_extract_all(line, '[^\x20\x09-\x0D]+')) AS n_words
  FROM lines WHERE regexp_matches(line, '[^\x20\x09-\x0D]')),
windows AS (
  SELECT doc_id, pos, 2 AS size, line || chr(10) || next_line AS run FROM worded WHERE next_line IS NOT NULL
  UNION ALL SELECT doc_id, pos, 1, '1' || line FROM worded WHERE n_lines = 1
  UNION ALL SELECT doc_id, pos, 1, '1' || line FROM worded WHERE n_words >= 50 AND n_lines > 1),
firsts AS (
  SELECT *, min((doc_id, pos)) OVER (PARTITION BY size, run) AS earliest FROM windows),
late AS (SELECT doc_id, pos, size FROM firsts WHERE earliest < (doc_id, pos)),
gone AS (
  SELECT DISTINCT doc_id, pos FROM late UNION SELECT doc_id, pos + 1 FROM late WHERE size = 2),
kept AS (
  SELECT l.doc_id, string_agg(l.line, chr(10) ORDER BY l.nr) AS text
  FROM lines l LEFT JOIN worded w USING (doc_id, nr) LEFT JOIN gone g ON g.doc_id = w.doc_id AND g.pos = w.pos
  WHERE g.pos IS NULL GROUP BY l.doc_id)
SELECT d.doc_id, coalesce(n.n_lines, 0) AS n_lines, coalesce(g.n, 0) AS n_removed, sha256(coalesce(k.text, '')) AS kept_sha256
FROM documents d LEFT JOIN (SELECT doc_id, count(*) AS n_lines FROM worded GROUP BY doc_id) n USING (doc_id)
LEFT JOIN (SELECT doc_id, count(*) AS n FROM gone GROUP BY doc_id) g USING (doc_id)
LEFT JOIN kept k USING (doc_id)
"""

_OP2 = rf"""
WITH texts AS (SELECT doc_id, {_WORDS} AS words FROM documents),
starts AS (
  SELECT doc_id, i, array_to_string(words[i : i + 12], ' ') AS run
  FROM (SELECT doc_id, words, unnest(range(1, len(words) - 11)) AS i FROM texts)),
late AS (
  SELECT doc_id, i FROM (SELECT doc_id, i, min(doc_id) OVER (PARTITION BY run) AS least FROM starts) WHERE least < doc_id),
gone AS (SELECT DISTINCT doc_id, i + k AS i FROM late, range(13) r(k)),
words AS (SELECT doc_id, unnest(words) AS word, generate_subscripts(words, 1) AS i FROM texts),
kept AS (
  SELECT doc_id, count(*) AS n, string_agg(word, ' ' ORDER BY i) AS text
  FROM words w ANTI JOIN gone g USING (doc_id, i) GROUP BY doc_id)
SELECT t.doc_id, len(words)::BIGINT AS n_words, (len(words) - coalesce(n, 0))::BIGINT AS n_removed, sha256(coalesce(text, '')) AS kept_sha256
FROM texts t LEFT JOIN kept USING (doc_id)
"""

_OP6 = r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS words FROM documents),
b AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS words FROM benchmark),
sized AS (SELECT item_id, words, least(len(words), 10) AS n FROM b WHERE len(words) > 0),
windows AS (
  SELECT DISTINCT item_id, n, array_to_string(words[i : i + n - 1], ' ') AS run
  FROM (SELECT item_id, words, n, unnest(range(1, len(words) - n + 2)) AS i FROM sized)),
starts AS (
  SELECT doc_id, n, i, array_to_string(words[i : i + n - 1], ' ') AS run
  FROM (SELECT doc_id, words, n, unnest(range(1, len(words) - n + 2)) AS i FROM d, (SELECT DISTINCT n FROM sized))),
hits AS (SELECT doc_id, item_id, i, n FROM starts JOIN windows USING (n, run)),
covered AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM hits) GROUP BY doc_id),
named AS (SELECT doc_id, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS ids FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS item_id FROM hits) GROUP BY doc_id)
SELECT doc_id, len(words)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(ids, '')) AS items_sha256, n_hit IS NOT NULL AS contaminated
FROM d LEFT JOIN covered USING (doc_id) LEFT JOIN named USING (doc_id)
"""

ORACLES: dict[str, str] = {"op6_decontamination": _OP6, "op1_line_dedup": _OP1, "op2_substring_dedup": _OP2}
