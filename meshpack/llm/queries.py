"""Registered queries: thin digests of what the operators return."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat_repair, chunk_dedup, decontaminate, line_rules, quality_lm, secret_scan, simhash, sp_sampling, token_count, toxicity
from .common import table


def op1_chat_repair(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every turn with its repaired role, action, cost and rendered fragment."""
    return chat_repair.repair_roles(table(spark, sf_dir, "conversations")).select("conv_id", "turn", "role", "new_role", "action", "cost", "n_inserted", "fragment")


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op3_chunk_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with its repeated passages: counts, ranges to cut, and who keeps the copies."""
    got = chunk_dedup.substring_dedup(table(spark, sf_dir, "documents"))
    return got.withColumn("has_repeats", F.col("n_shared") > 0)


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op5_quality_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_lm.quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_count.token_counts(table(spark, sf_dir, "documents"), keep=["doc_id"])


def op7_sp_sampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two distinct sampled segmentations of every document: piece ids, their digest, and inclusion scores."""
    return sp_sampling.segmentations(table(spark, sf_dir, "documents"))


def op8_line_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_rules.line_rules(table(spark, sf_dir, "documents"))


def op9_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.report(table(spark, sf_dir, "documents"))


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


QUERIES = {
    f.__name__: f
    for f in (
        op1_chat_repair, op2_decontaminate, op3_chunk_dedup, op4_toxicity, op5_quality_lm,
        op6_token_counts, op7_sp_sampling, op8_line_rules, op9_secret_scan, op10_simhash,
    )
}

UPPER, LOWER, DIGITS = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz", "0123456789"
_BENCH_WORDS = rf"regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
_DECONTAMINATE = f"""WITH d AS (SELECT row_number() OVER () AS r, doc_id, {_BENCH_WORDS} AS w FROM documents),
b AS (SELECT item_id::VARCHAR AS item, {_BENCH_WORDS} AS w FROM benchmark WHERE item_id IS NOT NULL),
bw AS (SELECT DISTINCT item, size, array_to_string(w[i:i + size - 1], ' ') AS k FROM
 (SELECT item, w, least(13, len(w)) AS size, unnest(range(1, greatest(len(w) - 12, 1) + 1)) AS i FROM b WHERE len(w) > 0)),
dw AS (SELECT r, i, size, array_to_string(w[i:i + size - 1], ' ') AS k FROM
 (SELECT r, w, size, unnest(range(1, len(w) - size + 2)) AS i FROM d, (SELECT DISTINCT size FROM bw) WHERE len(w) >= size)),
h AS (SELECT r, i, size, item FROM dw JOIN bw USING (size, k)),
n AS (SELECT r, count(DISTINCT p) AS n_hit FROM (SELECT r, unnest(range(i, i + size)) AS p FROM h) GROUP BY 1),
f AS (SELECT r, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT r, item FROM h) GROUP BY 1)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items, sha256(coalesce(items, '')) AS items_sha256,
coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated FROM d LEFT JOIN n USING (r) LEFT JOIN f USING (r)"""

_WORD = r"[^\x20\x09-\x0D]+"
_LINE_RULES = f"""WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(source, '') AS host, coalesce(text, '') AS t FROM documents),
w AS (SELECT r, regexp_extract_all(t, '{_WORD}') AS w FROM d),
wn AS (SELECT r, i, array_to_string(w[i:i + 4], ' ') AS k FROM (SELECT r, w, unnest(range(1, len(w) - 3)) AS i FROM w WHERE len(w) >= 5)),
rw AS (SELECT r, count(DISTINCT p) AS n_repeat_words FROM (SELECT r, unnest(range(i, i + 5)) AS p FROM wn JOIN (SELECT r, k FROM wn GROUP BY 1, 2 HAVING count(*) > 1) USING (r, k)) GROUP BY 1),
l AS (SELECT r, line, regexp_extract_all(line, '{_WORD}') AS lw FROM (SELECT r, unnest(string_split(t, chr(10))) AS line FROM d)),
dup AS (SELECT r, count(*) - count(DISTINCT line) AS n_dup_lines FROM l WHERE len(lw) > 0 GROUP BY 1),
norm AS (SELECT r, translate(array_to_string(lw, ' '), '{UPPER}{DIGITS}', '{LOWER}0000000000') AS k, sum(length(array_to_string(lw, ''))) AS chars FROM l WHERE len(lw) > 0 GROUP BY 1, 2),
freq AS (SELECT host, k FROM norm JOIN d USING (r) GROUP BY 1, 2 HAVING count(DISTINCT coalesce(doc_id::VARCHAR, 'row ' || r)) > {line_rules.LINE_DOCS}),
lost AS (SELECT r, count(*) AS n, sum(chars) AS c FROM norm JOIN d USING (r) JOIN freq USING (host, k) GROUP BY 1),
base AS (SELECT doc_id, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars, length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
 coalesce(n_dup_lines, 0)::BIGINT AS n_dup_lines, coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words, coalesce(lost.n, 0)::BIGINT AS n_removed_lines, coalesce(lost.c, 0)::BIGINT AS removed_chars
 FROM d JOIN w USING (r) LEFT JOIN rw USING (r) LEFT JOIN dup USING (r) LEFT JOIN lost USING (r))
SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed,
NOT (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AND 2 * (word_chars - removed_chars) >= word_chars AS kept FROM base"""

#: The others need hashes, models or libraries that plain SQL lacks; the tests hold them against plain versions.
ORACLE_SQL: dict[str, str] = {"op2_decontaminate": _DECONTAMINATE, "op8_line_rules": _LINE_RULES}
