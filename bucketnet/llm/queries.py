"""The queries of this subpackage: each applies one operator to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bucketnet.llm import fingerprint, langid, line_dedup, mixing, neardup, packing, quality_net, quality_rules, sharding, token_counts
from bucketnet.llm.common import table


def tokenizer_file(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(table(spark, sf_dir, "documents"), tokenizer_file("piece_bpe_32k.model"))


def op2_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = sharding.shard_documents(table(spark, sf_dir, "documents"), 16)
    return placed.select("doc_id", F.col("bytes").alias("size"), "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op3_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.fingerprint_documents(table(spark, sf_dir, "documents"))


def op4_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"), tokenizer_file("word_bpe_49k.json"))


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = line_dedup.dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    lines, removed = done.columns[-2:]
    return done.select("doc_id", F.col(lines).alias("n_lines"), F.col(removed).alias("lines_removed"), F.char_length("text").cast("long").alias("chars_left"), F.md5("text").alias("text_md5"))


def op6_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.score_quality(table(spark, sf_dir, "documents"))


def op7_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    rated = mixing.mix_rates(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), mixing.WEIGHTS)
    shares = [F.get("p", F.lit(i)).alias(f"p_{d}") for i, d in enumerate(mixing.DOMAINS)]
    return rated.select("doc_id", "n_tokens", *shares, "rate", "copies")


def op8_langid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.predict_language(table(spark, sf_dir, "documents"), modulus=3, rest=1)


def op10_quality_net(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_net.score_quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), modulus=5, rest=0)


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    grouped = neardup.group_near(table(spark, sf_dir, "documents"), shingle=4, budget=4)
    return grouped.select("doc_id", F.lpad(F.lower(F.hex("fp0")), 16, "0").alias("fingerprint"), "component_id")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (
    op1_token_counts, op2_sharding, op3_fingerprints, op4_packing, op5_line_dedup, op6_quality_rules, op7_mixing, op8_langid, op9_simhash, op10_quality_net)}
#: The other operators rest on hashes, tokenizers or fitted models that SQL does not have; tests/llm compares them with brute force.
ORACLES: dict[str, str] = {
    "op5_line_dedup": f"""
WITH lines AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, unnest(range(len(string_split(text, chr(10))))) AS i, len(string_split(text, chr(10))) AS n FROM documents),
info AS (SELECT *, CAST('0x' || substr(md5(line), 1, 8) AS BIGINT) AS h, length(line) - length(replace(line, ' ', '')) + 1 AS w FROM lines),
cuts AS (SELECT *, CASE WHEN i = n - 1 OR w >= {line_dedup.LONG_LINE} OR lead(w) OVER d >= {line_dedup.LONG_LINE} OR (coalesce(lag(h) OVER d, 0) * 31 + h) % {line_dedup.SPACING} = 0 THEN 1 ELSE 0 END AS ends,
    CAST(sum(w) OVER d AS BIGINT) AS upto FROM info WINDOW d AS (PARTITION BY doc_id ORDER BY i)),
numbered AS (SELECT *, upto - w AS start, coalesce(sum(ends) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS k FROM cuts),
spans AS (SELECT doc_id, min(i) AS a, max(i) AS b FROM numbered GROUP BY doc_id, k HAVING sum(w) >= {line_dedup.MIN_WORDS} AND (count(*) >= 2 OR max(w) >= {line_dedup.LONG_LINE})
    UNION SELECT doc_id, a, b FROM (SELECT doc_id, i AS a, max(i) OVER d AS b, max(upto) OVER d - start AS words FROM numbered
        WINDOW d AS (PARTITION BY doc_id ORDER BY start RANGE BETWEEN CURRENT ROW AND {line_dedup.PASSAGE_WORDS - 1} FOLLOWING)) WHERE words >= {line_dedup.PASSAGE_WORDS}
    UNION SELECT doc_id, a, b FROM (SELECT doc_id, min(i) OVER d AS a, i AS b, upto - min(start) OVER d AS words FROM numbered
        WINDOW d AS (PARTITION BY doc_id ORDER BY upto RANGE BETWEEN {line_dedup.PASSAGE_WORDS - 1} PRECEDING AND CURRENT ROW)) WHERE words >= {line_dedup.PASSAGE_WORDS}),
texts AS (SELECT doc_id, string_split(text, chr(10)) AS l FROM documents WHERE text IS NOT NULL),
judged AS (SELECT doc_id, a, b, row_number() OVER (PARTITION BY array_to_string(l[a + 1 : b + 1], chr(10)) ORDER BY doc_id, a) > 1 AS gone FROM spans JOIN texts USING (doc_id)),
removed AS (SELECT DISTINCT doc_id, unnest(range(a, b + 1)) AS i FROM judged WHERE gone),
left_over AS (SELECT l.doc_id, count(*) AS n_lines, count(r.i) AS lines_removed, coalesce(string_agg(l.line, chr(10) ORDER BY l.i) FILTER (r.i IS NULL), '') AS t
    FROM lines l LEFT JOIN removed r ON l.doc_id = r.doc_id AND l.i = r.i GROUP BY 1)
SELECT doc_id, n_lines, lines_removed, length(t) AS chars_left, md5(t) AS text_md5 FROM left_over""",
}
