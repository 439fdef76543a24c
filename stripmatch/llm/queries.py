"""The registered queries of this subpackage: each applies its operator to its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stripmatch.cluster import read_table


def tokenizer_file(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from stripmatch.llm.token_counts import count_tokens

    return count_tokens(read_table(spark, sf_dir, "documents"), tokenizer_file("word_bpe_49k.json"))


def op2_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    from stripmatch.llm.pieces import encode

    return encode(read_table(spark, sf_dir, "documents"), tokenizer_file("piece_bpe_32k.model"))


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from stripmatch.llm.quality_rules import fit_rules, quality_rules

    docs = read_table(spark, sf_dir, "documents")
    return quality_rules(docs, fit_rules(docs, read_table(spark, sf_dir, "labels")))


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from stripmatch.llm.mixing import plan_mix

    return plan_mix(read_table(spark, sf_dir, "documents"))


OP4_SQL = """
WITH d AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')) AS size,
         md5(coalesce(CAST(doc_id AS VARCHAR), '')) AS h
  FROM documents),
t AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
r AS (SELECT *, (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 AS k FROM t),
w AS (SELECT *, CASE k WHEN 0 THEN 5e0 WHEN 1 THEN 2e0 ELSE 1e0 END AS weight,
             CASE k WHEN 0 THEN -0.5e0 WHEN 1 THEN 0e0 ELSE 0.5e0 END AS slope, 2e0 * source_size AS most FROM r),
l AS (SELECT *, (1.5e0 * (SELECT sum(source_size) FROM t)
                 - coalesce(sum(most) OVER (ORDER BY most / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
              / ((SELECT sum(weight) FROM w)
                 - coalesce(sum(weight) OVER (ORDER BY most / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) AS level
      FROM w),
g AS (SELECT source, source_size, slope,
             coalesce(least((SELECT max(level) FROM l WHERE level * weight <= most) * weight, most), most) AS target FROM l),
p AS (SELECT d.doc_id, d.size, g.source_size, g.target, g.slope,
             coalesce(sum(d.size) OVER (PARTITION BY d.source ORDER BY d.h, d.doc_id, d.size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS start
      FROM d JOIN g ON d.source IS NOT DISTINCT FROM g.source),
c AS (SELECT *, CASE WHEN size > 0 AND start + size / 2e0 <= target
                     THEN CAST(floor((target - (start + size / 2e0)) / source_size) AS BIGINT) + 1 ELSE 0 END AS copies FROM p),
u AS (SELECT *, least(start / target, 1e0) AS u0, least((start + source_size) / target, 1e0) AS u1 FROM c)
SELECT doc_id, CAST(size AS BIGINT) AS size, source_size, target, CAST(copies AS BIGINT) AS copies, CAST(copies * size AS BIGINT) AS taken,
       CASE WHEN copies > 0 THEN 2 * u0 / ((1 - slope) + sqrt((1 - slope) * (1 - slope) + 4 * slope * u0)) END AS position,
       CASE WHEN copies > 1 THEN 2 * u1 / ((1 - slope) + sqrt((1 - slope) * (1 - slope) + 4 * slope * u1)) END AS position_again
FROM u
"""


def op5_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    from stripmatch.llm.quality_classifier import classify, fit_classifier

    docs = read_table(spark, sf_dir, "documents")
    return classify(docs, fit_classifier(docs, read_table(spark, sf_dir, "labels")))


def op6_secret_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Owner: the source; repository: the source's part in one language."""
    from stripmatch.llm.secrets import find_secrets, joined_spans

    full, _ = find_secrets(read_table(spark, sf_dir, "documents"), F.col("source"), F.concat_ws("/", "source", "lang"))
    of = lambda k: F.size(F.filter("base", lambda x: x["rank"] == k)).cast("long")
    return full.select("doc_id", of(0).alias("n_assign"), of(1).alias("n_access"), of(2).alias("n_hex"), F.sha2(joined_spans(F.array_sort("base")).cast("binary"), 256).alias("base_sha256"), joined_spans(F.col("spans")).alias("spans"), "n_live", "n_example")


def op7_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from stripmatch.llm.shingles import jaccard_components

    return jaccard_components(read_table(spark, sf_dir, "documents"), k=4, percent=85)


def op8_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from stripmatch.llm.repeats import remove_repeats

    return remove_repeats(read_table(spark, sf_dir, "documents"))


def op9_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from stripmatch.llm.vectors import near_vectors

    return near_vectors(read_table(spark, sf_dir, "embeddings"))


def op10_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    from stripmatch.llm.kneser_ney import score_documents

    return score_documents(read_table(spark, sf_dir, "documents"))


def queries() -> dict:
    return {f.__name__: f for f in (op1_token_counts, op2_sentencepiece, op3_quality_rules, op4_mixing, op5_quality_classifier, op6_secret_scans, op7_jaccard_join, op8_substring_dedup, op9_embedding_near_dedup, op10_lm_scoring)}


def oracle_sql() -> dict[str, str]:
    return {"op4_mixing": OP4_SQL}
