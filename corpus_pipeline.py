"""From raw documents to token ids: the stages of a training-corpus build, each on all that the one before kept.

ORACLE_SQL is None: the trained classifier and the tokenizer can't be said in SQL; `tests/llm/test_pipeline.py` compares
each stage with a brute-force version.

Defined cases, for all stages: an empty table gives no rows; null and empty texts are scored, grouped, masked and mixed
as empty ones (a mix takes none of them); extra columns are carried along whatever their names (the last stage returns
its own columns only); repeated rows stay repeated, except where a stage drops them for what they are: the rows of one
doc_id are judged each by its text in the first stage and together, by their id, in the second and the fourth.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stripmatch.cluster import read_table, scratch, written
from stripmatch.llm import store
from stripmatch.llm.mixing import mixed
from stripmatch.llm.pieces import encode
from stripmatch.llm.quality_classifier import accepted, fit_classifier
from stripmatch.llm.queries import tokenizer_file
from stripmatch.llm.secrets import masked
from stripmatch.llm.shingles import jaccard_components

ORACLE_SQL = None


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the rows that the classifier, fitted on this table's labels, scores at 0.3 or more."""
    return accepted(docs, fit_classifier(docs, read_table(spark, sf_dir, "labels")))


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the smallest doc_id of each group of documents that 5-word shingles link at 0.8 or more, and rows without an id."""
    bits, folder = store.range_bits(spark), store.new_folder(spark, "copies")
    with scratch(spark):  # the join's stores are several times the ids that come out of it
        groups = jaccard_components(docs, k=5, percent=80)
        store.write_lookup(groups.where("doc_id <> component_id").select(F.col("doc_id").cast("long")), bits, folder)
    return store.without(docs, "doc_id", folder, bits)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Mask every base span and every further span that looks live."""
    return masked(docs, F.col("source"), F.concat_ws("/", "source", "lang"))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop or repeat documents so that sources meet their target weights, in training order."""
    return mixed(docs)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document that is left."""
    return encode(docs, tokenizer_file("piece_bpe_32k.model"))


STAGES = [("quality_classifier", quality), ("jaccard_join", near_copies), ("secret_scan", secrets), ("source_mix", mix), ("sentencepiece", tokens)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages, each one's result written before the next reads it."""
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
