"""A training corpus in five stages: judge, deduplicate, mask secrets, mix sources, encode.

Each stage takes (spark, docs, sf_dir), works on all that the one before kept, and returns a DataFrame; all but the
last return the columns of documents. `run` writes each stage's rows to the shared folder and reads them again.
Null and empty texts are rejected by the first stage; empty tables pass through all stages.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from filterfleet.llm import byte_bpe, language_model, secret_scan, shingle_join, source_mix
from filterfleet.llm.common import materialize, table

DOCUMENT = ("doc_id", "text", "lang", "source", "n_chars")


def judge(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the language model accepts (operator 6)."""
    return language_model.accepted(docs, table(spark, sf_dir, "labels")).select(*DOCUMENT)


def deduplicate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each component of near copies, the document with the smallest id; of rows that repeat an id, one (operator 3)."""
    classes = shingle_join.similarity_classes(docs)
    first = classes.where("component_id is null or doc_id = component_id").select(F.col("doc_id").alias("of_id")).distinct()
    return docs.join(first, F.col("doc_id").eqNullSafe(F.col("of_id")), "left_semi").select(*DOCUMENT)


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with secrets replaced in their text (operator 9)."""
    return secret_scan.mask(docs.select(*DOCUMENT))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as its source's target takes it (operator 7)."""
    return source_mix.mixed(docs.select(*DOCUMENT))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, lang, source, n_tokens, ids (operator 2)."""
    tokens = byte_bpe.encode(docs.select("doc_id", "lang", "source", "text"), byte_bpe.vocabulary_path("byte_bpe_50k.json"))
    return tokens.select("doc_id", "lang", "source", F.size("ids").cast("bigint").alias("n_tokens"), "ids")


STAGES = [("quality classifier", judge), ("n-gram jaccard join", deduplicate), ("secret scans", mask_secrets), ("mixing sources", mix_sources), ("bpe encoding", encode)]

#: The language model has no SQL form, so the rows of the whole have none; each stage is tested by itself.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = materialize(stage(spark, docs, sf_dir), f"stage-{k}")
    return docs
