"""Corpus pipeline: five stages over documents, each calling one operator of densereps.llm.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written and read again as the next stage's
docs. All stages but the last return the columns of documents:

toxicity       drops the documents whose toxicity reaches the threshold learned from `labels`;
line_dedup     drops lines that at least three documents hold, except in the largest doc_id with each;
near_dedup     keeps the least doc_id of each group of near copies: texts linked, also over others, by sets of five-word
               shingles with a Jaccard similarity of 0.8 or more; fingerprints and their pivot distances join sets first,
               set prefixes find what those can't;
decontaminate  drops the documents of which at least one word in 20 lies in a window of a `benchmark` item;
encode         returns doc_id, lang, source, ids (little-endian unsigned 32-bit integers), n_tokens, and whether
               decoding gives the text back.

n_chars follows the text after line dedup. Nulls, empty texts and repeated rows have the results that the operators
define; extra columns pass through all stages but the last.
"""

from __future__ import annotations

import os
import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from densereps.llm import bpe, decontaminate, line_dedup, near_copies, toxicity
from densereps.plans.lineage import forget_unused, remove_at_end, shared_dir


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def stage_toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.remove_toxic(docs, _table(spark, sf_dir, "labels"))


def stage_line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    kept = line_dedup.drop_lines(docs)
    return kept.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in kept.columns else kept


def stage_near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_copies.keep_one(docs)


def stage_decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.remove_contamination(docs, _table(spark, sf_dir, "benchmark"))


def stage_encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    path = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
    coded = bpe.encode_and_decode(docs.select("doc_id", "lang", "source", "text"), "codes", path, public_tokenizers.PATTERN)
    same = F.col("codes.decoded") == F.coalesce("text", F.lit("")).cast("binary")
    return coded.select("doc_id", "lang", "source", "codes.ids", "codes.n_tokens", same.alias("round_trip"))


STAGES = [
    ("toxicity", stage_toxicity),
    ("line_dedup", stage_line_dedup),
    ("near_dedup", stage_near_dedup),
    ("decontaminate", stage_decontaminate),
    ("encode", stage_encode),
]

#: SQL can't express the trained classifier or the merges; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; what each returns is written to the shared folder, read again, and kept to the end."""
    at = os.path.join(shared_dir(spark), f"corpus-pipeline-{uuid.uuid4().hex}")
    remove_at_end(spark, at)
    docs = _table(spark, sf_dir, "documents")
    for i, (name, stage) in enumerate(STAGES):
        out = os.path.join(at, f"{i}-{name}")
        stage(spark, docs, sf_dir).write.parquet(out)
        docs = spark.read.parquet(out)
        forget_unused(spark)
    return docs
