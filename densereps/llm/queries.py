"""The queries of this subpackage and their SQL; each applies one operator to its whole table."""

from __future__ import annotations

import corpus_pipeline
import public_tokenizers
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from densereps.llm import bpe, decontaminate, langid, licenses, line_dedup, ppm, simhash, topk, toxicity, url_filter

#: Fixed rules of the URL query: verdict, host, path.
URL_RULES = [
    ("allow", "com", "/"),
    ("block", "example.com", "/en/"),
    ("allow", "www.example.com", "/en/"),
    ("block", "net", "/es/"),
    ("block", "net", "/fr/"),
]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fold_of(n: int) -> Column:
    """crc32 of doc_id as text, mod n; a null id counts as 0."""
    return F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(n)), F.lit(0))


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    seen = licenses.scan_licenses(table(spark, sf_dir, "documents").select("doc_id", "text"), "scan")
    sure = F.filter("scan.matches", lambda m: m["confirmed"])
    return seen.select(
        "doc_id", "scan.blocks", "scan.licenses", F.size(sure).alias("n_confirmed"),
        F.round(F.array_max(F.transform(sure, lambda m: m["saved"])), 6).alias("best_saved"),
        F.array_min(F.transform(sure, lambda m: m["different"])).alias("least_different"),
    )


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    held_out = fold_of(4) == 2
    found = langid.identify(docs, ~held_out, "found")
    return found.select("doc_id", held_out.alias("held_out"), "found.lang_pred", "found.score", "found.cross_entropy", "found.rejected")


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    scored, thresholds = toxicity.score(docs, table(spark, sf_dir, "labels"), "p")
    return scored.select(
        "doc_id", F.col("p.toxic").alias("score"), (F.col("p.toxic") >= thresholds["toxic"]).alias("toxic"),
        F.col("p.low_quality").alias("low_quality_score"),
    )


def op10_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return ppm.score_documents(docs, fold_of(10) == 0)


def op8_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    rules = url_filter.rule_table(spark, URL_RULES)
    return url_filter.filter_urls(table(spark, sf_dir, "pages"), rules).drop("url")


def op4_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    seen = decontaminate.scan_contamination(docs, table(spark, sf_dir, "benchmark"), "scan")
    return seen.select(
        "doc_id", "scan.n_words", "scan.n_hit", F.size("scan.item_ids").cast("long").alias("n_items"),
        F.sha2(F.array_join("scan.item_ids", ","), 256).alias("items_sha256"),
        decontaminate.is_contaminated(F.col("scan")).alias("contaminated"),
    )


def op5_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select(
        F.col("id").alias("doc_id"), F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), F.col("component").alias("component_id")
    )


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    kept = line_dedup.drop_lines(docs, "n_lines", "n_dropped")
    return kept.select("doc_id", "n_lines", "n_dropped", F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


def op3_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings")
    return topk.top_k(vectors, vectors.filter(F.col("vec_id") % 50 == 0))


def op7_byte_level_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    path = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
    coded = bpe.encode_and_decode(docs, "codes", path, public_tokenizers.PATTERN)
    return coded.select(
        "doc_id", "codes.n_tokens", F.sha2("codes.ids", 256).alias("ids_sha256"), F.sha2("codes.decoded", 256).alias("decoded_sha256")
    )


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {
    "op1_license_scan": op1_license_scan,
    "op2_language_id": op2_language_id,
    "op3_exact_top_k": op3_exact_top_k,
    "op4_benchmark_decontamination": op4_benchmark_decontamination,
    "op5_simhash_near_dedup": op5_simhash_near_dedup,
    "op6_toxicity": op6_toxicity,
    "op7_byte_level_bpe": op7_byte_level_bpe,
    "op8_url_filter": op8_url_filter,
    "op9_line_dedup": op9_line_dedup,
    "op10_lm_scoring": op10_lm_scoring,
    "pipeline": pipeline,
}
