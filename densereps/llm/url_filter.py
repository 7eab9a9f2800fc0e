"""URL filter: host-suffix and path-prefix expressions of each URL meet the rules on short hash prefixes.

Only DataFrame functions. Defined results: a null URL, or one without "://", has empty host and path and gets
the default verdict unless a rule has an empty host; of several rules that fit, the longest wins, then the one
with the longer host, then block; two rules with the same host and path count as one, block before allow. Rules
with a null in any column are left out. Repeated rows keep their own verdicts; columns besides the asked ones
are not read, so their names can't clash. Empty tables give empty results.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from densereps.plans.broadcasts import checked_join

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Hex digits of a digest that the join compares first.
PREFIX = 8


def host_of(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(url, r"://([^/?#]*)", 1), UPPER, LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"://[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_table(spark: SparkSession, rules: list[tuple[str, str, str]]) -> DataFrame:
    """Rules as (verdict, host, path)."""
    return spark.createDataFrame(rules, "verdict string, host string, path string")


def filter_urls(
    pages: DataFrame, rules: DataFrame, id_col: str = "page_id", url_col: str = "url", default: str = "allow"
) -> DataFrame:
    """(id, url, host, path, rule, verdict) for every row of pages; rules has host, path, verdict."""
    clean = (
        rules.select(F.translate("host", UPPER, LOWER).alias("h"), F.col("path").alias("p"), "verdict")
        .na.drop()
        .groupBy("h", "p")
        .agg(F.max(F.col("verdict") == "block").alias("blocks"))
    )
    shape = clean.agg(
        F.max(F.size(F.split("h", r"\."))).alias("labels"), F.sort_array(F.collect_set(F.length("p"))).alias("lengths")
    ).first()
    labels, lengths = shape["labels"] or 1, list(shape["lengths"] or [])
    digest = F.sha2(F.concat("h", "p"), 256)
    known = clean.select(
        F.substring(digest, 1, PREFIX).alias("r_prefix"), digest.alias("r_digest"), F.col("blocks")
    )
    rows = pages.select(
        F.monotonically_increasing_id().alias("rid"), F.col(id_col).alias("id"), F.col(url_col).alias("url"),
        host_of(F.col(url_col)).alias("host"), path_of(F.col(url_col)).alias("path"),
    )
    parts = F.split("host", r"\.")
    hosts = F.transform(
        F.sequence(F.greatest(F.lit(1), F.size(parts) - F.lit(labels - 1)), F.size(parts)),
        lambda i: F.array_join(F.slice(parts, i, F.size(parts)), "."),
    )
    paths = F.filter(F.array(*map(F.lit, lengths)).cast("array<int>"), lambda n: n <= F.length("path"))
    tried = (
        rows.withColumn("h", F.explode(hosts))
        .withColumn("n", F.explode_outer(paths))
        .withColumn("e", F.concat("h", F.substring(F.col("path"), F.lit(1), F.col("n"))))
        .withColumn("digest", F.sha2("e", 256))
        .withColumn("prefix", F.substring("digest", 1, PREFIX))
    )
    met = checked_join(tried, known, F.col("prefix") == F.col("r_prefix"), "left")
    # Precedence as one number: total length, host length, block before allow; it also tells which rule it is.
    weight = F.when(
        F.col("digest") == F.col("r_digest"),
        F.shiftleft(F.length("e").cast("long"), 32)
        + F.shiftleft(F.length("h").cast("long"), 1)
        + F.col("blocks").cast("long"),
    )
    best = met.groupBy("rid", "id", "url", "host", "path").agg(F.max(weight).alias("w"))
    size, hlen = F.shiftright("w", 32).cast("int"), F.shiftright(F.col("w").bitwiseAND(F.lit(0xFFFFFFFF)), 1).cast("int")
    rule = F.when(
        F.col("w").isNotNull(),
        F.concat(
            F.substring(F.col("host"), F.length("host") - hlen + 1, hlen), F.substring(F.col("path"), F.lit(1), size - hlen)
        ),
    )
    verdict = (
        F.when(F.col("w").isNull(), F.lit(default))
        .when(F.col("w").bitwiseAND(F.lit(1)) == 1, F.lit("block"))
        .otherwise(F.lit("allow"))
    )
    return best.select(
        F.col("id").alias(id_col), F.col("url").alias(url_col), "host", "path", rule.alias("rule"), verdict.alias("verdict")
    )
