"""The queries of this subpackage, each over its whole table, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import bpe_replay, license_scan, media_chunks, mixing, near_dedup, quality_rules, secret_scan, substring_dedup, training_order, url_filter


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_secret_scan": lambda s, d: secret_scan.scan(documents(s, d)),
        "op2_license_scan": lambda s, d: license_scan.scan(documents(s, d)),
        "op3_substring_dedup": lambda s, d: substring_dedup.remove_repeats(documents(s, d)),
        "op4_url_filter": lambda s, d: url_filter.match(url_filter.captures(table(s, d, "pages")), url_filter.entries(s).unionByName(url_filter.listed_hosts(table(s, d, "pages")))),
        "op5_training_order": lambda s, d: training_order.read_records(training_order.shards(documents(s, d))),
        "op6_near_dedup": lambda s, d: near_dedup.near_duplicates(documents(s, d)),
        "op7_bpe_replay": lambda s, d: bpe_replay.digests(documents(s, d)),
        "op8_quality_rules": lambda s, d: quality_rules.judge(documents(s, d), table(s, d, "labels")),
        "op9_mixing": lambda s, d: mixing.mix(documents(s, d)),
        "op10_media_chunks": lambda s, d: media_chunks.media_features(documents(s, d)),
    }


def oracle_sql() -> dict[str, str]:
    return {"op3_substring_dedup": substring_dedup.sql(), "op4_url_filter": url_filter.sql(), "op9_mixing": mixing.sql()}
