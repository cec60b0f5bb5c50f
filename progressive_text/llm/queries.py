"""One query for each operator over its whole table, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import byte_bpe, digest, line_templates, media, near_dup, packing, quality, shard_table, sorted_shards, token_counts
from .common import documents


def _quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return quality.score(docs, quality.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_quality_classifier": _quality,
    "op2_byte_bpe": lambda spark, d: byte_bpe.round_trip(documents(spark, d)),
    "op3_line_dedup": lambda spark, d: line_templates.drop_recurring(documents(spark, d), report=True, by=line_templates.like_lines),
    "op4_sharding": lambda spark, d: shard_table.store_and_read(documents(spark, d)),
    "op5_best_fit_packing": lambda spark, d: packing.pack(documents(spark, d)),
    "op6_token_counts": lambda spark, d: token_counts.count_tokens(documents(spark, d)),
    "op7_fingerprints": lambda spark, d: digest.compare_with_next(documents(spark, d)),
    "op8_sorted_shards": lambda spark, d: sorted_shards.store_and_read(documents(spark, d)),
    "op9_minhash_near_dedup": lambda spark, d: near_dup.near_duplicates(documents(spark, d), words=2),
    "op10_media_columns": lambda spark, d: media.store_and_describe(documents(spark, d), media.BOTH),
}

ORACLES: dict[str, str] = {"op3_line_dedup": line_templates.LIKE_SQL, "op4_sharding": shard_table.ORACLE_SQL}
