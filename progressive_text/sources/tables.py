"""The given tables, and the columns that workloads derive from them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def md5_number(text: Column) -> Column:
    """The first eight hex digits of md5 as a number; DuckDB: ('0x' || substr(md5(x), 1, 8))::BIGINT."""
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("bigint")


def with_counts(docs: DataFrame) -> DataFrame:
    """Synthetic like_count (below 1000) and view_count (below 10000) from the identifier."""
    number = lambda tag: md5_number(F.concat(F.lit(f"{tag}:"), F.col("doc_id").cast("string")))
    return docs.withColumns({"like_count": number("like") % 1000, "view_count": number("view") % 10000})


def labelled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that have labels, with class3: toxic, junk (low quality) or clean."""
    kind = F.when(F.col("toxic") == 1, "toxic").when(F.col("quality") == 0, "junk").otherwise("clean")
    return table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id").withColumn("class3", kind)


def balanced(df: DataFrame, flag: str, key: str = "doc_id", seed: int = 42) -> DataFrame:
    """As many rows of flag 0 as of flag 1: those of lowest md5 rank of the more frequent kind."""
    from ..operators.order import draw_rank, positions

    least = df.groupBy(flag).count().agg(F.min("count").alias("_least"))
    ranked = positions(df.withColumn("draw_rank", draw_rank(key, seed)), [flag], "draw_rank")
    return ranked.crossJoin(F.broadcast(least)).where("position <= _least").drop("position", "_least", "draw_rank")


def with_page_language(pages: DataFrame) -> DataFrame:
    """page_lang: the two letters that are a part of the URL's path."""
    return pages.withColumn("page_lang", F.regexp_extract("url", "/([a-z]{2})/", 1))


def event_time(events: DataFrame) -> DataFrame:
    """ts as a TIMESTAMP, which watermarks need."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def on_grid(events: DataFrame, seconds: int) -> DataFrame:
    """ts as the multiple of `seconds` that SQL's epoch(ts)::BIGINT // seconds names: the cast rounds to the nearest second (a
    half to the even one), so the last half second before a multiple is the next one's; the division truncates towards 1970."""
    whole = F.rint(F.unix_micros("ts") / 1e6).cast("bigint")
    return events.withColumn("_whole", whole).withColumn("ts", F.timestamp_seconds(F.expr(f"_whole div {seconds}") * seconds)).drop("_whole")
