"""Relational operators around the methods that Spark has no single call for."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.vectors import unit


def asof_join(left: DataFrame, right: DataFrame, by: list[str], at: str, take: list[str], prefix: str = "last_") -> DataFrame:
    """left with the columns of the latest right row of the same `by` at or before `at` (null if there is none).

    Both sides meet in one sorted pass by key: a union and a last non-null value over the rows so far.
    """
    marked = right.select(*by, at, F.struct(at, *take).alias("_r"), F.lit(0).alias("_side"), *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns if c not in (*by, at)])
    rows = left.select(*by, at, F.lit(None).cast(marked.schema["_r"].dataType).alias("_r"), F.lit(1).alias("_side"), *[c for c in left.columns if c not in (*by, at)])
    over = Window.partitionBy(*by).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    seen = marked.unionByName(rows).withColumn("_seen", F.last("_r", ignorenulls=True).over(over)).where("_side = 1")
    return seen.select(*left.columns, F.col(f"_seen.{at}").alias(f"{prefix}{at}"), *[F.col(f"_seen.{c}").alias(f"{prefix}{c}") for c in take])


def interval_join(left: DataFrame, right: DataFrame, by: list[str], left_at: Column, right_at: Column, width: int) -> DataFrame:
    """Pairs of the same `by` with 0 <= left_at - right_at <= width (whole numbers), by equality of bins: a left row looks
    into its bin and the one before, so no nested loop."""
    lefts = left.withColumn("_la", left_at).withColumn("_bin", F.explode(F.array(F.floor(F.col("_la") / width), F.floor(F.col("_la") / width) - 1)))
    rights = right.select(*[F.col(c).alias(f"r_{c}") for c in right.columns], right_at.alias("_ra")).withColumn("_rbin", F.floor(F.col("_ra") / width))
    same = F.col("_bin") == F.col("_rbin")
    for c in by:
        same = same & (F.col(c) == F.col(f"r_{c}"))
    return lefts.join(rights, same & F.col("_ra").between(F.col("_la") - width, F.col("_la"))).drop("_bin", "_rbin", "_la", "_ra")


def top_k(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    """The first k rows of each group; Spark keeps k rows a task and group before it shuffles."""
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("rank") <= k)


def pre_aggregated_rollup(df: DataFrame, keys: list[str], sums: dict[str, Column]) -> DataFrame:
    """A rollup of sums that expands the finest groups in place of the rows."""
    fine = df.groupBy(*keys).agg(*[F.sum(c).alias(k) for k, c in sums.items()])
    return fine.rollup(*keys).agg(*[F.sum(k).alias(k) for k in sums], F.grouping_id().alias("level"))


def word_grams(text: Column, words: int = 8) -> Column:
    """Hashes of all runs of so many words of a text, each once; blocks on which texts that share a passage agree."""
    parts = F.split(F.trim(F.regexp_replace(text, r"\s+", " ")), " ")
    starts = lambda p: F.sequence(F.lit(1), F.greatest(F.size(p) - (words - 1), F.lit(1)))
    runs = lambda p: F.array_distinct(F.transform(starts(p), lambda i: F.xxhash64(F.array_join(F.slice(p, i, words), " "))))
    return F.transform(F.array(parts), runs)[0]  # a lambda's variable, so a text is split once


def semantic_join(left: DataFrame, right: DataFrame, left_blocks: Column, right_blocks: Column, keys: tuple[str, str], labeler, text: str) -> DataFrame:
    """Pairs that a labeler accepts, of those that agree on a block: arrays of hashes in both tables, by columns that only
    their own table has. Candidates are keys alone until they are distinct; whole rows are joined to these."""
    a = left.select(keys[0], F.explode(left_blocks).alias("_block"))
    b = right.select(keys[1], F.explode(right_blocks).alias("_block"))
    pairs = a.join(b, "_block").select(*keys).distinct()
    return labeler.label(pairs.join(left, keys[0]).join(right, keys[1]), text).where("is_valid AND label")


def similarity_join(df: DataFrame, key: str, vector: str, by: str, gamma: float, block_rows: int = 2000) -> DataFrame:
    """a, b: pairs of rows of one group whose cosine is above gamma, a before b.

    A group is cut into blocks of about block_rows, and each two blocks meet in one matrix product: a task holds two blocks,
    however large a group is, and only pairs above gamma are rows.
    """
    most = df.groupBy(by).count().agg(F.max("count")).first()[0] or 1
    blocks = -(-most // block_rows)
    rows = df.where(F.col(vector).isNotNull()).select(F.col(key).alias("k"), F.col(by).alias("g"), F.col(vector).cast("array<double>").alias("x"), F.pmod(F.xxhash64(key), F.lit(blocks)).cast("int").alias("own"))
    first = rows.select("k", "g", "x", F.col("own").alias("i"), F.explode(F.sequence(F.col("own"), F.lit(blocks - 1))).alias("j"), F.lit(0).alias("side"))
    second = rows.select("k", "g", "x", F.explode(F.sequence(F.lit(0), F.col("own"))).alias("i"), F.col("own").alias("j"), F.lit(1).alias("side"))
    kind = dict(df.dtypes)[key]

    def meet(part: pd.DataFrame) -> pd.DataFrame:
        p, q = part[part.side == 0], part[part.side == 1]
        if p.empty or q.empty:
            return pd.DataFrame({"a": p.k[:0], "b": p.k[:0]})
        near = np.round(unit(np.stack(p.x.to_numpy())) @ unit(np.stack(q.x.to_numpy())).T, 9) > gamma
        at, to = np.nonzero(near)
        x, y = p.k.to_numpy()[at], q.k.to_numpy()[to]
        if part.i.iloc[0] == part.j.iloc[0]:
            x, y = x[x < y], y[x < y]
        return pd.DataFrame({"a": np.minimum(x, y), "b": np.maximum(x, y)})

    return first.unionByName(second).groupBy("g", "i", "j").applyInPandas(meet, f"a {kind}, b {kind}")


def semantic_top_k(df: DataFrame, labeler, text: str, k: int, key: str) -> DataFrame:
    """The k rows of highest score by a labeler; ties by key."""
    return labeler.label(df, text).where("is_valid").orderBy(F.desc("label"), key).limit(k)


def semantic_dedupe(df: DataFrame, text: str, key: str) -> DataFrame:
    """One row, of smallest key, for each text."""
    first = df.groupBy(F.sha2(text, 256).alias("_hash")).agg(F.min(key).alias("_key"))
    return df.join(first.select("_key"), F.col(key) == F.col("_key"), "left_semi")
