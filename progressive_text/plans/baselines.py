"""What progressive queries are compared with."""

from __future__ import annotations

from dataclasses import replace
from math import sqrt

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.estimate import random_share
from ..operators.labelers import Labeler
from ..operators.order import draw_rank
from .filter_engine import progressive_filter
from .group_engine import GroupConfig, progressive_group
from .layout import ALL, lay_out
from .query import Clock, DrawLog, ProgressLog, Stop
from .select_engine import progressive_select


def sem_map(df: DataFrame, labeler: Labeler, text: str, name: str = "label") -> DataFrame:
    """A batch semantic projection: every row is labelled."""
    return labeler.label(df, text).withColumnRenamed("label", name)


def sem_filter(df: DataFrame, labeler: Labeler, text: str) -> DataFrame:
    """A batch semantic filter: rows for which the labeler says true."""
    return labeler.label(df, text).where("is_valid AND label").drop("label", "is_valid")


def sem_group(df: DataFrame, labeler: Labeler, text: str, *aggregates) -> DataFrame:
    """A batch semantic grouping: category and aggregates (by default the number of rows)."""
    labelled = labeler.label(df, text).where("is_valid").withColumn("category", F.col("label").cast("string"))
    return labelled.groupBy("category").agg(*(aggregates or [F.count("*").alias("n_rows")]))


def full_scan(df: DataFrame, labeler: Labeler, text: str, *aggregates, by: list[str] | None = None, where: str = "is_valid", key: str = "doc_id", seed: int = 42) -> DataFrame:
    """The naive way: all rows in random order, one answer at the end."""
    shuffled = df.repartition(F.substring(draw_rank(key, seed), 1, 8))
    return labeler.label(shuffled, text).where(where).groupBy(*(by or [])).agg(*aggregates)


def ground_truth(df: DataFrame, *aggregates, by: list[str] | None = None, where: str | None = None) -> DataFrame:
    """The exact answer from columns that hold the labels."""
    return (df.where(where) if where else df).groupBy(*(by or [])).agg(*aggregates)


def random_filter(df: DataFrame, key: str, text: str, labeler: Labeler, value: str, **how) -> ProgressLog:
    """Online aggregation over a filter with simple random draws."""
    return progressive_filter(df, key, text, labeler, value, stratum=None, mode="random", **how)


def random_select(df: DataFrame, key: str, text: str, labeler: Labeler, **how) -> ProgressLog:
    return progressive_select(df, key, text, labeler, design="uniform", **how)


def static_group(df: DataFrame, key: str, text: str, labeler: Labeler, categories: list, config: GroupConfig | None = None, **how) -> ProgressLog:
    """Strata clustered once and never adjusted."""
    return progressive_group(df, key, text, labeler, categories, config=replace(config or GroupConfig(), adjust=False), **how)


def random_group(df: DataFrame, key: str, text: str, labeler: Labeler, categories: list, alpha: float = 0.95, round_fraction: float = 0.1, seed: int = 42, stop: Stop | None = None, clock: Clock | None = None, scope: str = "per_category") -> ProgressLog:
    """Shares of categories from simple random draws. scope 'pooled' adds up the variances of all categories, as the
    strata's printed interval does, so that intervals are alike."""
    spark, stop = df.sparkSession, stop or Stop(relative=False)
    rows = lay_out(df, key, text, labeler, {}, batch_share=round_fraction, seed=seed)
    total = rows.total
    log = ProgressLog(spark, total, clock or Clock())
    batch, counts, calls, draws = max(1, round(total * round_fraction)), dict.fromkeys(categories, 0), 0, DrawLog(spark)
    for step in range(-(-total // batch)):
        new = draws.append(step, labeler.label(rows.take({ALL: (step * batch, (step + 1) * batch)}), text).select(key, "label", "is_valid"))
        before = calls
        for r in new.groupBy("is_valid", "label").count().collect():
            calls += r["count"]
            if r.is_valid and r.label in counts:
                counts[r.label] += r["count"]
        shares = {c: random_share(counts[c], calls, total, alpha, len(categories)) for c in categories}
        pooled = sqrt(sum(w * w for _, w in shares.values()))
        cells = [{"grp": str(c), "n_valid": calls, "estimate": p, "half_width": pooled if scope == "pooled" else w, "half_width_own": w, "share": True} for c, (p, w) in shares.items()]
        if stop.reached(log.publish(step, calls, calls - before, cells, calls == total), step, calls):
            break
    log.details["draws"] = draws
    return log
