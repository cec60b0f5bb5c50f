"""Cost and accuracy measures over progress logs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def absolute_error(progress: DataFrame, truth: DataFrame, column: str = "estimate") -> DataFrame:
    """Progress with error and relative_error against truth (grp, truth)."""
    error = F.abs(F.col(column) - F.col("truth"))
    return progress.join(F.broadcast(truth), "grp").withColumns({"error": error, "relative_error": error / F.abs(F.nullif("truth", F.lit(0.0)))})


def interval(progress: DataFrame) -> DataFrame:
    return progress.select("step", "grp", "calls", "half_width", (2 * F.col("half_width")).alias("width"))


def time_to_bound(progress: DataFrame, bound: float = 0.05, by: str = "half_width", relative: bool = True, min_valid: int = 30, sustained: bool = False, cost: str = "calls") -> DataFrame:
    """grp, cost of the first step within the bound (null if none is), with sustained=True of the first from which all are.

    by 'half_width', 'half_width_stratified' or 'error' (after absolute_error). cost: 'calls', 'calls_fraction' or 'virtual_seconds'.
    """
    scale = F.abs("estimate" if by != "error" else "truth") if relative else F.lit(1.0)
    good = F.coalesce((F.col(by) <= bound * scale) & (F.col("n_valid") >= min_valid), F.lit(False))
    flagged = progress.withColumn("_good", good)
    if sustained:
        over = Window.partitionBy("grp").orderBy(F.desc("step")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
        flagged = flagged.withColumn("_good", F.min(F.col("_good").cast("int")).over(over) == 1)
    return flagged.groupBy("grp").agg(F.min(F.when(F.col("_good"), F.col(cost))).alias("cost"))


def share_to_bound(progress: DataFrame, full: float, **how) -> DataFrame:
    """Mean over groups of cost to the bound, over the full-data cost; null unless all groups reach it."""
    reached = time_to_bound(progress, **how)
    share = F.when(F.count("cost") == F.count("*"), F.avg("cost") / full)
    return reached.agg(share.alias("share"), (1 / F.nullif(share, F.lit(0.0))).alias("speedup"))


def speedup(shares: DataFrame, column: str = "share") -> DataFrame:
    return shares.withColumn("speedup", 1 / F.nullif(F.col(column), F.lit(0.0)))


def label_accuracy(predicted: DataFrame, truth: DataFrame, key: str = "doc_id") -> DataFrame:
    """n and the share of rows where label is the truth's label; a missing answer is wrong."""
    joined = truth.select(key, F.col("label").alias("_t")).join(predicted.select(key, F.col("label").alias("_p")), key, "left")
    right = (F.col("_t").cast("string") == F.col("_p").cast("string")).cast("int")
    return joined.agg(F.count("*").alias("n"), F.avg(F.coalesce(right, F.lit(0))).alias("accuracy"))


def confusion(predicted: DataFrame, truth: DataFrame, categories: list, key: str = "doc_id") -> DataFrame:
    joined = truth.select(key, F.col("label").alias("truth")).join(predicted.select(key, F.col("label").alias("_p")), key)
    return joined.groupBy("truth").pivot("_p", categories).count().na.fill(0)


def scaleout(seconds: dict[int, float]) -> dict[int, float]:
    """Speed-up over one instance of times to the same bound."""
    return {i: seconds[1] / s for i, s in seconds.items()}


def mean_time(runs: DataFrame) -> DataFrame:
    return runs.groupBy("query").agg(F.avg("seconds").alias("mean_seconds"), F.count("*").alias("runs"))


def coverage(logs: DataFrame, truth: DataFrame, estimate: str = "estimate", width: str = "half_width") -> DataFrame:
    """Of logs with a seed column: by step and group, the share of seeds whose interval holds the truth."""
    joined = logs.where(F.col(width).isNotNull()).join(F.broadcast(truth), "grp")
    inside = F.abs(F.col(estimate) - F.col("truth")) <= F.col(width) + 1e-12
    return joined.groupBy("step", "grp").agg(F.avg(inside.cast("int")).alias("coverage"), F.count("*").alias("seeds"))
