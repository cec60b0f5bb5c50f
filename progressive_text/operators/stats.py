"""Statistics of draws by stratum. Draw logs are aggregated once; what comes out has a row for each stratum (and category)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .estimate import GroupState


def valid_rate(draws: DataFrame, stratum: str = "stratum", label: str = "label") -> DataFrame:
    """stratum, n_drawn, n_valid, p_hat of a boolean label; no answer is false."""
    hit = F.coalesce(F.col(label).cast("int"), F.lit(0))
    return draws.groupBy(stratum).agg(F.count("*").alias("n_drawn"), F.sum(hit).cast("bigint").alias("n_valid"), F.avg(hit).alias("p_hat"))


def frequencies(draws: DataFrame, categories: list, stratum: str = "stratum") -> DataFrame:
    """stratum, category, x: drawn labels of the domain. Labels outside it are draws that fall in no category."""
    return draws.where(F.col("label").isin(*categories)).groupBy(stratum, F.col("label").alias("category")).agg(F.count("*").alias("x"))


def stratum_state(draws: DataFrame, sizes: DataFrame, categories: list, stratum: str = "stratum") -> DataFrame:
    """stratum, n_total, n_drawn, dominant, heterogeneity, norm_heterogeneity of all strata, drawn from or not."""
    k = len(categories)
    drawn = draws.groupBy(stratum).agg(F.count("*").alias("n_drawn"))
    p = F.col("x") / F.col("n_drawn")
    parts = frequencies(draws, categories, stratum).join(drawn, stratum)
    per = parts.groupBy(stratum).agg(F.sum(p * (1 - p)).alias("heterogeneity"), F.min(F.struct((-F.col("x")).alias("x"), F.col("category").cast("string").alias("c"))).alias("_top"))
    state = sizes.select(stratum, "n_total").join(drawn, stratum, "left").join(per, stratum, "left")
    het = F.coalesce("heterogeneity", F.lit(0.0))
    return state.select(
        stratum, "n_total", F.coalesce("n_drawn", F.lit(0)).cast("bigint").alias("n_drawn"), F.col("_top.c").alias("dominant"),
        het.alias("heterogeneity"), (het / (1 - 1 / k) if k > 1 else F.lit(0.0)).alias("norm_heterogeneity"),
    )


def group_states(draws: DataFrame, sizes: dict, categories: list, stratum: str = "stratum") -> dict[int, GroupState]:
    """The same for the driver: strata times categories numbers."""
    rows = draws.groupBy(stratum, "label").agg(F.count("*").alias("x")).collect()
    drawn, counts = dict.fromkeys(sizes, 0), {h: {} for h in sizes}
    for r in rows:
        drawn[r[stratum]] += r.x
        if r.label in categories:
            counts[r[stratum]][r.label] = r.x
    return {h: GroupState(sizes[h], drawn[h], counts[h]) for h in sizes}


def purity(states: DataFrame) -> DataFrame:
    """Greatest and size-weighted mean normalised heterogeneity."""
    w = F.col("n_total")
    return states.agg(F.max("norm_heterogeneity").alias("worst"), (F.sum(w * F.col("norm_heterogeneity")) / F.sum(w)).alias("weighted"))


def cumulative_valids(draws: DataFrame, valid: str = "is_valid", order: str = "step") -> DataFrame:
    """step, calls, valids so far: sums by step, then a window over the steps."""
    steps = draws.groupBy(order).agg(F.count("*").alias("calls"), F.sum(F.col(valid).cast("bigint")).alias("valids"))
    over = Window.partitionBy(F.lit(1)).orderBy(order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return steps.select(order, F.sum("calls").over(over).alias("calls"), F.sum("valids").over(over).alias("valids"))
