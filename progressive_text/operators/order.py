"""Draw order: a fixed permutation by md5, without any global sort.

The rank of a row is md5(seed:key). Ranks fall into slices by their first digits, uniformly and whatever the data, so
the position of a row in its stratum is the count of rows in earlier slices (an aggregate of few rows) and its place
inside one slice (a sort of a small part). A stratum with a third of all rows is as many slices as the others.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

SLICES = 256
#: Rows of a slice that one task sorts, where the number of rows is known.
SLICE_ROWS = 1_000_000


def draw_rank(key: str | Column, seed: int = 42) -> Column:
    key = F.col(key) if isinstance(key, str) else key
    return F.md5(F.concat_ws(":", F.lit(str(seed)), key.cast("string")))


def slice_of(rank: str | Column, slices: int = SLICES) -> Column:
    """Up to 65536 slices by the first four hex digits."""
    head = F.conv(F.substring(rank, 1, 4), 16, 10).cast("int")
    return F.floor(head * slices / 65536).cast("int")


def slices_for(total: int, batch: int = SLICE_ROWS) -> int:
    """Slices for a table of `total` rows that is drawn from in batches: a slice holds some batches, and few more than
    SLICE_ROWS rows."""
    return max(1, min(65536, -(-total // min(SLICE_ROWS, max(8000, 8 * batch)))))


def positions(df: DataFrame, by: Sequence[str], rank: str = "draw_rank", slices: int = SLICES, name: str = "position") -> DataFrame:
    """df with `position`, 1, 2, ... by rank within each group of `by` (all rows for an empty `by`). Nulls group together."""
    sliced = df.withColumn("_slice", slice_of(rank, slices))
    sizes = sliced.groupBy(*by, "_slice").agg(F.count("*").alias("_n"))
    # few rows: groups times slices
    over = Window.partitionBy(*(by or [F.lit(1)])).orderBy("_slice").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.withColumn("_before", F.coalesce(F.sum("_n").over(over), F.lit(0))).drop("_n")
    inside = F.row_number().over(Window.partitionBy(*by, "_slice").orderBy(rank))
    ranked = sliced.withColumn("_inside", inside)
    starts = starts.select(*[F.col(c).alias(f"_g_{c}") for c in by], F.col("_slice").alias("_s"), "_before")
    same = F.col("_slice") == F.col("_s")
    for c in by:  # plain equality keeps the partitioning of the window, so the rows are not moved again
        same = same & (F.col(c).eqNullSafe(F.col(f"_g_{c}")) if df.schema[c].nullable else F.col(c) == F.col(f"_g_{c}"))
    return ranked.join(starts, same).withColumn(name, (F.col("_before") + F.col("_inside")).cast("bigint")).select(*df.columns, name)


def rank_pool(df: DataFrame, key: str, strata: Sequence[str] = (), seed: int = 42, slices: int = SLICES) -> DataFrame:
    """df with draw_rank and position in its stratum."""
    return positions(df.withColumn("draw_rank", draw_rank(key, seed)), list(strata), "draw_rank", slices)


def take_next(pool: DataFrame, allocation: dict, stratum: str = "stratum", drawn: DataFrame | None = None, key: str = "key") -> DataFrame:
    """The next n_h undrawn rows of each stratum h by rank, under whatever strata the pool has now.

    `allocation` has one number for each stratum. With `drawn` (keys), positions are counted among the others.
    """
    left = pool.drop("position")
    if drawn is not None:
        left = left.join(drawn.select(key), key, "left_anti")
    wanted = [(h, n) for h, n in allocation.items() if n > 0]
    if not wanted:
        return positions(left.where("false"), [stratum])
    table = pool.sparkSession.createDataFrame(wanted, f"_h {dict(pool.dtypes)[stratum]}, _n bigint")
    return positions(left, [stratum]).join(F.broadcast(table), F.col(stratum) == F.col("_h")).where("position <= _n").select(*left.columns, "position")


def first_n(df: DataFrame, key: str, n: int, seed: int = 42) -> DataFrame:
    """A simple random draw of n rows from the whole table."""
    return rank_pool(df, key, seed=seed).where(F.col("position") <= n)
