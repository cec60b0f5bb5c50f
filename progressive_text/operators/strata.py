"""Strata of a table: from a column, from K-means on vectors, or from a fixed number of K-means rounds; and their overlay."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from math import ceil, e, log

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.vectors import unit


def strata_bounds(n: int, k: int, base: float = e) -> tuple[int, int]:
    """First and largest number of strata from the number of rows and of categories: K log N and 2 K log N, rounded up."""
    if n <= 1:
        return 1, 1
    return ceil(k * log(n, base)), ceil(2 * k * log(n, base))


def column_strata(df: DataFrame, column: str, most: int = 10_000) -> DataFrame:
    """df with `stratum`: the number of the column's value in order. Nulls are the last stratum. More than `most` values are
    refused: such a column is no stratum."""
    found = df.select(column).distinct().limit(most + 2).collect()
    if len(found) > most + 1:
        raise ValueError(f"{column} has more than {most} values")
    values = sorted(r[0] for r in found if r[0] is not None)
    table = df.sparkSession.createDataFrame([(v, i) for i, v in enumerate(values)] or [(None, 0)], f"_v {dict(df.dtypes)[column]}, _s int")
    return df.join(F.broadcast(table), F.col(column) == F.col("_v"), "left").withColumn("stratum", F.coalesce("_s", F.lit(len(values)))).drop("_v", "_s")


def assign_nearest(df: DataFrame, vector: str, centroids: np.ndarray, metric: str = "cosine") -> DataFrame:
    """df with `stratum`, the nearest centroid. Map side only: a matrix product for each Arrow batch, no row is expanded.
    Null and zero vectors go to a last stratum of their own, number len(centroids)."""
    at, own = unit(centroids) if metric == "cosine" else centroids, len(centroids)

    @F.pandas_udf("int")
    def nearest(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for vectors in parts:
            out = np.full(len(vectors), own, np.int32)
            good = np.array([v is not None and len(v) == at.shape[1] and bool(np.any(v)) for v in vectors], bool)
            if good.any():
                x = np.stack(vectors[good].to_numpy()).astype(np.float64)
                x = unit(x) if metric == "cosine" else x
                score = x @ at.T if metric == "cosine" else 2 * x @ at.T - (at * at).sum(1)
                out[good] = score.argmax(1)
            yield pd.Series(out)

    return df.withColumn("stratum", nearest(vector))


def kmeans_strata(df: DataFrame, h: int, vector: str = "embedding", metric: str = "cosine", seed: int = 42, fit_rows: int = 1_000_000, bisecting: bool = False) -> tuple[DataFrame, np.ndarray]:
    """(df with stratum, centroids): MLlib K-means, or its bisecting form, fitted on at most about fit_rows rows; all rows are assigned."""
    from pyspark.ml.clustering import BisectingKMeans, KMeans
    from pyspark.ml.functions import array_to_vector

    usable = df.where(F.col(vector).isNotNull() & F.exists(vector, lambda x: x != 0))
    n = usable.count()
    if n == 0:
        return df.withColumn("stratum", F.lit(0)), np.zeros((0, 1))
    if min(h, n) < 2:  # K-means needs two clusters; one stratum holds all rows with a vector
        centroids = np.ones((1, len(usable.select(vector).first()[0])))
        return assign_nearest(df, vector, centroids, metric), centroids
    if n > fit_rows:
        usable = usable.where(F.pmod(F.xxhash64(vector, F.lit(seed)), F.lit(1 << 30)) < int(fit_rows / n * (1 << 30)))
    kind = BisectingKMeans if bisecting else KMeans
    model = kind(k=min(h, n), seed=seed, distanceMeasure=metric, featuresCol="_v").fit(usable.select(array_to_vector(F.col(vector).cast("array<double>")).alias("_v")))
    centroids = np.array(model.clusterCenters())
    return assign_nearest(df, vector, centroids, metric), centroids


def lloyd_seeds(df: DataFrame, key: str, h: int, vector: str = "embedding", seed: int = 42) -> DataFrame:
    """stratum, centre: the vectors of the h rows of lowest md5 rank."""
    from .order import first_n

    few = first_n(df.where(F.col(vector).isNotNull()).select(key, vector), key, h, seed)
    return few.select((F.col("position") - 1).cast("int").alias("stratum"), F.col(vector).cast("array<double>").alias("centre"))


def lloyd_round(df: DataFrame, key: str, centres: DataFrame, vector: str = "embedding") -> DataFrame:
    """key, stratum by largest cosine (ties: lower number), in DataFrame functions; h centres are broadcast."""
    from ..functions.vectors import cosine

    pairs = df.select(key, vector).crossJoin(F.broadcast(centres)).withColumn("_near", F.round(cosine(vector, "centre"), 9))
    return pairs.groupBy(key).agg(F.max_by("stratum", F.struct("_near", -F.col("stratum"))).alias("stratum"))


def lloyd_strata(df: DataFrame, key: str, h: int, rounds: int = 5, vector: str = "embedding", seed: int = 42) -> tuple[DataFrame, np.ndarray]:
    """Repeatable K-means: md5-ranked seeds, a fixed number of rounds, centres are mean unit vectors (h times d numbers to the driver)."""
    seeds = sorted(lloyd_seeds(df, key, h, vector, seed).collect(), key=lambda r: r.stratum)
    centres = unit(np.array([r.centre for r in seeds], np.float64)) if seeds else np.zeros((0, 1))
    for _ in range(rounds - 1):
        sums = _vector_sums(assign_nearest(df.select(vector), vector, centres), "stratum", vector)
        centres = np.stack([unit(sums[i][1][None])[0] if i in sums else c for i, c in enumerate(centres)])
    return assign_nearest(df, vector, centres), centres


def _vector_sums(df: DataFrame, by: str, vector: str) -> dict[int, tuple[int, np.ndarray]]:
    """(count, sum of unit vectors) by stratum; each task sends one row a stratum."""

    def run(parts: Iterable[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total: dict[int, list] = {}
        for part in parts:
            part = part[part[vector].notna()]
            for h, rows in part.groupby(by):
                x = unit(np.stack(rows[vector].to_numpy()).astype(np.float64))
                held = total.setdefault(int(h), [0, np.zeros(x.shape[1])])
                held[0] += len(x)
                held[1] += x.sum(0)
        yield pd.DataFrame({"h": list(total), "n": [x[0] for x in total.values()], "s": [x[1].tolist() for x in total.values()]})

    rows = df.select(by, vector).mapInPandas(run, "h int, n bigint, s array<double>")
    places = rows.select("h", "n", F.posexplode("s").alias("i", "x")).groupBy("h", "i").agg(F.sum("n").alias("n"), F.sum("x").alias("x"))
    out: dict[int, tuple[int, np.ndarray]] = {}
    for r in places.groupBy("h").agg(F.first("n").alias("n"), F.array_sort(F.collect_list(F.struct("i", "x"))).alias("s")).collect():
        out[r.h] = (r.n, np.array([p.x for p in r.s]))
    return out


def sizes(assigned: DataFrame, stratum: str = "stratum") -> DataFrame:
    """stratum, n_total, weight (share of all rows)."""
    counts = assigned.groupBy(stratum).agg(F.count("*").alias("n_total"))
    return counts.withColumn("weight", F.col("n_total") / F.sum("n_total").over(Window.partitionBy(F.lit(1))))


def overlay(base: DataFrame, moves: DataFrame, key: str = "key") -> DataFrame:
    """base (key, stratum, ...) with the latest move of each key (t, key, to_stratum) applied."""
    last = moves.groupBy(key).agg(F.max_by("to_stratum", "t").alias("_to"))
    return base.join(last, key, "left").withColumn("stratum", F.coalesce("_to", "stratum")).drop("_to")
