"""Vectors as arrays: products, cosine, mean of a set."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def dot(a: str | Column, b: str | Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: str | Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: str | Column, b: str | Column) -> Column:
    """Null for null and zero vectors."""
    return dot(a, b) / F.nullif(norm(a) * norm(b), F.lit(0.0))


def mean_vector(df: DataFrame, by: str, vector: str = "embedding") -> DataFrame:
    """by, mean: sums by place merge in partial aggregation; only the d sums of a group meet."""
    places = df.select(by, F.posexplode(vector).alias("_place", "_x"))
    means = places.groupBy(by, "_place").agg(F.avg(F.col("_x").cast("double")).alias("_mean"))
    ordered = F.array_sort(F.collect_list(F.struct("_place", "_mean")))
    return means.groupBy(by).agg(F.transform(ordered, lambda p: p["_mean"]).alias("mean"))


def unit(rows: np.ndarray) -> np.ndarray:
    """Rows of length one; zero rows stay zero."""
    size = np.linalg.norm(rows, axis=1, keepdims=True)
    return np.divide(rows, size, out=np.zeros_like(rows, dtype=np.float64), where=size > 0)
