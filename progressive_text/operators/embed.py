"""Text to vectors: given ones, hashed letter n-grams, or a model behind an interface."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from typing import Protocol

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


class Embedder(Protocol):
    def embed(self, df: DataFrame, text: str) -> DataFrame:
        """df with `embedding` array<float>."""


@dataclass(frozen=True)
class GivenVectors:
    column: str = "embedding"

    def embed(self, df: DataFrame, text: str = "") -> DataFrame:
        return df.withColumn("embedding", F.col(self.column).cast("array<float>"))


@dataclass(frozen=True)
class HashedNgramEmbedder:
    """Unit vectors of hashed counts of letter n-grams of the whole text; null and empty texts have a null vector."""

    n: int = 3
    d: int = 64

    def embed(self, df: DataFrame, text: str = "text") -> DataFrame:
        n, d = self.n, self.d

        def one(text: str | None) -> list[float] | None:
            b = np.frombuffer((text or "").lower().encode(), np.uint8).astype(np.uint64)
            if len(b) < n:
                return None
            h = np.zeros(len(b) - n + 1, np.uint64)
            for k in range(n):
                h = h * np.uint64(1000003) + b[k : len(b) - n + 1 + k]
            h = h * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(40)
            v = np.bincount((h % np.uint64(d)).astype(np.int64), minlength=d).astype(np.float64)
            return (v / np.linalg.norm(v)).astype(np.float32).tolist()

        @F.pandas_udf("array<float>")
        def vectors(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
            for texts in parts:
                yield pd.Series([one(x) for x in texts])

        return df.withColumn("embedding", vectors(text))


@dataclass(frozen=True)
class ModelEmbedder:
    """factory() runs once in a task and gives a function from a list of texts to rows of numbers."""

    factory: Callable[[], Callable[[list[str]], np.ndarray]]
    batch: int = 256

    def embed(self, df: DataFrame, text: str = "text") -> DataFrame:
        from pyspark.ml.functions import predict_batch_udf
        from pyspark.sql.types import ArrayType, FloatType

        factory = self.factory

        def make():
            model = factory()
            return lambda texts: np.asarray(model([x or "" for x in texts]), np.float32)

        udf = predict_batch_udf(make, return_type=ArrayType(FloatType()), batch_size=self.batch)
        return df.withColumn("embedding", udf(F.coalesce(text, F.lit(""))))
