"""Refinement of strata for grouping: which draws do not fit their stratum, what looks like them, and where it goes."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import cosine, unit

#: Above so many minority vectors in a round they are not broadcast, but met in blocks of the joined side.
BROADCAST_ROWS = 50_000
#: Parts of a stratum that an existence join treats apart.
JOIN_SLICES = 64


def impure(states: DataFrame, theta: float) -> DataFrame:
    return states.where(F.col("norm_heterogeneity") > theta)


def minority(round_draws: DataFrame, states: DataFrame, stratum: str = "stratum") -> DataFrame:
    """This round's valid draws of the given strata whose label is not the dominant one."""
    dominant = states.select(F.col(stratum).alias("_h"), "dominant")
    joined = round_draws.join(F.broadcast(dominant), F.col(stratum) == F.col("_h"))
    return joined.where(F.col("label").cast("string") != F.col("dominant")).drop("_h", "dominant")


def lookalikes(pool: DataFrame, few: DataFrame, gamma: float, vector: str = "embedding", stratum: str = "stratum", method: str = "auto") -> DataFrame:
    """Rows of pool (undrawn) with cosine above gamma to a minority draw of their own stratum.

    'matrix' broadcasts the minority vectors (checked: at most BROADCAST_ROWS, a part of one round's draws) and takes
    matrix products batch by batch, without moving the pool; 'prune' does so for rows alone whose angle to the minority's
    mean differs from that of some minority vector by no more than gamma's angle. 'join' is an existence join for any
    number of them, by stratum and a slice of the pool that the minority is repeated for, so a large stratum is many
    tasks. 'auto' counts first. 'lsh' takes candidates from random hyperplanes and confirms them; it may miss some.
    """
    if method == "auto":
        method = "matrix" if few.count() <= BROADCAST_ROWS else "join"
    if method == "lsh":
        return _lsh(pool, few, gamma, vector, stratum)
    if method == "join":
        other = few.select(F.col(stratum).alias("_h"), F.col(vector).alias("_v"), F.explode(F.sequence(F.lit(0), F.lit(JOIN_SLICES - 1))).alias("_s"))
        sliced = pool.withColumn("_slice", F.pmod(F.xxhash64("key"), F.lit(JOIN_SLICES)).cast("int"))
        same = (F.col(stratum) == F.col("_h")) & (F.col("_slice") == F.col("_s")) & (cosine(vector, "_v") > gamma)
        return sliced.join(other, same, "left_semi").drop("_slice")
    held: dict[int, list] = {}
    for r in few.select(stratum, vector).where(F.col(vector).isNotNull()).toLocalIterator():
        held.setdefault(r[0], []).append(r[1])
    units = {h: unit(np.array(v, np.float64)) for h, v in held.items()}
    if not units:
        return pool.where("false")
    shared = pool.sparkSession.sparkContext.broadcast(units)
    reach = float(np.arccos(np.clip(gamma, -1, 1))) + 1e-9

    def near(x: np.ndarray, other: np.ndarray) -> np.ndarray:
        """Rows that the triangle inequality of angles leaves, seen from the mean of `other`."""
        centre = unit(other.mean(0)[None])[0]
        angles = np.sort(np.arccos(np.clip(other @ centre, -1, 1)))
        own = np.arccos(np.clip(x @ centre, -1, 1))
        return np.searchsorted(angles, own - reach) < np.searchsorted(angles, own + reach, "right")

    @F.pandas_udf("boolean")
    def alike(parts: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for strata, vectors in parts:
            out = np.zeros(len(strata), bool)
            known = vectors.notna().to_numpy()
            for h, other in shared.value.items():
                at = np.flatnonzero((strata == h).to_numpy() & known)
                for block in np.array_split(at, max(1, len(at) * len(other) // 4_000_000 + 1)):
                    if len(block):
                        x = unit(np.stack(vectors.iloc[block].to_numpy()).astype(np.float64))
                        left = near(x, other) if method == "prune" else np.ones(len(x), bool)
                        out[block[left]] = (np.round(x[left] @ other.T, 12) > gamma).any(axis=1)
            yield pd.Series(out)

    return pool.where(F.col(stratum).isin(*units)).where(alike(stratum, vector))


def _lsh(pool: DataFrame, few: DataFrame, gamma: float, vector: str, stratum: str, planes: int = 12, tables: int = 8) -> DataFrame:
    """Candidates share all signs of one table's hyperplanes within a stratum; exact cosine confirms."""
    rng = np.random.default_rng(5)
    known = few.select(vector).where(F.col(vector).isNotNull()).first()
    if known is None:
        return pool.where("false")
    d = len(known[0])
    normal = rng.normal(size=(tables, planes, d))

    @F.pandas_udf("array<int>")
    def codes(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for vectors in parts:
            x = np.stack([np.zeros(d) if v is None else np.asarray(v, np.float64) for v in vectors]) if len(vectors) else np.zeros((0, d))
            bits = np.einsum("nd,tpd->ntp", x, normal) > 0
            yield pd.Series(list((bits @ (1 << np.arange(planes))).astype(np.int32)))

    side = lambda df: df.withColumn("_codes", codes(vector)).select("*", F.posexplode("_codes").alias("_t", "_c")).drop("_codes")
    other = side(few.select(F.col(stratum).alias("_h"), vector)).select("_h", F.col(vector).alias("_v"), F.col("_t").alias("_t2"), F.col("_c").alias("_c2"))
    same = (F.col(stratum) == F.col("_h")) & (F.col("_t") == F.col("_t2")) & (F.col("_c") == F.col("_c2")) & (cosine(vector, "_v") > gamma)
    return side(pool).join(other, same, "left_semi").drop("_t", "_c").dropDuplicates(["key"])


def separated(few: DataFrame, alike: DataFrame) -> DataFrame:
    """key, stratum of both sets, which are disjoint: one is drawn, the other is not."""
    return few.select("key", "stratum").unionByName(alike.select("key", "stratum"))


def merge_target(own_label, own_mean: np.ndarray, source: int, dominants: dict, means: dict[int, np.ndarray], on_no_target: str = "keep") -> int | None:
    """The other stratum of the same dominant category whose mean vector is nearest (ties: lower number).
    Without one, None, or with 'nearest' the nearest of any category."""
    others = [h for h, c in dominants.items() if h != source and c == own_label and h in means]
    if not others and on_no_target == "nearest":
        others = [h for h in means if h != source]
    near = lambda h: round(float(unit(own_mean[None])[0] @ unit(means[h][None])[0]), 12)
    return min(others, key=lambda h: (-near(h), h)) if others else None
