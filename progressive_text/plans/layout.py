"""The table that a progressive query draws from: written once in draw order, so a step reads the row groups of its draws.

A row's place is (stratum, position). Files are sorted by it and their row groups hold about a batch, so a step's range of
positions prunes files and row groups by their statistics, and no step reads the whole table. Texts move once, when the
table is written, whatever the number of steps.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.labelers import Labeler
from ..operators.order import draw_rank, positions, slices_for
from ..sources.store import saved

#: In place of a stratum: all rows, of a table without strata or of every stratum.
ALL = object()
#: Groups or strata whose numbers the driver holds, at most.
MOST_GROUPS = 100_000


@dataclass(frozen=True)
class Layout:
    """Rows with the key and text under their own names, and _position, _rank, the strata's columns and others."""

    table: DataFrame
    strata: tuple[str, ...]
    total: int

    def sizes(self, *by: str) -> dict:
        """Rows of each stratum, or group of `by`: a tuple of values for each, at most MOST_GROUPS of them."""
        by = by or self.strata
        rows = self.table.groupBy(*by).agg(F.count("*").alias("_n")).limit(MOST_GROUPS + 1).collect()
        if len(rows) > MOST_GROUPS:
            raise ValueError(f"more than {MOST_GROUPS} groups: aggregate by fewer columns, or number the strata")
        return {tuple(r)[:-1]: r["_n"] for r in rows}

    def take(self, spans: dict) -> DataFrame:
        """Rows at positions (first, last] of each stratum, given as stratum (or ALL) -> (first, last)."""
        wanted = F.lit(False)
        for h, (lo, hi) in spans.items():
            if hi > lo:
                part = (F.col("_position") > lo) & (F.col("_position") <= hi)
                wanted = wanted | (part if h is ALL else (F.col(self.strata[0]) == F.lit(h)) & part)
        return self.table.where(wanted)


def check_names(*names: str) -> None:
    for name in names:
        if name in ("label", "is_valid") or name.startswith("_"):
            raise ValueError(f"the key and text columns must not be named {name}: labelers and engines use such names")


def lay_out(df: DataFrame, key: str, text: str, labeler: Labeler, strata: dict[str, Column], more: dict[str, Column] | None = None, batch_share: float = 0.01, batch: int | None = None, seed: int = 42) -> Layout:
    """Writes key, text, `strata` and `more` (private names, which begin with an underscore) in draw order.

    What a labeler keeps by row (truths from a table of labels) is joined here, once. Other columns of df are left out, so
    their names cannot clash.
    """
    check_names(key, text)
    total = df.count()
    batch = batch or max(1, int(total * batch_share))
    ready = labeler.prepare(df)
    own = [c for c in ready.columns if c.startswith("_truth")]
    columns = [F.col(c) for c in dict.fromkeys([key, text])] + [c.alias(n) for n, c in (strata | (more or {})).items()]
    slices = slices_for(total, batch)
    ranked = positions(ready.select(*columns, *own, draw_rank(key, seed).alias("_rank")), list(strata), "_rank", slices, "_position")
    rows_in_group = max(100, min(batch, total // slices // 8))  # many to a slice: few row groups hold the ends of two
    return Layout(saved(ranked, "draw-order", options={"parquet.block.row.count.limit": str(rows_in_group)}), tuple(strata), total)
