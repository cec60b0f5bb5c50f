"""What progressive queries share: stop rules, the log of answers, the draw log, and the time model."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.store import new_path

PROGRESS = "step int, calls bigint, calls_fraction double, grp string, n_valid bigint, estimate double, estimate_stratified double, half_width double, half_width_stratified double, ci_low double, ci_high double, relative_bound double, is_final boolean, virtual_seconds double"


@dataclass(frozen=True)
class Stop:
    """Rules that end drawing; any one that holds does. bound is relative to the estimate, or absolute for shares; purity is
    the greatest normalised heterogeneity that a stratum of a grouping may still have."""

    bound: float | None = None
    relative: bool = True
    budget: int | None = None
    max_steps: int | None = None
    min_valid: int = 30
    purity: float | None = None

    def sure(self, steps: int) -> int:
        """Of so many steps, those that are drawn whatever their answers are."""
        if self.bound is not None or self.budget is not None or self.purity is not None:
            return 0
        return steps if self.max_steps is None else min(steps, max(1, self.max_steps))

    def reached(self, rows: list[dict], step: int, calls: int, worst: float | None = None) -> bool:
        if self.purity is not None and worst is not None and worst <= self.purity:
            return True
        if self.budget is not None and calls >= self.budget:
            return True
        if self.max_steps is not None and step + 1 >= self.max_steps:
            return True
        if self.bound is None or not rows:
            return False
        return all(within(r, self.bound, self.relative, self.min_valid) for r in rows)


def within(row: dict, bound: float, relative: bool, min_valid: int) -> bool:
    if row["half_width"] is None or row["estimate"] is None or row["n_valid"] < min_valid:
        return False
    return row["half_width"] <= bound * (abs(row["estimate"]) if relative else 1.0)


@dataclass(frozen=True)
class Clock:
    """Virtual time: draws over serving instances, and what a query sets up before (embedding, clustering)."""

    seconds_per_call: float = 1.0
    instances: int = 1
    setup: float = 0.0
    serial_share: float = 0.0

    def step(self, calls: int) -> float:
        serial = calls * self.seconds_per_call * self.serial_share
        return serial + -(-calls // self.instances) * self.seconds_per_call * (1 - self.serial_share)

    def full_scan(self, n: int) -> float:
        return self.step(n)


@dataclass
class ProgressLog:
    """The answers of a query, one row for each step and output cell."""

    spark: SparkSession
    total: int
    clock: Clock = field(default_factory=Clock)
    rows: list[dict] = field(default_factory=list)
    seconds: float | None = None
    details: dict = field(default_factory=dict)

    def publish(self, step: int, calls: int, new_calls: int, cells: list[dict], final: bool) -> list[dict]:
        self.seconds = (self.clock.setup if self.seconds is None else self.seconds) + self.clock.step(new_calls)
        out = []
        for cell in cells:
            e, w = cell.get("estimate"), cell.get("half_width")
            share = cell.pop("share", False)
            lo, hi = (None, None) if e is None or w is None else (e - w, e + w)
            if share and lo is not None:
                lo, hi = max(0.0, lo), min(1.0, hi)
            bound = None if e in (None, 0) or w is None else w / abs(e)
            out.append({"estimate_stratified": None, "half_width_stratified": None, **cell, "step": step, "calls": calls, "calls_fraction": calls / max(1, self.total), "ci_low": lo, "ci_high": hi, "relative_bound": bound, "is_final": final, "virtual_seconds": self.seconds})
        self.rows += out
        return out

    def steps(self) -> Iterator[DataFrame]:
        for step in sorted({r["step"] for r in self.rows}):
            yield self._frame([r for r in self.rows if r["step"] == step])

    def frame(self, half_width: str = "half_width") -> DataFrame:
        """All answers; half_width names another interval that an engine has published beside its own, as half_width_own."""
        return self._frame(self.rows if half_width == "half_width" else [{**r, "half_width": r.get(half_width)} for r in self.rows])

    def result(self) -> DataFrame:
        last = max((r["step"] for r in self.rows), default=0)
        return self._frame([r for r in self.rows if r["step"] == last])

    def _frame(self, rows: list[dict]) -> DataFrame:
        names = [x.split()[0] for x in PROGRESS.split(", ")]
        return self.spark.createDataFrame([tuple(None if r.get(k) is None else r[k] for k in names) for r in rows], PROGRESS)


class DrawLog:
    """Labelled draws, appended step by step before anything aggregates them: a labeler is asked once for a draw.

    A step, or a block of them under its first one, is written to its own folder in overwrite mode, so repeating it after
    a failure replaces it.
    """

    def __init__(self, spark: SparkSession, path: str | None = None):
        self.spark, self.path, self.steps = spark, path or new_path(spark, "draws"), []
        self.schema = None

    def append(self, step: int, labelled: DataFrame, each: Column | None = None) -> DataFrame:
        labelled = labelled.withColumn("step", F.lit(step) if each is None else each)
        labelled.write.mode("overwrite").parquet(f"{self.path}/step={step:06d}")
        self.schema, self.steps = labelled.schema, [*self.steps, step]
        return self.step(step)

    def step(self, step: int) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(f"{self.path}/step={step:06d}")

    def all(self) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(*[f"{self.path}/step={s:06d}" for s in self.steps])


@dataclass(frozen=True)
class ProgressiveQuery:
    """A query by its class: 'select', 'filter' or 'group', with that engine's arguments."""

    kind: str
    df: DataFrame
    arguments: dict

    def run(self, stop: Stop | None = None) -> ProgressLog:
        from . import filter_engine, group_engine, select_engine

        engine = {"select": select_engine.progressive_select, "filter": filter_engine.progressive_filter, "group": group_engine.progressive_group}[self.kind]
        return engine(self.df, **self.arguments, **({"stop": stop} if stop else {}))
