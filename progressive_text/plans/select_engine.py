"""Extraction in the projection: draws in random order, a scalar from each text, means by structured groups."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.estimate import Moments, StratumDraws, draw_moments, stratified_filter, valid_mean
from ..operators.labelers import Labeler
from .layout import ALL, MOST_GROUPS, lay_out
from .query import Clock, DrawLog, ProgressLog, Stop


def progressive_select(
    df: DataFrame, key: str, text: str, labeler: Labeler, group_by: list[str] | None = None, agg: str = "avg", alpha: float = 0.95,
    design: str = "uniform", batch: int | None = None, seed: int = 42, stop: Stop | None = None, clock: Clock | None = None, fpc: bool = False,
) -> ProgressLog:
    """AVG, SUM or COUNT of valid extractions by group.

    design 'uniform' draws from the whole table, 'by_group' as many from each group and step. SUM and COUNT expand a
    group's draws to its rows, whose number is known: their intervals hold what the share of valid extractions varies by.
    Steps that no rule can leave out are labelled in growing blocks, a job or two each; every step is published.
    Empty tables give an empty log. Group columns may have any names; more than layout.MOST_GROUPS groups are refused.
    """
    spark, by, stop, clock = df.sparkSession, group_by or [], stop or Stop(), clock or Clock()
    groups = {f"_g{i}": F.col(c) for i, c in enumerate(by)}
    rows = lay_out(df, key, text, labeler, groups if design == "by_group" else {}, {} if design == "by_group" else groups, batch=batch, seed=seed)
    total = rows.total
    log = ProgressLog(spark, total, clock)
    if not total:
        return log
    sizes = rows.sizes(*groups) if groups else {(): total}
    batch = batch or max(1, total // 100)
    each = max(1, batch // len(sizes)) if design == "by_group" else batch
    steps = -(-(max(sizes.values()) if design == "by_group" else total) // each)
    draws, held, drawn, calls = DrawLog(spark), dict.fromkeys(sizes, Moments()), dict.fromkeys(sizes, 0), 0
    sure = stop.sure(steps)
    most = max(1, MOST_GROUPS // len(sizes))  # steps and groups whose numbers the driver holds at a time
    at = 0
    while at < steps:
        block = max(1, min(at, most, sure - at))  # as many as before, so few jobs, and each answer in at most twice the draws
        rows_of = labeler.label(rows.take({ALL: (at * each, (at + block) * each)}), text).withColumn("_step", F.expr(f"int((_position - 1) div {each})"))
        new = draws.append(at, rows_of.select(key, *groups, "label", "is_valid", "_step"), F.col("_step")).drop("_step")
        found: dict[int, list] = {}
        for (step, *g), x in draw_moments(new, F.col("is_valid"), F.col("label"), "step", *groups).items():
            found.setdefault(step, []).append((tuple(g), x))
        for step in range(at, at + block):
            before = calls
            for g, (n, m) in found.get(step, ()):
                drawn[g] += n
                held[g] += m
            calls = sum(drawn.values())
            cells = []
            for g, m in held.items():
                if agg == "avg":
                    mean, width = valid_mean(m, alpha, sizes[g] if fpc else None)
                else:
                    mean, width = stratified_filter([StratumDraws(sizes[g], drawn[g], m)], agg, alpha) if drawn[g] else (None, None)
                cells.append({"grp": ",".join(map(str, g)), "n_valid": m.n, "estimate": mean, "half_width": width})
            out = log.publish(step, calls, calls - before, cells, calls == total)
        if stop.reached(out, at + block - 1, calls):
            break
        at += block
    log.details["draws"] = draws
    return log
