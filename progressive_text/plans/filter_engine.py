"""Semantic predicate: a pilot ranks strata by valid rate, then strata are drawn from in that order."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import allocate
from ..operators.estimate import Moments, StratumDraws, draw_moments, stratified_filter, valid_mean
from ..operators.labelers import Labeler
from ..operators.order import rank_pool
from ..operators.stats import valid_rate
from .layout import lay_out
from .query import Clock, DrawLog, ProgressLog, Stop


def schedule(pool: DataFrame, pilot: int, batch: int, key: str = "key", seed: int = 42) -> DataFrame:
    """A labelled pool (key, stratum, label) as a draw log: step 0 is the pilot, then strata in the order of its valid rates.

    For tables whose labels are at hand (replays, experiments): one declaration in place of a loop. The driver holds
    one row for each stratum.
    """
    spark = pool.sparkSession
    ranked = rank_pool(pool, key, ["stratum"], seed)
    sizes = {r.stratum: r.n for r in pool.groupBy("stratum").agg(F.count("*").alias("n")).collect()}
    first = allocate.proportional(sizes, pilot)
    rates = {r.stratum: r.p_hat for r in valid_rate(_join_small(ranked, first, "_pilot").where("position <= _pilot")).collect()}
    order, start, table = allocate.priority(rates, sizes), 0, {}
    for h in sorted(sizes, key=order.get):
        table[h] = start
        start += sizes[h] - first[h]
    placed = _join_small(_join_small(ranked, first, "_pilot"), table, "_start")
    after = F.col("_start") + F.col("position") - F.col("_pilot") - 1
    step = F.when(F.col("position") <= F.col("_pilot"), F.lit(0)).otherwise(1 + F.floor(after / batch)).cast("bigint")
    return placed.withColumn("step", step).drop("_pilot", "_start")


def _join_small(df: DataFrame, numbers: dict, name: str) -> DataFrame:
    kind = dict(df.dtypes)["stratum"]
    table = df.sparkSession.createDataFrame(list(numbers.items()), f"_h {kind}, {name} bigint")
    return df.join(F.broadcast(table), F.col("stratum") == F.col("_h")).drop("_h")


def progressive_filter(
    df: DataFrame, key: str, text: str, labeler: Labeler, value: str, agg: str = "avg", stratum: str | None = "stratum", pilot: int | None = None,
    batch: int | None = None, alpha: float = 0.95, seed: int = 42, stop: Stop | None = None, mode: str = "strict", refresh_rates: bool = False,
    estimator: str = "pooled", clock: Clock | None = None, fpc: bool = False,
) -> ProgressLog:
    """AVG, SUM or COUNT of `value` over rows for which the labeler (a predicate) is true.

    mode 'strict' exhausts strata by falling pilot rate; 'proportional_to_rate' shares each batch by size times
    smoothed rate; 'random' ignores strata (the baseline). Both estimates are published: pooled over valid draws, and
    expanded by stratum; `estimator` names the one that stop rules look at. The last step of a full run is exact.
    The table is written once in draw order (see layout), and a step reads its own range of each stratum it draws from.
    """
    spark, stop, clock = df.sparkSession, stop or Stop(), clock or Clock()
    flat = mode == "random" or stratum is None
    none = F.lit("" if not flat and dict(df.dtypes)[stratum] == "string" else -1)  # rows without a stratum are one
    rows = lay_out(df, key, text, labeler, {"_stratum": F.lit(0) if flat else F.coalesce(F.col(stratum), none)}, {"_value": F.col(value).cast("double")}, batch=batch, seed=seed)
    sizes = {h: n for (h,), n in rows.sizes().items()}
    total = rows.total
    log = ProgressLog(spark, total, clock)
    if not total:
        return log
    pilot = pilot or max(total // 20, 2 * len(sizes))
    batch = batch or max(1, total // 100)
    draws = DrawLog(spark)
    drawn, valid, held = dict.fromkeys(sizes, 0), dict.fromkeys(sizes, 0), dict.fromkeys(sizes, Moments())
    step, order = 0, None
    while sum(drawn.values()) < total:
        left = {h: sizes[h] - drawn[h] for h in sizes}
        if step == 0:
            take = allocate.proportional(sizes, min(pilot, total), left)
        elif flat or mode == "proportional_to_rate":
            take = allocate.by_rate(sizes, valid, drawn, batch, left) if not flat else {0: min(batch, left[0])}
        else:
            if order is None or refresh_rates:
                ranks = allocate.priority({h: valid[h] / drawn[h] for h in sizes if drawn[h]}, sizes)
                order = sorted(ranks, key=ranks.get)
            take, rest = dict.fromkeys(sizes, 0), batch
            for h in order:
                take[h] = min(rest, left[h])
                rest -= take[h]
        labelled = labeler.label(rows.take({h: (drawn[h], drawn[h] + n) for h, n in take.items()}), text)
        new = draws.append(step, labelled.select(key, F.col("_stratum").alias("stratum"), "_value", "label", "is_valid"))
        found = draw_moments(new.withColumn("_hit", F.expr("coalesce(is_valid AND label, false)")), F.col("_hit"), F.col("_value"), "stratum", "_hit")
        for (h, hit), (n, m) in found.items():
            drawn[h] += n
            valid[h] += n if hit else 0
            held[h] += m
        calls, n_valid = sum(drawn.values()), sum(valid.values())
        pooled = valid_mean(sum(held.values(), Moments()), alpha, None if not fpc else round(total * n_valid / calls))
        strata = [StratumDraws(sizes[h], drawn[h], held[h]) for h in sizes]
        expanded = stratified_filter(strata, agg, alpha)
        first = pooled if agg == "avg" and estimator == "pooled" else expanded
        cell = {"grp": "", "n_valid": n_valid, "estimate": first[0], "half_width": first[1], "estimate_stratified": expanded[0], "half_width_stratified": expanded[1]}
        out = log.publish(step, calls, sum(take.values()), [cell], calls == total)
        if stop.reached(out, step, calls):
            break
        step += 1
    log.details |= {"draws": draws, "order": order}
    return log
