"""Semantic grouping: rounds of sampling, recording and adjustment of strata."""

from __future__ import annotations

from dataclasses import dataclass
from math import sqrt

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import allocate, refine
from ..operators.estimate import Moments, finite, group_shares, group_value, moments_of, normalised, z_of
from ..operators.labelers import Labeler
from ..operators.order import positions
from ..operators.stats import group_states
from ..operators.strata import _vector_sums, overlay
from ..sources.store import saved
from .layout import Layout, lay_out
from .query import Clock, DrawLog, ProgressLog, Stop


@dataclass(frozen=True)
class GroupConfig:
    """Parameters of the loop. h_max bounds the strata; theta is the normalised heterogeneity above which a stratum is
    refined; gamma the cosine above which an undrawn row looks like a draw that does not fit; smoothing the count that is
    added to each category of a stratum before draws are allocated (0: the bare rule)."""

    h_max: int = 32
    theta: float = 0.3
    gamma: float = 0.9
    alpha: float = 0.95
    round_fraction: float = 0.10
    floor: int = 1
    smoothing: float = 0.0
    adjust: bool = True
    estimator: str = "recorded"
    form: str = "estimator"
    scope: str = "pooled"
    on_no_target: str = "keep"
    literal_level: bool = False
    strict: bool = False
    lookalike_method: str = "auto"


def progressive_group(
    df: DataFrame, key: str, text: str, labeler: Labeler, categories: list, value: str | None = None, agg: str = "proportion",
    stratum: str = "stratum", vector: str = "embedding", config: GroupConfig | None = None, seed: int = 42, stop: Stop | None = None, clock: Clock | None = None,
) -> ProgressLog:
    """Share ('proportion'), number ('total'), or AVG/SUM of `value` for each category of the text.

    df has a stratum (an integer) for each row and, if strata are adjusted, a vector. `estimate` is the recorded estimate
    (strata as they are now, all draws), `estimate_stratified` the fresh one (each round by the strata it drew from,
    weighted by its draws), which moved draws cannot bias.

    The table is written once in draw order, with its vectors. Rows that change their stratum are a delta beside it: of the
    others, those of a first stratum up to a position are drawn and those beyond are not. So a round reads the next
    positions of each stratum and the delta, never the whole table. The driver holds numbers by stratum and category, and
    sums of vectors by stratum.
    """
    spark, config, stop, clock = df.sparkSession, config or GroupConfig(), stop or Stop(relative=False), clock or Clock()
    more = ({"_vector": F.col(vector)} if config.adjust else {}) | ({"_value": F.col(value).cast("double")} if value else {})
    rows = lay_out(df, key, text, labeler, {"_stratum": F.coalesce(F.col(stratum).cast("int"), F.lit(-1))}, more, config.round_fraction, seed=seed)
    total = rows.total
    log = ProgressLog(spark, total, clock)
    if not total:
        return log
    k, per_round = len(categories), max(1, round(total * config.round_fraction))
    strata = Strata(rows, key, {h: n for (h,), n in rows.sizes().items()})
    draws, calls, t, states = DrawLog(spark), 0, 0, None
    fresh, purity, actions = [], [], []
    while calls < total:
        before = group_states(strata.placed(draws), strata.sizes, categories) if t else {}
        left = {h: n - (before[h].n_drawn if t else 0) for h, n in strata.sizes.items()}
        if t == 0:
            take = allocate.proportional(strata.sizes, per_round, left)
        else:
            spread = {h: s.smoothed_heterogeneity(config.smoothing, k) for h, s in before.items()}
            take = allocate.neyman(strata.sizes, spread, per_round, left, config.floor)
        labelled = labeler.label(strata.next_rows(take, draws), text)
        new = draws.append(t, labelled.select(key, "stratum", "_first", "_position", "_rank", *more, "label", "is_valid"))
        strata.advance(new)
        new_calls = sum(take.values())
        calls += new_calls
        states = group_states(strata.placed(draws), strata.sizes, categories)
        fresh.append(_fresh_round(new, before, strata.sizes, left, take, categories, total))
        cells = _cells(states, fresh, categories, total, calls, config, agg, strata.placed(draws))
        out = log.publish(t, calls, new_calls, cells, calls == total)
        het = {h: normalised(s.heterogeneity, k) for h, s in states.items()}
        sizes = strata.sizes
        worst = max(het.values())
        purity.append({"round": t, "strata": len(sizes), "worst": worst, "weighted": sum(sizes[h] * het[h] for h in sizes) / total})
        impure = [h for h in sorted(sizes, key=lambda h: (-round(sizes[h] * het[h], 9), h)) if het[h] > config.theta]
        if stop.reached(out, t, calls, worst) or (config.strict and not impure):
            break
        if config.adjust and impure and calls < total:
            actions += _adjust(strata, draws, new, states, impure, config, t)
        t += 1
    log.details |= {"draws": draws, "purity": purity, "actions": actions, "assignment": strata.assignment(), "states": states}
    return log


class Strata:
    """Strata as they are now: the first ones of the table, and a delta of moved rows.

    `upto` says up to which position the rows that stayed in a first stratum are drawn. `moved` has the rows that changed
    their stratum (key, _first, _position, _rank, to_stratum), the latest move of each; it is a written table.
    """

    def __init__(self, rows: Layout, key: str, sizes: dict[int, int]):
        self.rows, self.key, self.sizes, self.first_sizes = rows, key, dict(sizes), dict(sizes)
        self.upto, self.moved, self.away = dict.fromkeys(sizes, 0), None, dict.fromkeys(sizes, 0)
        self.first_sums: dict | None = None
        self.shifts: list[tuple[dict, dict]] = []

    def _base(self) -> DataFrame:
        return self.rows.table.withColumnRenamed("_stratum", "_first")

    def next_rows(self, take: dict, draws: DrawLog) -> DataFrame:
        """The next rows of each stratum by rank, with `stratum`: whole rows, read from their own ranges of positions."""
        spans = {h: (self.upto[h], self.upto[h] + n + self.away[h]) for h, n in take.items() if n and h in self.upto}
        if self.moved is None:
            return self.rows.take(spans).withColumn("stratum", F.col("_stratum")).withColumnRenamed("_stratum", "_first")
        names = [self.key, "_first", "_position", "_rank", "stratum"]
        stayed = self.rows.take(spans).withColumnRenamed("_stratum", "_first").join(self.moved.select(self.key), self.key, "left_anti").withColumn("stratum", F.col("_first")).select(names)
        wanted = [h for h, n in take.items() if n]
        others = self.moved.where(F.col("to_stratum").isin(wanted)).join(draws.all().select(self.key), self.key, "left_anti")
        others = others.withColumnRenamed("to_stratum", "stratum").select(names)
        chosen = saved(_lowest(stayed.unionByName(others), take), "chosen")
        at = {r[0]: (r[1] - 1, r[2]) for r in chosen.groupBy("_first").agg(F.min("_position"), F.max("_position")).collect()}
        few = sum(take.values()) <= 100_000
        keys = chosen.select(self.key, "stratum")
        return self.rows.take(at).withColumnRenamed("_stratum", "_first").join(F.broadcast(keys) if few else keys, self.key)

    def advance(self, new: DataFrame) -> None:
        stayed = new if self.moved is None else new.join(self.moved.select(self.key), self.key, "left_anti")
        for r in stayed.groupBy("_first").agg(F.max("_position").alias("p")).collect():
            self.upto[r["_first"]] = max(self.upto[r["_first"]], r.p)

    def placed(self, draws: DrawLog) -> DataFrame:
        """All draws with the stratum that they are in now; labels that are not valid are null."""
        drawn = draws.all().drop("stratum")
        label = F.when(F.col("is_valid"), F.col("label")).alias("label")
        values = [c for c in drawn.columns if c == "_value"]
        if self.moved is None:
            return drawn.select(self.key, F.col("_first").alias("stratum"), label, *values)
        now = drawn.join(self.moved.select(self.key, "to_stratum"), self.key, "left")
        return now.select(self.key, F.coalesce("to_stratum", "_first").alias("stratum"), label, *values)

    def undrawn(self, strata: list[int], draws: DrawLog) -> DataFrame:
        """key, stratum, _first, _position, _rank, embedding of the undrawn rows of some strata."""
        names = [F.col(self.key).alias("key"), "stratum", "_first", "_position", "_rank", F.col("_vector").alias("embedding")]
        spans = {h: (self.upto[h], self.first_sizes[h]) for h in strata if h in self.upto}
        stayed = self.rows.take(spans).withColumnRenamed("_stratum", "_first").withColumn("stratum", F.col("_first"))
        if self.moved is None:
            return stayed.select(names)
        stayed = stayed.join(self.moved.select(self.key), self.key, "left_anti")
        others = self.moved.where(F.col("to_stratum").isin(strata)).join(draws.all().select(self.key), self.key, "left_anti").select(self.key, F.col("to_stratum").alias("stratum"))
        return stayed.select(names).unionByName(self._base().join(others, self.key).select(names))

    def move(self, away: DataFrame, target: dict[int, int], sums: dict) -> None:
        """Moves `away` (key, stratum, ...) to the targets of their strata."""
        table = away.sparkSession.createDataFrame(list(target.items()), "stratum int, to_stratum int")
        delta = away.join(F.broadcast(table), "stratum")
        for r in delta.groupBy("stratum", "to_stratum").count().collect():
            self.sizes[r.stratum] -= r["count"]
            self.sizes[r.to_stratum] = self.sizes.get(r.to_stratum, 0) + r["count"]
        self.sizes = {h: n for h, n in self.sizes.items() if n}
        self.shifts.append((sums, target))
        delta = delta.select(F.col("key").alias(self.key), "_first", "_position", "_rank", "to_stratum")
        if self.moved is not None:
            delta = delta.unionByName(self.moved.join(delta.select(self.key), self.key, "left_anti"))
        self.moved = saved(delta, "moves")
        gone = {r["_first"]: r["count"] for r in self.moved.groupBy("_first").count().collect()}
        self.away = {h: gone.get(h, 0) for h in self.upto}

    def mean_vectors(self) -> dict[int, np.ndarray]:
        """Mean unit vector of each stratum: sums of the first strata, taken once, and what moves have shifted since."""
        if self.first_sums is None:
            self.first_sums = _vector_sums(self.rows.table, "_stratum", "_vector")
        n, total = {h: x[0] for h, x in self.first_sums.items()}, {h: x[1].copy() for h, x in self.first_sums.items()}
        for sums, target in self.shifts:
            for h, to in target.items():
                if h in sums:
                    n[h], total[h] = n[h] - sums[h][0], total[h] - sums[h][1]
                    n[to], total[to] = n.get(to, 0) + sums[h][0], total.get(to, 0) + sums[h][1]
        return {h: total[h] / n[h] for h in total if n[h] > 0}

    def assignment(self) -> DataFrame:
        """key, stratum of all rows."""
        base = self._base().select(F.col(self.key).alias("key"), F.col("_first").alias("stratum"))
        if self.moved is None:
            return base
        return overlay(base, self.moved.select(F.lit(0).alias("t"), F.col(self.key).alias("key"), "to_stratum"))


def _lowest(rows: DataFrame, take: dict) -> DataFrame:
    """The n_h rows of lowest rank of each stratum h among some candidates."""
    table = rows.sparkSession.createDataFrame([(h, n) for h, n in take.items() if n], "_h int, _n bigint")
    placed = positions(rows, ["stratum"], "_rank", name="_place")
    return placed.join(F.broadcast(table), F.col("stratum") == F.col("_h")).where("_place <= _n").select(rows.columns)


def _fresh_round(new: DataFrame, before: dict, sizes: dict, left: dict, take: dict, categories: list, total: int) -> dict:
    """What one round says by itself: labels known before it, and the rest expanded from its own draws by stratum."""
    k_of = {h: {} for h in sizes}
    for r in new.where("is_valid").groupBy("stratum", "label").count().collect():
        k_of[r.stratum][r.label] = r["count"]
    known = {c: sum(s.counts.get(c, 0) for s in before.values()) for c in categories}
    usable = all(take[h] for h in sizes if left[h])
    shares, variances = {}, {}
    for c in categories:
        q = {h: k_of[h].get(c, 0) / take[h] for h in sizes if take[h]}
        shares[c] = (known[c] + sum(left[h] * q[h] for h in q)) / total
        variances[c] = sum((left[h] / total) ** 2 * finite(left[h], take[h]) * q[h] * (1 - q[h]) for h in q)
    return {"n": sum(take.values()), "share": shares, "variance": variances, "usable": usable}


def combine_fresh(rounds: list[dict], category, z: float) -> tuple[float | None, float | None]:
    rounds = [r for r in rounds if r["usable"]]
    weight = sum(r["n"] for r in rounds)
    if not weight:
        return None, None
    mean = sum(r["n"] * r["share"][category] for r in rounds) / weight
    return mean, z * sqrt(sum((r["n"] / weight) ** 2 * r["variance"][category] for r in rounds))


def _cells(states, fresh, categories, total, calls, config: GroupConfig, agg, placed: DataFrame) -> list[dict]:
    shares = group_shares(list(states.values()), categories, config.alpha, config.form, config.scope, config.literal_level)
    own = group_shares(list(states.values()), categories, config.alpha, config.form, "per_category", config.literal_level)
    level = z_of(config.alpha, len(categories), config.literal_level)
    by_value = {}
    if agg in ("avg", "sum"):
        for r in moments_of(placed.where("label IS NOT NULL"), "_value", "stratum", "label").collect():
            by_value[r.stratum, r.label] = Moments(r.n, r["mean"], r.m2)
    cells = []
    for c in categories:
        share, width, complete = shares[c]
        new_share, new_width = combine_fresh(fresh, c, level)
        if calls == total:
            new_share, new_width = share, 0.0
        cell = {"grp": str(c), "n_valid": calls, "estimate": share, "half_width": width if complete else None, "estimate_stratified": new_share, "half_width_stratified": new_width, "half_width_own": own[c][1] if complete else None, "share": agg == "proportion"}
        if agg == "total":
            cell |= {x: None if cell[x] is None else cell[x] * total for x in ("estimate", "half_width", "estimate_stratified", "half_width_stratified", "half_width_own")}
        if agg in ("avg", "sum"):
            found = group_value([(s.n_total, s.n_drawn, by_value.get((h, c), Moments())) for h, s in states.items()], agg, config.alpha)
            cell |= {"estimate": found[0], "half_width": found[1], "estimate_stratified": None, "half_width_stratified": None, "half_width_own": found[1], "n_valid": sum(m.n for (_, l), m in by_value.items() if l == c)}
        elif config.estimator == "fresh":
            cell |= {"estimate": cell["estimate_stratified"], "half_width": cell["half_width_stratified"]}
        cells.append(cell)
    return cells


def _adjust(strata: Strata, draws: DrawLog, new: DataFrame, states: dict, impure: list, config: GroupConfig, t: int) -> list[dict]:
    """Moves what does not fit its stratum; returns what was done. Every search uses the strata of the round's start."""
    spark = new.sparkSession
    dominant = spark.createDataFrame([(h, str(states[h].dominant())) for h in impure], "stratum int, dominant string")
    few = new.where("is_valid").select(F.col(strata.key).alias("key"), "stratum", "label", "_first", "_position", "_rank", F.col("_vector").alias("embedding"))
    few = saved(refine.minority(few, dominant), "minority")
    labels: dict[int, dict] = {}
    for r in few.groupBy("stratum", "label").count().collect():
        labels.setdefault(r.stratum, {})[r.label] = r["count"]
    if not labels:
        return []
    alike = refine.lookalikes(strata.undrawn(list(labels), draws), few, config.gamma, method=config.lookalike_method)
    names = ["key", "stratum", "_first", "_position", "_rank", "embedding"]
    away = saved(few.select(names).unionByName(alike.select(names)), "separated")
    sums = _vector_sums(away, "stratum", "embedding")
    means = dominants = None
    number, target, actions = len(strata.sizes), {}, []
    fresh_id = max([*strata.sizes, *strata.first_sizes, *[to for _, x in strata.shifts for to in x.values()]]) + 1
    for h in [h for h in impure if h in labels]:
        if number < config.h_max:
            target[h], fresh_id, number = fresh_id, fresh_id + 1, number + 1
            actions.append({"round": t, "stratum": h, "action": "split", "to": target[h]})
            continue
        if means is None:
            means = strata.mean_vectors()
            dominants = {g: s.dominant() for g, s in states.items() if s.n_drawn}
        label = min(labels[h], key=lambda c: (-labels[h][c], str(c)))
        to = refine.merge_target(label, sums[h][1] / sums[h][0], h, dominants, means, config.on_no_target) if h in sums else None
        actions.append({"round": t, "stratum": h, "action": "merge" if to is not None else "none", "to": to})
        if to is not None:
            target[h] = to
    if target:
        strata.move(away, target, sums)
    return actions
