"""Every interval: closed forms on the driver, and the same as Column expressions over few aggregated rows."""

from __future__ import annotations

from dataclasses import dataclass
from math import sqrt
from statistics import NormalDist

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def z(confidence: float) -> float:
    """Two-sided quantile: half of what is left lies in each tail."""
    return NormalDist().inv_cdf((1 + confidence) / 2)


def z_of(alpha: float, k: int = 1, literal_level: bool = False) -> float:
    """For k categories at once the tail mass is divided by k; literal_level divides the confidence itself, as printed."""
    return z(alpha / k) if literal_level else z(1 - (1 - alpha) / k)


@dataclass(frozen=True)
class Moments:
    """Count, mean and sum of squared deviations; + merges two of them without cancellation. A sum that is known beside them
    is added up by itself: for whole numbers it is exact, which count times mean is not."""

    n: int = 0
    mean: float = 0.0
    m2: float = 0.0
    known_sum: float | None = None

    def __add__(self, other: Moments) -> Moments:
        n = self.n + other.n
        if n == 0:
            return self
        d = other.mean - self.mean
        known = None if any(x.n and x.known_sum is None for x in (self, other)) else (self.known_sum or 0.0) + (other.known_sum or 0.0)
        return Moments(n, self.mean + d * other.n / n, self.m2 + other.m2 + d * d * self.n * other.n / n, known)

    @property
    def sum(self) -> float:
        return self.n * self.mean if self.known_sum is None else self.known_sum

    @property
    def variance(self) -> float | None:
        return self.m2 / (self.n - 1) if self.n > 1 else None


def moments_of(df: DataFrame, value: str, *by: str) -> DataFrame:
    """by, n, mean, m2 of the rows with a value."""
    return df.where(F.col(value).isNotNull()).groupBy(*by).agg(F.count(value).alias("n"), F.avg(value).alias("mean"), (F.var_pop(value) * F.count(value)).alias("m2"))


def draw_moments(draws: DataFrame, hit: Column, value: Column, *by: str) -> dict[tuple, tuple[int, Moments]]:
    """Group -> (draws, moments of the values of its hits) in one job; the driver gets a row a group."""
    v = F.when(hit, value.cast("double"))
    rows = draws.groupBy(*by).agg(F.count("*").alias("_n"), F.count(v).alias("_hits"), F.avg(v).alias("_mean"), (F.var_pop(v) * F.count(v)).alias("_m2"), F.sum(v).alias("_sum")).collect()
    return {tuple(r)[:-5]: (r["_n"], Moments(r["_hits"], r["_mean"], r["_m2"], r["_sum"]) if r["_hits"] else Moments()) for r in rows}


def valid_mean(m: Moments, alpha: float = 0.95, population: int | None = None) -> tuple[float | None, float | None]:
    """(mean, half-width) of valid values. Below two values there is no half-width; population applies the finite factor."""
    if m.n == 0:
        return None, None
    mean = m.mean if m.known_sum is None else m.known_sum / m.n
    if m.variance is None:
        return mean, None
    factor = max(0.0, (population - m.n) / (population - 1)) if population and population > 1 else 1.0
    return mean, z(alpha) * sqrt(m.variance / m.n * factor)


@dataclass(frozen=True)
class StratumDraws:
    """What a filter has drawn from one stratum: rows, draws, and the moments of valid values."""

    n_total: int
    n_drawn: int
    valid: Moments


def finite(n_total: int, n_drawn: int) -> float:
    """(N - m) / (m (N - 1)); 0 when all is drawn or the stratum has one row."""
    if n_total <= 1 or n_drawn >= n_total:
        return 0.0
    return (n_total - n_drawn) / (n_drawn * (n_total - 1)) if n_drawn else float("nan")


def stratified_filter(strata: list[StratumDraws], agg: str, alpha: float = 0.95) -> tuple[float | None, float | None]:
    """COUNT, SUM or AVG over the rows of a filter as expansions by stratum; AVG is a ratio with linearised variance.
    Strata without draws count as if they held no valid row, with no half-width."""
    total = count = 0.0
    complete = all(s.n_drawn for s in strata if s.n_total)
    drawn = [s for s in strata if s.n_drawn]
    for s in drawn:
        count += s.n_total * s.valid.n / s.n_drawn
        total += s.n_total * s.valid.sum / s.n_drawn
    if agg == "count":
        var = sum(s.n_total**2 * finite(s.n_total, s.n_drawn) * (p := s.valid.n / s.n_drawn) * (1 - p) for s in drawn)
        return count, z(alpha) * sqrt(var) if complete else None
    if agg == "avg" and count == 0:
        return None, None
    ratio = total / count if agg == "avg" else 0.0
    var, known = 0.0, complete
    for s in drawn:
        if s.n_drawn >= s.n_total:
            continue
        if s.n_drawn < 2:
            known = False
            continue
        n, m, v = s.n_total, s.n_drawn, s.valid
        mean = v.n * (v.mean - ratio) / m  # of (value - ratio) over all draws, invalid ones as 0
        squares = v.m2 + v.n * (v.mean - ratio) ** 2
        var += n * n * (1 - m / n) * (squares - m * mean * mean) / (m - 1) / m
    if agg == "sum":
        return total, z(alpha) * sqrt(max(0.0, var)) if known else None
    return ratio, z(alpha) * sqrt(max(0.0, var)) / count if known else None


@dataclass(frozen=True)
class GroupState:
    """A stratum of the grouping method: rows, draws, draws by category."""

    n_total: int
    n_drawn: int
    counts: dict

    def share(self, k) -> float:
        return self.counts.get(k, 0) / self.n_drawn if self.n_drawn else 0.0

    @property
    def heterogeneity(self) -> float:
        return sum(p * (1 - p) for p in (self.share(k) for k in self.counts)) if self.n_drawn else 0.0

    def smoothed_heterogeneity(self, more: float, k: int) -> float:
        """The same with `more` added to each of k categories' draws."""
        if more <= 0:
            return self.heterogeneity
        n = self.n_drawn + k * more
        return 1 - (sum((x + more) ** 2 for x in self.counts.values()) + (k - len(self.counts)) * more**2) / n**2

    def dominant(self):
        """The most frequent category, the first by name on a tie."""
        return min(self.counts, key=lambda k: (-self.counts[k], str(k))) if self.counts else None


def normalised(heterogeneity: float, k: int) -> float:
    """Heterogeneity over its greatest value 1 - 1/K; a single category is pure."""
    return heterogeneity / (1 - 1 / k) if k > 1 else 0.0


def group_shares(states: list[GroupState], categories: list, alpha: float = 0.95, form: str = "estimator", scope: str = "pooled", literal_level: bool = False) -> dict:
    """category -> (share, half-width, complete).

    form 'estimator': z sqrt(V), V being the variance of the estimate; 'printed' divides V by the draws once more.
    scope 'pooled': one V for all categories; 'per_category': each category's own. Strata without draws count as
    mixed as can be, and the result is then not complete.
    """
    n, k, draws = sum(s.n_total for s in states), len(categories), sum(s.n_drawn for s in states)
    if not n or not draws:
        return {c: (None, None, False) for c in categories}
    level, complete = z_of(alpha, k, literal_level), all(s.n_drawn for s in states if s.n_total)
    seen = sum(s.n_total for s in states if s.n_drawn)

    def variance(own) -> float:
        total = 0.0
        for s in states:
            if s.n_drawn:
                total += (s.n_total / n) ** 2 * finite(s.n_total, s.n_drawn) * own(s)
            elif s.n_total:
                total += (s.n_total / n) ** 2 * (1 - 1 / k)
        return total

    out = {}
    for c in categories:
        v = variance(lambda s: s.heterogeneity) if scope == "pooled" else variance(lambda s, c=c: s.share(c) * (1 - s.share(c)))
        share = sum(s.n_total * s.share(c) for s in states if s.n_drawn) / seen
        out[c] = (share, level * sqrt(v / draws if form == "printed" else v), complete)
    return out


def random_share(count: int, draws: int, n_total: int, alpha: float = 0.95, k: int = 1) -> tuple[float | None, float | None]:
    """Share and half-width of a simple random draw without replacement."""
    if not draws:
        return None, None
    p = count / draws
    return p, z_of(alpha, k) * sqrt(finite(n_total, draws) * p * (1 - p))


def group_value(strata: list[tuple[int, int, Moments]], agg: str, alpha: float = 0.95) -> tuple[float | None, float | None]:
    """AVG, SUM or COUNT of a structured value within one category: (rows, draws, moments of the category's draws) by stratum."""
    return stratified_filter([StratumDraws(*s) for s in strata], agg, alpha)


# Column forms, over aggregated rows


def half_width(variance: str | Column, n: str | Column, confidence: float = 0.95) -> Column:
    variance = F.col(variance) if isinstance(variance, str) else variance
    n = F.col(n) if isinstance(n, str) else n
    return F.when(n > 1, F.lit(z(confidence)) * F.sqrt(variance / n))


def finite_column(n_total: str = "n_total", n_drawn: str = "n_drawn") -> Column:
    n, m = F.col(n_total), F.col(n_drawn)
    return F.when((n <= 1) | (m >= n), F.lit(0.0)).when(m > 0, (n - m) / (m * (n - 1)))


def running(steps: DataFrame, value_columns: list[str], by: list[str], order: str = "step") -> DataFrame:
    """Running sums of few rows: aggregates of each step, by group."""
    over = Window.partitionBy(*(by or [F.lit(1)])).orderBy(order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return steps.select(*by, order, *[F.sum(c).over(over).alias(c) for c in value_columns])


def progress_of(draws: DataFrame, value: str, valid: str, by: list[str] | None = None, confidence: float = 0.95, order: str = "step") -> DataFrame:
    """Progress rows from a draw log with a step column: one aggregation over the draws, then windows over the steps.

    by, step, calls, n_valid, estimate, half_width. A group's first steps without a valid draw have a null estimate.
    """
    by = by or []
    v = F.when(F.col(valid), F.col(value).cast("double"))
    steps = draws.groupBy(*by, order).agg(F.count("*").alias("calls"), F.count(v).alias("n"), F.coalesce(F.sum(v), F.lit(0.0)).alias("s1"), F.coalesce(F.sum(v * v), F.lit(0.0)).alias("s2"))
    run = running(steps, ["calls", "n", "s1", "s2"], by, order)
    mean = F.when(F.col("n") > 0, F.col("s1") / F.col("n"))
    var = F.when(F.col("n") > 1, F.greatest(F.lit(0.0), (F.col("s2") - F.col("s1") * F.col("s1") / F.col("n")) / (F.col("n") - 1)))
    return run.select(*by, order, "calls", F.col("n").alias("n_valid"), mean.alias("estimate"), half_width(var, "n", confidence).alias("half_width"))
