"""Extraction in the projection and semantic filters, step by step."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.extract import JsonExtractor
from ..functions.rules import low_quality, low_quality_sql
from ..operators import allocate
from ..operators.estimate import finite_column, progress_of, running, z
from ..operators.labelers import ExtractLabeler, RuleLabeler
from ..operators.order import rank_pool
from ..operators.stats import cumulative_valids, valid_rate
from ..plans import filter_engine, metrics
from ..sources.tables import labelled, table, with_counts
from .batch import LABELLED, NUMBER
from .registry import query, r6

Z = repr(z(0.95))
PROGRESS = "calls, n AS n_valid, round(CASE WHEN n > 0 THEN s1 / n END, 6) AS estimate, round(CASE WHEN n > 1 THEN " + Z + " * sqrt(greatest(0, (s2 - s1 * s1 / n) / (n - 1)) / n) END, 6) AS half_width"


def running_sql(draws: str, by: str = "") -> str:
    """step (and by), calls, n, s1, s2 so far from a table of draws (step, ok, v)."""
    part = f"PARTITION BY {by}" if by else ""
    own = f"{by}, " if by else ""
    sums = ", ".join(f"sum({c}) OVER ({part} ORDER BY step)::{t} AS {c}" for c, t in (("calls", "BIGINT"), ("n", "BIGINT"), ("s1", "DOUBLE"), ("s2", "DOUBLE")))
    return f"SELECT {own}step, {sums} FROM (SELECT {own}step, count(*) AS calls, count(*) FILTER (ok) AS n, coalesce(sum(v) FILTER (ok), 0) AS s1, coalesce(sum(v * v) FILTER (ok), 0) AS s2 FROM {draws} GROUP BY ALL)"


# projection

EVENTS = "SELECT event_id, event_type, (props->>'$.k')::DOUBLE AS v, (props->>'$.k')::INT BETWEEN 5 AND 99 AS ok, md5('42:' || event_id) AS rk FROM events"
EXTRACT = ExtractLabeler(JsonExtractor("k INT", "k", 5, 99))


def _event_draws(spark, d, by, batch):
    ranked = rank_pool(table(spark, d, "events"), "event_id", by)
    return EXTRACT.label(ranked, "props").withColumn("step", F.floor((F.col("position") - 1) / batch))


@query(f"WITH p AS ({EVENTS}), draws AS (SELECT *, (row_number() OVER (ORDER BY rk) - 1) // 500 AS step FROM p) SELECT event_type, step, {PROGRESS} FROM ({running_sql('draws', 'event_type')})")
def select_progress_uniform(spark, d):
    return _progress(progress_of(_event_draws(spark, d, [], 500), "label", "is_valid", ["event_type"]), "event_type")


@query(f"WITH p AS ({EVENTS}), draws AS (SELECT *, (row_number() OVER (PARTITION BY event_type ORDER BY rk) - 1) // 100 AS step FROM p) SELECT event_type, step, {PROGRESS} FROM ({running_sql('draws', 'event_type')})")
def select_progress_by_group(spark, d):
    return _progress(progress_of(_event_draws(spark, d, ["event_type"], 100), "label", "is_valid", ["event_type"]), "event_type")


@query(f"SELECT event_type, count(*) AS calls, count(*) FILTER (ok) AS n_valid, round(avg(v) FILTER (ok), 6) AS estimate FROM ({EVENTS}) GROUP BY 1")
def select_final_exact(spark, d):
    draws = _event_draws(spark, d, [], 500)
    v = F.when(F.col("is_valid"), F.col("label").cast("double"))
    return draws.groupBy("event_type").agg(F.count("*").alias("calls"), F.count(v).alias("n_valid"), r6(F.avg(v)).alias("estimate"))


def _progress(df, *by):
    return df.select(*by, F.col("step").cast("bigint").alias("step"), "calls", "n_valid", r6("estimate").alias("estimate"), r6("half_width").alias("half_width"))


# filters: a pool (key, stratum, ok, v, rk), the pilot, priorities, steps


def filter_sql(pool: str, pilot: str = "greatest(total // 20, 2 * h)", batch: str = "greatest(1, total // 100)") -> str:
    return f"""pool AS ({pool}),
n AS (SELECT count(*) AS total, count(DISTINCT stratum) AS h FROM pool),
par AS (SELECT *, {pilot} AS m, {batch} AS batch FROM n),
sized AS (SELECT stratum, count(*) AS n_total FROM pool GROUP BY 1),
exact AS (SELECT stratum, n_total, (m - h) * n_total / total::DOUBLE AS x, m - h AS rest FROM sized, par),
alloc AS (SELECT stratum, n_total, 1 + floor(x + 1e-9)::BIGINT + (row_number() OVER (ORDER BY round(x - floor(x + 1e-9), 9) DESC, stratum) <= rest - sum(floor(x + 1e-9)) OVER ())::BIGINT AS n_pilot FROM exact),
ranked AS (SELECT pool.*, n_total, n_pilot, row_number() OVER (PARTITION BY stratum ORDER BY rk) AS position FROM pool JOIN alloc USING (stratum)),
rates AS (SELECT stratum, any_value(n_total) AS n_total, count(*) AS n_drawn, sum(ok::INT)::BIGINT AS n_valid, avg(ok::INT::DOUBLE) AS p_hat FROM ranked WHERE position <= n_pilot GROUP BY 1),
prior AS (SELECT *, row_number() OVER (ORDER BY p_hat DESC, n_total DESC, stratum) AS priority FROM rates),
draws AS (
  SELECT ranked.*, 0::BIGINT AS step FROM ranked WHERE position <= n_pilot
  UNION ALL
  SELECT r.*, 1 + (row_number() OVER (ORDER BY priority, position) - 1) // (SELECT batch FROM par) AS step FROM ranked r JOIN prior USING (stratum) WHERE position > r.n_pilot
)"""


W3 = f"SELECT doc_id AS key, lang AS stratum, quality = 1 AS ok, n_chars::DOUBLE AS v, md5('42:' || doc_id) AS rk FROM {LABELLED}"
W4 = f"SELECT doc_id AS key, source AS stratum, quality = 1 AS ok, (lang = 'en')::INT::DOUBLE AS v, md5('42:' || doc_id) AS rk FROM {LABELLED}"
W5 = f"SELECT doc_id AS key, source AS stratum, lang = 'fr' AS ok, ({NUMBER.format(tag='like')} % 1000)::DOUBLE AS v, md5('42:' || doc_id) AS rk FROM documents"
W3R = f"SELECT doc_id AS key, lang AS stratum, NOT {low_quality_sql()} AS ok, n_chars::DOUBLE AS v, md5('42:' || doc_id) AS rk FROM {LABELLED}"


def w3(spark, d):
    return labelled(spark, d).select(F.col("doc_id").alias("key"), F.col("lang").alias("stratum"), (F.col("quality") == 1).alias("label"), F.col("n_chars").cast("double").alias("v"))


def w4(spark, d):
    return labelled(spark, d).select(F.col("doc_id").alias("key"), F.col("source").alias("stratum"), (F.col("quality") == 1).alias("label"), (F.col("lang") == "en").cast("double").alias("v"))


def w5(spark, d):
    docs = with_counts(table(spark, d, "documents"))
    return docs.select(F.col("doc_id").alias("key"), F.col("source").alias("stratum"), (F.col("lang") == "fr").alias("label"), F.col("like_count").cast("double").alias("v"))


def w3_rules(spark, d):
    rows = RuleLabeler(~low_quality()).label(labelled(spark, d))
    return rows.select(F.col("doc_id").alias("key"), F.col("lang").alias("stratum"), "label", F.col("n_chars").cast("double").alias("v"))


def _params(pool) -> tuple[int, int]:
    r = pool.agg(F.count("*").alias("n"), F.count_distinct("stratum").alias("h")).first()
    return max(r.n // 20, 2 * r.h), max(1, r.n // 100)


def scheduled(pool):
    return filter_engine.schedule(pool, *_params(pool))


@query(f"WITH {filter_sql(W3)} SELECT stratum, n_total, n_pilot FROM alloc")
def filter_pilot_alloc(spark, d):
    pool = w3(spark, d)
    sizes = {r.stratum: r["count"] for r in pool.groupBy("stratum").count().collect()}
    take = allocate.proportional(sizes, _params(pool)[0])
    return spark.createDataFrame([(h, sizes[h], take[h]) for h in sizes], "stratum string, n_total bigint, n_pilot bigint")


@query(f"WITH {filter_sql(W3)} SELECT stratum, n_drawn, n_valid, round(p_hat, 6) AS p_hat FROM rates")
def filter_valid_rate(spark, d):
    return valid_rate(scheduled(w3(spark, d)).where("step = 0")).select("stratum", "n_drawn", "n_valid", r6("p_hat").alias("p_hat"))


@query(f"WITH {filter_sql(W3)} SELECT stratum, priority FROM prior")
def filter_priority(spark, d):
    pool = w3(spark, d)
    rates = {r.stratum: r.p_hat for r in valid_rate(scheduled(pool).where("step = 0")).collect()}
    sizes = {r.stratum: r["count"] for r in pool.groupBy("stratum").count().collect()}
    return spark.createDataFrame(list(allocate.priority(rates, sizes).items()), "stratum string, priority bigint")


@query(f"WITH {filter_sql(W3)} SELECT key, step FROM draws")
def filter_schedule(spark, d):
    return scheduled(w3(spark, d)).select("key", "step")


def _pooled(pool):
    return _progress(progress_of(scheduled(pool), "v", "label"))


for _name, _sql, _pool in (("filter_progress_pooled", W3, w3), ("filter_progress_rate_en", W4, w4), ("filter_progress_likes", W5, w5), ("filter_progress_rules", W3R, w3_rules)):
    query(f"WITH {filter_sql(_sql)} SELECT step, {PROGRESS} FROM ({running_sql('draws')})", _name)(lambda spark, d, pool=_pool: _pooled(pool(spark, d)))


RANDOM = "WITH p AS ({pool}), draws AS (SELECT *, (row_number() OVER (ORDER BY rk) - 1) // (SELECT greatest(1, count(*) // 100) FROM p) AS step FROM p)"


def _random(pool):
    batch = _params(pool)[1]
    return rank_pool(pool, "key").withColumn("step", F.floor((F.col("position") - 1) / batch))


for _name, _sql, _pool in (("filter_random_progress", W3, w3), ("filter_random_likes", W5, w5)):
    query(RANDOM.format(pool=_sql) + f" SELECT step, {PROGRESS} FROM ({running_sql('draws')})", _name)(lambda spark, d, pool=_pool: _progress(progress_of(_random(pool(spark, d)), "v", "label")))


GRID = """grid AS (SELECT step, stratum, n_total, calls, n, s1, s2 FROM (
  SELECT g.step, g.stratum, g.n_total, sum(coalesce(c.calls, 0)) OVER w AS calls, sum(coalesce(c.n, 0)) OVER w AS n, sum(coalesce(c.s1, 0)) OVER w AS s1, sum(coalesce(c.s2, 0)) OVER w AS s2
  FROM (SELECT DISTINCT step FROM draws) s CROSS JOIN sized z CROSS JOIN LATERAL (SELECT s.step, z.stratum, z.n_total) g(step, stratum, n_total)
  LEFT JOIN (SELECT step, stratum, count(*) AS calls, count(*) FILTER (ok) AS n, coalesce(sum(v) FILTER (ok), 0) AS s1, coalesce(sum(v * v) FILTER (ok), 0) AS s2 FROM draws GROUP BY ALL) c ON c.step = g.step AND c.stratum = g.stratum
  WINDOW w AS (PARTITION BY g.stratum ORDER BY g.step)))"""
FINITE = "CASE WHEN n_total <= 1 OR calls >= n_total THEN 0 ELSE (n_total - calls) / (calls * (n_total - 1))::DOUBLE END"


def grid(draws):
    """Running sums of every stratum at every step, drawn from in that step or not: steps times strata rows."""
    ok = F.col("label")
    own = draws.groupBy("step", "stratum").agg(F.count("*").alias("calls"), F.count(F.when(ok, 1)).alias("n"), F.coalesce(F.sum(F.when(ok, F.col("v"))), F.lit(0.0)).alias("s1"), F.coalesce(F.sum(F.when(ok, F.col("v") * F.col("v"))), F.lit(0.0)).alias("s2"))
    sized = draws.groupBy("stratum").agg(F.count("*").alias("n_total"))
    every = draws.select("step").distinct().crossJoin(F.broadcast(sized.select("stratum")))
    full = every.join(own, ["step", "stratum"], "left").na.fill(0)
    return running(full, ["calls", "n", "s1", "s2"], ["stratum"]).join(F.broadcast(sized), "stratum")


@query(f"""WITH {filter_sql(W3)}, {GRID} SELECT step, sum(calls)::BIGINT AS calls, sum(n)::BIGINT AS n_valid,
  round(sum(n_total * n / calls::DOUBLE), 6) AS n_rows, round(sum(n_total * s1 / calls) / nullif(sum(n_total * n / calls::DOUBLE), 0), 6) AS estimate FROM grid GROUP BY 1""")
def filter_progress_stratified(spark, d):
    g = grid(scheduled(w3(spark, d)))
    rows, total = F.sum(F.col("n_total") * F.col("n") / F.col("calls")), F.sum(F.col("n_total") * F.col("s1") / F.col("calls"))
    return g.groupBy("step").agg(F.sum("calls").alias("calls"), F.sum("n").alias("n_valid"), r6(rows).alias("n_rows"), r6(total / F.nullif(rows, F.lit(0.0))).alias("estimate"))


@query(f"""WITH {filter_sql(W3)}, {GRID} SELECT step, round(sum(n_total * n / calls::DOUBLE), 6) AS estimate,
  round({Z} * sqrt(sum(n_total * n_total * {FINITE} * (n / calls::DOUBLE) * (1 - n / calls::DOUBLE))), 6) AS half_width FROM grid GROUP BY 1""")
def filter_count_ci(spark, d):
    p, n = F.col("n") / F.col("calls"), F.col("n_total")
    var = F.sum(n * n * finite_column("n_total", "calls") * p * (1 - p))
    return grid(scheduled(w3(spark, d))).groupBy("step").agg(r6(F.sum(n * p)).alias("estimate"), r6(F.lit(z(0.95)) * F.sqrt(var)).alias("half_width"))


@query(f"WITH {filter_sql(W5)} SELECT step, sum(count(*)) OVER (ORDER BY step)::BIGINT AS calls, sum(sum(ok::INT)) OVER (ORDER BY step)::BIGINT AS valids FROM draws GROUP BY step")
def filter_cumulative_valids(spark, d):
    return cumulative_valids(scheduled(w5(spark, d)), "label")


def _bound_sql(by_step: str) -> str:
    return f"SELECT min(calls) FILTER (half_width <= 0.2 * abs(estimate) AND n_valid >= 30) AS calls_to_bound, max(calls) AS all_calls FROM ({by_step})"


@query(f"WITH {filter_sql(W3)} " + _bound_sql(f"SELECT step, {PROGRESS} FROM ({running_sql('draws')})"))
def filter_time_to_bound(spark, d):
    log = _pooled(w3(spark, d)).withColumn("grp", F.lit(""))
    return metrics.time_to_bound(log, 0.2).select(F.col("cost").alias("calls_to_bound")).crossJoin(log.agg(F.max("calls").alias("all_calls")))


@query(f"WITH {filter_sql(W3)} SELECT step, round(abs(s1 / n - truth), 6) AS error, round(abs(s1 / n - truth) / truth, 6) AS relative_error FROM ({running_sql("draws")}), (SELECT avg(v) AS truth FROM pool WHERE ok)")
def abs_error_progress(spark, d):
    pool = w3(spark, d)
    truth = pool.where("label").agg(F.avg("v").alias("truth")).withColumn("grp", F.lit(""))
    log = progress_of(scheduled(pool), "v", "label").withColumn("grp", F.lit(""))
    return metrics.absolute_error(log, truth).select("step", r6("error").alias("error"), r6("relative_error").alias("relative_error"))


@query(f"""WITH {filter_sql(W5)}, q AS (SELECT step, {PROGRESS} FROM ({running_sql('draws')})),
rd AS (SELECT *, (row_number() OVER (ORDER BY rk) - 1) // (SELECT batch FROM par) AS step FROM pool), rq AS (SELECT step, {PROGRESS} FROM ({running_sql('rd')})),
c AS (SELECT 'priority' AS method, min(calls) FILTER (half_width <= 0.2 * abs(estimate) AND n_valid >= 30) AS calls, max(calls) AS total FROM q
  UNION ALL SELECT 'random', min(calls) FILTER (half_width <= 0.2 * abs(estimate) AND n_valid >= 30), max(calls) FROM rq)
SELECT method, round(calls / total::DOUBLE, 6) AS share, round(total / calls::DOUBLE, 6) AS speedup FROM c""")
def speedup_table(spark, d):
    pool, out = w5(spark, d), None
    total = pool.count()
    for name, draws in (("priority", scheduled(pool)), ("random", _random(pool))):
        log = progress_of(draws, "v", "label").withColumn("grp", F.lit(""))
        share = metrics.share_to_bound(log, float(total), bound=0.2).select(F.lit(name).alias("method"), r6("share").alias("share"), r6("speedup").alias("speedup"))
        out = share if out is None else out.unionByName(share)
    return out
