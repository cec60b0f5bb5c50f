"""Whole runs of the three engines and of the baselines beside their SQL, and the experiments, whose rows have none.

Runs over rules, given labels and column strata (or strata of one K-means round) are the same in SQL. Experiments cluster
with MLlib or take wall time; tests hold their exact and monotone parts.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from ..functions import rules
from ..functions.extract import JsonExtractor
from ..operators.estimate import z_of
from ..operators.labelers import ExtractLabeler, LookupLabeler, PredicateLabeler, RuleLabeler
from ..operators.order import rank_pool
from ..operators.strata import column_strata
from ..plans import baselines, metrics, select_engine
from ..plans import workloads as W
from ..plans.filter_engine import progressive_filter
from ..plans.group_engine import GroupConfig, progressive_group
from ..plans.query import Stop
from ..sources.store import new_path
from ..sources.tables import labelled, table
from ..streaming import stream
from .filtering import EVENTS, FINITE, GRID, PROGRESS, RANDOM, W3, W3R, Z, filter_sql, running_sql
from .grouping import CATEGORIES, FINITE as GROUP_FINITE
from .grouping import RANDOM as GROUP_RANDOM
from .grouping import W8, ZK, alloc_sql, cte_sql, state_sql
from .registry import query, r6
from .sampling import lloyd_assignment

# the projection's engine

EXTRACT = ExtractLabeler(JsonExtractor("k INT", "k", 5, 99))
PLAIN = EVENTS.replace(" BETWEEN 5 AND 99", " BETWEEN 0 AND 99")
STEPS = "WITH p AS ({events}), sizes AS (SELECT event_type, count(*) AS n_total FROM p GROUP BY 1), draws AS (SELECT *, (row_number() OVER ({part}ORDER BY rk) - 1) // {batch} AS step FROM p), run AS ({run}) "


def _select_sql(batch: int, part: str = "") -> str:
    return STEPS.format(events=EVENTS, part=part, batch=batch, run=running_sql("draws", "event_type"))


def _select(spark, d, **how):
    log = select_engine.progressive_select(table(spark, d, "events"), "event_id", "props", EXTRACT, ["event_type"], **how)
    return log.frame().select(F.col("grp").alias("event_type"), F.col("step").cast("bigint").alias("step"), "n_valid", r6("estimate").alias("estimate"), r6("half_width").alias("half_width"))


@query(_select_sql(500) + f"SELECT event_type, step, n_valid, estimate, half_width FROM (SELECT event_type, step, {PROGRESS} FROM run)")
def select_loop_events(spark, d):
    """Mean of an extracted number by event type, step by step to the end of the table."""
    return _select(spark, d, batch=500)


@query(_select_sql(20, "PARTITION BY event_type ") + f"SELECT event_type, step, n_valid, estimate, half_width FROM (SELECT event_type, step, {PROGRESS} FROM run) WHERE step < 5")
def select_loop_by_group(spark, d):
    """The same with as many draws from each group, for five steps."""
    return _select(spark, d, batch=100, design="by_group", stop=Stop(max_steps=5))


@query(_select_sql(500) + f"SELECT event_type, step, n AS n_valid, round(n_total * n / calls::DOUBLE, 6) AS estimate, round({Z} * sqrt(n_total * n_total * {FINITE} * (n / calls::DOUBLE) * (1 - n / calls::DOUBLE)), 6) AS half_width FROM run JOIN sizes USING (event_type)")
def select_loop_count(spark, d):
    """Number of valid extractions by event type, with intervals."""
    return _select(spark, d, batch=500, agg="count")


@query(_select_sql(500) + f"SELECT event_type, step, n AS n_valid, round(n_total * s1 / calls, 6) AS estimate, round({Z} * sqrt(greatest(0, CASE WHEN calls >= n_total THEN 0 ELSE n_total * n_total * (1 - calls / n_total::DOUBLE) * (s2 - s1 * s1 / calls) / (calls - 1) / calls END)), 6) AS half_width FROM run JOIN sizes USING (event_type)")
def select_loop_sum(spark, d):
    """Sum of valid extractions by event type: the interval holds the spread of the valid share too."""
    return _select(spark, d, batch=500, agg="sum")


@query(f"WITH p AS (SELECT page_id, regexp_extract(url, '/([a-z]{{2}})/', 1) AS g, len(regexp_extract_all(html, '<p>'))::DOUBLE AS v, true AS ok, md5('42:' || page_id) AS rk FROM pages), draws AS (SELECT *, (row_number() OVER (ORDER BY rk) - 1) // (SELECT greatest(1, round(count(*) * 0.1)::BIGINT) FROM p) AS step FROM p), run AS ({running_sql('draws', 'g')}), every AS (SELECT * FROM (SELECT DISTINCT g FROM p) CROSS JOIN (SELECT DISTINCT step FROM draws)) SELECT e.g AS page_lang, e.step, coalesce(n, 0) AS n_valid, estimate, half_width FROM every e ASOF LEFT JOIN (SELECT g, step, {PROGRESS}, n FROM run) r ON e.g = r.g AND e.step >= r.step")
def select_loop_pages(spark, d):
    """Mean number of paragraphs by page language, step by step."""
    log = W.run(W.w2(spark, d), batch_share=0.1)
    return log.frame().select(F.col("grp").alias("page_lang"), F.col("step").cast("bigint").alias("step"), "n_valid", r6("estimate").alias("estimate"), r6("half_width").alias("half_width"))


# the filter's engine


def _quality(docs):
    return PredicateLabeler(LookupLabeler(docs.select("doc_id", "quality"), "doc_id", "quality"), 1)


#: A tenth of the table a step.
TENTH = "greatest(1, total // 10)"


def _filter(spark, d, labeler=None, **how):
    docs = labelled(spark, d)
    how = {"batch": max(1, docs.count() // 10)} | how
    return progressive_filter(column_strata(docs, "lang"), "doc_id", "text", labeler or _quality(docs), "n_chars", **how).frame()


def _rounded(frame, *columns):
    return frame.select(F.col("step").cast("bigint").alias("step"), "calls", "n_valid", *[r6(c).alias(c) for c in columns])


BOTH = f"""SELECT step, calls, n_valid, estimate, half_width, estimate_stratified FROM (SELECT step, {PROGRESS} FROM ({running_sql('draws')}))
JOIN (SELECT step, round(sum(n_total * s1 / calls) / nullif(sum(n_total * n / calls::DOUBLE), 0), 6) AS estimate_stratified FROM grid GROUP BY 1) USING (step)"""


@query(f"WITH {filter_sql(W3, batch=TENTH)}, {GRID} {BOTH}")
def filter_loop_by_lang(spark, d):
    """Mean length of good texts, all steps: the engine itself, with strata by language and given labels."""
    return _rounded(_filter(spark, d), "estimate", "half_width", "estimate_stratified")


@query(f"WITH {filter_sql(W3R, batch=TENTH)}, {GRID} {BOTH}")
def filter_loop_rules(spark, d):
    """The same with a rule as the semantic predicate."""
    return _rounded(_filter(spark, d, RuleLabeler(~rules.low_quality())), "estimate", "half_width", "estimate_stratified")


SUM_WIDTH = f"CASE WHEN bool_or(calls < 2 AND calls < n_total) THEN NULL ELSE round({Z} * sqrt(greatest(0, sum(CASE WHEN calls >= n_total THEN 0 ELSE n_total * n_total * (1 - calls / n_total::DOUBLE) * (s2 - s1 * s1 / calls) / greatest(1, calls - 1) / calls END))), 2) END AS half_width"


@query(f"WITH {filter_sql(W3, batch=TENTH)}, {GRID} SELECT step, sum(calls)::BIGINT AS calls, sum(n)::BIGINT AS n_valid, round(sum(n_total * s1 / calls), 6) AS estimate, {SUM_WIDTH} FROM grid GROUP BY 1")
def filter_sum_ci(spark, d):
    """Sum over the filter as an expansion by stratum, with its interval, from the engine's loop."""
    return _rounded(_filter(spark, d, agg="sum"), "estimate", "half_width").withColumn("half_width", F.round("half_width", 2))


@query(f"WITH {filter_sql(W3, batch=TENTH)}, {GRID} SELECT step, sum(calls)::BIGINT AS calls, sum(n)::BIGINT AS n_valid, round(sum(n_total * n / calls::DOUBLE), 6) AS estimate, round({Z} * sqrt(sum(n_total * n_total * {FINITE} * (n / calls::DOUBLE) * (1 - n / calls::DOUBLE))), 6) AS half_width FROM grid GROUP BY 1")
def filter_loop_count(spark, d):
    """Number of rows that the predicate accepts, from the engine's loop."""
    return _rounded(_filter(spark, d, agg="count"), "estimate", "half_width")


@query(RANDOM.format(pool=W3).replace("// 100", "// 10") + f" SELECT step, calls, n_valid, estimate, half_width FROM (SELECT step, {PROGRESS} FROM ({running_sql('draws')}))")
def filter_loop_random(spark, d):
    """The random baseline's loop over the same filter."""
    docs = labelled(spark, d)
    batch = max(1, docs.count() // 10)
    return _rounded(baselines.random_filter(docs, "doc_id", "text", _quality(docs), "n_chars", pilot=batch, batch=batch).frame(), "estimate", "half_width")


RATE_BATCH = "greatest(12, total // 6)"


@query(f"""WITH {filter_sql(W3, batch=RATE_BATCH)}, {alloc_sql("more", "rates", "n_total * (n_valid + 1) / (n_drawn + 2)::DOUBLE", "SELECT batch FROM par", "n_total - n_drawn")},
two AS (SELECT r.stratum, 0::BIGINT AS step, ok, v FROM ranked r WHERE position <= n_pilot UNION ALL SELECT r.stratum, 1, ok, v FROM ranked r JOIN more USING (stratum) WHERE position > n_pilot AND position <= n_pilot + n_draws)
SELECT step, calls, n_valid, estimate, half_width FROM (SELECT step, {PROGRESS} FROM ({running_sql('two')}))""")
def filter_loop_rate(spark, d):
    """Draws by size times smoothed rate: the pilot and one batch."""
    total = labelled(spark, d).count()
    return _rounded(_filter(spark, d, mode="proportional_to_rate", batch=max(12, total // 6), stop=Stop(max_steps=2)), "estimate", "half_width")


@query(f"WITH {filter_sql(W3, batch=TENTH)} SELECT step, half_width, round(2 * hw, 6) AS width FROM (SELECT step, {PROGRESS}, CASE WHEN n > 1 THEN {Z} * sqrt(greatest(0, (s2 - s1 * s1 / n) / (n - 1)) / n) END AS hw FROM ({running_sql('draws')}))")
def filter_interval_width(spark, d):
    """Half-width and width of the interval at each step."""
    return metrics.interval(_filter(spark, d)).select(F.col("step").cast("bigint").alias("step"), r6("half_width").alias("half_width"), r6("width").alias("width"))


SEEDS = (1, 2, 3, 4, 5, 6, 7, 8)
COVERED = W3.replace("md5('42:' || doc_id)", "md5(seed || ':' || doc_id)").replace("SELECT doc_id", "SELECT seed, doc_id") + f" CROSS JOIN (SELECT unnest([{', '.join(map(str, SEEDS))}]) AS seed)"


@query(f"WITH p AS ({COVERED}), draws AS (SELECT *, (row_number() OVER (PARTITION BY seed ORDER BY rk) - 1) // (SELECT greatest(1, count(*) // 80) FROM p) AS step FROM p), r AS (SELECT seed, step, calls, n, s1 / n AS e, {Z} * sqrt(greatest(0, (s2 - s1 * s1 / n) / (n - 1)) / n) AS hw FROM ({running_sql('draws', 'seed')}) WHERE n > 1) SELECT step, round(avg((abs(e - truth) <= hw + 1e-12)::INT), 6) AS coverage, count(*) AS seeds FROM r, (SELECT avg(v) AS truth FROM p WHERE ok) GROUP BY 1")
def filter_coverage(spark, d):
    """Share of seeds whose interval holds the truth, by step of random draws."""
    from ..operators.estimate import progress_of

    rows = labelled(spark, d).select(F.col("doc_id").alias("key"), (F.col("quality") == 1).alias("label"), F.col("n_chars").cast("double").alias("v"))
    batch, logs = max(1, rows.count() // 10), []
    for seed in SEEDS:
        draws = rank_pool(rows, "key", seed=seed).withColumn("step", F.floor((F.col("position") - 1) / batch))
        logs.append(progress_of(draws, "v", "label").withColumns({"seed": F.lit(seed), "grp": F.lit("")}))
    truth = rows.where("label").agg(F.avg("v").alias("truth")).withColumn("grp", F.lit(""))
    return metrics.coverage(W._union(logs), truth).select(F.col("step").cast("bigint").alias("step"), r6("coverage").alias("coverage"), "seeds")


# the grouping's engine, on given vectors with strata of one K-means round

TWO = f"""draws1 AS (SELECT pos.* FROM pos JOIN take0 ON pos.stratum = take0.stratum JOIN take1 ON pos.stratum = take1.stratum WHERE position > take0.n_draws AND position <= take0.n_draws + take1.n_draws),
both_rounds AS (SELECT key, stratum, label FROM draws0 UNION ALL SELECT key, stratum, label FROM draws1), {state_sql("state1", "both_rounds")}"""


def share_sql(state: str, step: int) -> str:
    p = "(coalesce(x, 0) / n_drawn::DOUBLE)"
    width = lambda v: f"round({ZK} * sqrt(sum((n_total / total::DOUBLE) ** 2 * {GROUP_FINITE} * {v})), 6)"
    return f"SELECT {step}::BIGINT AS step, c.k AS category, round(sum(n_total * coalesce(x, 0) / n_drawn::DOUBLE) / sum(n_total), 6) AS share, {width('het')} AS half_width, {width(f'{p} * (1 - {p})')} AS half_width_own FROM (SELECT unnest(range(10))::VARCHAR AS k) c CROSS JOIN {state} s CROSS JOIN per LEFT JOIN {state}_f f ON f.stratum = s.stratum AND f.label = c.k GROUP BY c.k"


def _vectors(spark, d):
    e = table(spark, d, "embeddings").select("vec_id", F.col("label").cast("string").alias("kind"), "embedding")
    return e.join(lloyd_assignment(spark, d), "vec_id"), LookupLabeler(e.select("vec_id", "kind"), "vec_id", "kind")


def _group(spark, d, **config):
    df, labeler = _vectors(spark, d)
    return progressive_group(df, "vec_id", "kind", labeler, CATEGORIES, config=GroupConfig(**config), stop=Stop(max_steps=2, relative=False))


def _shares(log):
    rows = [(r["step"], r["grp"], round(r["estimate"], 6), round(r["half_width"], 6), round(r["half_width_own"], 6)) for r in log.rows]
    return log.spark.createDataFrame(rows, "step bigint, category string, share double, half_width double, half_width_own double")


@query(cte_sql() + f", {TWO} {share_sql('state0', 0)} UNION ALL {share_sql('state1', 1)}")
def group_loop_static(spark, d):
    """Two rounds of the engine over strata that stay: by size, then by size and spread."""
    return _shares(_group(spark, d, adjust=False))


@query(cte_sql() + f""", {TWO}, f AS (SELECT c.k, s.n_total, a.n_draws AS n0, b.n_draws AS n1, count(*) FILTER (d.r = 0 AND d.label = c.k) AS x0, count(*) FILTER (d.r = 1 AND d.label = c.k) AS x1
  FROM (SELECT unnest(range(10))::VARCHAR AS k) c CROSS JOIN sized s JOIN take0 a USING (stratum) JOIN take1 b USING (stratum)
  LEFT JOIN (SELECT 0 AS r, stratum, label FROM draws0 UNION ALL SELECT 1, stratum, label FROM draws1) d ON d.stratum = s.stratum GROUP BY c.k, s.stratum, s.n_total, a.n_draws, b.n_draws),
g AS (SELECT k, total, sum(n0) AS w0, sum(n1) AS w1, sum(n_total * x0 / n0::DOUBLE) / total AS s0, (sum(x0) + sum((n_total - n0) * x1 / n1::DOUBLE)) / total AS s1,
  sum((n_total / total::DOUBLE) ** 2 * (n_total - n0) / (n0 * (n_total - 1))::DOUBLE * (x0 / n0::DOUBLE) * (1 - x0 / n0::DOUBLE)) AS v0,
  sum(((n_total - n0) / total::DOUBLE) ** 2 * CASE WHEN n_total - n0 <= 1 OR n1 >= n_total - n0 THEN 0 ELSE (n_total - n0 - n1) / (n1 * (n_total - n0 - 1))::DOUBLE END * (x1 / n1::DOUBLE) * (1 - x1 / n1::DOUBLE)) AS v1
  FROM f CROSS JOIN per GROUP BY k, total)
SELECT k AS category, round((w0 * s0 + w1 * s1) / (w0 + w1), 6) AS share, round({ZK} * sqrt((w0 / (w0 + w1)::DOUBLE) ** 2 * v0 + (w1 / (w0 + w1)::DOUBLE) ** 2 * v1), 6) AS half_width FROM g""")
def group_share_fresh(spark, d):
    """The estimate of each round under the strata that it drew from, weighted by draws, after two rounds."""
    rows = [(r["grp"], round(r["estimate_stratified"], 6), round(r["half_width_stratified"], 6)) for r in _group(spark, d, adjust=False).rows if r["step"] == 1]
    return spark.createDataFrame(rows, "category string, share double, half_width double")


SPLIT_GAMMA, SPLIT_THETA = 0.15, 0.5
SPLIT = cte_sql(SPLIT_GAMMA, SPLIT_THETA) + f""", opened AS (SELECT stratum, row_number() OVER (ORDER BY round(n_total * norm, 9) DESC, stratum) AS turn FROM impure WHERE stratum IN (SELECT stratum FROM few)),
moved AS (SELECT a.key, a.label, a.rk, CASE WHEN s.key IS NOT NULL AND o.turn IS NOT NULL THEN (SELECT max(stratum) FROM sized) + o.turn ELSE a.stratum END AS stratum FROM a LEFT JOIN sep s ON a.key = s.key LEFT JOIN opened o ON a.stratum = o.stratum),
sized2 AS (SELECT stratum, count(*) AS n_total FROM moved GROUP BY 1), known AS (SELECT m.* FROM moved m JOIN draws0 USING (key)), {state_sql("state0b", "known", "sized2")},
{alloc_sql("take2", "state0b", "n_total * sqrt(het)", "SELECT n FROM per", "n_total - n_drawn")},
draws2 AS (SELECT key, stratum, label FROM (SELECT *, row_number() OVER (PARTITION BY stratum ORDER BY rk) AS place FROM moved WHERE key NOT IN (SELECT key FROM draws0)) JOIN take2 USING (stratum) WHERE place <= n_draws),
both2 AS (SELECT key, stratum, label FROM known UNION ALL SELECT key, stratum, label FROM draws2), {state_sql("state2", "both2", "sized2")}"""


def _adjusted(spark, d):
    return _group(spark, d, gamma=SPLIT_GAMMA, theta=SPLIT_THETA, h_max=64)


@query(SPLIT + f" {share_sql('state0', 0)} UNION ALL {share_sql('state2', 1)}")
def group_loop_adjusted(spark, d):
    """Two rounds of the engine with strata split between them: draws that do not fit leave with their look-alikes."""
    return _shares(_adjusted(spark, d))


@query(SPLIT + " SELECT key, stratum FROM moved")
def group_loop_assignment(spark, d):
    """The strata of all rows after these two rounds' one adjustment."""
    return _adjusted(spark, d).details["assignment"].select("key", F.col("stratum").cast("bigint").alias("stratum"))


@query(SPLIT + " SELECT 0::BIGINT AS round, count(*) AS strata, round(max(norm), 6) AS worst, round(sum(n_total * norm) / sum(n_total), 6) AS weighted FROM state0 UNION ALL SELECT 1, count(*), round(max(norm), 6), round(sum(n_total * norm) / sum(n_total), 6) FROM state2")
def group_purity_rounds(spark, d):
    """Number of strata and their normalised heterogeneity, round by round."""
    rows = [(p["round"], p["strata"], round(p["worst"], 6), round(p["weighted"], 6)) for p in _adjusted(spark, d).details["purity"]]
    return spark.createDataFrame(rows, "round bigint, strata bigint, worst double, weighted double")


@query(GROUP_RANDOM.format(pool=W8) + f" SELECT step, k AS category, round(x / calls::DOUBLE, 6) AS share, round({z_of(0.95, 4)!r} * sqrt(CASE WHEN calls >= total THEN 0 ELSE (total - calls) / (calls * (total - 1))::DOUBLE END * (x / calls::DOUBLE) * (1 - x / calls::DOUBLE)), 6) AS half_width FROM t")
def group_loop_random(spark, d):
    """Language shares by random draws: the baseline's loop."""
    log = W.run(W.w8(spark, d), "random")
    return log.frame().select(F.col("step").cast("bigint").alias("step"), F.col("grp").alias("category"), r6("estimate").alias("share"), r6("half_width").alias("half_width"))


# runs over clustered strata


@query()
def filter_loop_kmeans(spark, d):
    return W.run(W.with_strata(W.w3(spark, d), 5), batch_share=0.1).frame()


@query()
def filter_loop_balanced(spark, d):
    """Rate of English among good texts, as many good as bad."""
    return W.run(W.with_strata(W.w4(spark, d), 4), batch_share=0.1).frame()


@query()
def filter_loop_view_counts(spark, d):
    return W.run(W.with_strata(W.w5(spark, d, "view_count"), 5), batch_share=0.1).frame()


@query()
def filter_loop_turns(spark, d):
    return W.run(W.with_strata(W.w6(spark, d), 4), batch_share=0.1).frame()


@query()
def group_loop_full(spark, d):
    return W.run(W.with_strata(W.w7(spark, d), 8), config=GroupConfig(h_max=16, gamma=0.97)).frame()


@query()
def group_loop_value(spark, d):
    return W.run(W.with_strata(W.w8b(spark, d), 8), config=GroupConfig(adjust=False)).frame()


# experiments


@query()
def compare_filter(spark, d):
    """Share of draws to the 5 % bound of two filters, by priority and at random."""
    return W._union([W.compare(W.with_strata(w(spark, d), 5), ("ours", "random"), batch_share=0.05) for w in (W.w4, W.w5)])


ADJUST = GroupConfig(h_max=16, gamma=0.97)


@query()
def compare_strategies(spark, d):
    """Language shares, whose strata are well aligned: adjusted, static, random."""
    return W.compare_grouping(W.with_strata(W.w8(spark, d), 8), config=ADJUST)


@query()
def compare_strategies_three(spark, d):
    """Shares of three classes, whose strata are moderately aligned."""
    return W.compare_grouping(W.with_strata(W.w7(spark, d), 8), config=ADJUST)


@query()
def compare_strategies_unaligned(spark, d):
    """Shares of ten labels that the vectors say little of."""
    return W.compare_grouping(W.with_strata(W.w7b(spark, d), 8), config=GroupConfig(h_max=16, gamma=0.3))


@query()
def error_two_averages(spark, d):
    return W.error_against_draws(spark, d)


@query()
def interval_panels(spark, d):
    return W.interval_panels(spark, d, batch_share=0.1)


@query()
def ablation_strata(spark, d):
    return W.ablation_strata(W.w5(spark, d), batch_share=0.05)


@query()
def ablation_theta_gamma(spark, d):
    """First strata, purity threshold and similarity threshold of the three-class grouping, one at a time."""
    return W.ablation_grouping(W.w7(spark, d), stop=Stop(bound=0.05, relative=False))


@query()
def total_times(spark, d):
    """Wall seconds of full scan, batch system and ours, for an extraction, a filter and a grouping."""
    return W.total_times([W.w1(spark, d), lambda: W.with_strata(W.w3(spark, d), 5), lambda: W.with_strata(W.w7(spark, d), 8)], config=replace(ADJUST, scope="per_category"))


@query()
def scaleout_measured(spark, d):
    """Wall seconds to the same draws with 1 to 4 served instances: a filter and a grouping."""
    good = W.Served(lambda: W.with_strata(W.w4(spark, d), 4), lambda text: str(not rules.low_quality_of(text)).lower(), "string", seconds=0.1, steps=3, how={"batch_share": 0.3})
    language = W.Served(lambda: W.with_strata(W.w8(spark, d), 8), rules.language_of, "string", seconds=0.08, steps=2, how={"config": GroupConfig(adjust=False, scope="per_category")})
    return W.scaleouts([good, language])


@query()
def scaleout_model(spark, d):
    return W.scaleout_model(W.with_strata(W.w4(spark, d), 4), batch_share=0.1)


# streams


@query(f"SELECT event_type, calls, n AS n_valid, round(s1 / n, 6) AS estimate, round({Z} * sqrt(greatest(0, (s2 - s1 * s1 / n) / (n - 1)) / n), 6) AS half_width FROM (SELECT event_type, count(*) AS calls, count(*) FILTER (ok) AS n, sum(v) FILTER (ok) AS s1, sum(v * v) FILTER (ok) AS s2 FROM ({PLAIN}) GROUP BY 1)")
def stream_progress_final(spark, d):
    """W1 as two streaming queries; the last trigger's answers."""
    events = table(spark, d, "events").select("event_id", "event_type", "props")
    draws = rank_pool(events, "event_id").withColumn("step", F.floor((F.col("position") - 1) / max(1, events.count() / 4))).drop("draw_rank", "position")
    source, spec = new_path(spark, "staged"), stream.StreamSpec("label", ("event_type",))
    stream.stage_draws(draws, source)
    log = stream.DirTransport(new_path(spark, "transport"))
    labeler = ExtractLabeler(JsonExtractor("k INT", "k", 0, 99))
    stream.label_stream(spark, source, spark.read.parquet(source).schema, labeler, "props", log, new_path(spark, "checkpoint")).awaitTermination()
    out = new_path(spark, "answers")
    labelled = log.read(spark, spark.read.parquet(log.path).schema)
    stream.progressive_stream(labelled, spec, out, new_path(spark, "checkpoint")).awaitTermination()
    every = spark.read.option("basePath", out).parquet(out)
    last = every.agg(F.max("trigger").alias("t")).first().t
    every = every.where(F.col("trigger") == last)
    return every.select("event_type", "calls", "n_valid", r6("estimate").alias("estimate"), r6("half_width").alias("half_width"))
