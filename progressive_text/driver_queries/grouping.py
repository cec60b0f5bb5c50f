"""The phases of semantic grouping, one by one, on given vectors (ten categories, strata of one K-means round)."""

from __future__ import annotations

from statistics import NormalDist

import numpy as np
from pyspark.sql import functions as F

from ..functions.vectors import mean_vector
from ..operators import allocate, refine
from ..operators.estimate import GroupState, Moments, group_shares, group_value, moments_of, random_share, z_of
from ..operators.order import draw_rank, rank_pool, take_next
from ..operators.stats import frequencies, group_states, purity, stratum_state
from ..sources.store import saved
from ..sources.tables import table
from .batch import LABELLED
from .registry import query, r6
from .sampling import LLOYD, lloyd_assignment

CATEGORIES = [str(i) for i in range(10)]
THETA, GAMMA, H_MAX = 0.9, 0.3, 11
ZK = repr(z_of(0.95, 10))


def alloc_sql(name: str, source: str, weight: str, n: str, left: str) -> str:
    """A floor of one, the rest by weight and largest remainder; no stratum is full here."""
    return f"""{name} AS (
  SELECT stratum, 1 + floor(x + 1e-9)::BIGINT + (row_number() OVER (ORDER BY round(x - floor(x + 1e-9), 9) DESC, stratum) <= rest - sum(floor(x + 1e-9)) OVER ())::BIGINT AS n_draws
  FROM (SELECT stratum, (({n}) - count(*) OVER ()) AS rest, (({n}) - count(*) OVER ()) * ({weight}) / sum({weight}) OVER () AS x FROM {source} WHERE {left} > 0))"""


def state_sql(name: str, draws: str, sized: str = "sized") -> str:
    return f"""{name}_f AS (SELECT stratum, label, count(*) AS x FROM {draws} GROUP BY ALL),
{name} AS (SELECT s.stratum, n_total, n_drawn, dominant, het, het / 0.9 AS norm FROM {sized} s JOIN (
  SELECT stratum, sum(x)::BIGINT AS n_drawn, (list(label ORDER BY x DESC, label))[1] AS dominant, sum((x / t) * (1 - x / t)) AS het
  FROM (SELECT *, sum(x) OVER (PARTITION BY stratum)::DOUBLE AS t FROM {name}_f) GROUP BY 1) USING (stratum))"""


def cte_sql(gamma: float = GAMMA, theta: float = THETA) -> str:
    return f"""WITH {LLOYD},
sized AS (SELECT stratum, count(*) AS n_total FROM a GROUP BY 1),
per AS (SELECT count(*) AS total, round(count(*) * 0.1)::BIGINT AS n FROM a),
{alloc_sql("take0", "sized", "n_total::DOUBLE", "SELECT n FROM per", "n_total")},
pos AS (SELECT a.*, row_number() OVER (PARTITION BY stratum ORDER BY rk) AS position FROM a),
draws0 AS (SELECT pos.* FROM pos JOIN take0 USING (stratum) WHERE position <= n_draws),
{state_sql("state0", "draws0")},
{alloc_sql("take1", "state0", "n_total * sqrt(het)", "SELECT n FROM per", "n_total - n_drawn")},
impure AS (SELECT *, row_number() OVER (ORDER BY n_total * norm DESC, stratum) AS turn FROM state0 WHERE norm > {theta}),
few AS (SELECT d.key, d.stratum, d.label, d.vec FROM draws0 d JOIN impure i USING (stratum) WHERE d.label <> i.dominant),
alike AS (SELECT p.key, p.stratum, p.vec FROM pos p JOIN impure USING (stratum) WHERE p.key NOT IN (SELECT key FROM draws0)
  AND EXISTS (SELECT 1 FROM few f WHERE f.stratum = p.stratum AND round(list_cosine_similarity(f.vec, p.vec), 12) > {gamma})),
sep AS (SELECT key, stratum, vec FROM few UNION ALL SELECT key, stratum, vec FROM alike)"""


CTE = cte_sql()


def _pool(spark, d):
    e = table(spark, d, "embeddings").select("vec_id", F.col("label").cast("string").alias("label"), "embedding")
    return saved(e.join(lloyd_assignment(spark, d), "vec_id").select(F.col("vec_id").alias("key"), "stratum", "label", "embedding", draw_rank("vec_id").alias("draw_rank")), "groups")


def _sizes(pool) -> dict:
    return {r.stratum: r["count"] for r in pool.groupBy("stratum").count().collect()}


def _round0(spark, d):
    """pool, sizes, allocation and draws of the first round."""
    pool = _pool(spark, d)
    sizes = _sizes(pool)
    take = allocate.proportional(sizes, round(sum(sizes.values()) * 0.1))
    return pool, sizes, take, saved(take_next(pool, take), "draws")


def _sized(spark, sizes):
    return spark.createDataFrame(list(sizes.items()), "stratum int, n_total bigint")


def _numbers(spark, numbers: dict, name: str):
    return spark.createDataFrame([(h, n) for h, n in numbers.items()], f"stratum bigint, {name} bigint")


@query(CTE + " SELECT stratum, n_draws FROM take0")
def group_alloc_round0(spark, d):
    return _numbers(spark, _round0(spark, d)[2], "n_draws")


@query(CTE + " SELECT key, stratum FROM draws0")
def group_draws_round0(spark, d):
    return _round0(spark, d)[3].select("key", F.col("stratum").cast("bigint").alias("stratum"))


@query(CTE + " SELECT stratum, label AS category, x FROM state0_f")
def group_frequencies(spark, d):
    return frequencies(_round0(spark, d)[3], CATEGORIES).select(F.col("stratum").cast("bigint").alias("stratum"), "category", "x")


def _state(spark, d):
    pool, sizes, _, draws = _round0(spark, d)
    return stratum_state(draws, _sized(spark, sizes), CATEGORIES)


@query(CTE + " SELECT stratum, n_total, n_drawn, dominant, round(het, 6) AS heterogeneity, round(norm, 6) AS norm_heterogeneity FROM state0")
def group_state_round0(spark, d):
    return _state(spark, d).select(F.col("stratum").cast("bigint").alias("stratum"), "n_total", "n_drawn", "dominant", r6("heterogeneity").alias("heterogeneity"), r6("norm_heterogeneity").alias("norm_heterogeneity"))


@query(CTE + " SELECT stratum, n_draws FROM take1")
def group_neyman_round1(spark, d):
    _, sizes, take, draws = _round0(spark, d)
    het = {h: s.heterogeneity for h, s in group_states(draws, sizes, CATEGORIES).items()}
    return _numbers(spark, allocate.neyman(sizes, het, round(sum(sizes.values()) * 0.1), {h: sizes[h] - take[h] for h in sizes}), "n_draws")


@query(CTE + " SELECT stratum, round(norm, 6) AS norm_heterogeneity FROM impure")
def group_impure(spark, d):
    return refine.impure(_state(spark, d), THETA).select(F.col("stratum").cast("bigint").alias("stratum"), r6("norm_heterogeneity").alias("norm_heterogeneity"))


def _refined(spark, d):
    pool, sizes, _, draws = _round0(spark, d)
    states = saved(stratum_state(draws, _sized(spark, sizes), CATEGORIES), "states")
    bad = refine.impure(states, THETA)
    few = refine.minority(draws, bad)
    rest = pool.join(draws.select("key"), "key", "left_anti").join(bad.select("stratum"), "stratum", "left_semi")
    return pool, sizes, states, few, rest


def _keys(df):
    return df.select("key", F.col("stratum").cast("bigint").alias("stratum"))


@query(CTE + " SELECT key, stratum, label FROM few")
def group_minority(spark, d):
    return _refined(spark, d)[3].select("key", F.col("stratum").cast("bigint").alias("stratum"), "label")


for _method in ("matrix", "join"):

    @query(CTE + " SELECT key, stratum FROM alike", name=f"group_lookalikes_{_method}")
    def _lookalikes(spark, d, method=_method):
        _, _, _, few, rest = _refined(spark, d)
        return _keys(refine.lookalikes(rest, few, GAMMA, method=method))


@query(CTE + " SELECT key, stratum FROM sep")
def group_separated(spark, d):
    _, _, _, few, rest = _refined(spark, d)
    return _keys(refine.separated(few, refine.lookalikes(rest, few, GAMMA)))


def _turns(states) -> list:
    rows = sorted(refine.impure(states, THETA).collect(), key=lambda r: (-round(r.n_total * r.norm_heterogeneity, 9), r.stratum))
    return [r.stratum for r in rows]


@query(CTE + f""", opened AS (SELECT stratum, turn FROM impure WHERE turn <= {H_MAX} - (SELECT count(*) FROM sized) AND stratum IN (SELECT stratum FROM few))
SELECT a.key, CASE WHEN s.key IS NOT NULL AND o.turn IS NOT NULL THEN (SELECT max(stratum) FROM sized) + o.turn ELSE a.stratum END AS stratum
FROM a LEFT JOIN sep s ON a.key = s.key LEFT JOIN opened o ON a.stratum = o.stratum""")
def group_split_assignment(spark, d):
    from ..operators.strata import overlay

    pool, sizes, states, few, rest = _refined(spark, d)
    away = refine.separated(few, refine.lookalikes(rest, few, GAMMA))
    open_for = H_MAX - len(sizes)
    target = [(h, max(sizes) + 1 + i) for i, h in enumerate(_turns(states)[:open_for])]
    moves = away.join(F.broadcast(spark.createDataFrame(target, "stratum int, to_stratum int")), "stratum").select(F.lit(0).alias("t"), "key", "to_stratum")
    return _keys(overlay(pool.select("key", "stratum"), moves))


UNIT_MEANS = """{n} AS (SELECT stratum, list(m ORDER BY i) AS mean FROM (SELECT stratum, i, avg(v) AS m FROM (SELECT stratum, unnest(vec) AS v, generate_subscripts(vec, 1) AS i FROM {t}) GROUP BY ALL) GROUP BY 1)"""


@query(CTE + f""", {UNIT_MEANS.format(n="means", t="a")}, {UNIT_MEANS.format(n="own", t="sep")},
want AS (SELECT stratum, (list(label ORDER BY x DESC, label))[1] AS label FROM (SELECT stratum, label, count(*) AS x FROM few GROUP BY ALL) GROUP BY 1)
SELECT source AS stratum, coalesce(target, -1) AS target FROM (
  SELECT w.stratum AS source, t.stratum AS target, row_number() OVER (PARTITION BY w.stratum ORDER BY round(list_cosine_similarity(o.mean, m.mean), 12) DESC, t.stratum) AS o
  FROM want w JOIN own o ON w.stratum = o.stratum LEFT JOIN state0 t ON t.dominant = w.label AND t.stratum <> w.stratum LEFT JOIN means m ON m.stratum = t.stratum) WHERE o = 1""")
def group_merge_target(spark, d):
    pool, sizes, states, few, rest = _refined(spark, d)
    away = refine.separated(few, refine.lookalikes(rest, few, GAMMA)).join(pool.select("key", "embedding"), "key")
    vectors = lambda df: {r.stratum: np.array(r["mean"]) for r in mean_vector(df, "stratum").collect()}
    means, own = vectors(pool), vectors(away)
    dominants = {r.stratum: r.dominant for r in states.collect()}
    counts: dict = {}
    for r in few.groupBy("stratum", "label").count().collect():
        counts.setdefault(r.stratum, {})[r.label] = r["count"]
    rows = []
    for h in own:
        label = min(counts[h], key=lambda c, h=h: (-counts[h][c], c))
        to = refine.merge_target(label, own[h], h, dominants, means)
        rows.append((h, -1 if to is None else to))
    return spark.createDataFrame(rows, "stratum bigint, target bigint")


FINITE = "CASE WHEN n_total <= 1 OR n_drawn >= n_total THEN 0 ELSE (n_total - n_drawn) / (n_drawn * (n_total - 1))::DOUBLE END"
SHARE = "SELECT c.k AS category, round(sum(n_total * coalesce(x, 0) / n_drawn::DOUBLE) / sum(n_total), 6) AS share, round({z} * sqrt(sum((n_total / total::DOUBLE) ** 2 * {f} * {v})){more}, 6) AS half_width FROM (SELECT unnest(range(10))::VARCHAR AS k) c CROSS JOIN state0 s CROSS JOIN per LEFT JOIN state0_f f ON f.stratum = s.stratum AND f.label = c.k GROUP BY 1"
P = "(coalesce(x, 0) / n_drawn::DOUBLE)"
VARIANTS = {
    "group_share_ci_pooled": ({}, {"z": ZK, "v": "het", "more": ""}),
    "group_share_ci_printed": ({"form": "printed"}, {"z": ZK, "v": "het", "more": " / sqrt(sum(n_drawn))"}),
    "group_share_ci_per_category": ({"scope": "per_category"}, {"z": ZK, "v": f"{P} * (1 - {P})", "more": ""}),
    "group_share_ci_literal_level": ({"literal_level": True}, {"z": repr(NormalDist().inv_cdf((1 + 0.95 / 10) / 2)), "v": "het", "more": ""}),
}
for _name, (_how, _sql) in VARIANTS.items():

    @query(CTE + " " + SHARE.format(f=FINITE, **_sql), name=_name)
    def _share(spark, d, how=_how):
        _, sizes, _, draws = _round0(spark, d)
        shares = group_shares(list(group_states(draws, sizes, CATEGORIES).values()), CATEGORIES, **how)
        return spark.createDataFrame([(c, round(s, 6), round(w, 6)) for c, (s, w, _) in shares.items()], "category string, share double, half_width double")


@query(CTE + " SELECT round(max(norm), 6) AS worst, round(sum(n_total * norm) / sum(n_total), 6) AS weighted FROM state0")
def purity_table(spark, d):
    return purity(_state(spark, d)).select(r6("worst").alias("worst"), r6("weighted").alias("weighted"))


@query(CTE + " SELECT label AS category, round(sum(n_total * x / n_drawn::DOUBLE), 6) AS n_rows FROM state0 JOIN state0_f USING (stratum) GROUP BY 1")
def group_total(spark, d):
    _, sizes, _, draws = _round0(spark, d)
    states = list(group_states(draws, sizes, CATEGORIES).values())
    total = sum(sizes.values())
    rows = [(c, round(s * total, 6)) for c, (s, _, _) in group_shares(states, CATEGORIES).items() if any(x.counts.get(c) for x in states)]
    return spark.createDataFrame(rows, "category string, n_rows double")


RANDOM = "WITH p AS ({pool}), r AS (SELECT *, (row_number() OVER (ORDER BY rk) - 1) // (SELECT round(count(*) * 0.1)::BIGINT FROM p) AS step, count(*) OVER () AS total FROM p), c AS (SELECT step, k, total, count(*) AS calls, count(*) FILTER (label = k) AS x FROM r CROSS JOIN (SELECT DISTINCT label AS k FROM p) GROUP BY ALL), t AS (SELECT step, k, total, sum(calls) OVER w AS calls, sum(x) OVER w AS x FROM c WINDOW w AS (PARTITION BY k ORDER BY step))"
W8 = "SELECT doc_id AS key, lang AS label, md5('42:' || doc_id) AS rk FROM documents"


@query(RANDOM.format(pool=W8) + f" SELECT step, k AS category, round(x / calls::DOUBLE, 6) AS share, round({z_of(0.95, 4)!r} * sqrt(CASE WHEN calls >= total THEN 0 ELSE (total - calls) / (calls * (total - 1))::DOUBLE END * (x / calls::DOUBLE) * (1 - x / calls::DOUBLE)), 6) AS half_width FROM t")
def group_share_random(spark, d):
    docs = rank_pool(table(spark, d, "documents").select(F.col("doc_id").alias("key"), F.col("lang").alias("label")), "key")
    total = docs.count()
    steps = docs.groupBy(F.floor((F.col("position") - 1) / round(total * 0.1)).cast("bigint").alias("step")).pivot("label", ["de", "en", "es", "fr"]).count().na.fill(0)
    rows, so_far = [], dict.fromkeys(("de", "en", "es", "fr"), 0)
    for r in sorted(steps.collect(), key=lambda r: r.step):  # ten rows
        so_far = {k: n + r[k] for k, n in so_far.items()}
        for k, n in so_far.items():
            p, w = random_share(n, sum(so_far.values()), total, 0.95, 4)
            rows.append((r.step, k, round(p, 6), round(w, 6)))
    return spark.createDataFrame(rows, "step bigint, category string, share double, half_width double")


STATIC = f"SELECT doc_id AS key, lang AS stratum, class3 AS label, md5('42:' || doc_id) AS rk, n_chars FROM {LABELLED}"
STATIC_CTE = f"""WITH a AS ({STATIC}), sized AS (SELECT stratum, count(*) AS n_total FROM a GROUP BY 1), per AS (SELECT count(*) AS total, round(count(*) * 0.2)::BIGINT AS n FROM a),
{alloc_sql("take0", "sized", "n_total::DOUBLE", "SELECT n FROM per", "n_total")},
draws0 AS (SELECT p.* FROM (SELECT *, row_number() OVER (PARTITION BY stratum ORDER BY rk) AS position FROM a) p JOIN take0 USING (stratum) WHERE position <= n_draws),
d AS (SELECT stratum, count(*) AS n_drawn FROM draws0 GROUP BY 1)"""


def _static(spark, d):
    from ..sources.tables import labelled

    pool = labelled(spark, d).select(F.col("doc_id").alias("key"), F.col("lang").alias("stratum"), F.col("class3").alias("label"), "n_chars", draw_rank("doc_id").alias("draw_rank"))
    sizes = _sizes(pool)
    return sizes, take_next(pool, allocate.proportional(sizes, round(sum(sizes.values()) * 0.2)))


@query(STATIC_CTE + " SELECT k AS category, round(sum(n_total * x / n_drawn::DOUBLE) / sum(n_total), 6) AS share FROM (SELECT c.k, s.stratum, n_total, n_drawn, (SELECT count(*) FROM draws0 q WHERE q.stratum = s.stratum AND q.label = c.k) AS x FROM (SELECT unnest(['clean', 'junk', 'toxic']) AS k) c CROSS JOIN sized s JOIN d USING (stratum)) GROUP BY 1")
def group_share_static(spark, d):
    sizes, draws = _static(spark, d)
    states: list[GroupState] = list(group_states(draws, sizes, ["clean", "junk", "toxic"]).values())
    return spark.createDataFrame([(c, round(s, 6)) for c, (s, _, _) in group_shares(states, ["clean", "junk", "toxic"]).items()], "category string, share double")


@query(STATIC_CTE + ", v AS (SELECT stratum, label, count(*) AS n, sum(n_chars) AS s FROM draws0 GROUP BY ALL) SELECT label AS category, round(sum(n_total * s / n_drawn::DOUBLE) / sum(n_total * n / n_drawn::DOUBLE), 6) AS mean_value FROM v JOIN sized USING (stratum) JOIN d USING (stratum) GROUP BY 1")
def group_avg_value(spark, d):
    sizes, draws = _static(spark, d)
    drawn = {r.stratum: r["count"] for r in draws.groupBy("stratum").count().collect()}
    by = {(r.stratum, r.label): Moments(r.n, r["mean"], r.m2) for r in moments_of(draws, "n_chars", "stratum", "label").collect()}
    rows = [(c, round(group_value([(sizes[h], drawn[h], by.get((h, c), Moments())) for h in sizes], "avg")[0], 6)) for c in sorted({c for _, c in by})]
    return spark.createDataFrame(rows, "category string, mean_value double")


@query(STATIC_CTE + f""", v AS (SELECT stratum, label, sum(n_chars) AS s1, sum(n_chars::DOUBLE * n_chars) AS s2 FROM draws0 GROUP BY ALL),
g AS (SELECT k, n_total, n_drawn, coalesce(s1, 0) AS s1, coalesce(s2, 0) AS s2 FROM (SELECT DISTINCT label AS k FROM draws0) c CROSS JOIN sized JOIN d USING (stratum) LEFT JOIN v ON v.stratum = sized.stratum AND v.label = c.k)
SELECT k AS category, round(sum(n_total * s1 / n_drawn::DOUBLE), 6) AS total,
  CASE WHEN bool_or(n_drawn < 2 AND n_drawn < n_total) THEN NULL ELSE round({z_of(0.95)!r} * sqrt(greatest(0, sum(CASE WHEN n_drawn >= n_total THEN 0 ELSE n_total * n_total * (1 - n_drawn / n_total::DOUBLE) * (s2 - s1 * s1 / n_drawn) / greatest(1, n_drawn - 1) / n_drawn END))), 2) END AS half_width FROM g GROUP BY 1""")
def group_sum_value(spark, d):
    """Sum of a structured value by category, with its interval."""
    sizes, draws = _static(spark, d)
    drawn = {r.stratum: r["count"] for r in draws.groupBy("stratum").count().collect()}
    by = {(r.stratum, r.label): Moments(r.n, r["mean"], r.m2) for r in moments_of(draws, "n_chars", "stratum", "label").collect()}
    rows = []
    for c in sorted({c for _, c in by}):
        total, width = group_value([(sizes[h], drawn[h], by.get((h, c), Moments())) for h in sizes], "sum")
        rows.append((c, round(total, 6), None if width is None else round(width, 2)))
    return spark.createDataFrame(rows, "category string, total double, half_width double")


