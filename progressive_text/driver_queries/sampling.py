"""Strata, vectors and draw order."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.vectors import cosine, mean_vector
from ..operators.order import draw_rank, first_n, rank_pool, slice_of
from ..operators.strata import column_strata, lloyd_round, lloyd_seeds, sizes, strata_bounds
from ..sources.tables import labelled, table
from .registry import query, r6

H = 8
VEC = "list_transform(embedding, lambda x: x::DOUBLE)"
#: Strata of the embeddings after one round of K-means from md5-ranked seeds.
LLOYD = f"""e AS (SELECT vec_id AS key, label::VARCHAR AS label, {VEC} AS vec, md5('42:' || vec_id) AS rk FROM embeddings),
seeds AS (SELECT row_number() OVER (ORDER BY rk) - 1 AS stratum, vec AS centre FROM e ORDER BY rk LIMIT {H}),
a AS (SELECT key, label, vec, rk, stratum FROM (
  SELECT e.*, s.stratum, row_number() OVER (PARTITION BY key ORDER BY round(list_cosine_similarity(vec, centre), 9) DESC, s.stratum) AS o FROM e, seeds s) WHERE o = 1)"""


@query("SELECT dense_rank() OVER (ORDER BY lang) - 1 AS stratum, lang, count(*) AS n_total FROM documents GROUP BY lang")
def strata_by_column(spark, d):
    return column_strata(table(spark, d, "documents"), "lang").groupBy(F.col("stratum").cast("bigint").alias("stratum"), "lang").agg(F.count("*").alias("n_total"))


@query("SELECT lang AS stratum, count(*) AS n_total, round(count(*) / (sum(count(*)) OVER ())::DOUBLE, 6) AS weight FROM documents GROUP BY 1")
def strata_sizes(spark, d):
    return sizes(table(spark, d, "documents").withColumn("stratum", F.col("lang"))).select("stratum", "n_total", r6("weight").alias("weight"))


@query("SELECT n, k, ceil(k * ln(n))::BIGINT AS h0, ceil(2 * k * ln(n))::BIGINT AS h_max FROM (SELECT count(*) AS n, 4::BIGINT AS k FROM documents UNION ALL SELECT 15000, 3)")
def strata_bounds_rule(spark, d):
    n = table(spark, d, "documents").count()
    return spark.createDataFrame([(m, k, *strata_bounds(m, k)) for m, k in ((n, 4), (15000, 3))], "n bigint, k bigint, h0 bigint, h_max bigint")


def lloyd_assignment(spark, d):
    e = table(spark, d, "embeddings")
    return lloyd_round(e, "vec_id", lloyd_seeds(e, "vec_id", H))


@query(f"WITH {LLOYD} SELECT key AS vec_id, stratum FROM a")
def strata_lloyd_one_round(spark, d):
    return lloyd_assignment(spark, d).select("vec_id", F.col("stratum").cast("bigint").alias("stratum"))


@query(f"WITH {LLOYD} SELECT key AS vec_id, stratum, round(list_cosine_similarity(vec, centre), 6) AS near FROM e, seeds")
def cosine_to_centroid(spark, d):
    e = table(spark, d, "embeddings")
    pairs = e.crossJoin(F.broadcast(lloyd_seeds(e, "vec_id", H)))
    return pairs.select("vec_id", F.col("stratum").cast("bigint").alias("stratum"), r6(cosine("embedding", "centre")).alias("near"))


@query(f"SELECT label::BIGINT AS label, i - 1 AS place, round(avg(v), 6) AS mean_value FROM (SELECT label, unnest({VEC}) AS v, generate_subscripts(embedding, 1) AS i FROM embeddings) GROUP BY 1, 2")
def mean_vector_by_label(spark, d):
    means = mean_vector(table(spark, d, "embeddings"), "label")
    return means.select(F.col("label").cast("bigint").alias("label"), F.posexplode("mean").alias("place", "v")).select("label", F.col("place").cast("bigint").alias("place"), r6("v").alias("mean_value"))


@query("SELECT doc_id, row_number() OVER (ORDER BY md5('42:' || doc_id)) AS position FROM documents QUALIFY position <= 100")
def draw_random_first_n(spark, d):
    return first_n(table(spark, d, "documents").select("doc_id"), "doc_id", 100).select("doc_id", "position")


@query("SELECT doc_id, lang, row_number() OVER (PARTITION BY lang ORDER BY md5('42:' || doc_id)) AS position FROM documents QUALIFY position <= 20")
def draw_per_stratum_first_n(spark, d):
    return rank_pool(table(spark, d, "documents").select("doc_id", "lang"), "doc_id", ["lang"]).where("position <= 20").select("doc_id", "lang", "position")


@query("SELECT (('0x' || substr(md5('42:' || doc_id), 1, 4))::BIGINT * 16) // 65536 AS slice, count(*) AS n_rows FROM documents GROUP BY 1")
def draw_slices(spark, d):
    return table(spark, d, "documents").groupBy(slice_of(draw_rank("doc_id"), 16).cast("bigint").alias("slice")).agg(F.count("*").alias("n_rows"))


@query("SELECT quality::BIGINT AS quality, count(*) AS n_rows FROM (SELECT *, row_number() OVER (PARTITION BY quality ORDER BY md5('42:' || doc_id)) AS p FROM labels JOIN documents USING (doc_id)) WHERE p <= (SELECT min(c) FROM (SELECT count(*) AS c FROM labels JOIN documents USING (doc_id) GROUP BY quality)) GROUP BY 1")
def balanced_subset(spark, d):
    from ..sources.tables import balanced

    return balanced(labelled(spark, d), "quality").groupBy(F.col("quality").cast("bigint").alias("quality")).agg(F.count("*").alias("n_rows"))
