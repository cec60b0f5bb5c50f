"""Sources, sinks, samples and user-defined functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F

from ..operators.order import rank_pool
from ..sources.store import new_path
from ..sources.tables import table
from .registry import query, r6

EVENTS = "SELECT event_id, event_type, value FROM events"


def _events(spark, d):
    return table(spark, d, "events").select("event_id", "event_type", "value")


for _format in ("json", "csv", "parquet"):

    @query(f"SELECT event_type, count(*) AS n, round(sum(value), 6) AS total FROM ({EVENTS}) WHERE event_type <> 'view' GROUP BY 1", name=f"op_format_{_format}")
    def _format_round_trip(spark, d, kind=_format):
        """Written by event type (a folder each) and read with a declared schema; the filter prunes folders."""
        path, rows = new_path(spark, kind), _events(spark, d)
        rows.write.partitionBy("event_type").format(kind).save(path)
        back = spark.read.schema("event_id bigint, value double, event_type string").format(kind).load(path)
        return back.where("event_type <> 'view'").groupBy("event_type").agg(F.count("*").alias("n"), r6(F.sum("value")).alias("total"))


def _fields(spark, events):
    @F.udtf(returnType="field: string, value: string")
    class Fields:
        """One row for each field of JSON text."""

        def eval(self, text: str):
            import json

            yield from ((k, str(v)) for k, v in json.loads(text or "{}").items())

    spark.udtf.register("fields_of", Fields)
    events.createOrReplaceTempView("events_of_udtf")
    return spark.sql("SELECT event_id, f.field, f.value FROM events_of_udtf, LATERAL fields_of(props) f")


@query("SELECT event_id, 'k' AS field, (props->>'$.k') AS value FROM events")
def op_udtf_all_fields(spark, d):
    return _fields(spark, table(spark, d, "events"))


@query("SELECT event_type, round(avg(value), 6) AS mean_value FROM events GROUP BY 1")
def op_udaf_mean(spark, d):
    @F.pandas_udf("double")
    def mean(v: pd.Series) -> float:
        return float(v.mean())

    return _events(spark, d).groupBy("event_type").agg(r6(mean("value")).alias("mean_value"))


@query("SELECT e.event_type, n_events, n_users FROM (SELECT event_type, count(*) AS n_events FROM events GROUP BY 1) e JOIN (SELECT event_type, count(DISTINCT user_id) AS n_users FROM events GROUP BY 1) u ON e.event_type = u.event_type")
def op_cogroup(spark, d):
    def meet(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        kind = (a if len(a) else b).event_type.iloc[0]
        return pd.DataFrame({"event_type": [kind], "n_events": [int(a.n.sum())], "n_users": [int(b.n.sum())]})

    events = table(spark, d, "events")
    a = events.groupBy("event_type", F.pmod("event_id", F.lit(7)).alias("part")).agg(F.count("*").alias("n")).groupBy("event_type")
    b = events.groupBy("event_type").agg(F.count_distinct("user_id").alias("n")).groupBy("event_type")
    return a.cogroup(b).applyInPandas(meet, "event_type string, n_events bigint, n_users bigint")


@query("SELECT lang, map_keys(m)[1] AS top_source, map_values(m)[1] AS n FROM (SELECT lang, map([arg_max(source, n * 1000 - substr(source, 4)::INT)], [max(n)]) AS m FROM (SELECT lang, source, count(*) AS n FROM documents GROUP BY ALL) GROUP BY 1)")
def op_map_struct(spark, d):
    counts = table(spark, d, "documents").groupBy("lang", "source").agg(F.count("*").alias("n"))
    best = F.max_by(F.struct("source", "n"), F.col("n") * 1000 - F.substring("source", 4, 9).cast("int"))
    m = counts.groupBy("lang").agg(F.map_from_entries(F.array(best)).alias("m"))
    return m.select("lang", F.map_keys("m")[0].alias("top_source"), F.map_values("m")[0].alias("n"))


@query("SELECT lang, doc_id, position FROM (SELECT lang, doc_id, row_number() OVER (PARTITION BY lang ORDER BY md5('9:' || doc_id)) AS position FROM documents) WHERE position <= 5")
def op_sample_exact(spark, d):
    return rank_pool(table(spark, d, "documents").select("lang", "doc_id"), "doc_id", ["lang"], seed=9).where("position <= 5").select("lang", "doc_id", "position")


@query()
def op_sample_bernoulli(spark, d):
    """A sampling operator: about a tenth of all rows, and other shares by language."""
    docs = table(spark, d, "documents").select("doc_id", "lang")
    return docs.sample(0.1, seed=3).withColumn("how", F.lit("uniform")).unionByName(docs.sampleBy("lang", {"en": 0.05, "fr": 0.5}, seed=3).withColumn("how", F.lit("by language")))


@query("SELECT length(line)::BIGINT AS n_chars, count(*) AS n FROM (SELECT unnest(string_split(text, chr(10))) AS line FROM conversations) GROUP BY 1")
def op_scan_text(spark, d):
    """Turns written as lines of text files and read back."""
    path = new_path(spark, "text")
    table(spark, d, "conversations").select("text").write.text(path)
    return spark.read.text(path).groupBy(F.length("value").cast("bigint").alias("n_chars")).agg(F.count("*").alias("n"))


@query("SELECT event_id, (props->>'$.k') AS by_tuple, '{\"k\":' || (props->>'$.k') || '}' AS again, (props->>'$.k')::BIGINT AS by_variant, false AS other FROM events")
def op_json_more(spark, d):
    """json_tuple, to_json of a declared schema, and VARIANT."""
    events = table(spark, d, "events")
    rows = events.select("event_id", "props", F.json_tuple("props", "k").alias("by_tuple"))
    variant = F.try_variant_get(F.try_parse_json("props"), "$.k", "bigint")
    return rows.select("event_id", "by_tuple", F.to_json(F.from_json("props", "k BIGINT")).alias("again"), variant.alias("by_variant"), F.try_variant_get(F.try_parse_json("props"), "$.none", "string").isNotNull().alias("other"))


@query("SELECT doc_id, (a + 0)::BIGINT AS only_a, (b + c)::BIGINT AS both, ((a > 2)::INT + (b + c > 2)::INT)::BIGINT AS n_large FROM (SELECT doc_id, doc_id % 7 AS a, doc_id % 5 AS b, n_chars % 3 AS c FROM documents)")
def op_map_more(spark, d):
    """map_zip_with, map_filter and transform_values."""
    docs = table(spark, d, "documents")
    x = F.create_map(F.lit("a"), F.col("doc_id") % 7, F.lit("b"), F.col("doc_id") % 5)
    both = F.map_zip_with(x, F.create_map(F.lit("b"), F.col("n_chars") % 3), lambda k, v, w: F.coalesce(v, F.lit(0)) + F.coalesce(w, F.lit(0)))
    both = docs.select("doc_id", F.transform_values(both, lambda k, v: v.cast("bigint")).alias("m"))
    return both.select("doc_id", F.col("m")["a"].alias("only_a"), F.col("m")["b"].alias("both"), F.size(F.map_filter("m", lambda k, v: v > 2)).cast("bigint").alias("n_large"))
