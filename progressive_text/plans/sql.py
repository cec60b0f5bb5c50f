"""SQL surface: semantic functions for batch SQL, and progressive queries from pieces of SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import rules
from ..operators.labelers import Labeler, PredicateLabeler, RuleLabeler
from ..operators.strata import column_strata
from .filter_engine import progressive_filter
from .group_engine import GroupConfig, progressive_group
from .query import ProgressLog, Stop
from .select_engine import progressive_select


def register(spark: SparkSession) -> None:
    """sem_filter(text), sem_class(text) and sem_language(text) as SQL functions over the rule labelers.

    They are SQL functions, not Python ones, so the optimizer sees through them. sem_extract(text, field) is a
    number that JSON text has under a field.
    """
    t = "text"
    noisy = f"regexp_count({t}, r'{rules.NOISE}') > 0.3 * size(split({t}, ' ')) OR regexp_count({t}, r' \\| ') >= 5 OR size(array_distinct(split({t}, ' '))) < 0.2 * size(split({t}, ' '))"
    words = f"split(regexp_replace(lower({t}), '{rules.LETTERS}', ' '), ' ')"
    listed = lambda ws: "array(" + ", ".join(f"'{w}'" for w in ws) + ")"
    insulted = f"arrays_overlap({words}, {listed(rules.INSULTS)})"
    votes = ", ".join(f"named_struct('v', -size(filter({words}, w -> array_contains({listed(ws)}, w))), 'k', '{k}')" for k, ws in sorted(rules.FREQUENT.items()))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sem_filter(text STRING) RETURNS BOOLEAN RETURN NOT ({noisy})")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sem_class(text STRING) RETURNS STRING RETURN CASE WHEN {insulted} THEN 'toxic' WHEN {noisy} THEN 'junk' ELSE 'clean' END")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sem_language(text STRING) RETURNS STRING RETURN array_min(array({votes})).k")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sem_extract(text STRING, field STRING) RETURNS DOUBLE RETURN try_cast(get_json_object(text, concat('$.', field)) AS DOUBLE)")


def progressive(
    spark: SparkSession, view: str, key: str, text: str = "text", select: str = "*", where: str | None = None, semantic_where: Labeler | str | None = None,
    group_by: list[str] | None = None, semantic_group: Labeler | None = None, extract: Labeler | None = None, categories: list | None = None,
    agg: str = "avg", value: str | None = None, strata: str | None = None, stop: Stop | None = None, **how,
) -> ProgressLog:
    """A progressive query over a view: structured projections and predicates first (they reach the scan), then the
    semantic part: extract (in the projection), semantic_where (a predicate) or semantic_group (categories)."""
    df: DataFrame = spark.sql(f"SELECT {select} FROM {view}" + (f" WHERE {where}" if where else ""))
    if isinstance(semantic_where, str):
        semantic_where = PredicateLabeler(RuleLabeler(F.expr(semantic_where)), True)
    if extract is not None:
        return progressive_select(df, key, text, extract, group_by, agg, stop=stop, **how)
    if strata:
        df = column_strata(df, strata)
    if semantic_where is not None:
        return progressive_filter(df, key, text, semantic_where, value or key, agg, stratum="stratum" if strata else None, stop=stop, **how)
    config = how.pop("config", GroupConfig(adjust=False))
    df = df if strata else df.withColumn("stratum", F.lit(0))
    return progressive_group(df, key, text, semantic_group, categories or [], value, "proportion" if value is None else agg, config=config, stop=stop, **how)
