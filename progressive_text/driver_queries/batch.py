"""Ground truth, batch semantic operators, labelers and extraction."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import rules
from ..functions.extract import JsonExtractor, RegexExtractor
from ..operators.labelers import CachedLabeler, CategoryLabeler, ExtractLabeler, LookupLabeler, NoisyLabeler, PredicateLabeler, RuleLabeler
from ..plans import baselines, metrics
from ..sources.store import new_path
from ..sources.tables import balanced, labelled, table, with_counts, with_page_language
from .registry import query, r6

CLASS3 = "CASE WHEN toxic = 1 THEN 'toxic' WHEN quality = 0 THEN 'junk' ELSE 'clean' END"
LABELLED = f"(SELECT d.*, l.quality, l.toxic, {CLASS3} AS class3 FROM documents d JOIN labels l ON d.doc_id = l.doc_id)"
NUMBER = "('0x' || substr(md5('{tag}:' || doc_id), 1, 8))::BIGINT"
MEAN = "round(avg({v}::DOUBLE), 6) AS mean_value, count(*) AS n_rows"


def _mean(v: str):
    return r6(F.avg(F.col(v).cast("double"))).alias("mean_value"), F.count("*").alias("n_rows")


@query(f"SELECT {MEAN.format(v='n_chars')} FROM {LABELLED} WHERE quality = 1")
def truth_avg_len_quality(spark, d):
    return baselines.ground_truth(labelled(spark, d), *_mean("n_chars"), where="quality = 1")


@query(f"""WITH b AS (SELECT *, row_number() OVER (PARTITION BY quality ORDER BY md5('42:' || doc_id)) AS p FROM {LABELLED}),
m AS (SELECT min(c) AS c FROM (SELECT count(*) AS c FROM b GROUP BY quality))
SELECT round(avg((lang = 'en')::INT::DOUBLE), 6) AS mean_value, count(*) AS n_rows FROM b, m WHERE p <= c AND quality = 1""")
def truth_rate_en_quality(spark, d):
    rows = balanced(labelled(spark, d), "quality").withColumn("en", (F.col("lang") == "en").cast("int"))
    return baselines.ground_truth(rows, *_mean("en"), where="quality = 1")


for _tag, _mod in (("like", 1000), ("view", 10000)):

    @query(f"SELECT {MEAN.format(v=f'({NUMBER.format(tag=_tag)} % {_mod})')} FROM documents WHERE lang = 'fr'", name=f"truth_{_tag}s_fr")
    def _truth_counts(spark, d, tag=_tag):
        return baselines.ground_truth(with_counts(table(spark, d, "documents")), *_mean(f"{tag}_count"), where="lang = 'fr'")


def _shares(df, column: str):
    counts = df.groupBy(F.col(column).cast("string").alias("category")).agg(F.count("*").alias("n_rows"))
    return counts.join(F.broadcast(df.agg(F.count("*").alias("_t")))).select("category", "n_rows", r6(F.col("n_rows") / F.col("_t")).alias("share"))


SHARES = "SELECT {c}::VARCHAR AS category, count(*) AS n_rows, round(count(*) / sum(count(*)) OVER ()::DOUBLE, 6) AS share FROM {t} GROUP BY 1"
query(SHARES.format(c="class3", t=LABELLED), "truth_share_class3")(lambda spark, d: _shares(labelled(spark, d), "class3"))
query(SHARES.format(c="lang", t="documents"), "truth_share_lang")(lambda spark, d: _shares(table(spark, d, "documents"), "lang"))
query(SHARES.format(c="label", t="embeddings"), "truth_share_emb_label")(lambda spark, d: _shares(table(spark, d, "embeddings"), "label"))

K = JsonExtractor("k INT", "k", 0, 99)
PARAGRAPHS = RegexExtractor("<p>", "int", count=True)


@query(f"SELECT event_type, {MEAN.format(v='(props->>\'$.k\')::INT')} FROM events GROUP BY 1")
def truth_avg_k_by_event(spark, d):
    return baselines.full_scan(table(spark, d, "events"), ExtractLabeler(K), "props", *_mean("label"), by=["event_type"], key="event_id")


@query(f"SELECT regexp_extract(url, '/([a-z]{{2}})/', 1) AS page_lang, {MEAN.format(v='len(regexp_extract_all(html, \'<p>\'))')} FROM pages GROUP BY 1")
def truth_paragraphs_by_lang(spark, d):
    return baselines.full_scan(with_page_language(table(spark, d, "pages")), ExtractLabeler(PARAGRAPHS), "html", *_mean("label"), by=["page_lang"], key="page_id")


@query("SELECT conv_id, turn, round(length(text)::DOUBLE, 6) AS length, role FROM conversations WHERE " + rules.language_sql() + " = 'es'")
def truth_spanish_turns(spark, d):
    turns = baselines.sem_filter(table(spark, d, "conversations"), PredicateLabeler(RuleLabeler(rules.language()), "es"), "text")
    return turns.select("conv_id", "turn", r6(F.length("text")).alias("length"), "role")


@query(f"SELECT regexp_extract(p_name, '([a-z]+)$', 1) AS category, {MEAN.format(v='p_retailprice')} FROM part GROUP BY 1")
def truth_price_by_noun(spark, d):
    return baselines.sem_group(table(spark, d, "part"), RuleLabeler(rules.noun()), "p_name", *_mean("p_retailprice"))


@query("SELECT event_id, (props->>'$.k')::BIGINT AS k FROM events")
def batch_sem_map(spark, d):
    return baselines.sem_map(table(spark, d, "events"), ExtractLabeler(K), "props", "k").select("event_id", F.col("k").cast("bigint").alias("k"))


@query("SELECT doc_id, n_chars FROM documents WHERE " + rules.low_quality_sql())
def batch_sem_filter(spark, d):
    return baselines.sem_filter(table(spark, d, "documents"), RuleLabeler(rules.low_quality()), "text").select("doc_id", "n_chars")


@query(f"SELECT {rules.language_sql()} AS category, {MEAN.format(v='n_chars')} FROM documents GROUP BY 1")
def batch_sem_group(spark, d):
    return baselines.sem_group(table(spark, d, "documents"), RuleLabeler(rules.language()), "text", *_mean("n_chars"))


for _name, _rule, _sql in (("toxic", rules.toxic, rules.toxic_sql), ("quality", rules.low_quality, rules.low_quality_sql), ("language", rules.language, rules.language_sql)):

    @query(f"SELECT doc_id, ({_sql()})::VARCHAR AS label FROM documents", name=f"label_rule_{_name}")
    def _label_rule(spark, d, rule=_rule):
        return RuleLabeler(rule()).label(table(spark, d, "documents")).select("doc_id", F.col("label").cast("string").alias("label"))


LANGS = ("de", "en", "es", "fr")
NEXT = "CASE lang WHEN 'de' THEN 'en' WHEN 'en' THEN 'es' WHEN 'es' THEN 'fr' ELSE 'de' END"
NOISY = "CASE WHEN ('0x' || substr(md5('7:' || doc_id), 1, 8))::BIGINT >= {limit} THEN {other} ELSE {truth} END"


def _truth(spark, d, column: str):
    return LookupLabeler(labelled(spark, d) if column == "class3" else table(spark, d, "documents"), "doc_id", column)


@query(f"SELECT doc_id, {NOISY.format(limit=int(0.9 * (1 << 32)), other=NEXT, truth='lang')} AS label FROM documents")
def label_noisy_90(spark, d):
    return NoisyLabeler(_truth(spark, d, "lang"), 0.90, LANGS).label(table(spark, d, "documents")).select("doc_id", "label")


NEXT3 = "CASE class3 WHEN 'clean' THEN 'junk' WHEN 'junk' THEN 'toxic' ELSE 'clean' END"
MODELS = {"model_small": (0.90, 0.84), "model_large": (0.95, 0.88)}
_parts = []
for _set, _t, _truth_col, _next, _rule_sql in (("language", "documents", "lang", NEXT, rules.language_sql()), ("class3", LABELLED, "class3", NEXT3, rules.class3_sql())):
    for _m, _acc in MODELS.items():
        _parts.append(f"SELECT '{_m}' AS model, '{_set}' AS data, count(*) AS n, round(avg(({NOISY.format(limit=int(_acc[_set == 'class3'] * (1 << 32)), other=_next, truth=_truth_col)} = {_truth_col})::INT::DOUBLE), 6) AS accuracy FROM {_t}")
    _parts.append(f"SELECT 'rules' AS model, '{_set}' AS data, count(*) AS n, round(avg(({_rule_sql} = {_truth_col})::INT::DOUBLE), 6) AS accuracy FROM {_t}")
    _parts.append(f"SELECT 'truth' AS model, '{_set}' AS data, count(*) AS n, 1.0::DOUBLE AS accuracy FROM {_t}")


@query(" UNION ALL ".join(_parts))
def label_accuracy_matrix(spark, d):
    out = None
    for data, column, categories, rule in (("language", "lang", LANGS, rules.language()), ("class3", "class3", ("clean", "junk", "toxic"), rules.class3())):
        docs, truth = labelled(spark, d) if column == "class3" else table(spark, d, "documents"), _truth(spark, d, column)
        models = {m: NoisyLabeler(truth, acc[data == "class3"], categories) for m, acc in MODELS.items()} | {"rules": RuleLabeler(rule), "truth": truth}
        for name, labeler in models.items():
            got = metrics.label_accuracy(labeler.label(docs), docs.withColumn("label", F.col(column))).select(F.lit(name).alias("model"), F.lit(data).alias("data"), "n", r6("accuracy").alias("accuracy"))
            out = got if out is None else out.unionByName(got)
    return out


@query(f"SELECT lang AS truth, count(*) FILTER (p = 'de') AS de, count(*) FILTER (p = 'en') AS en, count(*) FILTER (p = 'es') AS es, count(*) FILTER (p = 'fr') AS fr FROM (SELECT lang, {rules.language_sql()} AS p FROM documents) GROUP BY 1")
def label_confusion(spark, d):
    docs = table(spark, d, "documents")
    return metrics.confusion(RuleLabeler(rules.language()).label(docs), docs.withColumn("label", F.col("lang")), list(LANGS))


@query("SELECT event_type, count(*) AS calls, sum((k BETWEEN 10 AND 90)::INT)::BIGINT AS n_valid FROM (SELECT event_type, (props->>'$.k')::INT AS k FROM events) GROUP BY 1")
def extract_json_valid(spark, d):
    got = ExtractLabeler(JsonExtractor("k INT", "k", 10, 90)).label(table(spark, d, "events"), "props")
    return got.groupBy("event_type").agg(F.count("*").alias("calls"), F.sum(F.col("is_valid").cast("bigint")).alias("n_valid"))


@query("SELECT p_partkey, nullif(regexp_extract(p_name, '([a-z]+)$', 1), '') AS noun FROM part")
def extract_regex_noun(spark, d):
    return ExtractLabeler(RegexExtractor("([a-z]+)$")).label(table(spark, d, "part"), "p_name").select("p_partkey", F.col("label").alias("noun"))


@query("SELECT event_type, count(*) FILTER (event_type IN ('click', 'view')) AS n_valid, count(*) AS calls FROM events GROUP BY 1")
def label_closed_domain(spark, d):
    got = CategoryLabeler(RuleLabeler(F.col("event_type")), ("click", "view")).label(table(spark, d, "events"), "props")
    return got.groupBy("event_type").agg(F.sum(F.col("is_valid").cast("bigint")).alias("n_valid"), F.count("*").alias("calls"))


@query("SELECT count(*) AS n_rows, count(DISTINCT text) AS calls, 0::BIGINT AS calls_again FROM documents")
def label_cache_distinct_calls(spark, d):
    cache, docs = CachedLabeler(RuleLabeler(rules.language()), new_path(spark, "memo")), table(spark, d, "documents")
    rows = cache.label(docs)
    cache.label(docs)
    return rows.agg(F.count("*").alias("n_rows")).select("n_rows", F.lit(cache.calls[0]).cast("bigint").alias("calls"), F.lit(cache.calls[1]).cast("bigint").alias("calls_again"))
