"""Progressive engines against exact answers and invariants."""

from __future__ import annotations

from math import isclose

import numpy as np
import pytest
from pyspark.sql import functions as F

from progressive_text.functions import rules
from progressive_text.functions.extract import JsonExtractor
from progressive_text.operators import refine
from progressive_text.operators.embed import HashedNgramEmbedder, ModelEmbedder
from progressive_text.operators.labelers import CachedLabeler, ExtractLabeler, LookupLabeler, NoisyLabeler, PredicateLabeler, RuleLabeler, ServiceLabeler, SimulatedService
from progressive_text.operators.order import draw_rank, positions, rank_pool, slices_for, take_next
from progressive_text.operators.stats import group_states
from progressive_text.operators.strata import assign_nearest, column_strata, kmeans_strata, lloyd_strata, overlay
from progressive_text.plans import baselines, filter_engine, group_engine, metrics, select_engine
from progressive_text.plans import workloads as W
from progressive_text.plans.layout import ALL, lay_out
from progressive_text.plans.query import DrawLog, ProgressiveQuery, Stop
from progressive_text.plans.sql import progressive, register
from progressive_text.sources.store import new_path
from progressive_text.sources.tables import labelled, table


CATEGORIES = [str(i) for i in range(10)]


@pytest.fixture(scope="module")
def docs(spark):
    return labelled(spark, "/root/testdata/sf0.001").cache()


def good(docs):
    return PredicateLabeler(LookupLabeler(docs.select("doc_id", "quality"), "doc_id", "quality"), 1)


def test_positions_are_a_permutation_in_each_group(spark):
    df = spark.range(500).select(F.col("id").alias("key"), (F.col("id") % 3).alias("g")).withColumn("draw_rank", draw_rank("key"))
    for r in positions(df, ["g"]).groupBy("g").agg(F.sort_array(F.collect_list("position")).alias("p"), F.count("*").alias("n")).collect():
        assert r.p == list(range(1, r.n + 1))
    ordered = [r.key for r in positions(df, []).orderBy("position").collect()]
    assert ordered == [r.key for r in df.orderBy("draw_rank").collect()]
    assert positions(df.where("false"), ["g"]).count() == 0


def test_draws_never_repeat(spark):
    pool = rank_pool(spark.range(50).select(F.col("id").alias("key"), (F.col("id") % 2).cast("int").alias("stratum")), "key", ["stratum"])
    first = take_next(pool, {0: 10, 1: 3})
    second = take_next(pool, {0: 30, 1: 2}, drawn=first)
    assert first.count() == 13 and second.count() == 17 and first.join(second, "key").count() == 0


@pytest.mark.parametrize("mode", ["strict", "proportional_to_rate", "random"])
def test_filter_ends_on_the_exact_answer(docs, mode):
    log = filter_engine.progressive_filter(column_strata(docs, "lang"), "doc_id", "text", good(docs), "n_chars", batch=30, mode=mode)
    truth = docs.where("quality = 1").agg(F.avg("n_chars")).first()[0]
    last = log.rows[-1]
    assert last["is_final"] and last["calls"] == docs.count() and isclose(last["estimate"], truth) and isclose(last["estimate_stratified"], truth)
    assert last["half_width_stratified"] == 0
    drawn = log.details["draws"].all()
    assert drawn.count() == drawn.select("doc_id").distinct().count() == docs.count()


def test_filter_stops_and_handles_nothing(spark, docs):
    log = filter_engine.progressive_filter(column_strata(docs, "lang"), "doc_id", "text", good(docs), "n_chars", batch=20, stop=Stop(budget=40))
    assert log.rows[-1]["calls"] < docs.count()
    never = RuleLabeler(F.lit(False))
    assert filter_engine.progressive_filter(column_strata(docs, "lang"), "doc_id", "text", never, "n_chars", batch=60).rows[-1]["estimate"] is None
    assert filter_engine.progressive_filter(docs.where("false").withColumn("stratum", F.lit(0)), "doc_id", "text", never, "n_chars").rows == []
    one = filter_engine.progressive_filter(docs.limit(1).withColumn("stratum", F.lit(0)), "doc_id", "text", RuleLabeler(F.lit(True)), "n_chars")
    assert len(one.rows) == 1 and one.rows[0]["half_width"] is None


def test_select_ends_on_the_exact_answer(spark, sf):
    events = table(spark, sf, "events")
    log = select_engine.progressive_select(events, "event_id", "props", ExtractLabeler(JsonExtractor("k INT", "k", 0, 99)), ["event_type"], batch=250)
    want = {r.event_type: r.m for r in events.groupBy("event_type").agg(F.avg(F.get_json_object("props", "$.k").cast("int")).alias("m")).collect()}
    assert all(isclose(r["estimate"], want[r["grp"]]) for r in log.rows if r["is_final"]) and len(log.rows) == 20
    assert log.result().count() == 5 and log.frame().count() == 20 and len(list(log.steps())) == 4


def test_extraction_refuses_what_does_not_fit(spark):
    rows = spark.createDataFrame([("{\"k\": 5}",), ("{\"k\": \"x\"}",), ("{",), (None,), ("{\"k\": 500}",), ("",)], "props string")
    got = ExtractLabeler(JsonExtractor("k INT", "k", 0, 99)).label(rows, "props")
    assert [r.is_valid for r in got.collect()] == [True, False, False, False, False, False]


def grouped(spark, docs, **config):
    e = table(spark, "/root/testdata/sf0.001", "embeddings").select("vec_id", "embedding", F.col("label").cast("string").alias("kind")).where("vec_id < 200")
    strata, _ = kmeans_strata(e, 4)
    labeler = LookupLabeler(e.select("vec_id", "kind"), "vec_id", "kind")
    categories = [str(i) for i in range(10)]
    return e, group_engine.progressive_group(strata.cache(), "vec_id", "kind", labeler, categories, config=group_engine.GroupConfig(**{"h_max": 6, "gamma": 0.3, "round_fraction": 0.25} | config))


@pytest.mark.parametrize("adjust", [True, False])
def test_group_ends_on_the_exact_shares(spark, docs, adjust):
    e, log = grouped(spark, docs, adjust=adjust)
    want = {r.kind: r["count"] / 200 for r in e.groupBy("kind").count().collect()}
    final = [r for r in log.rows if r["is_final"]]
    assert len(final) == 10
    for r in final:
        assert isclose(r["estimate"], want[r["grp"]]) and isclose(r["estimate_stratified"], want[r["grp"]]) and r["half_width"] == 0
    drawn = log.details["draws"].all()
    assert drawn.count() == drawn.select("vec_id").distinct().count() == 200
    now = log.details["assignment"]
    assert now.count() == now.select("key").distinct().count() == 200
    strata = [p["strata"] for p in log.details["purity"]]
    assert max(strata) <= 6 and (strata[-1] > 4) == adjust
    assert all(0 <= p["worst"] <= 1 for p in log.details["purity"])


def test_group_merges_at_the_largest_number_of_strata(spark, docs):
    _, log = grouped(spark, docs, h_max=4)
    assert {a["action"] for a in log.details["actions"]} <= {"merge", "none"} and log.rows[-1]["is_final"]


def test_lookalikes_agree_across_methods(spark):
    rows = [(1, 0, [1.0, 0.0]), (2, 0, [0.1, 0.9]), (3, 0, [1.0, 0.05]), (4, 0, [0.6, 0.8]), (5, 1, [0.0, 1.0]), (6, 0, None), (7, 0, [0.0, 0.0])]
    pool = spark.createDataFrame(rows, "key bigint, stratum int, embedding array<float>")
    few = spark.createDataFrame([(9, 0, "y", [0.0, 1.0])], "key bigint, stratum int, label string, embedding array<float>")
    for gamma, want in ((0.9, {2}), (0.7, {2, 4}), (1.0, set())):
        for method in ("matrix", "join", "auto"):
            assert {r.key for r in refine.lookalikes(pool, few, gamma, method=method).collect()} == want, (gamma, method)
    assert {r.key for r in refine.lookalikes(pool.where("embedding IS NOT NULL"), few, 0.9, method="lsh").collect()} <= {2}


def test_strata_cover_all_rows(spark, sf):
    e = table(spark, sf, "embeddings").select("vec_id", "embedding")
    odd = e.unionByName(spark.createDataFrame([(-1, [0.0] * 64), (-2, None)], "vec_id bigint, embedding array<float>"))
    for strata, centres in (kmeans_strata(odd, 5), lloyd_strata(e, "vec_id", 5), kmeans_strata(odd, 3, bisecting=True)):
        assert strata.count() in (500, 502) and strata.agg(F.max("stratum")).first()[0] <= len(centres)
    assert {r.stratum for r in assign_nearest(odd, "embedding", kmeans_strata(odd, 5)[1]).where("vec_id < 0").collect()} == {5}
    assert {r.stratum for r in kmeans_strata(odd, 1)[0].select("stratum").distinct().collect()} == {0, 1}
    base = spark.createDataFrame([(1, 0), (2, 1)], "key bigint, stratum int")
    moves = spark.createDataFrame([(0, 1, 5), (1, 1, 7)], "t int, key bigint, to_stratum int")
    assert {r.key: r.stratum for r in overlay(base, moves).collect()} == {1: 7, 2: 1}


def test_noise_keeps_its_accuracy_and_its_answers(spark):
    truth = spark.range(4000).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 2 == 0, "a").otherwise("b").alias("t"), F.lit("x").alias("text"))
    noisy = NoisyLabeler(LookupLabeler(truth, "doc_id", "t"), 0.9, ("a", "b"))
    got = metrics.label_accuracy(noisy.label(truth), truth.withColumn("label", F.col("t"))).first().accuracy
    assert abs(got - 0.9) < 0.02
    assert noisy.label(truth).exceptAll(noisy.label(truth)).isEmpty()


def test_service_retries_batches_and_endpoints(spark):
    rows = spark.range(100).select("id", F.concat(F.lit("t"), F.col("id").cast("string")).alias("text"))

    def client(endpoint):
        failed = set()

        def ask(texts):
            if "t13" in texts:
                raise OSError("never answers")
            if texts[0] not in failed:
                failed.add(texts[0])
                raise OSError("once")
            return [x[1:] for x in texts]

        return ask

    got = ServiceLabeler(client, ("one", "two"), batch_size=1, retries=1).label(rows)
    assert got.where("NOT is_valid").count() == 1 and got.where("is_valid AND label = CAST(id AS STRING)").count() == 99
    busy = ServiceLabeler(client, ("one", "two"), batch_size=1, retries=3, routing="least_busy").label(rows)
    assert busy.where("is_valid").count() == 99


def test_cache_asks_once_for_a_text(spark):
    rows = spark.createDataFrame([(i, f"t{i % 7}") for i in range(30)] + [(99, None)], "id int, text string")
    cache = CachedLabeler(RuleLabeler(F.length("text")), new_path(spark, "memo"))
    assert cache.label(rows).count() == 31 and cache.calls == [8]
    assert cache.label(rows).where("label = 2").count() == 30 and cache.calls == [8, 0]


def test_scale_out_is_sub_linear():
    times = {i: SimulatedService(RuleLabeler(None), 1.0, i, 0.3).seconds(100) for i in (1, 2, 3, 4)}
    speed = metrics.scaleout(times)
    assert speed[1] == 1 < speed[2] < speed[3] < speed[4] < 4


def test_baselines_and_measures(spark, docs):
    truth = baselines.ground_truth(docs, F.avg("n_chars").alias("truth"), where="quality = 1").withColumn("grp", F.lit(""))
    log = baselines.random_filter(docs, "doc_id", "text", good(docs), "n_chars", batch=30)
    errors = metrics.absolute_error(log.frame(), truth)
    assert errors.orderBy(F.desc("step")).first().error < 1e-9
    assert metrics.time_to_bound(log.frame(), 1e-9).first().cost is None
    assert metrics.time_to_bound(log.frame(), 100.0, min_valid=1).first().cost is not None
    assert metrics.time_to_bound(errors, 0.5, by="error", sustained=True, min_valid=1).first().cost <= docs.count()
    share = baselines.random_group(docs, "doc_id", "text", LookupLabeler(docs.select("doc_id", "class3"), "doc_id", "class3"), ["clean", "junk", "toxic"], round_fraction=0.5)
    assert share.rows[-1]["is_final"] and isclose(sum(r["estimate"] for r in share.rows[-3:]), 1.0)


def test_structured_predicates_reach_the_scan_and_labelers_run_once(spark, sf):
    rows = table(spark, sf, "documents").where("lang = 'fr'")
    plan = ServiceLabeler(lambda e: (lambda t: t)).label(rows.select("doc_id", "text"))._jdf.queryExecution().toString()
    assert "EqualTo(lang,fr)" in plan and plan.split("== Physical Plan ==")[1].count("MapInPandas") == 1


def test_sql_surface(spark, docs, sf):
    register(spark)
    docs.createOrReplaceTempView("labelled_docs")
    rows = spark.sql("SELECT sem_language('the of and to') AS l, sem_class('you idiot') AS c, sem_extract('{\"k\": 4}', 'k') AS k, sem_filter('plain words here to read on') AS f").first()
    assert tuple(rows) == ("en", "toxic", 4.0, True)
    log = progressive(spark, "labelled_docs", "doc_id", where="lang = 'en'", semantic_where="length(text) > 500", value="n_chars", strata="source", batch=60)
    want = docs.where("lang = 'en' AND length(text) > 500").agg(F.avg("n_chars")).first()[0]
    assert isclose(log.rows[-1]["estimate"], want)
    query = ProgressiveQuery("filter", column_strata(docs, "lang"), {"key": "doc_id", "text": "text", "labeler": good(docs), "value": "n_chars", "batch": 60})
    assert query.run(Stop(max_steps=1)).rows[-1]["step"] == 0


def rows_read(spark, df) -> int:
    """Rows that the scans of a frame give, by the metrics of its plan."""
    df.collect()
    found, todo = 0, [df._jdf.queryExecution().executedPlan()]
    while todo:
        node = todo.pop()
        if node.getClass().getSimpleName() == "AdaptiveSparkPlanExec":
            todo.append(node.executedPlan())
            continue
        if node.getClass().getSimpleName().endswith("QueryStageExec"):
            todo.append(node.plan())
            continue
        if node.getClass().getSimpleName() == "FileSourceScanExec":
            found += node.metrics().apply("numOutputRows").value()
        children = node.children()
        todo += [children.apply(i) for i in range(children.size())]
    return found


def test_a_step_reads_about_its_draws(spark):
    docs = column_strata(table(spark, "/root/testdata/sf0.1", "documents"), "lang")
    rows = lay_out(docs, "doc_id", "text", RuleLabeler(F.lit(True)), {"_stratum": F.col("stratum")}, {"_value": F.col("n_chars").cast("double")}, batch=100)
    sizes = {h: n for (h,), n in rows.sizes().items()}
    assert rows.total == sum(sizes.values()) == 10_000
    one = rows.take({1: (1000, 1100)})
    assert one.count() == 100 and rows_read(spark, one) <= 500
    pilot = rows.take({h: (0, n // 20) for h, n in sizes.items()})
    assert pilot.count() == sum(n // 20 for n in sizes.values()) and rows_read(spark, pilot) <= 2000
    plan = one._jdf.queryExecution().toString()
    assert "GreaterThan(_position,1000)" in plan and "EqualTo(_stratum,1)" in plan
    whole = lay_out(docs, "doc_id", "text", RuleLabeler(F.lit(True)), {}, batch=100)
    assert rows_read(spark, whole.take({ALL: (5000, 5100)})) <= 500


def test_texts_move_once_when_they_are_laid_out(spark, sf):
    docs = column_strata(table(spark, sf, "documents"), "lang")
    plan = positions(docs.select("doc_id", "text", "stratum", draw_rank("doc_id").alias("_rank")), ["stratum"], "_rank", 4, "_position")._jdf.queryExecution().executedPlan().toString()
    moved = [x for x in plan.split("\n") if "Exchange hashpartitioning" in x and "_slice" in x.split("), ENSURE")[0]]
    assert len(moved) == 2 and "rangepartitioning" not in plan  # the rows, and the counts by slice
    assert slices_for(10**11, 10**9) == 65536 and slices_for(10**7, 10**5) == 13 and slices_for(50, 5) == 1 and slices_for(0, 1) == 1


def test_names_of_user_columns_do_not_clash(spark, docs):
    truth = docs.where("quality = 1").agg(F.avg("n_chars")).first()[0]
    odd = column_strata(docs, "lang").select("doc_id", "text", F.col("stratum").alias("key"), F.col("n_chars").alias("label"), F.lit("x").alias("is_valid"), F.lit(1).alias("step"), F.lit(3).alias("stratum"), F.lit(2).alias("_lost"), F.lit(9).alias("position"))
    for mode in ("strict", "random"):
        last = filter_engine.progressive_filter(odd, "doc_id", "text", good(docs), "label", stratum="key", batch=60, mode=mode).rows[-1]
        assert isclose(last["estimate"], truth)
    log = select_engine.progressive_select(odd.withColumn("event", F.concat(F.lit("{\"k\": "), F.col("label") % 50, F.lit("}"))), "doc_id", "event", ExtractLabeler(JsonExtractor("k INT", "k", 0, 99)), ["step", "is_valid"], batch=60)
    want = docs.agg(F.avg(F.col("n_chars") % 50)).first()[0]
    assert log.rows[-1]["grp"] == "1,x" and isclose(log.rows[-1]["estimate"], want)
    labeler = LookupLabeler(docs.select("doc_id", "class3"), "doc_id", "class3")
    log = group_engine.progressive_group(odd, "doc_id", "text", labeler, ["clean", "junk", "toxic"], "label", "avg", stratum="key", config=group_engine.GroupConfig(adjust=False, round_fraction=0.5))
    want = {r.class3: r.m for r in docs.groupBy("class3").agg(F.avg("n_chars").alias("m")).collect()}
    assert all(isclose(r["estimate"], want[r["grp"]]) for r in log.rows if r["is_final"])
    with pytest.raises(ValueError):
        filter_engine.progressive_filter(odd, "label", "text", good(docs), "key")


def test_strata_may_be_null_and_are_not_too_many(spark, docs):
    holed = column_strata(docs, "lang").withColumn("stratum", F.when(F.col("stratum") > 0, F.col("stratum")))
    last = filter_engine.progressive_filter(holed, "doc_id", "text", good(docs), "n_chars", batch=60).rows[-1]
    assert last["calls"] == docs.count()
    with pytest.raises(ValueError):
        column_strata(docs, "doc_id", most=10)


@pytest.mark.parametrize("how", [{"refresh_rates": True}, {"fpc": True}, {"estimator": "stratified"}])
def test_filter_variants(docs, how):
    log = filter_engine.progressive_filter(column_strata(docs, "lang"), "doc_id", "text", good(docs), "n_chars", batch=20, **how)
    truth = docs.where("quality = 1").agg(F.avg("n_chars")).first()[0]
    assert isclose(log.rows[-1]["estimate"], truth) and log.rows[-1]["calls"] == docs.count()
    plain = filter_engine.progressive_filter(column_strata(docs, "lang"), "doc_id", "text", good(docs), "n_chars", batch=20)
    if "fpc" in how:
        assert log.rows[-1]["half_width"] == 0 and all(a["half_width"] <= b["half_width"] for a, b in zip(log.rows, plain.rows, strict=True) if a["half_width"] is not None)
    if "estimator" in how:
        assert [r["estimate"] for r in log.rows] == [r["estimate_stratified"] for r in plain.rows]


def test_sum_and_count_of_a_projection(spark, sf):
    events = table(spark, sf, "events")
    labeler = ExtractLabeler(JsonExtractor("k INT", "k", 20, 99))
    k = F.get_json_object("props", "$.k").cast("int")
    want = events.where(k.between(20, 99)).agg(F.sum(k).alias("sum"), F.count("*").alias("count")).first()
    for agg in ("sum", "count"):
        inside = 0
        for seed in range(6):
            log = select_engine.progressive_select(events, "event_id", "props", labeler, agg=agg, batch=200, seed=seed, stop=Stop(max_steps=1))
            r = log.rows[0]
            inside += abs(r["estimate"] - want[agg]) <= r["half_width"]
        assert inside >= 4
        log = select_engine.progressive_select(events, "event_id", "props", labeler, agg=agg, batch=200, stop=Stop(bound=0.5))
        assert len(log.rows) == 1  # COUNT has an interval that a bound can end it by
        assert isclose(select_engine.progressive_select(events, "event_id", "props", labeler, agg=agg, batch=500).rows[-1]["estimate"], want[agg])


def test_purity_ends_a_grouping(spark, docs):
    labeler = LookupLabeler(docs.select("doc_id", "lang"), "doc_id", "lang")
    df = column_strata(docs, "lang")
    log = group_engine.progressive_group(df, "doc_id", "text", labeler, ["de", "en", "es", "fr"], config=group_engine.GroupConfig(adjust=False, round_fraction=0.2), stop=Stop(purity=0.1, relative=False))
    assert log.rows[-1]["step"] == 0 and log.details["purity"][0]["worst"] == 0
    smooth = group_engine.progressive_group(df, "doc_id", "text", labeler, ["de", "en", "es", "fr"], config=group_engine.GroupConfig(adjust=False, round_fraction=0.2, smoothing=1.0, floor=0))
    assert smooth.rows[-1]["is_final"]


def test_lookalikes_of_many_vectors(spark):
    rng = np.random.default_rng(1)
    base = rng.normal(size=(40, 16))
    vectors = [(i, int(i % 3), [float(x) for x in base[i % 40] + rng.normal(size=16) * 0.25]) for i in range(600)]
    pool = spark.createDataFrame(vectors[60:], "key bigint, stratum int, embedding array<double>")
    few = spark.createDataFrame([(k, h, "y", v) for k, h, v in vectors[:60]], "key bigint, stratum int, label string, embedding array<double>")
    want = {r.key for r in refine.lookalikes(pool, few, 0.85, method="matrix").collect()}
    assert 20 < len(want) < 500
    for method in ("join", "prune"):
        assert {r.key for r in refine.lookalikes(pool, few, 0.85, method=method).collect()} == want
    found = {r.key for r in refine.lookalikes(pool, few, 0.85, method="lsh").collect()}
    assert found <= want and len(found) >= 0.8 * len(want)
    none = few.withColumn("embedding", F.lit(None).cast("array<double>"))
    assert all(refine.lookalikes(pool, none, 0.85, method=m).count() == 0 for m in ("lsh", "matrix", "join", "prune"))


@pytest.mark.parametrize("way", ["keep", "nearest"])
def test_merge_without_a_stratum_of_that_category(way):
    means = {0: np.array([1.0, 0.0]), 1: np.array([0.0, 1.0]), 2: np.array([0.7, 0.7])}
    got = refine.merge_target("x", np.array([0.1, 0.9]), 0, {0: "x", 1: "y", 2: "z"}, means, way)
    assert got == (1 if way == "nearest" else None)


def test_moves_keep_rows_draws_and_means(spark):
    """After rounds of splits and merges: sizes, mean vectors and undrawn rows are those of the assignment."""
    e = table(spark, "/root/testdata/sf0.001", "embeddings").select("vec_id", "embedding", F.col("label").cast("string").alias("kind")).where("vec_id < 300")
    strata, _ = kmeans_strata(e, 4)
    labeler = LookupLabeler(e.select("vec_id", "kind"), "vec_id", "kind")
    rows = lay_out(strata, "vec_id", "kind", labeler, {"_stratum": F.col("stratum")}, {"_vector": F.col("embedding")}, 0.2)
    held, draws = group_engine.Strata(rows, "vec_id", {h: n for (h,), n in rows.sizes().items()}), DrawLog(spark)
    config = group_engine.GroupConfig(h_max=6, gamma=0.2, theta=0.1)
    for t in range(4):
        drawn = draws.all().count() if t else 0
        states = group_states(held.placed(draws), held.sizes, CATEGORIES) if t else {}
        left = {h: n - (states[h].n_drawn if t else 0) for h, n in held.sizes.items()}
        take = {h: min(10, n) for h, n in left.items()}
        new = draws.append(t, labeler.label(held.next_rows(take, draws), "kind").select("vec_id", "stratum", "_first", "_position", "_rank", "_vector", "label", "is_valid"))
        assert {r.stratum: r["count"] for r in new.groupBy("stratum").count().collect()} == {h: n for h, n in take.items() if n}
        held.advance(new)
        assert draws.all().select("vec_id").distinct().count() == drawn + sum(take.values())
        now = {r.key: r.stratum for r in held.assignment().collect()}
        ids = {r.vec_id for r in draws.all().collect()}
        assert {(r.key, r.stratum) for r in held.undrawn(list(held.sizes), draws).collect()} == {(k, h) for k, h in now.items() if k not in ids}
        states = group_states(held.placed(draws), held.sizes, CATEGORIES)
        actions = group_engine._adjust(held, draws, new, states, sorted(held.sizes), config, t)
        now = {r.key: r.stratum for r in held.assignment().collect()}
        assert len(now) == 300 and held.sizes == {h: list(now.values()).count(h) for h in set(now.values())} and len(held.sizes) <= 6
        means = held.mean_vectors()
        vectors = {r.vec_id: np.array(r.embedding) / np.linalg.norm(r.embedding) for r in e.collect()}
        for h in held.sizes:
            assert np.allclose(means[h], np.mean([vectors[k] for k, g in now.items() if g == h], axis=0), atol=1e-6)
    assert {a["action"] for a in actions} <= {"merge", "none", "split"}


def test_comparisons_use_like_intervals(spark):
    got = W.compare_grouping(W.with_strata(W.w8(spark, "/root/testdata/sf0.001"), 4), bound=0.2, config=group_engine.GroupConfig(h_max=8, gamma=0.97)).collect()
    by = {(r.method, r.interval): r.share for r in got}
    assert set(by) == {(m, i) for m in ("ours", "static") for i in ("own", "pooled", "fresh")} | {("random", i) for i in ("own", "pooled")}
    for m in ("ours", "static", "random"):
        assert by[m, "own"] <= by[m, "pooled"]


def test_errors_end_at_zero_and_scale_out_gains(spark):
    errors = W.error_against_draws(spark, "/root/testdata/sf0.001", strata=3, batch_share=0.25)
    last = errors.where("calls_fraction = 1").collect()
    assert len(last) == 8 and all(r.error < 1e-6 for r in last)
    assert all(0 < r.share <= 1 for r in W.share_to_error(errors).collect())
    w = W.with_strata(W.w8(spark, "/root/testdata/sf0.001"), 4)
    got = W.scaleout(w, rules.language_of, "string", (1, 4), seconds=0.1, steps=1, config=group_engine.GroupConfig(adjust=False, round_fraction=0.5)).orderBy("instances").collect()
    assert got[0].calls == got[1].calls == 100 and got[1].speedup > 1.5


def test_one_endpoint_is_one_task(spark):
    rows = spark.range(0, 64, 1, 8).select("id", F.lit("x").alias("text"))
    for endpoints, tasks, wanted in ((("one",), 1, 1), (("one",), 2, 2), (("one", "two"), 1, 2)):
        got = ServiceLabeler(lambda e: (lambda texts: texts), endpoints, tasks_per_endpoint=tasks).label(rows)
        assert got.where("is_valid").count() == 64 and got.select(F.spark_partition_id()).distinct().count() == wanted


def test_served_runs_go_side_by_side_with_whole_waits(spark):
    import time

    w = W.with_strata(W.w8(spark, "/root/testdata/sf0.001"), 4)
    start = time.perf_counter()
    got = W.scaleout(w, rules.language_of, "string", (1, 1, 1), seconds=0.15, steps=1, config=group_engine.GroupConfig(adjust=False, round_fraction=0.25)).collect()
    assert [r.calls for r in got] == [50] * 3 and all(r.seconds >= 50 * 0.15 for r in got)
    assert time.perf_counter() - start < 0.8 * sum(r.seconds for r in got)


def test_side_by_side_keeps_to_its_slots(spark):
    from concurrent.futures import ThreadPoolExecutor
    from time import sleep

    sizes, busy, ready, seen = [1, 2, 3, 4, 9], [], [], []
    order = W.SideBySide(4, len(sizes))

    def go(n):
        with order.run(n) as turn:
            ready.append(n)
            turn()
            busy.append(min(n, 4))
            seen.append((len(ready), sum(busy)))
            sleep(0.05)
            busy.remove(min(n, 4))

    with ThreadPoolExecutor(len(sizes)) as pool:
        list(pool.map(go, sizes))
    assert all(r == len(sizes) for r, _ in seen) and max(b for _, b in seen) == 4 and order.free == 4
    order = W.SideBySide(4, 2)

    def fails(n):
        with order.run(n) as turn:
            if n == 1:
                raise ValueError("in setting up")
            turn()

    with ThreadPoolExecutor(2) as pool:
        first, second = pool.submit(fails, 1), pool.submit(fails, 2)
        assert isinstance(first.exception(), ValueError) and isinstance(second.exception(), RuntimeError)


def test_side_by_side_starts_low_ranks_first():
    from concurrent.futures import ThreadPoolExecutor
    from time import sleep

    ranks, started = [4, 2, 9, 1, 3, 1], []
    order = W.SideBySide(2, len(ranks))

    def go(rank):
        with order.run(1, rank) as turn:
            sleep(0.01 * (10 - rank))
            turn()
            started.append(rank)
            sleep(0.1)

    with ThreadPoolExecutor(len(ranks)) as pool:
        list(pool.map(go, ranks))
    assert started[:2] == [1, 1] and sorted(started[2:4]) == [2, 3] and sorted(started[4:]) == [4, 9] and not order.waiting


def test_a_task_asks_its_endpoints_one_request_at_a_time(spark):
    import time

    def client(endpoint):
        from threading import Lock

        open_now, lock = [0], Lock()

        def ask(texts):
            with lock:
                open_now[0] += 1
                seen = open_now[0]
            time.sleep(0.1 * len(texts))
            with lock:
                open_now[0] -= 1
            return [f"{endpoint} {seen} {x}" for x in texts]

        return ask

    rows = spark.range(0, 48, 1, 8).select("id", F.col("id").cast("string").alias("text"))
    for endpoints, each, tasks in ((("a", "b", "c"), 3, 1), (("a", "b", "c", "d"), 2, 2), (("a",), 1, 1)):
        start = time.perf_counter()
        got = ServiceLabeler(client, endpoints, batch_size=4, max_inflight=1, endpoints_per_task=each).label(rows).select("*", F.spark_partition_id().alias("p")).collect()
        assert time.perf_counter() - start >= 48 * 0.1 / len(endpoints)
        assert len({r.p for r in got}) == tasks and {r.label.split()[1] for r in got} == {"1"} and {r.label.split()[0] for r in got} == set(endpoints)
        assert sorted(int(r.label.split()[2]) for r in got) == list(range(48)) and all(r.is_valid and r.label.split()[2] == r.text for r in got)
    with pytest.raises(ValueError):
        ServiceLabeler(client, ("a", "b", "c"), endpoints_per_task=2).label(rows)


def test_served_runs_of_many_instances_go_side_by_side(spark):
    import time

    served = W.Served(lambda: W.with_strata(W.w8(spark, "/root/testdata/sf0.001"), 4), rules.language_of, "string", 0.45, 0.05, 1, {"config": group_engine.GroupConfig(adjust=False, round_fraction=0.25)})
    start = time.perf_counter()
    got = W.scaleouts([served], (3, 3, 3)).collect()
    wall = time.perf_counter() - start
    assert [r.calls for r in got] == [50] * 3 and all(r.seconds >= 50 * 0.45 / 3 for r in got)
    assert wall < 0.9 * sum(r.seconds for r in got)


def test_rule_twins(spark, sf):
    docs = table(spark, sf, "documents").select("text", rules.language().alias("l"), rules.low_quality().alias("q")).collect()
    assert [(r.l, r.q) for r in docs] == [(rules.language_of(r.text), rules.low_quality_of(r.text)) for r in docs]


def test_embedders(spark, sf):
    docs = table(spark, sf, "documents").select("doc_id", "text", "lang")
    got = HashedNgramEmbedder(d=32).embed(docs, "text")
    assert got.where(F.size("embedding") == 32).count() == docs.count()
    assert HashedNgramEmbedder(d=32).embed(docs, "text").exceptAll(got).isEmpty()
    by_model = ModelEmbedder(lambda: lambda texts: np.array([[len(t), t.count("e"), 1.0] for t in texts], np.float32)).embed(docs, "text")
    assert all([*r.embedding] == [len(r.text), r.text.count("e"), 1.0] for r in by_model.collect())


def test_mean_time(spark):
    runs = spark.createDataFrame([("a", 1.0), ("a", 3.0), ("b", 5.0)], "query string, seconds double")
    assert {(r["query"], r.mean_seconds, r.runs) for r in metrics.mean_time(runs).collect()} == {("a", 2.0, 2), ("b", 5.0, 1)}


def test_simulated_service_takes_its_time(spark):
    import time

    rows = spark.range(40).select(F.col("id").alias("doc_id"), F.lit("x").alias("text"))
    start = time.perf_counter()
    assert SimulatedService(RuleLabeler(F.lit("a")), 0.05, 2, real=True).label(rows).where("is_valid").count() == 40
    assert time.perf_counter() - start >= 0.9


def test_one_task_waits_for_many_instances_and_leaves_rows_as_they_are(spark):
    import time

    rows = spark.range(40).select("id", F.lit("x").alias("text"), F.when(F.col("id") > 0, F.lit(2**53 + 1)).alias("n"))
    for instances, tasks in ((4, 1), (4, 2), (2, None)):
        start = time.perf_counter()
        got = SimulatedService(RuleLabeler(F.lit("a")), 0.1, instances, real=True, tasks=tasks).label(rows).select("*", F.spark_partition_id().alias("p")).collect()
        assert time.perf_counter() - start >= 40 / instances * 0.1
        assert len({r.p for r in got}) == (tasks or instances) and {(r.id, r.n) for r in got} == {(i, 2**53 + 1 if i else None) for i in range(40)}
    with pytest.raises(ValueError):
        SimulatedService(RuleLabeler(F.lit("a")), 0.1, 4, real=True, tasks=3).label(rows)


def test_methods_with_long_waits_wait_side_by_side(spark, sf):
    import time

    w = W.w1(spark, sf)
    rows, instances = w.df.count(), spark.sparkContext.defaultParallelism
    start = time.perf_counter()
    got = W.total_times([w], seconds_per_row=0.04, batch_share=0.5, apart=5.0).collect()
    assert [r.method for r in got] == ["full_scan", "batch_semantic", "ours"] and all(r.total_seconds >= rows * 0.04 / instances for r in got)
    assert time.perf_counter() - start < 0.6 * sum(r.total_seconds for r in got)


@pytest.mark.parametrize("slots", [4, 8])
def test_later_workloads_are_made_and_run_beside_long_waits(spark, sf, slots, monkeypatch):
    """With whole waits of all, and after the long ones where no slot is left for them."""
    import time
    from dataclasses import replace

    monkeypatch.setattr(type(spark.sparkContext), "defaultParallelism", slots)
    w, made = W.w1(spark, sf), []

    def later():
        made.append(time.perf_counter() - start)
        return replace(w, name="later", df=w.df.where("event_id < 100"))

    start = time.perf_counter()
    got = W.total_times([w, later], seconds_per_row=0.02 * slots, batch_share=0.5, apart=5.0).collect()
    wall = time.perf_counter() - start
    assert [(r.workload, r.method) for r in got] == [(n, m) for n in ("W1", "later") for m in ("full_scan", "batch_semantic", "ours")]
    long, short = ([r.total_seconds for r in got if r.workload == n] for n in ("W1", "later"))
    assert min(long) >= w.df.count() * 0.02 > 5 > min(short) >= 100 * 0.02 and made[0] < min(long)
    assert wall < max(long) + sum(short) if slots == 8 else wall > max(long) + sum(short)


def test_an_error_beside_long_waits_ends_all(spark, sf):
    from dataclasses import replace

    w = W.w1(spark, sf)
    with pytest.raises(ValueError, match="no such index"):
        W.total_times([replace(w, df=w.df.where("event_id < 400")), lambda: (_ for _ in ()).throw(ValueError("no such index"))], seconds_per_row=0.02, batch_share=0.5, apart=1.0)


@pytest.mark.parametrize("design", ["uniform", "by_group"])
def test_projection_takes_few_jobs_for_many_steps(spark, sf, design):
    """Steps that no rule can leave out are labelled in blocks, with the answers and draws of single steps."""
    events, labeler = spark.read.parquet(f"{sf}/events.parquet").limit(600), ExtractLabeler(JsonExtractor("k INT", "k", 5, 99))
    how = {"agg": "sum", "batch": 25, "design": design}
    spark.sparkContext.setJobGroup(f"blocks-{design}", "")
    log = select_engine.progressive_select(events, "event_id", "props", labeler, ["event_type"], **how)
    jobs = len(spark.sparkContext.statusTracker().getJobIdsForGroup(f"blocks-{design}"))
    spark.sparkContext.setJobGroup("other", "")
    single = select_engine.progressive_select(events, "event_id", "props", labeler, ["event_type"], stop=Stop(budget=10**9), **how)
    plain = lambda x: [(r["step"], r["calls"], r["grp"], r["n_valid"], r["is_final"]) for r in x.rows]
    steps = 1 + log.rows[-1]["step"]
    assert plain(log) == plain(single) and steps >= 20 and jobs < 2 * steps
    assert all((a["estimate"] is None) == (b["estimate"] is None) and (a["estimate"] is None or isclose(a["estimate"], b["estimate"])) for a, b in zip(log.rows, single.rows, strict=True))
    drawn = lambda x: sorted((r.event_id, r.step) for r in x.details["draws"].all().collect())
    assert drawn(log) == drawn(single) and Stop(max_steps=3).sure(9) == 3 and Stop(bound=0.1).sure(9) == 0
