"""The streaming form ends where batch does, also after a restart; late rows and windows."""

from __future__ import annotations

from datetime import datetime

from pyspark.sql import functions as F

from progressive_text.functions.extract import JsonExtractor
from progressive_text.operators.labelers import ExtractLabeler
from progressive_text.operators.order import rank_pool
from progressive_text.sources.store import new_path
from progressive_text.sources.tables import event_time, table
from progressive_text.streaming import stream

SPEC = stream.StreamSpec("label", ("event_type",))
LABELER = ExtractLabeler(JsonExtractor("k INT", "k", 0, 99))


def staged(spark, sf, steps):
    draws = rank_pool(table(spark, sf, "events").select("event_id", "event_type", "props"), "event_id")
    draws = draws.withColumn("step", F.floor((F.col("position") - 1) / (1000 / steps))).drop("draw_rank", "position")
    path = new_path(spark, "staged")
    stream.stage_draws(draws, path)
    return draws, path


def test_stream_equals_batch_and_restarts(spark, sf):
    draws, source = staged(spark, sf, 4)
    schema = spark.read.parquet(source).schema
    log, check = stream.DirTransport(new_path(spark, "log")), new_path(spark, "check")
    for _ in range(2):  # the second start finds nothing new
        stream.label_stream(spark, source, schema, LABELER, "props", log, check).awaitTermination()
    assert spark.read.parquet(log.path).count() == 1000
    out, check = new_path(spark, "answers"), new_path(spark, "check")
    labelled = log.read(spark, spark.read.parquet(log.path).schema)
    stream.progressive_stream(labelled, SPEC, out, check).awaitTermination()
    stream.progressive_stream(labelled, SPEC, out, check).awaitTermination()
    every = spark.read.parquet(out)
    last = every.agg(F.max("trigger").alias("t")).first().t
    got = every.where(F.col("trigger") == last).drop("trigger")
    want = stream.answers(stream.moments(LABELER.label(draws, "props"), SPEC), SPEC)
    digits = lambda df: {tuple(round(x, 9) if isinstance(x, float) else x for x in r) for r in df.collect()}
    assert digits(got) == digits(want) and last >= 3


def test_stop_passes_over_later_triggers(spark, sf):
    _, source = staged(spark, sf, 4)
    out = new_path(spark, "answers")
    rows = LABELER.label(spark.readStream.schema(spark.read.parquet(source).schema).option("maxFilesPerTrigger", 1).parquet(source), "props")
    stream.progressive_stream(rows, SPEC, out, new_path(spark, "check"), stop=lambda df: df.agg(F.sum("calls")).first()[0] >= 500).awaitTermination()
    assert spark.read.parquet(out).select("trigger").distinct().count() == 2


def test_late_rows_are_dropped(spark, sf):
    events = event_time(table(spark, sf, "events")).select("event_id", "ts", "event_type", "value")
    days = [r[0] for r in events.select(F.to_date("ts").alias("d")).distinct().orderBy("d").limit(6).collect()]
    path = new_path(spark, "days")
    late = events.where(F.to_date("ts") == F.lit(days[0])).limit(2).cache()
    on_time = events.join(late.select("event_id"), "event_id", "left_anti")
    for k, part in enumerate([*[on_time.where(F.to_date("ts") == F.lit(d)) for d in days[:5]], late, on_time.where(F.to_date("ts") == F.lit(days[5]))]):
        part.coalesce(1).write.mode("append").parquet(path)
        if k == 5:
            n_late = part.count()
    source = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path)
    out, check = new_path(spark, "windows"), new_path(spark, "check")
    stream.windowed(source, "1 day", late="1 hour").writeStream.format("parquet").option("path", out).option("checkpointLocation", check).outputMode("append").trigger(availableNow=True).start().awaitTermination()
    seen = {r.window_start.date(): r.n for r in spark.read.parquet(out).groupBy("window_start").agg(F.sum("n_events").alias("n")).collect()}
    assert n_late == 2 and seen[days[0]] == on_time.where(F.to_date("ts") == F.lit(days[0])).count()


def test_stratum_state_in_a_store(spark):
    before = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        path, out = new_path(spark, "labels"), new_path(spark, "states")
        for rows in ([(0, "x"), (0, "x"), (1, "y")], [(0, "y"), (1, "y"), (0, "x")]):
            spark.createDataFrame(rows, "stratum int, label string").coalesce(1).write.mode("append").parquet(path)
        source = spark.readStream.schema("stratum int, label string").option("maxFilesPerTrigger", 1).parquet(path)

        def keep(batch, trigger):
            batch.write.mode("overwrite").parquet(f"{out}/trigger={trigger}")

        stream.stratum_state_stream(source).writeStream.outputMode("update").option("checkpointLocation", new_path(spark, "check")).trigger(availableNow=True).foreachBatch(keep).start().awaitTermination()
        last = {r.stratum: (r.n_drawn, r.dominant, round(r.heterogeneity, 6)) for r in spark.read.parquet(out).where("trigger = 1").collect()}
        assert last == {0: (4, "x", 0.375), 1: (2, "y", 0.0)}
    finally:
        spark.conf.set("spark.sql.streaming.stateStore.providerClass", before)


def files_of(spark, parts, schema):
    path = new_path(spark, "parts")
    for rows in parts:
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)


def run_append(spark, rows):
    out = new_path(spark, "out")
    rows.writeStream.format("parquet").option("path", out).option("checkpointLocation", new_path(spark, "check")).outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(rows.schema).parquet(out)


def at(minute: int):
    return datetime(2024, 1, 1, minute // 60, minute % 60)


def test_repeats_within_the_watermark_go(spark):
    schema = "event_id bigint, ts timestamp"
    source = files_of(spark, [[(1, at(0)), (2, at(1))], [(1, at(5)), (3, at(6))], [(3, at(7)), (4, at(8))]], schema)
    got = [r.event_id for r in run_append(spark, stream.without_repeats(source, "event_id", "1 hour")).collect()]
    assert sorted(got) == [1, 2, 3, 4]


def test_streams_meet_within_an_interval(spark):
    schema = "event_id bigint, user_id bigint, ts timestamp"
    left = files_of(spark, [[(1, 7, at(0)), (2, 8, at(0))], [(3, 7, at(50))], [(9, 9, at(600))]], schema)
    right = files_of(spark, [[(11, 7, at(10)), (12, 8, at(45))], [(13, 7, at(75)), (14, 7, at(40))], [(19, 9, at(601))]], schema)
    got = run_append(spark, stream.near_in_time(left, right, "user_id", "30 minutes", "2 hours")).collect()
    assert sorted((r.left_id, r.right_id) for r in got) == [(1, 11), (3, 13), (9, 19)]


def test_staging_is_one_job_in_order(spark, sf):
    jobs = []
    for steps in (3, 8):
        spark.sparkContext.setJobGroup(f"staging-{steps}", "as many jobs for any number of steps")
        draws, path = staged(spark, sf, steps)
        jobs.append(len(spark.sparkContext.statusTracker().getJobIdsForGroup(f"staging-{steps}")))
    spark.sparkContext.setJobGroup("other", "")
    assert abs(jobs[0] - jobs[1]) <= 2  # stages of one adaptive query
    names = sorted(f.rsplit("/", 1)[1] for f in spark.read.parquet(path).inputFiles())
    assert [n[:11] for n in names] == [f"step-{k:06d}" for k in range(8)]
    assert spark.read.parquet(path).exceptAll(draws.select(*spark.read.parquet(path).columns)).isEmpty() and spark.read.parquet(path).count() == draws.count()
    many = new_path(spark, "many")
    stream.stage_draws(draws, many, files_per_step=3)
    assert len(spark.read.parquet(many).inputFiles()) > 8 and spark.read.parquet(many).count() == draws.count()
